import subprocess
import sys
from pathlib import Path

import duckdb
import pandas as pd
import pytest

from cubefactor import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
ROOT = Path(__file__).resolve().parents[1]


@pytest.fixture(scope="module")
def reference(sf_dir):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return con


def lines(frame: pd.DataFrame):
    def show(v):
        if isinstance(v, (list, dict)):
            return str(v)
        if pd.isna(v):
            return "null"
        if isinstance(v, float):
            return str(int(v)) if v.is_integer() else repr(round(v, 6))
        return str(v)

    return sorted(tuple(show(v) for v in row) for row in frame[sorted(frame.columns)].itertuples(index=False))


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_its_sql(spark, sf_dir, reference, name):
    got = registry.queries()[name](spark, sf_dir).toPandas()
    expected = reference.execute(registry.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(expected.columns)
    assert lines(got) == lines(expected)


def test_every_oracle_has_a_query():
    assert set(registry.oracle_sql()) <= set(registry.queries())


@pytest.mark.parametrize("name", ["converge_column_cd", "converge_averaged_sgd", "machine_speedup", "stratified_sgd_run", "recommend_hours"])
def test_experiments_give_rows(spark, sf_dir, name):
    assert registry.queries()[name](spark, sf_dir).count() > 0


def test_the_engine_does_not_need_the_corpus_operators():
    code = "import sys; import cubefactor.registry; assert not any('llm' in m for m in sys.modules if m.startswith('cubefactor'))"
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True)
    for path in (ROOT / "cubefactor").rglob("*.py"):
        assert "llm" in path.parts or "llm" not in path.read_text()


def test_changes_against_a_first_value_of_zero(spark, tmp_path):
    """Division by zero follows the SQL: infinities and NaN, no error."""
    con = duckdb.connect()
    rows = [(1, 1, 0.0), (2, 1, 0.0), (3, 1, 5.0), (4, 1, -5.0), (5, 2, 4.0), (6, 2, 0.0), (7, 3, -0.0), (8, 3, 2.0), (9, 4, None), (10, 4, 1.0)]
    con.execute("CREATE TABLE events (event_id BIGINT, user_id BIGINT, value DOUBLE, ts TIMESTAMP, event_type VARCHAR)")
    con.executemany("INSERT INTO events SELECT ?, ?, ?, TIMESTAMP '2024-01-01', 'view'", rows)
    con.execute(f"COPY events TO '{tmp_path}/events.parquet'")
    got = registry.queries()["window_lag"](spark, str(tmp_path)).toArrow().to_pylist()
    expected = con.execute(registry.oracle_sql()["window_lag"]).to_arrow_table().to_pylist()
    show = lambda rows: sorted(tuple(str(r[c]) for c in sorted(r)) for r in rows)
    assert len(got) == 10 and show(got) == show(expected)


def test_neighbours_come_from_the_table_of_cells(spark, sf_dir):
    """The rows compared are those of the cells, read from storage, not numbers made up to the mode's length."""
    assert registry.queries()["similar_rows"](spark, sf_dir).inputFiles()
