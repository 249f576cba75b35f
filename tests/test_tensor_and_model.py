import numpy as np
import pytest
from pyspark.sql import functions as F

from cubefactor import metrics, synth
from cubefactor.functions import udtf
from cubefactor.functions.init import hash_factors
from cubefactor.model import FactorModel
from cubefactor.operators import tensor as T
from cubefactor.operators.lineage import written
from cubefactor.solvers.subset_als import FullALS
from cubefactor.sources import tables


def test_cells_from_facts(spark):
    facts = spark.createDataFrame([("b", 1, 2.0), ("b", 1, 4.0), ("a", 2, None), (None, 1, 1.0), ("a", 1, float("nan")), ("c", 3, 5.0)], "k string, j int, v double")
    t = T.encode(T.raw_cells(facts, [F.col("k"), F.col("j")], F.avg("v")), 2)
    assert t.dims == [2, 2] and sorted(map(tuple, t.cells.collect())) == [(0, 0, 3.0), (1, 1, 5.0)]
    assert sorted(map(tuple, T.decode(t.cells, t).select("k1", "k2", "x").collect())) == [("b", 1, 3.0), ("c", 3, 5.0)]
    empty = T.encode(T.raw_cells(facts.limit(0), [F.col("k"), F.col("j")], F.avg("v")), 2)
    assert empty.dims == [0, 0] and empty.cells.count() == 0


def test_dictionaries_number_keys_over_many_partitions(spark):
    raw = spark.range(5000).select((F.col("id") * 7 % 5000).alias("k1"), F.lit(1.0).alias("x")).repartition(16)
    rows = T.dictionary(raw, 1).collect()
    assert sorted((r["key"], r["idx"]) for r in rows) == [(k, k) for k in range(5000)]


def test_validation_counts(spark):
    cells = spark.createDataFrame([(0, 0, 1.0), (0, 0, 2.0), (5, 0, 1.0), (None, 1, 1.0), (1, 1, float("nan"))], "i1 long, i2 long, x double")
    assert tuple(T.validate(cells, [3, 3]).first()) == (5, 1, 1, 1, 1)


def test_tensor_algebra(spark):
    t = T.TensorFrame(spark.createDataFrame([(0, 0, 1, 1.0), (1, 0, 1, 2.0), (1, 2, 0, 4.0)], "i1 long, i2 long, i3 long, x double"), [2, 3, 2])
    assert sorted(map(tuple, T.fix_mode(t, 1, 1).cells.collect())) == [(0, 1, 2.0), (2, 0, 4.0)]
    assert sorted(map(tuple, T.marginalize(t, [3]).cells.collect())) == [(0, 4.0), (1, 3.0)]
    assert sorted(map(tuple, T.unfold(t, 2).cells.collect())) == [(0, 2, 1.0), (0, 3, 2.0), (2, 1, 4.0)]
    assert T.combine(t, T.rescale(t, 1.0, 2.0), -1).cells.agg(F.sum("x")).first()[0] == 7.0 - 8.0
    train, test = T.split(t, 2)
    assert train.cells.count() + test.count() == 3


def test_text_round_trip(spark, tmp_path):
    t = synth.planted(spark, [5, 6], 20, 1)
    tables.write_coo(t.cells, f"{tmp_path}/coo")
    back = tables.read_coo(spark, f"{tmp_path}/coo", 2)
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, t.cells.collect()))
    (tmp_path / "bad.tsv").write_text("1\t2\t3.5\nnothing\n1\tx\t2\n")
    assert tables.read_coo(spark, f"{tmp_path}/bad.tsv", 2).collect() == [(0, 1, 3.5)] and tables.bad_lines(spark, f"{tmp_path}/bad.tsv", 2) == 2
    (tmp_path / "c.json").write_text('{"i1": 1, "i2": 1, "x": 2.0}\nbroken\n')
    assert tables.read_coo(spark, f"{tmp_path}/c.json", 2, fmt="json").collect() == [(0, 0, 2.0)]


@pytest.fixture(scope="module")
def fitted(spark):
    t = synth.planted(spark, [15, 8, 6], 400, 2, 0.01)
    t = T.TensorFrame(written(t.cells, "fitted"), t.dims)
    return t, FullALS(2, outer_iters=3, reg_param=0.001, storage="single").fit(t)


def test_save_load_and_predict(spark, fitted, tmp_path):
    t, model = fitted
    model.save(f"{tmp_path}/model")
    again = FactorModel.load(spark, f"{tmp_path}/model")
    assert again.rank == 2 and again.dims == [15, 8, 6]
    assert metrics.rmse(again, t.cells) == pytest.approx(metrics.rmse(model, t.cells))
    unknown = spark.createDataFrame([(99, 0, 0, 1.0)], "i1 long, i2 long, i3 long, x double")
    assert model.predict(unknown).first()["prediction"] == 0.0 and model.predict(unknown, 0.5, 1.0).first()["prediction"] == 0.5
    assert metrics.cold_cells(t, unknown) == 1
    shuffled = model.predict(t.cells, broadcast=False).agg(F.sum("prediction")).first()[0]
    assert shuffled == pytest.approx(model.predict(t.cells).agg(F.sum("prediction")).first()[0])


def test_ranking_neighbours_components(spark, fitted):
    t, model = fitted
    users = spark.createDataFrame([(0,), (3,)], "i1 long")
    best = model.recommend(users, 2, 3, {3: 1}).collect()
    grid = {u: sorted(((-sum(a * b * c for a, b, c in zip(f[1][u], f[2][j], f[3][1])), j) for j in range(8)))[:3] for f in [factors(model)] for u in (0, 3)}
    assert {u: [r["i2"] for r in sorted(best, key=lambda r: r["rank"]) if r["i1"] == u] for u in (0, 3)} == {u: [j for _, j in v] for u, v in grid.items()}
    assert not {(r["i1"], r["i2"]) for r in model.recommend(users, 2, 8, {3: 1}, t.cells).collect()} & {(r["i1"], r["i2"]) for r in t.cells.collect()}
    near = model.similar(1, 0, 4).collect()
    assert len(near) == 4 and all(-1.0001 <= r["cosine"] <= 1.0001 and r["idx"] != 0 for r in near)
    assert model.components(2, 3).count() == 6
    ranked = model.recommend(users, 2, 8, {3: 1})
    assert 0 <= metrics.precision_at_k(ranked, t.cells, "i1", "i2", 3).first()[0] <= 1


def factors(model):
    out = {n: {} for n in (1, 2, 3)}
    for r in model.factors.collect():
        out[r["mode"]][r["idx"]] = r["f"]
    return out


def test_fold_in_gives_back_the_last_solved_mode(fitted):
    t, model = fitted
    rows = {r["idx"]: r["a"] for r in model.fold_in(t.cells, 3, 0.001).collect()}
    own = factors(model)[3]
    assert all(np.allclose(rows[i], own[i], atol=1e-8) for i in rows)


def test_report_and_portable_factors(spark, fitted):
    t, model = fitted
    r = metrics.report(model, t.cells).first()
    assert r["cells"] == t.cells.count() and r["rmse"] == pytest.approx(metrics.rmse(model, t.cells)) and r["r2"] > 0.9
    values = [v for row in hash_factors(spark, [50, 50], 4).collect() for v in row["f"]]
    assert min(values) >= 0 and max(values) < 1 and len(set(values)) > 100


def test_table_function(spark):
    udtf.register(spark)
    rows = spark.sql("SELECT * FROM mode_copies(array(4L, 7L), 2.5D)").collect()
    assert [tuple(r) for r in rows] == [(1, 4, 2.5), (2, 7, 2.5)]
