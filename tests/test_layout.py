import time
from itertools import product

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from cubefactor import synth
from cubefactor.functions.init import start_slice
from cubefactor.operators import layout
from cubefactor.operators.lineage import written
from cubefactor.operators.tensor import TensorFrame, mode_counts
from cubefactor.plans import planner


def one_by_one(counts, machines, capacity, overall):
    load, held, out = [0] * machines, [0] * machines, {}
    for weight in sorted(counts, reverse=True):
        m = min((m for m in range(machines) if held[m] < capacity), key=lambda m: (load[m], held[m], overall[m], m))
        load[m] += weight
        held[m] += 1
        overall[m] += weight
        out[weight, m] = out.get((weight, m), 0) + 1
    return out


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 9), min_size=1, max_size=40), st.integers(1, 6))
def test_classes_equal_row_by_row_placement(counts, machines):
    capacity = -(-len(counts) // machines)
    one, two = [0] * machines, [0] * machines
    classes = [(w, counts.count(w)) for w in set(counts)]
    got = {(w, m): n for w, m, n in layout.greedy_classes(classes, machines, capacity, one)}
    assert got == one_by_one(counts, machines, capacity, two) and one == two


def test_a_million_equal_rows_are_placed_at_once():
    began = time.time()
    overall = [0] * 40
    got = layout.greedy_classes([(3, 600_000), (1, 400_000)], 40, 25_000, overall)
    assert time.time() - began < 1 and sum(n for _, _, n in got) == 1_000_000
    assert max(overall) - min(overall) <= 3


def test_ranges_leave_no_machine_idle(spark):
    counts = spark.range(101).selectExpr("1 AS mode", "id AS idx", "1L AS nnz")
    rows = {r["machine"]: r["count"] for r in layout.assign_sequential(counts, [101], 40).groupBy("machine").count().collect()}
    assert set(rows) == set(range(40)) and set(rows.values()) == {2, 3}


def test_start_rows_do_not_repeat(spark):
    rows = start_slice(spark, 100_000, 2, [0, 1, 2, 3], 42, "random")
    assert rows.distinct().count() >= 100_000 and rows.select(F.col("a")[0].alias("v")).distinct().count() > 99_000
    counts = spark.range(4000).selectExpr("explode(array(1, 2)) AS mode", "id AS idx", "1L AS nnz")
    by_mode = layout.assign_random(counts, [4000, 4000], 8).groupBy("idx").agg(F.countDistinct("machine").alias("n"))
    assert 3200 < by_mode.where("n = 2").count() < 3800


@pytest.fixture(scope="module")
def skewed(spark):
    rows = [(i, j, 1.0) for i in range(20) for j in range(0, 40, i + 1)]
    return TensorFrame(written(spark.createDataFrame(rows, "i1 long, i2 long, x double"), "skewed"), [20, 40])


def test_greedy_is_best_and_within_capacity(skewed):
    ratio = {}
    for how in ("sequential", "random", "greedy"):
        assigned = layout.assign(skewed, 4, how)
        assert assigned.count() == mode_counts(skewed).count()
        rows = {r["mode"]: r for r in layout.balance(assigned, 4).collect()}
        ratio[how] = rows[1]["ratio"]
        if how == "greedy":
            assert rows[1]["max_rows"] <= 5 and rows[2]["max_rows"] <= 10
    assert ratio["greedy"] <= min(ratio.values())
    with pytest.raises(ValueError):
        layout.assign(skewed, 4, "alphabetical")


def test_mode_copies_need_no_further_shuffle(skewed):
    assigned = layout.assign(skewed, 4, "greedy").persist()
    copies = [layout.distribute(skewed.cells, assigned, n, 4) for n in (1, 2)]
    for n, copy in enumerate(copies, 1):
        assert copy.count() == skewed.cells.count()
        plan = copy.groupBy("machine", f"i{n}").sum("x")
        text = plan._jdf.queryExecution().executedPlan().toString().split("InMemoryTableScan")[0]
        assert "Exchange" not in text
    assert layout.mode_copy_sizes(skewed, assigned).groupBy("mode").sum("cells").collect()[0][1] == skewed.cells.count()
    for c in copies:
        c.unpersist()


@pytest.mark.parametrize(("machines", "modes"), [(2, 3), (3, 3), (2, 5), (4, 2)])
def test_strata_are_disjoint_and_cover_all_blocks(spark, machines, modes):
    rows = [tuple(r) for r in layout.strata(spark, machines, modes).collect()]
    blocks = [r[2:] for r in rows]
    assert sorted(blocks) == sorted(product(range(machines), repeat=modes))
    for s in {r[0] for r in rows}:
        mine = [r[2:] for r in rows if r[0] == s]
        assert len(mine) == machines and all(len(set(b)) == machines for b in zip(*mine))


def test_placement_example_with_four_machines(spark):
    """Three modes, sequential rows: a machine stores the cells of its rows of any mode; copies of cells are counted per mode."""
    t = synth.planted(spark, [4, 4, 4], 30, 1)
    t = TensorFrame(written(t.cells, "example"), t.dims)
    assigned = {(r["mode"], r["idx"]): r["machine"] for r in layout.assign(t, 4, "sequential").collect()}
    assert all(machine == idx for (_, idx), machine in assigned.items())
    blocks = layout.with_blocks(t, 4).collect()
    assert all(r[f"b{n}"] == r[f"i{n}"] for r in blocks for n in (1, 2, 3))


def test_planner_decides_by_size():
    assert planner.choose_kernel(12) == "sql" and planner.choose_kernel(13) == "arrow"
    assert [planner.choose_exchange([d], 10) for d in (10**4, 10**6, 10**8)] == ["broadcast", "dfs", "join"]
    assert planner.choose_storage(10**6, [24, 10**5], 40) == "single" and planner.choose_storage(10**6, [10**4] * 3, 40) == "mode_copies"
    assert planner.choose_storage(10**9, [10**4] * 3, 40, disk_bytes=10**9) == "single"


def test_the_schedule_holds_every_cell_of_the_table_once(spark, sf_dir):
    from cubefactor import registry
    from cubefactor.sources.catalog import tensor

    rows = registry.queries()["strata_schedule"](spark, sf_dir).groupBy("machines").agg(F.count("*").alias("blocks"), F.sum("cells").alias("cells")).collect()
    assert {r["machines"]: (r["blocks"], r["cells"]) for r in rows} == {m: (m**3, tensor(spark, sf_dir, "events3").cells.count()) for m in (2, 3)}
