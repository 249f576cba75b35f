import pytest
from pyspark.sql import functions as F

from cubefactor import registry
from cubefactor.functions.kernels import attach, normal_equations, normal_equations_arrow, packed
from cubefactor.functions.init import start_slice
from cubefactor.operators import layout
from cubefactor.operators.exchange import publish
from cubefactor.operators.tensor import TensorFrame
from cubefactor.plans import planner
from cubefactor.solvers.subset_als import SubsetALS
from cubefactor.sources.catalog import tensor
from cubefactor.sources.tables import load


def plan(frame):
    return frame._jdf.queryExecution().executedPlan().toString()


def test_filters_and_columns_reach_the_scan(spark, sf_dir):
    text = plan(registry.queries()["scan_filter_project"](spark, sf_dir))
    assert "PushedFilters: [IsNotNull(l_quantity)" in text and "GreaterThan(l_quantity,45.0)" in text
    schema = text.split("ReadSchema: ")[1]
    assert "l_orderkey" in schema and "l_comment" not in schema and "l_tax" not in schema


def test_normal_equations_stay_in_generated_code_with_partial_sums(spark, sf_dir):
    t = tensor(spark, sf_dir, "events3")
    slices = [start_slice(spark, d, n, [0, 1], 42, "random") for n, d in enumerate(t.dims, 1)]
    joined = attach(t.cells, slices, "a", modes=[2, 3])
    sums = normal_equations(joined, 1, 2, ["a1", "a2", "a3"], F.col("x"), ["i1"])
    text = plan(sums)
    assert "partial_sum" in text and "BroadcastHashJoin" in text and "Python" not in text and "SortMergeJoin" not in text
    arrow = normal_equations_arrow(joined, 1, 2, ["a1", "a2", "a3"], F.col("x"), ["i1"])
    one, two = ({r["i1"]: [round(v, 9) for v in r[1:]] for r in f.collect()} for f in (sums, arrow))
    assert one == two


def test_group_joins_shuffle_only_when_slices_are_large(spark, sf_dir):
    t = tensor(spark, sf_dir, "events3")
    slices = [start_slice(spark, d, n, [0], 42, "random") for n, d in enumerate(t.dims, 1)]
    assert "BroadcastExchange" in plan(attach(t.cells, slices, "a", True))
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        assert "BroadcastExchange" not in plan(attach(t.cells, slices, "a", False))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_tiles_keep_the_cells_in_place(spark, sf_dir):
    """Slices above the limit of one broadcast are joined in tiles: no Exchange but the broadcasts', same sums."""
    t = tensor(spark, sf_dir, "events3")
    assigned = layout.assign(t, 4, "greedy").persist()
    copy = layout.distribute(t.cells, assigned, 1, 4, t.dims[0])
    copy.count()  # the partitioning of a copy is known once it is made
    slices = [start_slice(spark, d, n, [0, 1], 42, "random") for n, d in enumerate(t.dims, 1)]
    sums = [normal_equations(attach(copy, slices, "a", how, [2, 3]), 1, 2, ["a1", "a2", "a3"], F.col("x"), ["machine", "i1"]) for how in (True, 3)]
    text = plan(sums[1]).split("InMemoryTableScan")[0].replace("BroadcastExchange", "")
    assert "Exchange" not in text
    one, two = ({r["i1"]: [round(v, 9) for v in r[2:]] for r in f.collect()} for f in sums)
    assert one == two
    copy.unpersist()
    assert planner.choose_exchange([10**7] * 5, 10) == "tiles" and planner.tile_count([10**7] * 5, 10) == 4


def test_star_joins_broadcast_their_dimensions(spark, sf_dir):
    assert plan(registry.queries()["join_broadcast_star"](spark, sf_dir)).count("BroadcastHashJoin") >= 2
    assert "SortMergeJoin" in plan(registry.queries()["join_sortmerge"](spark, sf_dir))
    assert load(spark, sf_dir, "nation").count() == 25


def test_broadcast_slices_are_packed_and_rows_stay_with_their_indices(spark):
    """A broadcast has an entry per block of rows, and gaps, indices below zero and beyond the end have no row."""
    known = [i for i in range(1000) if i % 7 and not 300 <= i < 600 or i == 517]
    part = spark.createDataFrame([(i, [float(i), i / 2]) for i in known], "idx long, a array<double>")
    assert packed(part).count() == 4
    wanted = [-257, -1, *range(1030), 5000]
    cells = spark.createDataFrame([(i,) for i in wanted], "i1 long")
    for how in (True, "packed", 3):
        got = {r["i1"]: r["a1"] for r in attach(cells, [part], "a", how).collect()}
        assert sorted(got) == sorted(wanted)
        for i in wanted:
            assert not got[i] or all(v is None for v in got[i]) if i not in known else got[i] == [float(i), i / 2]


def test_long_slices_do_not_go_through_the_driver(spark):
    assert planner.choose_exchange([900_000, 1_200_000, 80], 1) == "dfs"


def test_slices_of_many_rows_are_not_held_by_the_driver_row_by_row(spark, monkeypatch):
    assert SubsetALS(3, group_width=2)._spread("broadcast", [112_000, 5], 2) == ["packed", True]
    rows = [((a * 7) % 40, a % 3, (a * 5) % 4, float(a % 5)) for a in range(200)]
    cells = spark.createDataFrame(rows, "i1 long, i2 long, i3 long, x double").dropDuplicates(["i1", "i2", "i3"])
    fit = lambda: SubsetALS(3, group_width=2, outer_iters=1, storage="single", machines=2).fit(TensorFrame(cells, [40, 3, 4]))
    values = lambda model: [(r["mode"], r["idx"], *r["f"]) for r in model.factors.orderBy("mode", "idx").collect()]
    plain, plans, rewrite = values(fit()), [], SubsetALS._rewrite
    monkeypatch.setattr(planner, "PLAIN_ROWS", 20)
    long_slice = spark.range(40).select(F.col("id").alias("idx"), F.array(F.lit(0.5)).alias("a"))
    assert "LocalRelation" not in publish(long_slice, 40, "broadcast")._jdf.queryExecution().optimizedPlan().toString()

    def seen(self, placed, *args, **options):
        plans.append(placed[0]._jdf.queryExecution().optimizedPlan().toString().count("InMemoryRelation"))
        return rewrite(self, placed, *args, **options)

    monkeypatch.setattr(SubsetALS, "_rewrite", seen)
    for one, two in zip(plain, values(fit()), strict=True):
        assert one == pytest.approx(two, abs=1e-9)
    assert len(plans) == 4 and plans[2] == 0  # the second group starts from a table
