import numpy as np

from cubefactor import synth
from cubefactor.operators.lineage import written
from cubefactor.operators.tensor import TensorFrame
from cubefactor.solvers.subset_als import FullALS
from cubefactor.streaming import windows
from cubefactor.streaming.foldin import FoldIn


def run(stream, name, mode="append"):
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination(120)
    assert query.exception() is None
    return stream.sparkSession.table(name)


def test_windows_of_a_stream_equal_the_batch(spark, sf_dir):
    events = windows.read_events(spark, f"{sf_dir}/events.parquet*")
    got = {(r["start"], r["stop"]): r["n"] for r in run(windows.tumbling(events, "1 day", late="1 hour"), "tumbled").collect()}
    whole = {(r["start"], r["stop"]): r["n"] for r in windows.tumbling(windows.zoned(spark.read.parquet(f"{sf_dir}/events.parquet")), "1 day").collect()}
    assert got.items() <= whole.items() and len(whole) - len(got) <= 1  # the last window stays open


def test_late_events_are_dropped(spark, tmp_path):
    schema = "event_id long, ts timestamp, value double"
    source = tmp_path / "in"
    source.mkdir()
    for k, rows in enumerate([[(1, "2024-01-01 10:00:00"), (2, "2024-01-03 10:00:00")], [(7, "2024-01-03 11:00:00")], [(3, "2024-01-01 11:00:00"), (4, "2024-01-03 12:00:00")], [(5, "2024-01-09 00:00:00")], [(6, "2024-01-12 00:00:00")]]):
        spark.createDataFrame([(i, t, 1.0) for i, t in rows], "event_id long, ts string, value double").selectExpr("event_id", "cast(ts as timestamp) ts", "value").coalesce(1).write.mode("append").parquet(f"{source}/{k}")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").option("recursiveFileLookup", "true").parquet(str(source))
    rows = run(windows.tumbling(stream, "1 day", late="1 hour"), "late").collect()
    assert {str(r["start"])[:10]: r["n"] for r in rows}.get("2024-01-03") == 3
    assert all(r["n"] == 1 for r in rows if str(r["start"]).startswith("2024-01-01"))


def test_each_event_once(spark, sf_dir):
    events = windows.read_events(spark, f"{sf_dir}/events.parquet*")
    twice = events.union(events)
    assert run(windows.deduplicated(twice), "once").count() == spark.read.parquet(f"{sf_dir}/events.parquet").count()


def test_fold_in_by_batches_equals_one_solve(spark, tmp_path):
    t = synth.planted(spark, [12, 6, 5], 200, 2, 0.01)
    t = TensorFrame(written(t.cells, "stream"), t.dims)
    model = FullALS(2, outer_iters=2, reg_param=0.01, storage="single").fit(t)
    t.cells.repartition(3).write.parquet(f"{tmp_path}/cells")
    seen = []
    fold = FoldIn(model.slices(), 1, 2, 0.01, then=lambda rows, batch: seen.append(batch))
    stream = spark.readStream.schema(t.cells.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/cells")
    query = stream.writeStream.foreachBatch(fold).trigger(availableNow=True).start()
    query.awaitTermination(120)
    assert query.exception() is None and len(seen) == 3
    fold(t.cells, fold.last)  # a batch that comes again changes nothing
    got = {r["idx"]: r["a"] for r in fold.rows().collect()}
    expected = {r["idx"]: r["a"] for r in model.fold_in(t.cells, 1, 0.01).collect()}
    assert got.keys() == expected.keys() and all(np.allclose(got[i], expected[i]) for i in got)


def test_stream_is_scored_with_static_factors(spark, tmp_path):
    t = synth.planted(spark, [6, 5], 20, 1)
    model = FullALS(1, outer_iters=1, storage="single").fit(TensorFrame(written(t.cells, "score"), t.dims))
    t.cells.write.parquet(f"{tmp_path}/s")
    stream = spark.readStream.schema(t.cells.schema).parquet(f"{tmp_path}/s")
    got = run(windows.scored(stream, model.slices(), 1), "scored")
    assert sorted(round(r["prediction"], 9) for r in got.collect()) == sorted(round(r["prediction"], 9) for r in model.predict(t.cells).collect())


def test_fold_in_goes_on_after_a_restart(spark, tmp_path):
    t = synth.planted(spark, [8, 5, 4], 80, 2, 0.01)
    t = TensorFrame(written(t.cells, "restart"), t.dims)
    model = FullALS(2, outer_iters=1, reg_param=0.01, storage="single").fit(t)
    first, second = t.cells.where("i2 < 2"), t.cells.where("i2 >= 2")
    state = f"{tmp_path}/state"
    FoldIn(model.slices(), 1, 2, 0.01, state=state)(first, 0)
    again = FoldIn(model.slices(), 1, 2, 0.01, state=state)
    again(first, 0)  # delivered once more after the restart
    again(second, 1)
    got = {r["idx"]: r["a"] for r in again.rows().collect()}
    expected = {r["idx"]: r["a"] for r in model.fold_in(t.cells, 1, 0.01).collect()}
    assert again.last == 1 and got.keys() == expected.keys() and all(np.allclose(got[i], expected[i]) for i in got)
