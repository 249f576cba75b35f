import pytest

from cubefactor.plans import cost

GIB, MIB = 1 << 30, 1 << 20


def scale(name):
    n, length, nnz, k = cost.SCALES[name]
    return [length] * n, nnz, k


def test_published_memory():
    dims, _, k = scale("S4")
    assert cost.memory("full_als", dims, k) / GIB == pytest.approx(186, rel=0.01)
    assert cost.memory("column_cd", dims, k) / MIB == pytest.approx(387, rel=0.025)
    assert cost.memory("subset_als", dims, k) / MIB == pytest.approx(1912, rel=0.025)
    longer = [10_000_000] * 3
    assert cost.memory("averaged_sgd", longer, 100) / GIB == pytest.approx(11.2, rel=0.01)
    assert cost.memory("column_cd", longer, 100) / MIB == pytest.approx(234, rel=0.025)
    assert cost.memory("subset_als", longer, 100) / MIB == pytest.approx(1147, rel=0.025)


def test_only_the_column_group_methods_fit_everywhere():
    for name in cost.SCALES:
        dims, _, k = scale(name)
        status = {m: cost.feasible(m, dims, k, 10, cost.machines_of(m)) for m in cost.METHODS}
        assert status["column_cd"] == status["subset_als"] == "ok"
    assert status["full_als"] == status["averaged_sgd"] == status["stratified_sgd"] == "oom"


def test_how_measures_move_with_parameters():
    dims, nnz, k = scale("S2")
    for method in cost.METHODS:
        assert cost.flops(method, 2 * nnz, dims, k) <= 2 * cost.flops(method, nnz, dims, k) + 1
        assert cost.flops(method, nnz, dims, k, m=20) == pytest.approx(2 * cost.flops(method, nnz, dims, k, m=40), rel=1e-6)
    assert cost.flops("full_als", nnz, dims, 1000) > 50 * cost.flops("full_als", nnz, dims, 100)
    assert cost.flops("column_cd", nnz, dims, 1000) == 10 * cost.flops("column_cd", nnz, dims, 100)
    assert cost.exchanged("stratified_sgd", dims, k, m=10) == 2 * cost.exchanged("stratified_sgd", dims, k, m=5)
    assert cost.memory("subset_als", dims, k, c=20) == 2 * cost.memory("subset_als", dims, k, c=10)


def test_redistributions():
    assert cost.redistributions(10, 40, 10, 3) == 10 * 4 * 5
    assert cost.redistributions(10, 40, 10, 3, storage="mode_copies") == 3
    assert cost.redistributions(10, 45, 10, 3) == 10 * 5 * 5  # the last group is narrower
    with pytest.raises(ValueError):
        cost.flops("guess", 1, [1], 1)


def test_sizes_are_counted_in_the_tables(spark, sf_dir, tmp_path):
    """The cost tables follow the rows of the given tables."""
    from cubefactor import registry
    from cubefactor.registry.costs import sizes
    from cubefactor.sources.catalog import tensor

    dims, nnz, _ = sizes(spark, sf_dir, ["events3"])["events3"]
    t = tensor(spark, sf_dir, "events3")
    assert (dims, nnz) == (t.dims, t.cells.count())
    for name in ("events", "lineitem"):
        spark.read.parquet(f"{sf_dir}/{name}.parquet").limit(500).write.parquet(f"{tmp_path}/{name}.parquet")
    for name in ("cost_table", "exchange_table", "memory_table", "redistribution_table"):
        whole, part = (sorted(map(tuple, registry.queries()[name](spark, d).collect())) for d in (sf_dir, str(tmp_path)))
        assert len(whole) == len(part) and whole != part


def test_outcomes_follow_the_lengths_of_the_table(monkeypatch, spark):
    from cubefactor.registry import experiments

    asked = []
    longest = [100]
    monkeypatch.setattr(experiments, "sizes", lambda spark, sf, names: asked.append(names) or {"supply3": ([10, longest[0], 5], 1000, 100)})
    status = lambda: {(r["method"], r["factor"], r["step"]): r["status"] for r in experiments.scaling_status(spark, "").collect()}
    assert set(status().values()) == {"ok"}
    longest[0] = 1_000_000
    assert status() == {(m, f, s + 1): experiments.published_status(m, f, s) for m in cost.METHODS for f in ("modes", "length", "cells", "rank") for s in range(4)}
    assert asked == [["supply3"]] * 2


def test_verdicts_follow_the_size_of_the_table(spark):
    """From the published size on the verdicts are the published ones; a short table leaves memory out of them."""
    verdicts = lambda dims, nnz: {r["method"]: tuple(r)[1:] for r in cost.scalability(spark, dims, nnz).collect()}
    published = {"column_cd": (1, 1, 1, 1, 1), "subset_als": (1, 1, 1, 1, 1), "full_als": (1, 1, 0, 0, 1), "averaged_sgd": (1, 1, 0, 0, 0), "stratified_sgd": (0, 1, 1, 1, 0)}
    assert verdicts([1_000_000] * 3, 10**8) == published
    short = verdicts([100, 1000, 80], 60_000)
    assert short == published | {"full_als": (1, 1, 1, 0, 1), "averaged_sgd": (1, 1, 1, 1, 0)}
