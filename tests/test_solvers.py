import numpy as np
import pytest
from pyspark.sql import functions as F

import reference
from cubefactor import metrics, synth
from cubefactor.functions.kernels import solve_batch
from cubefactor.functions.schedule import inverse_time
from cubefactor.operators.lineage import written
from cubefactor.operators.tensor import TensorFrame, permute, split
from cubefactor.solvers.baselines import BiasModel, MeanModel, mllib_als
from cubefactor.solvers.sgd import AveragedSGD, StratifiedSGD, sgd_cells
from cubefactor.solvers.subset_als import ColumnCD, FullALS, SubsetALS

DIMS = [12, 7, 5]


@pytest.fixture(scope="module")
def small(spark):
    t = synth.planted(spark, DIMS, 160, 2, 0.05)
    return TensorFrame(written(t.cells, "small"), t.dims)


@pytest.fixture(scope="module")
def arrays(small):
    rows = small.cells.collect()
    return np.array([[r[m] for m in small.modes] for r in rows]), np.array([r["x"] for r in rows])


def dense(model):
    out = [np.zeros((d, model.rank)) for d in model.dims]
    for r in model.factors.collect():
        out[r["mode"] - 1][r["idx"]] = r["f"]
    return out


def close(model, factors, tolerance=1e-8):
    for a, b in zip(dense(model), factors):
        np.testing.assert_allclose(a, b, atol=tolerance)


@pytest.mark.parametrize("storage", ["mode_copies", "single", "none"])
def test_columns_equal_the_reference_under_every_storage(small, arrays, storage):
    model = ColumnCD(2, outer_iters=2, reg_param=0.05, storage=storage, machines=3).fit(small)
    close(model, reference.subset_als(*arrays, DIMS, 2, [[0], [1]] * 2, lam=0.05))


@pytest.mark.parametrize(("width", "groups", "kernel", "solver"), [(2, [[0, 1], [2]], "sql", "cholesky"), (3, [[0, 1, 2]], "arrow", "inverse"), (2, [[0, 1], [2]], "arrow", "lstsq")])
def test_groups_equal_the_reference(small, arrays, width, groups, kernel, solver):
    """Also with a last group that is narrower."""
    model = SubsetALS(3, group_width=width, outer_iters=1, inner_iters=2, reg_param=0.05, column_order="fixed", storage="single", kernel=kernel, solver=solver).fit(small)
    close(model, reference.subset_als(*arrays, DIMS, 3, groups, inner=2, lam=0.05))


def test_plain_penalty_and_unfused_columns(small, arrays):
    model = ColumnCD(2, outer_iters=1, reg_param=0.3, reg="plain", fused=False, storage="single").fit(small)
    close(model, reference.subset_als(*arrays, DIMS, 2, [[0], [1]], lam=0.3, weighted=False))


def test_all_columns_at_once_equal_full_least_squares(small, arrays):
    expected = reference.subset_als(*arrays, DIMS, 3, [[0, 1, 2]], lam=0.05)
    close(FullALS(3, outer_iters=1, reg_param=0.05, storage="single").fit(small), expected)
    close(SubsetALS(3, group_width=3, outer_iters=1, reg_param=0.05, column_order="fixed", storage="single").fit(small), expected)


@pytest.mark.parametrize("how", ["sequential", "random"])
def test_the_result_does_not_depend_on_the_layout(small, arrays, how):
    model = ColumnCD(1, outer_iters=1, reg_param=0.05, machines=5, assignment=how, exchange="dfs").fit(small)
    close(model, reference.subset_als(*arrays, DIMS, 1, [[0]], lam=0.05))


def test_lineage_cuts_and_shuffled_slices_change_nothing(small, arrays):
    model = ColumnCD(2, outer_iters=1, reg_param=0.05, checkpoint_every=1, exchange="join", machines=2).fit(small)
    close(model, reference.subset_als(*arrays, DIMS, 2, [[0], [1]], lam=0.05))


def test_random_order_draws_every_column_once():
    for iteration in range(5):
        groups = SubsetALS(7, group_width=3).column_groups(3, "random", iteration)
        assert sorted(sum(groups, [])) == list(range(7)) and [len(g) for g in groups] == [3, 3, 1]


@pytest.mark.parametrize("reg", ["weighted", "plain"])
def test_loss_never_rises(small, arrays, reg):
    losses = []
    for outer in (1, 2, 3):
        model = SubsetALS(2, group_width=1, outer_iters=outer, reg_param=0.1, reg=reg, column_order="fixed", storage="single").fit(small)
        losses.append(metrics.loss(model, small, 0.1, reg).first()["loss"])
        assert losses[-1] == pytest.approx(reference.loss(dense(model), *arrays, 0.1, reg == "weighted"))
    assert losses == sorted(losses, reverse=True)


def test_two_modes_four_modes_and_renamed_modes(spark):
    for dims in ([9, 8], [6, 5, 4, 3]):
        t = synth.planted(spark, dims, 90, 2, 0.05)
        t = TensorFrame(written(t.cells, "dims"), t.dims)
        rows = t.cells.collect()
        index, x = np.array([[r[m] for m in t.modes] for r in rows]), np.array([r["x"] for r in rows])
        close(ColumnCD(2, outer_iters=1, reg_param=0.05, storage="single").fit(t), reference.subset_als(index, x, dims, 2, [[0], [1]], lam=0.05))
    turned = permute(t, [2, 1, 4, 3])
    assert turned.dims == [5, 6, 3, 4] and turned.cells.count() == t.cells.count()


def test_degenerate_tensors(spark):
    one = TensorFrame(spark.createDataFrame([(0, 0, 3.0)], "i1 long, i2 long, x double"), [2, 2])
    model = FullALS(1, outer_iters=1, reg_param=0.0, solver="lstsq", storage="single").fit(one)
    assert metrics.rmse(model, one.cells) == pytest.approx(0, abs=1e-9)
    assert dense(model)[0][1, 0] == 0  # a row without cells is zero
    assert solve_batch(np.array([[1.0, 1.0, 1.0, 2.0, 2.0, 1.0]]), 2, 0.0, "plain") == pytest.approx(np.array([[1.0, 1.0]]))


@pytest.mark.parametrize("bad", [{"group_width": 5}, {"group_width": 0}, {"reg": "none"}, {"outer_iters": 0}, {"reg_param": -1}, {"storage": "tape"}])
def test_parameters_are_checked(bad):
    with pytest.raises(ValueError):
        SubsetALS(4, **({"group_width": 2} | bad))


def test_replicas_take_no_row_assignment_and_many_strata_are_refused(small):
    with pytest.raises(ValueError):
        AveragedSGD(2, assignment="greedy")
    with pytest.raises(RuntimeError):
        StratifiedSGD(2, machines=30).fit(small)


def test_gradient_cells_equal_the_reference(arrays):
    index, x = arrays
    ours, theirs = reference.start(DIMS, 3, zero_first=False), reference.start(DIMS, 3, zero_first=False)
    divided = reference.start(DIMS, 3, zero_first=False)
    for f in divided:
        f += 0.1
    again = [f.copy() for f in divided]
    sgd_cells(index, x, ours, None, 0.1, 0.02)
    reference.sgd_pass(index, x, theirs, 0.1, 0.02)
    sgd_cells(index, x, divided, None, 0.1, 0.02, "divide")
    sgd_cells(index, x, again, None, 0.1, 0.02)
    for a, b, c, d in zip(ours, theirs, divided, again):
        np.testing.assert_allclose(a, b, atol=1e-12)
        np.testing.assert_allclose(c, d, atol=1e-9)
    assert inverse_time(0.5, 1) == 0.5 and inverse_time(0.5, 3) == 0.25


def test_convergence_order_on_planted_data(spark):
    t = synth.planted(spark, [40, 20, 10], 3000, 3, 0.01)
    train, test = split(TensorFrame(written(t.cells, "order"), t.dims))
    options = {"outer_iters": 4, "reg_param": 0.001}
    error = {
        "full": FullALS(4, storage="single", **options),
        "subset": SubsetALS(4, group_width=2, storage="single", **options),
        "column": ColumnCD(4, storage="single", **options),
        "averaged": AveragedSGD(4, eta0=0.05, machines=4, **options),
        "touched": AveragedSGD(4, eta0=0.05, machines=4, average="touched", split="per_iter", **options),
        "stratified": StratifiedSGD(4, eta0=0.05, machines=2, reg="plain", **options),
    }
    error = {k: metrics.rmse(s.fit(train), test) for k, s in error.items()}
    mean = MeanModel().fit(train)
    floor = mean.predict(test).agg(F.sqrt(F.avg((F.col("x") - F.col("prediction")) ** 2))).first()[0]
    assert error["full"] <= error["subset"] * 1.1 <= error["column"] * 1.2 < error["averaged"]
    assert error["stratified"] < error["averaged"] < floor and error["touched"] < floor
    assert BiasModel().fit(train).predict(test).agg(F.avg("prediction")).first()[0] is not None


def test_matrix_solver_of_spark_agrees_in_accuracy(spark):
    t = synth.planted(spark, [30, 20], 500, 2, 0.01)
    t = TensorFrame(written(t.cells, "matrix"), t.dims)
    ours = metrics.rmse(FullALS(2, outer_iters=6, reg_param=0.001, storage="single").fit(t), t.cells)
    theirs = mllib_als(t, 2, 8, 0.001).transform(t.cells.select(F.col("i1").cast("int"), F.col("i2").cast("int"), "x"))
    error = theirs.agg(F.sqrt(F.avg((F.col("x") - F.col("prediction")) ** 2))).first()[0]
    assert ours < 0.05 and error < 0.1


def test_early_stop_and_trace(small):
    model = ColumnCD(1, outer_iters=9, reg_param=0.05, tol=1e-3, storage="single").fit(small)
    assert 2 <= len(model.trace) < 9 and all(t["status"] == "ok" for t in model.trace)
