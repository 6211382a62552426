import numpy as np
import pytest

from dense_tucker.model.decomposition import Decomposition
from dense_tucker.model.meta import TensorMeta
from dense_tucker.operators import blocks as B
from dense_tucker.operators import cells as C
from dense_tucker.operators import decompose as D
from dense_tucker.operators.stage_metrics import observed
from dense_tucker.plans.planner import STRATEGIES, strategy

SHAPE = (6, 5, 4)


@pytest.fixture(scope="module")
def array():
    return np.random.default_rng(0).integers(-5, 6, SHAPE).astype(float)


@pytest.mark.parametrize("grid", [(1, 1, 1), (2, 2, 1), (3, 1, 2)])
def test_block_products(spark, array, grid):
    t = B.distribute(C.from_array(spark, array), SHAPE, grid)
    assert np.array_equal(B.collect_array(t), array)
    a = np.random.default_rng(1).integers(-2, 3, (4, 5)).astype(float)
    want = np.einsum("kj,ijl->ikl", a, array)
    assert np.array_equal(B.collect_array(B.ttm(t, 1, a)), want)
    assert np.array_equal(B.collect_array(B.regrid(t, (1, 3, 2))), array)
    assert np.allclose(B.gram(t, 0), np.einsum("ijk,ljk->il", array, array))


def test_cells_agree_with_numpy(spark, array):
    cells = C.from_array(spark, array)
    a = np.random.default_rng(2).normal(size=(3, 4))
    want = np.einsum("kl,ijl->ijk", a, array)
    assert np.allclose(C.as_array(C.ttm(cells, 2, C.matrix_frame(spark, a)), (6, 5, 3)), want)
    assert np.allclose(C.as_array(C.ttm_fibers(C.to_fibers(cells, 2), 2, a), (6, 5, 3)), want)
    assert np.array_equal(C.as_array(C.fold(C.unfold(cells, 1, SHAPE), 1, SHAPE), SHAPE), array)


def reference_sweep(x, factors, K):
    new = list(factors)
    for n in range(x.ndim):
        z = x
        for m in range(x.ndim):
            if m != n:
                z = np.moveaxis(np.tensordot(new[m].T, z, (1, m)), 0, m)
        u = np.linalg.svd(np.moveaxis(z, n, 0).reshape(x.shape[n], -1), full_matrices=True)[0]
        new[n] = u[:, : K[n]]
    return new


def test_latest_sweep_is_alternating_update(spark, array):
    meta = TensorMeta(SHAPE, (2, 2, 2))
    start = D.random_init(meta)
    errors = {}
    for name in STRATEGIES:
        made = strategy(meta, 4, name)
        t = B.distribute(C.from_array(spark, array), SHAPE, made.scheme.grids[0])
        dec = D.sweep(t, Decomposition(meta, np.zeros(meta.K), start), made, "frozen")
        errors[name] = [f @ f.T for f in dec.factors]
    for name in STRATEGIES:
        assert all(np.allclose(a, b, atol=1e-8) for a, b in zip(errors[name], errors["chain_K"], strict=True))
    made = strategy(meta, 4, "chain_K")
    t = B.distribute(C.from_array(spark, array), SHAPE, made.scheme.grids[0])
    h = D.sweep_until(t, D.seq_init(t, meta), made, 0.0, 3)
    assert not h.error_increased and h.errors[-1] <= h.errors[0] + 1e-12
    full = D.errors(t, h.best)["rel_error"]
    assert full == pytest.approx(h.best.error, abs=1e-9)
    dec = D.sweep(t, Decomposition(meta, np.zeros(meta.K), start), made, "latest")
    order = [0, 1, 2]
    want = reference_sweep(array, start, meta.K)
    if [c.kind for c in made.tree.children] and order == [0, 1, 2]:
        for f, g in zip(dec.factors, want, strict=True):
            assert np.allclose(f @ f.T, g @ g.T, atol=1e-7)


def test_full_rank_and_storage(spark, array, tmp_path):
    meta = TensorMeta(SHAPE, SHAPE)
    t = B.distribute(C.from_array(spark, array), SHAPE, (2, 1, 2))
    dec = D.seq_init(t, meta)
    assert np.allclose(dec.reconstruct(), array)
    for f in dec.factors:
        assert np.allclose(f.T @ f, np.eye(f.shape[1]))
    dec.save(spark, str(tmp_path / "dec"))
    assert np.allclose(Decomposition.load(spark, str(tmp_path / "dec")).reconstruct(), array)
    got = C.as_array(C.reconstruct(dec.core_frame(spark), dec.factors), SHAPE)
    assert np.allclose(got, array)


def test_measured_sweep(spark, array):
    meta = TensorMeta(SHAPE, (2, 2, 2))
    made = strategy(meta, 4, "opt_dynamic")
    seen = D.Measured()
    t = B.distribute(C.from_array(spark, array), SHAPE, made.scheme.grids[0])
    D.sweep(t, D.seq_init(t, meta), made, measured=seen)
    assert seen.ttms == sum(r["kind"] == "mode" for r in made.rows()) and seen.regrids == made.scheme.regrids and seen.wall_s > 0
    assert (seen.shuffle_bytes > 0) == (seen.moved_elements > 0) and seen.compute_task_s > 0


def test_observed_stages(spark):
    with observed(spark) as quiet:
        spark.range(100).selectExpr("id + 1 as x").write.format("noop").mode("overwrite").save()
    with observed(spark) as busy:
        spark.range(100).repartition(5, "id").write.format("noop").mode("overwrite").save()
    with observed(spark) as idle:
        pass
    assert quiet.stages == 1 and quiet.shuffle_bytes == 0 and quiet.task_s > 0
    assert busy.stages == 2 and busy.shuffle_bytes == busy.read_bytes > 0
    assert idle.stages == 0 and spark.sparkContext.getLocalProperty("spark.jobGroup.id") is None
