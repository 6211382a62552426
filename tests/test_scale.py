"""Guards, reductions and distributed forms of the engine and the planner."""

from dataclasses import replace
from itertools import permutations
from math import prod

import numpy as np
import pytest

from dense_tucker.model.decomposition import Decomposition
from dense_tucker.model.meta import NAMED, TensorMeta
from dense_tucker.operators import blocks as B
from dense_tucker.operators import cells as C
from dense_tucker.operators import decompose as D
from dense_tucker.plans import grids as G
from dense_tucker.plans import optimal, trees
from dense_tucker.plans.planner import STRATEGIES, strategy
from dense_tucker.sources import builders as S
from dense_tucker.streaming import events as E
from dense_tucker.workloads import experiments as X


def test_repeated_cells_are_summed(spark):
    cells = spark.createDataFrame([(0, 0, 1.0), (0, 0, 2.0), (1, 2, 5.0)], "i0 int, i1 int, v double")
    assert B.collect_array(B.distribute(cells, (2, 3), (1, 2))).tolist() == [[3, 0, 0], [0, 0, 5]]


def test_half_gram_in_strips(spark, monkeypatch):
    x = np.random.default_rng(0).normal(size=(37, 9, 4))
    t = B.distribute(C.from_array(spark, x), x.shape, (2, 3, 1))
    monkeypatch.setattr(B, "_cuts", lambda n, columns, size=100: [(i, min(n, i + 5)) for i in range(0, n, 5)])
    for mode in range(3):
        m = np.moveaxis(x, mode, 0).reshape(x.shape[mode], -1)
        assert np.allclose(B.gram(t, mode), m @ m.T)
        a, s = B.left_svd(t, mode, 3)
        b, r = B.left_svd(t, mode, 3, "distributed")
        assert np.allclose(s, r) and np.allclose(np.abs(np.diag(a.T @ b)), 1, atol=1e-4)


def test_long_modes_go_by_iteration(spark, monkeypatch):
    monkeypatch.setattr(B, "GRAM_LENGTH", 10)
    x = np.random.default_rng(1).normal(size=(12, 5))
    t = B.distribute(C.from_array(spark, x), x.shape, (2, 1))
    with pytest.raises(ValueError, match="distributed"):
        B.gram(t, 0)
    assert np.allclose(B.left_svd(t, 0, 3)[1], np.linalg.svd(x)[1][:3])
    with pytest.raises(ValueError, match="blocks"):
        C.gram(C.from_array(spark, np.zeros((600, 1))), 0, (600, 1))


def test_shared_matrices_are_bounded(spark, monkeypatch):
    monkeypatch.setattr(B, "SHARED_BYTES", 100)
    t = B.distribute(C.from_array(spark, np.ones((4, 5))), (4, 5), (1, 1))
    with pytest.raises(ValueError, match="at most 100"):
        B.ttm(t, 0, np.ones((4, 4)))


def test_whole_modes_keep_the_blocks(spark):
    t = B.distribute(C.from_array(spark, np.ones((6, 8, 4))), (6, 8, 4), (6, 2, 1))
    for mode in range(3):
        grid = B._whole_mode_grid(t, mode)
        assert grid[mode] == 1 and prod(grid) == 12 and all(q <= n for q, n in zip(grid, t.shape, strict=True))
    tight = B.Blocked(t.df, (6, 2, 2), (6, 2, 1))
    with pytest.warns(UserWarning, match="no grid of 12 blocks"):
        assert prod(B._whole_mode_grid(tight, 0)) == 4


def test_reconstruction_by_blocks(spark):
    rng = np.random.default_rng(2)
    dec = Decomposition(TensorMeta((6, 5, 4), (2, 3, 2)), rng.normal(size=(2, 3, 2)), [rng.normal(size=(n, k)) for n, k in ((6, 2), (5, 3), (4, 2))])
    t = B.reconstruct(spark, dec.core, dec.factors, (3, 2, 1))
    assert t.df.count() == 6 and np.allclose(B.collect_array(t), dec.reconstruct())


def test_sweeps_go_on_from_a_checkpoint(spark, tmp_path):
    x = np.random.default_rng(3).normal(size=(6, 5, 4))
    meta = TensorMeta(x.shape, (2, 2, 2))
    made = strategy(meta, 4, "opt_dynamic")
    t = B.distribute(C.from_array(spark, x), meta.L, made.scheme.grids[0])
    start = D.initial(t, meta, "random")
    whole = D.sweep_until(t, start, made, 0.0, 3)
    D.sweep_until(t, start, made, 0.0, 2, checkpoint=str(tmp_path / "run"))
    assert D.saved_sweeps(spark, str(tmp_path / "run")) == [1, 2]
    rest = D.sweep_until(t, start, made, 0.0, 3, checkpoint=str(tmp_path / "run"))
    assert len(rest.errors) == 2 and rest.errors == pytest.approx(whole.errors[2:])


def test_best_chain_order():
    rng = np.random.default_rng(4)
    for _ in range(200):
        shapes = {m: (int(rng.integers(1, 12)), int(rng.integers(1, 12))) for m in range(4)}

        def cost(order, shapes=shapes):
            size, total = prod(n for _, n in shapes.values()), 0.0
            for m in order:
                k, n = shapes[m]
                total += k * size
                size = size / n * k
            return total

        assert cost(C.best_order(shapes)) == pytest.approx(min(map(cost, permutations(shapes))))


@pytest.mark.parametrize("rule", ["full", "children_only"])
def test_distributed_dynamic_grids(spark, rule):
    for meta, p in ((TensorMeta((25, 25, 7), (8, 8, 4)), 16), (TensorMeta((8, 6, 4, 5), (4, 2, 4, 3)), 12), (NAMED["HCCI"], 8)):
        for tree in (optimal.optimal_tree(meta)[0], trees.chain_tree(list(range(meta.n)))):
            one, two = G.best_dynamic_scheme(tree, meta, p, rule), G.best_dynamic_scheme_distributed(spark, tree, meta, p, rule)
            assert one.total == two.total and one.grids == two.grids
    assert sorted(tuple(r["q"]) for r in G.grid_frame(spark, TensorMeta((9,) * 3, (4, 8, 2)), 12).collect()) == [tuple(map(int, g)) for g in G.enumerate_grids(12, 3, (4, 8, 2))]


def numpy_sweep(x, factors, K, order):
    """Alternating update of the factors in this order, by full singular value decompositions."""
    new = list(factors)
    for n in order:
        z = x
        for m in range(x.ndim):
            if m != n:
                z = np.moveaxis(np.tensordot(new[m].T, z, (1, m)), 0, m)
        new[n] = np.linalg.svd(np.moveaxis(z, n, 0).reshape(x.shape[n], -1), full_matrices=True)[0][:, : K[n]]
    core = x
    for m, f in enumerate(new):
        core = np.moveaxis(np.tensordot(f.T, core, (1, m)), 0, m)
    return new, float(np.sqrt(max(0.0, (x**2).sum() - (core**2).sum()) / (x**2).sum()))


@pytest.mark.parametrize("name", ["ta", "tb", "td"])
def test_sweeps_of_the_tables_equal_numpy(spark, small, name):
    L, K = S.specs()[name].L, S.specs()[name].K
    meta = TensorMeta(L, K, name)
    x = C.as_array(S.filled_cells(spark, small, name), L)
    for which in STRATEGIES:
        made = strategy(meta, 4, which)
        t = B.distribute(S.filled_cells(spark, small, name), L, made.scheme.grids[0])
        start = Decomposition(meta, np.zeros(K), D.random_init(meta))
        dec = D.sweep(t, start, made, "latest")
        order = [n.mode for *_, n in made.tree.walk() if n.kind == "leaf"]
        want, error = numpy_sweep(x, start.factors, K, order)
        assert D.errors(t, dec, "norms")["rel_error"] == pytest.approx(error, abs=1e-9)
        assert D.errors(t, dec)["rel_error"] == pytest.approx(error, abs=1e-9)
        for f, g in zip(dec.factors, want, strict=True):
            assert np.allclose(f @ f.T, g @ g.T, atol=1e-6)


def test_rows_outside_the_domain_are_counted(spark, small):
    for name in ("tb", "tl"):
        row = S.outside_rows(spark, small, name).first()
        assert row["outside"] == 0 and row["facts"] > 0
    assert S.lengths(spark, small, "tl")[0] == S.read(spark, small, "pages").selectExpr("count(distinct regexp_extract(url, '://([^/?#]+)', 1))").first()[0]


def test_shrunk_benchmark():
    for n in (5, 6):
        metas = X.shrunk(n, 20)
        assert len({(m.L, m.K) for m in metas}) == 20 and all(m.n == n and m.cardinality() <= 500_000 for m in metas)
        assert all(len(G.valid_grids(m, 32)) for m in metas)


def test_streams_end_in_files(spark, small):
    stream = E.read(spark, E.stage(spark, small))
    rows = E.drain(stream.select("event_id"))
    assert rows.inputFiles() and rows.count() == S.read(spark, small, "events").count()


def test_shared_folder_is_asked_for(spark, monkeypatch):
    from types import SimpleNamespace

    from dense_tucker.sources.files import new_path

    far = SimpleNamespace(conf=SimpleNamespace(get=lambda *a: None), sparkContext=SimpleNamespace(getCheckpointDir=lambda: None, master="spark://far:7077"))
    with pytest.raises(ValueError, match="checkpoint"):
        new_path(far, "x")


def test_squeezing_an_overlong_mode_keeps_all_errors(spark):
    x = np.random.default_rng(5).normal(size=(70, 3, 4)) * np.linspace(1, 3, 4)
    for shape, mode in (((70, 3, 4), 0), ((3, 70, 4), 1)):
        y = np.moveaxis(x, 0, mode)
        meta = TensorMeta(shape, tuple(40 if m == mode else 2 for m in range(3)))
        for grid in ((1, 1, 2), (3, 2, 1)):
            t = B.distribute(C.from_array(spark, y), y.shape, grid)
            s, small = D.squeezed(t, meta)
            assert s.shape[mode] == 12 and small.K[mode] == 12
            z = B.collect_array(s)
            assert np.isclose((z**2).sum(), (x**2).sum()) and all(np.allclose(B.gram(s, m), B.gram(t, m)) for m in range(3) if m != mode)
            order = optimal.seq_init_order(meta)[0]
            assert D.errors(s, D.seq_init(s, small, order), "norms")["rel_error"] == pytest.approx(D.errors(t, D.seq_init(t, meta, order))["rel_error"], abs=1e-9)
    meta = TensorMeta(x.shape, (3, 2, 2))
    t = B.distribute(C.from_array(spark, x), x.shape, (2, 1, 1))
    s, small = D.squeezed(t, meta)
    for policy in ("latest", "frozen"):
        made, order = strategy(meta, 2, "opt_dynamic"), optimal.seq_init_order(meta)[0]
        a = D.sweep_until(t, D.seq_init(t, meta, order), made, 0.0, 2, policy)
        b = D.sweep_until(s, D.seq_init(s, small, order), replace(made, meta=small), 0.0, 2, policy)
        assert a.errors == pytest.approx(b.errors, abs=1e-9)
    square = B.distribute(C.from_array(spark, x), x.shape, (2, 1, 1))
    assert B.squeeze(square, 1) is square


def test_kept_tensors_have_no_tasks_without_blocks(spark):
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "64")
    try:
        t = B.distribute(C.from_array(spark, np.ones((6, 8))), (6, 8), (2, 1)).persist()
        assert t.df.rdd.getNumPartitions() <= 4 and t.df.count() == 2
        t.unpersist()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


@pytest.mark.parametrize("rows", [500_000, 60])
def test_late_rows_do_not_hang_on_the_number_of_files(spark, small, tmp_path, monkeypatch, rows):
    import duckdb

    from dense_tucker.workloads import streams

    monkeypatch.setattr(E, "FILE_ROWS", rows, raising=False)
    S.read(spark, small, "events").repartition(3).write.parquet(f"{tmp_path}/events.parquet")
    c = duckdb.connect()
    c.sql(f"create view events as select * from '{tmp_path}/events.parquet/*.parquet'")
    assert tuple(streams.late(spark, str(tmp_path)).first()) == c.sql(streams.ORACLES["stream_watermark_late"]).fetchall()[0]
