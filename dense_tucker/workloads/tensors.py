"""Tensor algebra and decomposition queries."""

from __future__ import annotations

from functools import reduce
from math import prod

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.decomposition import Decomposition
from ..model.meta import TensorMeta
from ..operators import blocks as B
from ..operators import cells as C
from ..operators import decompose as D
from ..plans.planner import STRATEGIES, plan, strategy
from ..sources import builders as S
from ..sources.files import new_path

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
_SPECS = S.specs()


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def keys(n: int) -> str:
    return ", ".join(f"i{k}" for k in range(n))


def matrix_array(k: int, n: int) -> np.ndarray:
    i, j = np.indices((k, n))
    return (((j + 1) * (i + 2)) % 5 - 2).astype(float)


def _matrix_sql(k: int, n: int) -> str:
    return f"(select k::int as k, l::int as l, (((l + 1) * (k + 2)) % 5 - 2)::double as a from (select unnest(range({k})) as k), (select unnest(range({n})) as l))"


def ttm_sql(inner: str, n: int, mode: int, k: int, length: int) -> str:
    rest = ", ".join(f"m.k as i{j}" if j == mode else f"t.i{j}" for j in range(n))
    return f"select {rest}, sum(t.v * m.a) as v from ({inner}) t join {_matrix_sql(k, length)} m on t.i{mode} = m.l group by all"


def chain_sql(name: str, modes: list[int]) -> str:
    spec = _SPECS[name]
    out = S.cells_sql(name)
    for m in modes:
        out = ttm_sql(out, len(spec.L), m, spec.K[m], spec.L[m])
    return out


def meta_of(name: str, spark: SparkSession | None = None, sf_dir: str = "") -> TensorMeta:
    spec = _SPECS[name]
    L = S.lengths(spark, sf_dir, name) if spark is not None else spec.L
    return TensorMeta(L, spec.K, name)


def _matrices(spark: SparkSession, name: str, modes: list[int]) -> dict[int, DataFrame]:
    spec = _SPECS[name]
    return {m: C.integer_matrix(spark, spec.K[m], spec.L[m]) for m in modes}


def _register_cells() -> None:
    for name in ("ta", "tb", "tc", "td", "td4", "te", "tf", "tg", "th", "ti", "tk", "tl"):
        add(f"tensor_{name}_cells", lambda s, d, name=name: S.cells(s, d, name), S.cells_sql(name))
    add("tensor_tj_filled", lambda s, d: S.filled_cells(s, d, "tj"), f"select i0, i1, i2, cast(sum(v) as double) as v from ({S.facts_sql('tj')}) where i0 between 0 and 199 and i1 between 0 and 199 and i2 between 0 and 82 group by i0, i1, i2")
    for name, modes in (("ta", range(5)), ("tb", range(3)), ("tc", range(6))):
        spec = _SPECS[name]
        for m in modes:
            add(f"ttm_mode{m + 1}_{name}", lambda s, d, name=name, m=m: C.ttm(S.cells(s, d, name), m, _matrices(s, name, [m])[m]), chain_sql(name, [m]))
        for m in list(modes) if name != "tc" else []:
            others = [k for k in range(len(spec.L)) if k != m]
            add(f"chain_all_but_{m + 1}_{name}", lambda s, d, name=name, o=others: C.ttm_chain(S.cells(s, d, name), _matrices(s, name, o)), chain_sql(name, others))
    add("chain_12", lambda s, d: C.ttm_chain(S.cells(s, d, "tb"), _matrices(s, "tb", [0, 1]), [0, 1]), chain_sql("tb", [1, 0]))
    add("chain_21", lambda s, d: C.ttm_chain(S.cells(s, d, "tb"), _matrices(s, "tb", [0, 1]), [1, 0]), chain_sql("tb", [0, 1]))
    add("core_projection_int", lambda s, d: C.ttm_chain(S.cells(s, d, "tb"), _matrices(s, "tb", [0, 1, 2])), chain_sql("tb", [2, 1, 0]))
    add("ttm_fibers_tb", lambda s, d: C.ttm_fibers(C.to_fibers(S.cells(s, d, "tb"), 2), 2, matrix_array(4, 7)), chain_sql("tb", [2]))

    def blocked(s, d, grid, mode):
        t = B.distribute(S.filled_cells(s, d, "tb"), _SPECS["tb"].L, grid)
        return B.to_cells(B.ttm(t, mode, matrix_array(_SPECS["tb"].K[mode], _SPECS["tb"].L[mode])))

    for tag, grid, mode in (("221_m1", (2, 2, 1), 0), ("221_m3", (2, 2, 1), 2), ("124_m2", (1, 2, 4), 1), ("811_m1", (8, 1, 1), 0)):
        add(f"ttm_blocks_{tag}_tb", lambda s, d, g=grid, m=mode: blocked(s, d, g, m), chain_sql("tb", [mode]))


def _register_layouts() -> None:
    tb = S.cells_sql("tb")
    L = _SPECS["tb"].L
    cols = {0: "i1 * 7 + i2", 1: "i0 * 7 + i2", 2: "i0 * 25 + i1"}
    for m in range(3):
        add(f"unfold_mode{m + 1}_tb", lambda s, d, m=m: C.unfold(S.cells(s, d, "tb"), m, L), f"select i{m} as row, cast({cols[m]} as bigint) as col, v from ({tb})")
    add("fold_roundtrip_tb", lambda s, d: C.fold(C.unfold(S.cells(s, d, "tb"), 1, L), 1, L), tb)
    add(
        "fibers_mode2_tb",
        lambda s, d: C.to_fibers(S.cells(s, d, "tb"), 1).select("i0", "i2", F.size("x").cast("bigint").alias("n"), F.aggregate("x", F.lit(0.0), lambda a, b: a + b).alias("total"), F.element_at("x", 1).alias("first"), F.element_at("x", -1).alias("last")),
        f"select i0, i2, count(*) as n, sum(v) as total, min_by(v, i1) as first, max_by(v, i1) as last from ({tb}) group by i0, i2",
    )
    add(
        "tensor_card_fibers",
        lambda s, d: s.createDataFrame([(n, m + 1, meta_of(n).cardinality(), meta_of(n).fiber_count(m)) for n in ("ta", "tb", "tc", "td") for m in range(len(_SPECS[n].L))], "tensor string, mode int, cells bigint, fibers bigint"),
        " union all ".join(f"select '{n}' as tensor, {m + 1} as mode, cast(count(*) as bigint) as cells, cast(count(*) / {_SPECS[n].L[m]} as bigint) as fibers from ({S.cells_sql(n)})" for n in ("ta", "tb", "tc", "td") for m in range(len(_SPECS[n].L))),
    )
    place = "cast(floor(((i0 + 1) * 2 - 1) / 25) as int) * 2 + cast(floor(((i1 + 1) * 2 - 1) / 25) as int)"

    def sizes(s, d, grid, start=None):
        t = B.distribute(S.filled_cells(s, d, "tb"), L, start or grid)
        t = B.regrid(t, grid)
        n = F.aggregate("shape", F.lit(1).cast("bigint"), lambda a, b: a * b)
        lo = [F.element_at("lo", k + 1).cast("int").alias(f"lo{k}") for k in range(3)]
        sums = B.to_cells(t).groupBy(*[F.expr(f"((i{k} + 1) * {q} - 1) div {length}").alias(f"b{k}") for k, (q, length) in enumerate(zip(grid, L, strict=True))]).agg(F.sum("v").alias("total"))
        at = F.expr("cast((b0 * {1} + b1) * {2} + b2 as int)".format(*grid))
        return t.df.select("bid", *lo, n.alias("cells")).join(sums.select(at.alias("bid"), "total"), "bid")

    block_sql = f"select cast({place} as int) as bid, min(i0) as lo0, min(i1) as lo1, min(i2) as lo2, count(*) as cells, sum(v) as total from ({tb}) group by 1"
    add("distribute_block_sizes", lambda s, d: sizes(s, d, (2, 2, 1)), block_sql)
    add("regrid_blocks_tb", lambda s, d: sizes(s, d, (2, 2, 1), (1, 3, 4)), block_sql)
    add("regrid_identity_tb", lambda s, d: B.to_cells(B.regrid(B.distribute(S.filled_cells(s, d, "tb"), L, (4, 1, 2)), (1, 5, 3))), tb)
    add("filter_subblock", lambda s, d: S.cells(s, d, "tb").where("i0 between 12 and 24 and i1 between 0 and 11"), f"select * from ({tb}) where i0 between 12 and 24 and i1 between 0 and 11")


def gram_sql(name: str, mode: int, digits: int | None = None) -> str:
    n = len(_SPECS[name].L)
    same = " and ".join(f"a.i{k} = b.i{k}" for k in range(n) if k != mode)
    g = "sum(a.v * b.v)" if digits is None else f"round(sum(a.v * b.v), {digits})"
    return f"with t as ({S.cells_sql(name)}) select a.i{mode} as i, b.i{mode} as j, {g} as g from t a join t b on {same} and a.i{mode} <= b.i{mode} group by 1, 2"


def _gram_blocks(s, d, name, mode, grid):
    L = S.lengths(s, d, name)
    g = B.gram(B.distribute(S.filled_cells(s, d, name), L, grid), mode)
    return s.createDataFrame([(i, j, float(g[i, j])) for i in range(len(g)) for j in range(i, len(g))], "i int, j int, g double")


def _register_spectra() -> None:
    for name, modes in (("ta", range(5)), ("td", range(3))):
        for m in modes:
            add(f"gram_mode{m + 1}_{name}", lambda s, d, name=name, m=m: C.gram(S.cells(s, d, name), m, _SPECS[name].L), gram_sql(name, m))
    add("gram_blocks_ta", lambda s, d: _gram_blocks(s, d, "ta", 2, (1, 1, 2, 3, 1)), gram_sql("ta", 2))
    add("gram_self_join", lambda s, d: C.gram(S.cells(s, d, "tf"), 0, _SPECS["tf"].L), gram_sql("tf", 0))
    for m in (1, 2):
        add(f"gram_mode{m + 1}_te", lambda s, d, m=m: C.gram(S.cells(s, d, "te"), m, S.lengths(s, d, "te")).select("i", "j", F.round("g", 4).alias("g")), gram_sql("te", m, 4))

    def two(s, d):
        g = B.gram(B.distribute(S.filled_cells(s, d, "ta"), _SPECS["ta"].L, (1, 2, 1, 1, 1)), 1)
        _, values = B.leading_eigvecs(g, 2)
        return s.createDataFrame([(k + 1, round(float(v / 1e6), 3)) for k, v in enumerate(values)], "k int, value double")

    add(
        "eig_linestatus_ta",
        two,
        f"with g as ({gram_sql('ta', 1)}), e as (select max(g) filter (i = 0 and j = 0) as a, max(g) filter (i = 0 and j = 1) as b, max(g) filter (i = 1) as c from g) "
        "select 1 as k, round(((a + c) / 2 + sqrt(((a - c) / 2) * ((a - c) / 2) + b * b)) / 1e6, 3) as value from e union all select 2, round(((a + c) / 2 - sqrt(((a - c) / 2) * ((a - c) / 2) + b * b)) / 1e6, 3) from e",
    )

    def trace(s, d):
        t = B.distribute(S.filled_cells(s, d, "tb"), _SPECS["tb"].L, (2, 1, 2))
        return s.createDataFrame([(m + 1, float(f"{B.leading_eigvecs(B.gram(t, m), 1)[1].sum():.8e}")) for m in range(3)], "mode int, energy double")

    add("eig_trace_tb", trace, f"select unnest([1, 2, 3]) as mode, cast(format('{{:.8e}}', sum(v * v)) as double) as energy from ({S.cells_sql('tb')})")
    add("agg_norms", lambda s, d: C.norms(S.cells(s, d, "ta")), f"select sum(v * v) as norm2, max(abs(v)) as max_abs, sum(abs(v)) as l1 from ({S.cells_sql('ta')})")

    def solvers(s, d):
        """Squared singular values by subspace iteration, which sum to what the Gram matrix's leading ones do, over the tensor's squared norm; and the angle between the subspaces."""
        t = B.distribute(S.filled_cells(s, d, "tb"), _SPECS["tb"].L, (2, 2, 1)).persist()
        rows = []
        for m in range(3):
            k = _SPECS["tb"].K[m]
            a, x = B.left_svd(t, m, k)
            b, y = B.left_svd(t, m, k, "distributed", oversample=17)
            cosines = np.linalg.svd(a.T @ b, compute_uv=False)
            rows += [(m + 1, i + 1, float(x[i]), float(y[i]), float(cosines[i])) for i in range(k)]
        t.unpersist()
        return s.createDataFrame(rows, "mode int, component int, by_gram double, by_iteration double, cosine double")

    add("svd_distributed_equals_gram", solvers)
    # with all components kept, the squared singular values of any mode sum to the squared norm
    def energies(s, d):
        t = B.distribute(S.filled_cells(s, d, "td"), _SPECS["td"].L, (2, 1, 2)).persist()
        rows = [(m + 1, how, float(f"{(B.left_svd(t, m, _SPECS['td'].L[m], how)[1] ** 2).sum():.6e}")) for m in range(3) for how in ("gram", "distributed")]
        t.unpersist()
        return s.createDataFrame(rows, "mode int, solver string, energy double")

    add("svd_energy_td", energies, f"select mode, solver, cast(format('{{:.6e}}', e) as double) as energy from (select sum(v * v) as e from ({S.cells_sql('td')})), (select unnest([1, 2, 3]) as mode), (select unnest(['gram', 'distributed']) as solver)")


def _blocked(s, d, name, p, strat="opt_dynamic", K=None):
    L = S.lengths(s, d, name)
    meta = TensorMeta(L, K or _SPECS[name].K, name)
    made = strategy(meta, p, strat)
    return meta, made, B.distribute(S.filled_cells(s, d, name), L, made.scheme.grids[0])


def _full(s, d, name, how):
    """A decomposition with K = L gives the tensor back."""
    L = _SPECS[name].L
    meta, made, t = _blocked(s, d, name, 2, K=L)
    dec = D.seq_init(t, meta) if how == "init" else D.sweep(t, D.initial(t, meta, "random"), made, "latest")
    return C.from_array(s, dec.reconstruct()).select(*[f"i{k}" for k in range(len(L))], (F.round("v") + 0.0).alias("v"))


def _sweep_rows(s, d, name, p):
    meta, made, t = _blocked(s, d, name, p)
    h = D.sweep_until(t, D.seq_init(t, meta), made, 0.0, 2)
    return s.createDataFrame([(name, i, float(e), h.error_increased) for i, e in enumerate(h.errors)], "tensor string, sweep int, rel_error double, error_increased boolean")


def _register_decompositions() -> None:
    td = S.cells_sql("td")
    add("seq_init_fullrank", lambda s, d: _full(s, d, "td", "init"), td)
    add("sweep_fullrank", lambda s, d: _full(s, d, "td", "sweep"), td)
    add("fullrank_roundtrip_tb", lambda s, d: _full(s, d, "tb", "init"), S.cells_sql("tb"))
    add("fullrank_padded_th", lambda s, d: _full(s, d, "th", "init"), S.cells_sql("th"))

    def rank_one(s, d):
        spec = _SPECS["ta"]
        base = S.cells(s, d, "ta")
        margins = [base.groupBy(f"i{k}").agg((F.sum("v") % 97 + 1).alias("v")).orderBy(f"i{k}").toPandas()["v"].to_numpy() for k in range(5)]
        x = margins[0]
        for m in margins[1:]:
            x = np.multiply.outer(x, m)
        meta = TensorMeta(spec.L, (1,) * 5, "rank1")
        t = B.distribute(C.from_array(s, x), meta.L, (1, 1, 1, 1, 1))
        dec = D.sweep(t, D.seq_init(t, meta), plan(meta, 1))
        return C.from_array(s, dec.reconstruct()).withColumn("v", F.round("v"))

    margins = ", ".join(f"m{k} as (select i{k}, sum(v) % 97 + 1 as w{k} from t group by i{k})" for k in range(5))
    add("rank1_exact", rank_one, f"with t as ({S.cells_sql('ta')}), {margins} select {keys(5)}, {' * '.join(f'w{k}' for k in range(5))} as v from m0, m1, m2, m3, m4")

    def orthonormal(s, d):
        meta, made, t = _blocked(s, d, "tb", 8)
        dec = D.sweep(t, D.seq_init(t, meta), made)
        rows = [(m + 1, i, j, abs(round(float((f.T @ f)[i, j]), 6))) for m, f in enumerate(dec.factors) for i in range(f.shape[1]) for j in range(f.shape[1])]
        return s.createDataFrame(rows, "mode int, i int, j int, g double")

    add("factor_orthonormal", orthonormal, " union all ".join(f"select {m + 1} as mode, i::int as i, j::int as j, case when i = j then 1.0::double else 0.0::double end as g from (select unnest(range({k})) as i), (select unnest(range({k})) as j)" for m, k in enumerate(_SPECS["tb"].K)))

    def identity(s, d):
        rows = []
        for name, p in (("ta", 4), ("tb", 8), ("td", 4)):
            meta, made, t = _blocked(s, d, name, p)
            dec = D.seq_init(t, meta)
            core = float((dec.core**2).sum())
            lost = (D.errors(t, dec)["rel_error"] ** 2) * D.squared_norm(t)
            rows.append((name, float(f"{core + lost:.8e}")))
        return s.createDataFrame(rows, "tensor string, core_and_gap double")

    add("error_norm_identity", identity, " union all ".join(f"select '{n}' as tensor, cast(format('{{:.8e}}', sum(v * v)) as double) as core_and_gap from ({S.cells_sql(n)})" for n in ("ta", "tb", "td")))
    for name, p in (("ta", 8), ("tb", 8), ("tc", 8), ("td", 4), ("te", 8), ("tf", 4), ("tk", 8)):
        add(f"sweep_{name}", lambda s, d, name=name, p=p: _sweep_rows(s, d, name, p))

    def inits(s, d):
        meta, made, t = _blocked(s, d, "tb", 8)
        rows = []
        for how in ("sequential", "hosvd", "random", "given"):
            dec = D.initial(t, meta, how, D.random_init(meta, 5) if how == "given" else None)
            after = D.sweep(t, dec, made, "latest")
            rows.append((how, D.errors(t, dec, "norms")["rel_error"], D.errors(t, after, "norms")["rel_error"]))
        return s.createDataFrame(rows, "init string, error_before double, error_after double")

    add("init_variants_tb", inits)
    add("seq_init_tb", lambda s, d: D.planned_seq_init(_blocked(s, d, "tb", 8)[2], meta_of("tb"), 8).factor_frame(s))
    add("error_measures_tb", lambda s, d: s.createDataFrame([(k, float(v)) for k, v in (lambda m, p, t: D.errors(t, D.seq_init(t, m)))(*_blocked(s, d, "tb", 8)).items()], "measure string, value double"))
    add("mode_scores_tb", lambda s, d: (lambda m, p, t: D.seq_init(t, m).mode_scores(s, 0))(*_blocked(s, d, "tb", 8)))

    def same(s, d):
        first, rows = None, []
        for name in STRATEGIES:
            meta, made, t = _blocked(s, d, "tb", 8, name)
            dec = D.sweep(t, D.initial(t, meta, "random"), made, "frozen")
            spaces = [f @ f.T for f in dec.factors]
            first = first or spaces
            rows.append((name, max(float(np.abs(a - b).max()) for a, b in zip(spaces, first, strict=True)), float(D.errors(t, dec)["rel_error"])))
        return s.createDataFrame(rows, "strategy string, greatest_gap double, rel_error double")

    add("strategies_agree_tb", same)

    def stored(s, d):
        path = new_path(s, "decomposition")
        L = _SPECS["td"].L
        meta, _, t = _blocked(s, d, "td", 2, K=L)
        D.seq_init(t, meta).save(s, path)
        return C.from_array(s, Decomposition.load(s, path).reconstruct()).withColumn("v", F.round("v") + 0.0)

    add("io_decomposition_roundtrip", stored, td)

    def part(s, d):
        L = _SPECS["td"].L
        meta, _, t = _blocked(s, d, "td", 2, K=L)
        dec = D.seq_init(t, meta)
        out = C.reconstruct_slice(dec.core_frame(s), dec.factors, {1: (2, 4), 2: (0, 6)})
        return out.withColumn("v", F.round("v") + 0.0)

    def rebuilt(s, d):
        meta, _, t = _blocked(s, d, "td", 2, K=_SPECS["td"].L)
        dec = D.seq_init(t, meta)
        return B.to_cells(B.reconstruct(s, dec.core, dec.factors, (2, 1, 3))).withColumn("v", F.round("v") + 0.0)

    add("reconstruct_blocks_td", rebuilt, td)
    best = ("ta", [0, 1, 2, 3])
    add("chain_best_order_ta", lambda s, d: C.ttm_chain(S.cells(s, d, best[0]), _matrices(s, *best), "best", {m: (_SPECS["ta"].K[m], _SPECS["ta"].L[m]) for m in best[1]}), chain_sql(*best))
    add("reconstruct_slice_td", part, f"select * from ({td}) where i1 between 2 and 3 and i2 between 0 and 5")
    names = [n for n in _SPECS if n not in ("te", "ti")]
    add("src_outside_rows", lambda s, d: reduce(DataFrame.unionAll, [S.outside_rows(s, d, n) for n in names]), " union all ".join(S.outside_sql(n) for n in names))
    L = (12, 9, 7)
    add("src_random_tensor", lambda s, d: S.random_cells(s, L), f"select (id // 63)::int as i0, (id // 7 % 9)::int as i1, (id % 7)::int as i2, (((id % 1000003) * 7919 + 104729) % 1009)::double as v from (select unnest(range({prod(L)})) as id)")


_register_cells()
_register_layouts()
_register_spectra()
_register_decompositions()
