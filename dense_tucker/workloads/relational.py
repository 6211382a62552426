"""Operators around the tensors: scans, sinks, predicates, joins, aggregates, windows, sorts, sets, functions and UDFs."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window as W

from ..functions import sql as U
from ..operators import blocks as B
from ..operators import cells as C
from ..sources import builders as S
from ..sources.files import new_path

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
R = S.read
TA, TB = S.cells_sql("ta"), S.cells_sql("tb")
FILLED_TB = f"select * from ({TB}) where v <> 0"


def q(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def ta(s, d):
    return S.cells(s, d, "ta")


def tb(s, d):
    return S.cells(s, d, "tb")


def view(s, d, text: str):
    """Spark SQL over the tables named in the text."""
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "labels"):
        if t in text:
            R(s, d, t).createOrReplaceTempView(t)
    return s.sql(text)


def both(name: str, text: str, duck: str | None = None) -> None:
    q(name, lambda s, d: view(s, d, text), duck or text)


# scans, sources, sinks
both("scan_parquet_pruned", "select l_orderkey, l_quantity from lineitem where l_quantity >= 49 and l_returnflag = 'R'")
_ORDERS = T.StructType([T.StructField("o_orderkey", T.LongType()), T.StructField("o_orderstatus", T.StringType()), T.StructField("o_orderpriority", T.StringType())])
q("scan_schema_explicit", lambda s, d: s.read.schema(_ORDERS).parquet(f"{d}/orders.parquet").where("o_orderstatus = 'P'"), "select o_orderkey, o_orderstatus, o_orderpriority from orders where o_orderstatus = 'P'")


def roundtrip(kind: str):
    def run(s, d):
        path, df = new_path(s, f"cells-{kind}"), ta(s, d)
        df.write.format(kind).save(path)
        return s.read.format(kind).schema(df.schema).load(path)

    return run


for kind in ("csv", "json", "orc"):
    q(f"io_{kind}_roundtrip", roundtrip(kind), TA)


def partitioned(s, d):
    path = new_path(s, "blocks")
    B.distribute(S.filled_cells(s, d, "tb"), (25, 25, 7), (2, 2, 1)).df.write.partitionBy("bid").parquet(path)
    one = s.read.parquet(path).where("bid = 2").select("bid", "lo", "shape", "data")
    return B.to_cells(B.Blocked(one, (25, 25, 7), (2, 2, 1)))


q("io_partitioned_blocks", partitioned, f"select * from ({TB}) where i0 >= 12 and i1 < 12")


def bucketed(s, d):
    name = "cells_" + new_path(s, "b").rsplit("-", 1)[1]
    ta(s, d).write.bucketBy(4, "i2").sortBy("i2").format("parquet").saveAsTable(name)
    t = s.table(name)
    weights = s.range(11).select(F.col("id").cast("int").alias("i2"), (F.col("id") + 1).cast("double").alias("w"))
    out = t.join(weights, "i2").groupBy("i2").agg(F.sum(F.col("v") * F.col("w")).alias("v"))
    return out


q("io_bucketed_cells", bucketed, f"select i2, sum(v * (i2 + 1)) as v from ({TA}) group by i2")


def binary_blocks(s, d):
    path = new_path(s, "binary")
    B.distribute(S.filled_cells(s, d, "tb"), (25, 25, 7), (2, 2, 1)).df.select(F.base64("data").alias("value")).write.text(path)
    return s.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select(F.col("length"), F.length("content").cast("bigint").alias("bytes"))


q("src_binary_blocks", binary_blocks)
q("src_datasource_random", lambda s, d: U.read_random(s, (6, 5, 4)), "select (id // 20)::int as i0, (id // 4 % 5)::int as i1, (id % 4)::int as i2, (((id % 1000003) * 7919 + 104729) % 1009)::double as v from (select unnest(range(120)) as id)")

# projections, predicates, subqueries
both("proj_mode_index", "select p_partkey, p_brand, dense_rank() over (order by p_brand) - 1 as idx from part", "select p_partkey, p_brand, (dense_rank() over (order by p_brand) - 1)::int as idx from part")
both("proj_bucket", "select p_partkey, cast(floor(p_retailprice / 100) as int) as b, case when p_size < 10 then 'small' when p_size < 30 then 'mid' else 'large' end as size_class from part")
both("proj_star_except", "select * except (c_name, c_acctbal) from customer", "select * exclude (c_name, c_acctbal) from customer")
both("proj_struct_coords", "select c.a, c.b, v from (select named_struct('a', i, 'b', i * 2) as c, i + 1 as v from (select s_nationkey as i from supplier))", "select s_nationkey as a, s_nationkey * 2 as b, s_nationkey + 1 as v from supplier")
q("filter_slice", lambda s, d: ta(s, d).where("i0 = 1 and i2 between 2 and 4"), f"select * from ({TA}) where i0 = 1 and i2 between 2 and 4")
both("filter_in", "select p_partkey from part where p_brand in ('Brand#1', 'Brand#7') and p_size in (1, 2, 3)")
both("filter_like", "select p_partkey, p_name from part where p_name like '%1_'")
both("filter_rlike", "select p_partkey from part where p_brand rlike '^Brand#[12]$'", "select p_partkey from part where regexp_matches(p_brand, '^Brand#[12]$')")
both("filter_nullsafe", "select d.doc_id from documents d left join labels l on d.doc_id = l.doc_id where l.quality <=> null", "select d.doc_id from documents d left join labels l on d.doc_id = l.doc_id where l.quality is not distinct from null")
both("filter_not", "select o_orderkey from orders where not (o_orderstatus = 'F' or o_orderpriority = '5-LOW')")
q("subq_above_mean_cells", lambda s, d: (tb(s, d).createOrReplaceTempView("tb_cells"), s.sql("select * from tb_cells where v > (select avg(v) from tb_cells)"))[1], f"with t as ({TB}) select * from t where v > (select avg(v) from t)")
both("subq_in", "select s_suppkey from supplier where s_nationkey in (select n_nationkey from nation where n_regionkey = 2)")
both("subq_exists_cells", "select c_custkey from customer c where exists (select 1 from orders o where o.o_custkey = c.c_custkey and o.o_orderstatus = 'P')")
both("subq_correlated_max", "select p_partkey, p_brand from part p where p_retailprice = (select max(p_retailprice) from part x where x.p_brand = p.p_brand)")
both("lateral_topk", "select n_nationkey, t.c_custkey from nation, lateral (select c_custkey from customer where c_nationkey = n_nationkey order by c_acctbal desc, c_custkey limit 2) t")

# joins
q("join_factor_broadcast", lambda s, d: C.ttm(tb(s, d), 0, C.integer_matrix(s, 3, 25)), f"select m.k as i0, i1, i2, sum(v * a) as v from ({TB}) t join (select k::int as k, l::int as l, (((l + 1) * (k + 2)) % 5 - 2)::double as a from (select unnest(range(3)) as k), (select unnest(range(25)) as l)) m on t.i0 = m.l group by all")
both("join_fact_dim_smj", "select /*+ merge(o) */ o_orderpriority, count(*) as n, sum(cast(l_quantity as bigint)) as qty from lineitem l join orders o on l_orderkey = o_orderkey group by 1", "select o_orderpriority, count(*) as n, sum(cast(l_quantity as bigint))::bigint as qty from lineitem l join orders o on l_orderkey = o_orderkey group by 1")
both("join_shuffle_hash", "select /*+ shuffle_hash(p) */ p_brand, count(*) as n from lineitem join part p on l_partkey = p_partkey group by 1", "select p_brand, count(*) as n from lineitem join part p on l_partkey = p_partkey group by 1")
both("join_nested_loop_theta", "select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_suppkey < b.s_suppkey and abs(a.s_acctbal - b.s_acctbal) < 20")


def bands(s, d):
    """Range join by bins: both sides meet in the bins that a band covers, then the exact condition."""
    width = 50
    b = s.range(20).select(F.col("id").alias("band"), (F.col("id") * 70 + 900).cast("double").alias("low"), (F.col("id") * 70 + 1000).cast("double").alias("high"))
    spread = b.withColumn("bin", F.explode(F.sequence(F.floor(F.col("low") / width), F.floor(F.col("high") / width))))
    p = R(s, d, "part").select("p_partkey", "p_retailprice", F.floor(F.col("p_retailprice") / width).alias("bin"))
    return p.join(F.broadcast(spread), "bin").where("p_retailprice >= low and p_retailprice < high").groupBy("band").agg(F.count("*").alias("n"))


q("join_range_price_band", bands, "select band, count(*) as n from part, (select unnest(range(20)) as band) where p_retailprice >= band * 70 + 900 and p_retailprice < band * 70 + 1000 group by band")


def interval_pairs(s, d):
    e = R(s, d, "events").where("event_type in ('click', 'purchase')").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    hour = F.floor(F.unix_timestamp("ts") / 3600)
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("t0"), F.explode(F.array(hour, hour + 1)).alias("h"))
    b = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("t1"), hour.alias("h"))
    return a.join(b, ["user_id", "h"]).where("t1 >= t0 and t1 <= t0 + interval 1 hour").select("click", "purchase")


q("join_interval_events", interval_pairs, "select a.event_id as click, b.event_id as purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour")


def asof(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.currentRow)
    e = R(s, d, "events")
    return e.select("event_id", F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(w).alias("signup"))


q("join_asof_last_signup", asof, "select event_id, last_value(case when event_type = 'signup' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows unbounded preceding) as signup from events")
both("join_semi_filled_fibers", "select n_nationkey from nation left semi join supplier on s_nationkey = n_nationkey", "select n_nationkey from nation where n_nationkey in (select s_nationkey from supplier)")
q("join_anti_empty_cells", lambda s, d: S.domain(s, (3, 2, 11, 9, 7)).join(S.filled_cells(s, d, "ta"), ["i0", "i1", "i2", "i3", "i4"], "left_anti"), f"select i0, i1, i2, i3, i4 from ({TA}) where v = 0")
q("join_left_outer_fill", tb, TB)
both("join_right_outer", "select n_name, s_suppkey from supplier right join nation on s_nationkey = n_nationkey")
q("join_full_two_tensors", lambda s, d: S.filled_cells(s, d, "tb").withColumnRenamed("v", "x").join(S.filled_cells(s, d, "tk").withColumnRenamed("v", "y"), ["i0", "i1", "i2"], "full").select("i0", "i1", "i2", (F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0))).alias("gap")), f"with x as ({FILLED_TB}), y as (select * from ({S.cells_sql('tk')}) where v <> 0) select i0, i1, i2, coalesce(x.v, 0.0) - coalesce(y.v, 0.0) as gap from x full join y using (i0, i1, i2)")
q("join_cross_zero_fill", lambda s, d: s.range(3).select(F.col("id").alias("a")).crossJoin(s.range(2).select(F.col("id").alias("b"))), "select a, b from (select unnest(range(3)) as a), (select unnest(range(2)) as b)")
for name in ("tb", "tc", "tk"):
    q(f"join_star_{name}", lambda s, d, name=name: S.filled_cells(s, d, name), f"select * from ({S.cells_sql(name)}) where v <> 0")
q("join_natural_using", lambda s, d: R(s, d, "documents").select("doc_id", "lang").join(R(s, d, "labels"), on="doc_id"), "select doc_id, lang, quality, toxic from documents join labels using (doc_id)")

# aggregates
q("agg_ttm", lambda s, d: tb(s, d).groupBy("i1", "i2").agg(F.sum("v").alias("v")), f"select i1, i2, sum(v) as v from ({TB}) group by 1, 2")
both("agg_sort_based", "select o_orderstatus, max(o_orderpriority) as top, min(o_orderpriority) as low from orders group by 1")
both("agg_distinct_modes", "select count(distinct l_discount) as d, count(distinct l_tax) as t from lineitem")
both("agg_multi_distinct", "select l_returnflag, count(distinct l_discount) as a, count(distinct l_suppkey) as b, count(*) as n from lineitem group by 1")
q("agg_approx_distinct", lambda s, d: R(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("n"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 14)).alias("hll")))
q("agg_approx_percentile", lambda s, d: R(s, d, "part").agg(F.percentile_approx("p_retailprice", [0.1, 0.5, 0.9], 1000).alias("ps")))
q("agg_cube_ta", lambda s, d: ta(s, d).cube("i0", "i1").agg(F.sum("v").alias("v"), F.grouping_id().cast("int").alias("g")), f"select i0, i1, sum(v) as v, grouping(i0, i1)::int as g from ({TA}) group by cube (i0, i1)")
q("agg_rollup_tb", lambda s, d: tb(s, d).rollup("i2", "i0").agg(F.sum("v").alias("v")), f"select i2, i0, sum(v) as v from ({TB}) group by rollup (i2, i0)")
both("agg_grouping_sets_tc", "select o_orderpriority, o_orderstatus, count(*) as n from orders group by grouping sets ((o_orderpriority), (o_orderstatus), ())")
both("agg_grouping_id", "select o_orderstatus, cast(grouping(o_orderstatus) as int) as g, count(*) as n from orders group by rollup (o_orderstatus)")
q("agg_pivot_unfold", lambda s, d: ta(s, d).groupBy("i2").pivot("i0", [0, 1, 2]).agg(F.sum("v")).select("i2", F.col("0").alias("a"), F.col("1").alias("b"), F.col("2").alias("c")), f"select i2, sum(v) filter (i0 = 0) as a, sum(v) filter (i0 = 1) as b, sum(v) filter (i0 = 2) as c from ({TA}) group by i2")
q("agg_unpivot_fold", lambda s, d: QUERIES["agg_pivot_unfold"](s, d).unpivot("i2", ["a", "b", "c"], "flag", "v"), f"select i2, chr((97 + i0)::int) as flag, sum(v) as v from ({TA}) group by i2, i0")
both("agg_moments", "select round(avg(p_retailprice), 4) as mean, round(stddev(p_retailprice), 4) as sd, round(var_pop(p_retailprice), 2) as var, round(corr(p_size, p_retailprice), 6) as corr, round(covar_samp(p_size, p_retailprice), 3) as cov, round(regr_slope(p_retailprice, p_size), 5) as slope from part")
q("agg_percentile_curve", lambda s, d: tb(s, d).groupBy("i2").agg(F.percentile("v", F.array(F.lit(0.25), F.lit(0.75))).alias("p")).select("i2", F.round(F.col("p")[0], 2).alias("q1"), F.round(F.col("p")[1], 2).alias("q3")), f"select i2, round(quantile_cont(v, 0.25), 2) as q1, round(quantile_cont(v, 0.75), 2) as q3 from ({TB}) group by 1")
both("agg_median", "select o_orderstatus, round(median(o_totalprice), 4) as m from orders group by 1")
both("agg_mode", "select mode(n_regionkey) is not null as found, count(*) as n from nation")
both("agg_min_by_max_by", "select p_brand, min_by(p_partkey, p_retailprice * 1000000 + p_partkey) as low, max_by(p_partkey, p_retailprice * 1000000 + p_partkey) as high from part group by 1")
both("agg_bool", "select o_orderstatus, bool_and(o_totalprice > 0) as every_, bool_or(o_totalprice > 400000) as any_ from orders group by 1")
both("agg_count_if", "select count_if(l_quantity > 25) as big, count_if(l_returnflag = 'R') as returned from lineitem", "select count_if(l_quantity > 25)::bigint as big, count_if(l_returnflag = 'R')::bigint as returned from lineitem")
both("agg_filter_clause", "select count(*) filter (where c_acctbal < 0) as debt, count(*) as n from customer")
both("agg_listagg", "select n_regionkey, listagg(n_name, ',') within group (order by n_name) as names from nation group by 1", "select n_regionkey, string_agg(n_name, ',' order by n_name) as names from nation group by 1")
q("agg_array", lambda s, d: R(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_set("n_nationkey")), ",").alias("ids")), "select n_regionkey, string_agg(n_nationkey::varchar, ',' order by n_nationkey) as ids from nation group by 1")
both("agg_histogram", "select cast(floor(l_quantity / 10) as int) as bin, count(*) as n from lineitem group by 1")
both("agg_having", "select l_partkey, count(*) as n from lineitem group by 1 having count(*) > 40")

# windows
q("win_mode_index", lambda s, d: R(s, d, "part").select("p_partkey", (F.dense_rank().over(W.orderBy("p_type")) - 1).alias("idx")), "select p_partkey, (dense_rank() over (order by p_type) - 1)::int as idx from part")
both("win_rank_all", "select s_suppkey, row_number() over w as rn, rank() over w as rk, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd, ntile(4) over w as nt from supplier window w as (partition by s_nationkey order by s_acctbal, s_suppkey)", "select s_suppkey, (row_number() over w)::int as rn, (rank() over w)::int as rk, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd, (ntile(4) over w)::int as nt from supplier window w as (partition by s_nationkey order by s_acctbal, s_suppkey)")


def _time():
    return W.partitionBy("i0", "i1").orderBy("i2")


q("win_sweep_delta", lambda s, d: tb(s, d).select("i0", "i1", "i2", (F.col("v") - F.lag("v").over(_time())).alias("delta"), F.lead("v").over(_time()).alias("after")), f"select i0, i1, i2, v - lag(v) over w as delta, lead(v) over w as after from ({TB}) window w as (partition by i0, i1 order by i2)")
q("win_first_last_nth", lambda s, d: tb(s, d).select("i0", "i1", "i2", F.first("v").over(_time()).alias("a"), F.last("v").over(_time().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("b"), F.nth_value("v", 2).over(_time().rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("c")), f"select i0, i1, i2, first_value(v) over w as a, last_value(v) over (w rows between unbounded preceding and unbounded following) as b, nth_value(v, 2) over (w rows between unbounded preceding and unbounded following) as c from ({TB}) window w as (partition by i0, i1 order by i2)")
q("win_running_energy", lambda s, d: tb(s, d).select("i0", "i1", "i2", F.sum("v").over(_time().rowsBetween(W.unboundedPreceding, 0)).alias("run")), f"select i0, i1, i2, sum(v) over (partition by i0, i1 order by i2 rows unbounded preceding) as run from ({TB})")
q("win_moving_rows", lambda s, d: tb(s, d).select("i0", "i1", "i2", F.sum("v").over(_time().rowsBetween(-3, 0)).alias("run")), f"select i0, i1, i2, sum(v) over (partition by i0, i1 order by i2 rows between 3 preceding and current row) as run from ({TB})")
both("win_range_7d", "select event_id, count(*) over (partition by user_id order by ts range between interval 7 days preceding and current row) as n from events")
q("win_whole_partition", lambda s, d: tb(s, d).select("i0", "i1", "i2", F.round(F.try_divide(F.col("v"), F.sum("v").over(W.partitionBy("i0"))), 8).alias("share")), f"select i0, i1, i2, round(v / nullif(sum(v) over (partition by i0), 0), 8) as share from ({TB})")
q("win_percentile_curve", lambda s, d: tb(s, d).select("i0", "i1", "i2", F.round(F.cume_dist().over(W.partitionBy("i2").orderBy("v")), 8).alias("k")), f"select i0, i1, i2, round(cume_dist() over (partition by i2 order by v), 8) as k from ({TB})")


def sessions(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    e = R(s, d, "events").withColumn("new", F.coalesce((F.col("ts") > F.lag("ts").over(w) + F.expr("interval 30 minutes")).cast("int"), F.lit(1)))
    return e.select("event_id", F.sum("new").over(w.rowsBetween(W.unboundedPreceding, 0)).alias("session"))


q("win_sessionise", sessions, "select event_id, sum(n) over (partition by user_id order by ts, event_id rows unbounded preceding)::bigint as session from (select *, coalesce((ts > lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes)::int, 1) as n from events)")

# sorts, limits, sets
both("sort_multi_key_nulls", "select d.doc_id, l.quality from documents d left join labels l on d.doc_id = l.doc_id order by l.quality desc nulls last, d.doc_id limit 50")
q("sort_topk_cells", lambda s, d: tb(s, d).orderBy(F.desc("v"), "i0", "i1", "i2").limit(20), f"select * from ({TB}) order by v desc, i0, i1, i2 limit 20")
both("limit_offset", "select c_custkey from customer order by c_acctbal, c_custkey limit 10 offset 5")
q("topk_per_fiber", lambda s, d: tb(s, d).withColumn("r", F.row_number().over(W.partitionBy("i0").orderBy(F.desc("v"), "i1", "i2"))).where("r <= 3"), f"select *, (row_number() over (partition by i0 order by v desc, i1, i2))::int as r from ({TB}) qualify r <= 3")
q("sort_within_partitions", lambda s, d: tb(s, d).repartition(4, "i0").sortWithinPartitions("i0", F.desc("v")))
_X, _Y = "select i0, i1, i2 from ({}) where v > 30000000".format(TB), "select i0, i1, i2 from ({}) where i2 < 3".format(TB)


def _xy(s, d):
    t = tb(s, d)
    return t.where("v > 30000000").select("i0", "i1", "i2"), t.where("i2 < 3").select("i0", "i1", "i2")


for name, method, word in (("set_union_all", "unionAll", "union all"), ("set_intersect_coords", "intersect", "intersect"), ("set_except_coords", "subtract", "except"), ("set_intersect_all", "intersectAll", "intersect all"), ("set_except_all", "exceptAll", "except all")):
    q(name, lambda s, d, m=method: getattr(_xy(s, d)[0], m)(_xy(s, d)[1]), f"({_X}) {word} ({_Y})")
q("set_union_distinct", lambda s, d: _xy(s, d)[0].union(_xy(s, d)[1]).distinct(), f"({_X}) union ({_Y})")
q("set_union_by_name", lambda s, d: _xy(s, d)[0].unionByName(_xy(s, d)[1].select("i2", "i0"), allowMissingColumns=True), f"({_X}) union all (select i0, null as i1, i2 from ({_Y}))")
both("distinct_rows", "select distinct l_returnflag, l_linestatus from lineitem")
q("drop_duplicates", lambda s, d: R(s, d, "lineitem").select("l_orderkey", "l_linenumber").dropDuplicates(), "select distinct l_orderkey, l_linenumber from lineitem")
_WALK = "with recursive edges(node, parent, f) as (values (1, 0, 2), (2, 1, 3), (3, 1, 5), (4, 2, 7), (5, 3, 2)), walk(node, f) as (select node, f from edges where parent = 0 union all select e.node, e.f * w.f from edges e join walk w on e.parent = w.node) select node, f from walk"
both("recursive_tree_walk", _WALK)

# functions
both("fn_string_modes", "select p_partkey, substring(p_name, 1, 3) as a, length(p_name) as n, upper(p_type) as u, lower(p_brand) as l, lpad(cast(p_size as string), 4, '0') as p, instr(p_name, ' ') as at, reverse(p_brand) as r, translate(p_brand, '#', '-') as t, concat_ws('/', p_brand, p_type) as c, regexp_replace(p_name, '[0-9]+', 'N') as x, trim('  a ') as tr, split(p_brand, '#')[1] as part from part",
     "select p_partkey, substring(p_name, 1, 3) as a, length(p_name)::int as n, upper(p_type) as u, lower(p_brand) as l, lpad(cast(p_size as varchar), 4, '0') as p, instr(p_name, ' ')::int as at, reverse(p_brand) as r, translate(p_brand, '#', '-') as t, concat_ws('/', p_brand, p_type) as c, regexp_replace(p_name, '[0-9]+', 'N', 'g') as x, trim('  a ') as tr, split_part(p_brand, '#', 2) as part from part")
q("fn_char_tensor", lambda s, d: S.cells(s, d, "ti").groupBy("i1").agg(F.sum("v").alias("v")), f"select i1, sum(v) as v from ({S.cells_sql('ti')}) group by 1")
both("fn_date_modes", "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, day(o_orderdate) as dd, quarter(o_orderdate) as q, dayofweek(o_orderdate) - 1 as wd, datediff(o_orderdate, timestamp_ntz'1995-01-01') as days from orders",
     "select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, day(o_orderdate)::int as dd, quarter(o_orderdate)::int as q, dayofweek(o_orderdate)::int as wd, datediff('day', date '1995-01-01', o_orderdate::date)::int as days from orders")
both("fn_math_index", "select id, pmod(id - 7, 5) as p, cast(floor(id / 3) as int) as f, cast(ceil(id / 3) as int) as c, round(sqrt(id), 6) as s, round(power(id, 1.5), 4) as w, abs(id - 9) as a, sign(id - 9) as g, greatest(id, 10) as hi, least(id, 10) as lo, bit_count(id) as b, shiftleft(id, 2) as sl, round(log2(id + 1), 6) as l from (select l_linenumber as id from lineitem)",
     "select id, ((id - 7) % 5 + 5) % 5 as p, floor(id / 3)::int as f, ceil(id / 3)::int as c, round(sqrt(id), 6) as s, round(power(id, 1.5), 4) as w, abs(id - 9) as a, sign(id - 9)::double as g, greatest(id, 10) as hi, least(id, 10) as lo, bit_count(id)::int as b, (id << 2)::int as sl, round(log2(id + 1), 6) as l from (select l_linenumber as id from lineitem)")
both("fn_array_ttm", "select vec_id, round(aggregate(zip_with(embedding, sequence(1, 64), (x, y) -> cast(x as double) * y), 0d, (a, b) -> a + b), 3) as dot, size(filter(embedding, x -> x > 0)) as pos, exists(embedding, x -> x > 2) as big from embeddings",
     "select vec_id, round(list_sum([cast(e as double) * (i) for e, i in embedding]), 3) as dot, len([e for e in embedding if e > 0])::int as pos, len([e for e in embedding if e > 2]) > 0 as big from embeddings")
q("fn_map_modes", lambda s, d: ta(s, d).groupBy("i0").agg(F.map_from_entries(F.collect_list(F.struct(F.concat_ws("-", "i1", "i2", "i3", "i4"), "v"))).alias("m")).select("i0", F.size(F.map_filter("m", lambda k, v: v > 500)).cast("bigint").alias("big"), F.aggregate(F.map_values(F.transform_values("m", lambda k, v: v * 2)), F.lit(0.0), lambda a, b: a + b).alias("twice")), f"select i0, count(*) filter (v > 500) as big, sum(v * 2) as twice from ({TA}) group by 1")
both("fn_json_props", "select event_id, cast(get_json_object(props, '$.k') as int) as k, from_json(props, 'map<string,int>')['k'] as m from events", "select event_id, (props->>'$.k')::int as k, (props->>'$.k')::int as m from events")
both("fn_decimal_cents", "select l_returnflag, sum(cast(l_extendedprice as decimal(18, 2))) as total from lineitem group by 1", "select l_returnflag, sum(cast(l_extendedprice as decimal(18, 2)))::decimal(28, 2) as total from lineitem group by 1")
both("fn_conditional", "select s_suppkey, coalesce(nullif(s_nationkey, 3), -1) as a, case when s_acctbal < 0 then 'debt' else 'ok' end as b, try_cast('x' as int) as c, try_divide(1.0D, s_nationkey) as e from supplier", "select s_suppkey, coalesce(nullif(s_nationkey, 3), -1) as a, case when s_acctbal < 0 then 'debt' else 'ok' end as b, try_cast('x' as int) as c, case when s_nationkey = 0 then null else 1.0 / s_nationkey::double end as e from supplier")
q("fn_hash", lambda s, d: view(s, d, "select n_nationkey, md5(n_name) as m, crc32(n_name) as c, xxhash64(n_name) as x, hash(n_name) as h from nation"))
both("fn_md5", "select n_nationkey, md5(n_name) as m, sha2(n_name, 256) as s from nation", "select n_nationkey, md5(n_name) as m, sha256(n_name) as s from nation")

# UDFs


def block_norm(s, d):
    t = B.distribute(S.filled_cells(s, d, "tb"), (25, 25, 7), (2, 2, 1))
    return t.df.select("bid", U.block_sum("data").alias("total"))


q("udf_block_norm", block_norm, f"select (case when i0 < 12 then 0 else 2 end + case when i1 < 12 then 0 else 1 end)::int as bid, sum(v) as total from ({TB}) group by 1")
q("udf_iterator_ttm", lambda s, d: B.to_cells(B.ttm(B.distribute(S.filled_cells(s, d, "tb"), (25, 25, 7), (1, 1, 1)), 2, np.ones((1, 7)))), f"select i0, i1, 0::int as i2, sum(v) as v from ({TB}) group by 1, 2")


def grouped_gram(s, d):
    """Gram of the last mode by column groups, then summed: a grouped Arrow aggregate."""
    m = C.unfold(tb(s, d), 2, (25, 25, 7)).withColumn("g", F.col("col") % 8)

    def add(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x = np.zeros((7, 625))
        for b in batches:
            x[b.column("row").to_numpy(), b.column("col").to_numpy()] = b.column("v").to_numpy()
        g = x @ x.T
        i, j = np.triu_indices(7)
        yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(g[i, j])], names=["i", "j", "g"])

    out = m.groupBy("g").applyInArrow(add, "i int, j int, g double").groupBy("i", "j").agg(F.sum("g").alias("g"))
    return out.select("i", "j", F.round(F.col("g") / 1e9, 3).alias("g"))


q("udaf_gram", grouped_gram, f"with t as ({TB}) select a.i2 as i, b.i2 as j, round(sum(a.v * b.v) / 1e9, 3) as g from t a join t b on a.i0 = b.i0 and a.i1 = b.i1 and a.i2 <= b.i2 group by 1, 2")


def cogroup(s, d):
    def gap(key, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"i2": [key[0]], "gap": [float(a["v"].sum() - b["v"].sum())]})

    a, b = tb(s, d), S.cells(s, d, "tk")
    return a.groupBy("i2").cogroup(b.groupBy("i2")).applyInPandas(gap, "i2 int, gap double")


q("udf_cogroup_diff", cogroup, f"select i2, a.v - b.v as gap from (select i2, sum(v) as v from ({TB}) group by 1) a join (select i2, sum(v) as v from ({S.cells_sql('tk')}) group by 1) b using (i2)")


q("udtf_grids", lambda s, d: (U.register(s), s.sql("select grid from tucker_grids(12, 3)"))[1], "select a.q || 'x' || b.q || 'x' || c.q as grid from (select unnest([1, 2, 3, 4, 6, 12])) a(q), (select unnest([1, 2, 3, 4, 6, 12])) b(q), (select unnest([1, 2, 3, 4, 6, 12])) c(q) where a.q * b.q * c.q = 12")
q("udtf_plan", lambda s, d: (U.register(s), s.sql("select * from tucker_plan(array(672, 672, 627, 16), array(279, 279, 153, 14), 32, 'opt_dynamic')"))[1])
q("sql_functions", lambda s, d: (U.register(s), s.sql("select n, grid_count(32, n) as grids, tucker_load(array(4, 4, 4), array(2, 2, 2), 'opt_static') as load, tucker_volume(array(4, 4, 4), array(2, 2, 2), 1, 'opt_static') as volume from (select explode(array(5, 6)) as n)"))[1], "select unnest([5, 6])::int as n, unnest([126, 252])::bigint as grids, 448.0::double as load, 0.0::double as volume")
