"""Streaming queries; their batch twins are the oracles."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..model.meta import TensorMeta
from ..plans.planner import strategy
from ..sources import builders as S
from ..sources.files import new_path
from ..streaming import events as E

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def stream(s, d, late: int = 0):
    """Staged events, a slice at a time."""
    path = E.stage(s, d, late)
    return E.read(s, path, E.files_of_slice(s, path))


def _ntz(column: str):
    return F.col(column).cast("timestamp_ntz")


def tumbling(s, d):
    agg = stream(s, d).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    return E.drain(agg, "complete").select(_ntz("window.start").alias("start"), "event_type", "n")


add("stream_tumbling_cells", tumbling, "select date_trunc('hour', ts) as start, event_type, count(*) as n from events group by 1, 2")


def sliding(s, d):
    agg = stream(s, d).groupBy(F.window("ts", "6 hours", "1 hour")).agg(F.count("*").alias("n"))
    return E.drain(agg, "complete").select(_ntz("window.start").alias("start"), "n")


add("stream_sliding_cells", sliding, "select date_trunc('hour', ts) - to_hours(k::int) as start, count(*) as n from events, (select unnest(range(6)) as k) group by 1")


def session(s, d):
    agg = stream(s, d).groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"))
    return E.drain(agg, "complete").select("user_id", _ntz("session_window.start").alias("start"), "n")


add("stream_session_users", session, "select user_id, min(ts) as start, count(*) as n from (select *, sum(new_) over (partition by user_id order by ts, event_id rows unbounded preceding) as k from (select *, coalesce((ts >= lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes)::int, 1) as new_ from events)) group by user_id, k")


def late(s, d):
    """Windows closed by a one-hour watermark while one row in 20 comes a file late: such rows are dropped and counted."""
    agg = stream(s, d, 20).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    out = E.drain(agg, "append").agg(F.sum("n").alias("kept"), F.count("*").alias("days"))
    return out.withColumn("all_rows", F.lit(S.read(s, d, "events").count()))


#: A row is late where its day ended an hour or more before the latest time in files but the one before (late rows are told by the watermark before the current one); a day counts once the last watermark has passed it.
_LATE_SQL = """
with placed as (select event_id, ts, least(4, least(4, datediff('day', date '2024-01-01', cast(ts as date)) // 6) + case when event_id % 20 = 0 then 1 else 0 end) as slot from events),
marks as (select slot, (select max(ts) from placed p where p.slot < s.slot - 1) - interval 1 hour as mark from (select distinct slot from placed) s),
kept as (select date_trunc('day', ts) + interval 1 day as stop from placed join marks using (slot) where mark is null or date_trunc('day', ts) + interval 1 day > mark)
select cast(count(*) as bigint) as kept, count(distinct stop) as days, (select count(*) from events) as all_rows from kept where stop <= (select max(ts) - interval 1 hour from placed)
"""
add("stream_watermark_late", late, _LATE_SQL)


def dedup(s, d):
    path = E.stage(s, d)
    s.read.parquet(path).where("event_id % 3 = 0").write.mode("append").parquet(path)
    return E.drain(E.read(s, path).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


add("stream_dedup", dedup, "select event_id, user_id from events")


def static_join(s, d):
    words = s.createDataFrame([(v, i) for i, v in enumerate(S.EVENTS)], "event_type string, idx int")
    return E.drain(stream(s, d).join(F.broadcast(words), "event_type").select("event_id", "idx"))


add("stream_static_join", static_join, "select event_id, (case event_type when 'click' then 0 when 'error' then 1 when 'purchase' then 2 when 'signup' then 3 else 4 end)::int as idx from events")


def stream_join(s, d):
    path = E.stage(s, d)
    a = E.read(s, path).where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("t0")).withWatermark("t0", "1 hour")
    b = E.read(s, path).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("u"), F.col("ts").alias("t1")).withWatermark("t1", "1 hour")
    return E.drain(a.join(b, F.expr("user_id = u and t1 >= t0 and t1 <= t0 + interval 1 hour")).select("click", "purchase"))


add("stream_stream_join", stream_join, "select a.event_id as click, b.event_id as purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour")


def stateful(s, d):
    out = E.drain(E.fibers_by_user(stream(s, d)), "update")
    return out.groupBy("user_id").agg(F.max("total").alias("total"), F.max_by(F.col("fiber")[12], "total").alias("noon"))


add("stream_stateful_fiber", stateful, "select user_id, count(*) as total, count(*) filter (hour(ts) = 12) as noon from events group by 1")


def modes(s, d):
    """Final counts by type under the complete and update modes (the latest update of a key is its count)."""
    path = E.stage(s, d)
    agg = E.read(s, path).groupBy("event_type").agg(F.count("*").alias("n"))
    a = E.drain(agg, "complete").select(F.lit("complete").alias("mode"), "event_type", "n")
    b = E.drain(agg, "update").groupBy("event_type").agg(F.max("n").alias("n")).select(F.lit("update").alias("mode"), "event_type", "n")
    c = E.drain(E.read(s, path).select("event_type"), "append").groupBy("event_type").agg(F.count("*").alias("n")).select(F.lit("append").alias("mode"), "event_type", "n")
    return a.union(b).union(c)


add("stream_output_modes", modes, "select unnest(['complete', 'update', 'append']) as mode, event_type, n from (select event_type, count(*) as n from events group by 1)")
add("stream_incremental_tensor", lambda s, d: E.incremental_cells(stream(s, d)), f"select * from ({S.cells_sql('td4')}) where v <> 0")


def warm(s, d):
    meta = TensorMeta(S.specs()["td"].L, S.specs()["td"].K, "td")
    return s.createDataFrame(E.warm_sweeps(stream(s, d), meta, strategy(meta, 4, "opt_dynamic")), "batch int, rel_error double")


add("stream_warm_sweeps", warm)


def sink(s, d):
    path = new_path(s, "sink")
    E.drain_batches(stream(s, d).select("event_id", "value"), lambda df, n: df.write.mode("overwrite").parquet(f"{path}/batch={n}"))
    return s.read.parquet(path).select("event_id", "value")


add("sink_foreach_batch", sink, "select event_id, value from events")
add("sink_memory", lambda s, d: E.drain_to_memory(stream(s, d).where("event_type = 'signup'").select("event_id")), "select event_id from events where event_type = 'signup'")
