"""Queries of the streaming forms over a file stream of events, against batch SQL."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.estimate import Spec
from ..sources.sketches import scratch
from ..streaming import streams as S
from . import oracle as O
from .registry import register
from .workloads import table

BASE = Spec(k=64, family="md5_60", tighten="none", on_short="count")


def _stream(s: SparkSession, d: str) -> DataFrame:
    s.conf.set("spark.sql.session.timeZone", "UTC")
    return S.events(s, S.spread(s, f"{d}/events.parquet"))


def st_sample(s, d):
    stream = _stream(s, d).select(F.col("user_id").alias("lk"), F.col("event_id").alias("jk"))
    return S.drain(S.stream_sample(stream, "lk", 0.25, "SL1:"), "sample").distinct()


register("st_sample", st_sample, f"select user_id as lk, event_id as jk from events where {O.digest(chr(39) + 'SL1:' + chr(39), 'user_id')} < {2**58}")


def st_estimate(s, d):
    running = S.RunningEstimate(s, scratch(s, "running"), replace(BASE, policy="fixed", p=1 / 32), 1 / 32)
    rows = _stream(s, d).select(F.col("user_id").alias("keep"), F.date_trunc("hour", "ts").alias("on"))
    S.drain(rows, "estimate", each=running.add)
    return running.result().select("kept", "kth_hash", F.round("z_hat").cast("long").alias("z_hat"))


register("st_estimate", st_estimate, f"select kept, kth_hash, z_hat from ({O.estimate('user_user_hour', 64, 'fixed', 1 / 32, short='e.kept / th.p')})")

_DAY = "select cast(date_trunc('day', ts) as timestamp) as start, count(*) as n from events where date_trunc('day', ts) + interval 1 day <= (select max(ts) - interval 1 day from events) group by 1"
register("st_tumbling", lambda s, d: S.drain(S.windowed_counts(_stream(s, d), "1 day"), "tumbling").select(F.col("start").cast("timestamp_ntz").alias("start"), "n"), _DAY)


def st_sliding(s, d):
    return S.drain(S.windowed_counts(_stream(s, d), "2 hours", "1 hour"), "sliding").select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


register(
    "st_sliding", st_sliding,
    "select start, count(*) as n from (select unnest([date_trunc('hour', ts), date_trunc('hour', ts) - interval 1 hour]) as start from events) where start + interval 2 hour <= (select max(ts) - interval 1 day from events) group by 1",
)


def st_session(s, d):
    out = S.drain(S.session_counts(_stream(s, d), "6 hours"), "session")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


register(
    "st_session", st_session,
    "select user_id, min(ts) as start, count(*) as n from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as g from (select *, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval 6 hour then 0 else 1 end as fresh from events)) "
    "group by user_id, g having max(ts) + interval 6 hour <= (select max(ts) - interval 1 day from events)",
)


def st_dedup(s, d):
    pairs = _stream(s, d).withWatermark("ts", "1 day").select("user_id", "event_type", "ts")
    return S.drain(pairs.dropDuplicates(["user_id", "event_type"]).select("user_id", "event_type"), "dedup")


register("st_dedup", st_dedup, "select distinct user_id, event_type from events")


def st_join(s, d):
    stream = _stream(s, d)
    kinds = sorted(r[0] for r in table(s, d, "events").select("event_type").distinct().collect())
    return S.drain(S.stream_join(stream.where(F.col("event_type") == kinds[0]), stream.where(F.col("event_type") == kinds[1]), "2 hours"), "join")


register(
    "st_join", st_join,
    "with k as (select list_sort(list(distinct event_type)) as k from events) select a.event_id as a_id, b.event_id as b_id from events a join events b on a.user_id = b.user_id and b.ts between a.ts and a.ts + interval 2 hour, k where a.event_type = k.k[1] and b.event_type = k.k[2]",
)


def st_static_join(s, d):
    users = table(s, d, "customer").select("c_custkey", "c_mktsegment")
    return S.drain(_stream(s, d).join(users, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"), "static")


register("st_static_join", st_static_join, "select event_id, c_mktsegment from events join customer on user_id = c_custkey")


def st_windowed_size(s, d):
    old = s.conf.get("spark.sql.streaming.stateStore.providerClass", None)
    s.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        out = S.drain(S.stream_windowed_size(_stream(s, d), 8), "windowed")
    finally:
        if old is None:
            s.conf.unset("spark.sql.streaming.stateStore.providerClass")
        else:
            s.conf.set("spark.sql.streaming.stateStore.providerClass", old)
    return out.select("day", "kept", F.round("z_hat").cast("long").alias("z_hat"))


register(
    "st_windowed_size", st_windowed_size,
    f"with e as (select distinct cast(floor(epoch_ms(ts) / 86400000) as bigint) as day, cast(floor(epoch_ms(ts) / 60000) as bigint) as minute, user_id from events), "
    f"a as (select day, minute, {O.digest(chr(39) + 'L1:' + chr(39), 'user_id')} as x from e), b as (select minute, {O.digest(chr(39) + 'R1:' + chr(39), 'user_id')} as y from e), "
    f"h as (select distinct day, (x - y) & {O.MASK} as h from a join b using (minute)), k as (select *, row_number() over (partition by day order by h) as i from h), "
    f"o as (select day, count(*) as kept, max(h) as kth from k where i <= 8 group by day) select day, kept, cast(round(case when kept >= 8 then {8.0 * 2**60!r}::double / greatest(kth, 1) else kept end) as bigint) as z_hat from o "
    "where (day + 1) * 86400000 <= (select epoch_ms(max(ts)) - 3600000 from events)",
)


def st_late(s, d):
    """The first day again after all others: its rows are behind the watermark and fall out of the window."""
    path = scratch(s, "late")
    e = table(s, d, "events")
    first = e.agg(F.min("ts").alias("t")).first()["t"]
    again = e.where(F.col("ts") < F.lit(first) + F.expr("interval 1 day"))
    e.coalesce(1).write.parquet(path)
    stream = S.events(s, path)
    state, out = scratch(s, "late-state"), scratch(s, "late-out")
    for rows in (None, again):
        if rows is not None:
            rows.coalesce(1).write.mode("append").parquet(path)
        counts = S.windowed_counts(stream, "1 day")
        counts.writeStream.trigger(availableNow=True).option("checkpointLocation", state).format("parquet").option("path", out).outputMode("append").start().awaitTermination()
    return s.read.parquet(out).select(F.col("start").cast("timestamp_ntz").alias("start"), "n")


register("st_late", st_late, _DAY)
