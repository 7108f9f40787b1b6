"""Streaming queries over events, drained to batch tables, with SQL twins where the final state is a plain aggregate."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import PRIME, coefficients
from ..operators import sets, signature
from ..sources.io import load, scratch
from ..streaming import streams

K = 8


def _epoch(c: str):
    return F.unix_seconds(F.col(c)).alias("start_s")


def tumbling_counts(spark, sf):
    """Rows per event type and day, complete mode."""
    s = streams.windowed_sets(streams.source(spark, sf), "event_type", "user_id", "1 day")
    return streams.drain(s, "complete").select(_epoch("window.start"), "event_type", "n")


def sliding_counts(spark, sf):
    s = streams.windowed_sets(streams.source(spark, sf), "event_type", "user_id", "2 days", "1 day")
    return streams.drain(s, "complete").select(_epoch("window.start"), "event_type", "n")


def session_counts(spark, sf):
    """Sessions of each user, closed after 30 quiet minutes."""
    s = streams.sessions(streams.source(spark, sf), "user_id", "30 minutes")
    return streams.drain(s, "complete").select(_epoch("session_window.start"), "user_id", "n")


def signature_minima(spark, sf):
    """Running minima of the users of each event type: equal to the batch signature."""
    s = streams.signature_minima(streams.source(spark, sf), "event_type", "user_id", K)
    z = F.array(*(F.col(f"z{j}") for j in range(K)))
    return streams.drain(s, "complete").select("event_type", F.posexplode(z).alias("j", "z")).select("event_type", F.col("j").cast("long").alias("j"), "z")


def window_resemblance(spark, sf):
    """Estimated resemblance of the user sets of adjacent days, from streamed minima per day and type."""
    e = streams.source(spark, sf).select(F.concat_ws(":", "event_type", F.to_date("ts").cast("string")).alias("key"), "user_id")
    rows = streams.drain(streams.signature_minima(e, "key", "user_id", 16), "complete")
    d = rows.select(F.substring_index("key", ":", 1).alias("event_type"), F.to_date(F.substring_index("key", ":", -1)).alias("day"), F.array(*(F.col(f"z{j}") for j in range(16))).alias("z"))
    a, b = d.alias("a"), d.alias("b")
    j = a.join(b, (F.col("a.event_type") == F.col("b.event_type")) & (F.datediff(F.col("b.day"), F.col("a.day")) == 1))
    same = F.size(F.filter(F.zip_with("a.z", "b.z", lambda x, y: (x == y).cast("int")), lambda v: v == 1))
    return j.select(F.col("a.event_type").alias("event_type"), F.col("a.day").cast("string").alias("day"), F.round(same / 16.0, 6).alias("r_hat"))


def late_dropped(spark, sf):
    """Events streamed, stopped, and resumed with the first day's rows ten days late for a watermark of one hour: none of those
    is counted.  Beside it the control: the same files without a watermark, where all of them are."""
    e = load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    path, out, state = (scratch(spark, x) for x in ("late", "late-out", "late-state"))
    e.coalesce(1).write.parquet(path)
    first = e.agg(F.min("ts").alias("t")).first().t
    early = F.col("window.start") < F.lit(first) - F.expr("interval 2 days")

    def run():
        s = streams.from_path(spark, path, e.schema)
        return streams.drain(s.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n")), "append", out=out, state=state)

    run()
    late = e.where(F.to_date("ts") == F.to_date(F.lit(first))).withColumn("ts", F.col("ts") - F.expr("interval 10 days"))
    late.coalesce(1).write.mode("append").parquet(path)
    kept = run().where(early).agg(F.count("*").alias("late_windows"))
    every = streams.drain(streams.from_path(spark, path, e.schema).groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n")), "complete")
    return kept.crossJoin(every.where(early).agg(F.sum("n").alias("late_rows")))  # one row each


def dedup_watermark(spark, sf):
    """Each user and event type once per day, within the watermark."""
    e = streams.source(spark, sf).withColumn("day", F.to_date("ts"))
    return streams.drain(e.withWatermark("ts", "1 hour").dropDuplicates(["user_id", "event_type", "day"]).select("user_id", "event_type", "day", "ts")).select("user_id", "event_type", F.col("day").cast("string").alias("day"))


def static_join(spark, sf):
    """Streamed events against a static table: how often each type's users are among the first ten customers."""
    c = load(spark, sf, "customer").select("c_custkey", "c_mktsegment")
    s = streams.source(spark, sf).join(c, F.col("user_id") == F.col("c_custkey")).groupBy("event_type", "c_mktsegment").agg(F.count("*").alias("n"))
    return streams.drain(s, "complete").select("event_type", "c_mktsegment", "n")


def interval_join(spark, sf):
    """Views followed by a purchase of the same user within an hour, both sides streamed."""
    e = streams.source(spark, sf)
    v = e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "1 hour")
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts").withWatermark("ts", "1 hour")
    j = v.join(p, (F.col("u") == F.col("user_id")) & (F.col("ts") >= F.col("t")) & (F.col("ts") <= F.col("t") + F.expr("interval 1 hour")))
    return streams.drain(j.select("view_id", "purchase_id"))


def stateful_detector(spark, sf):
    """Suppliers' signatures streamed through band state: those that meet an earlier one."""
    path = scratch(spark, "signatures")
    sig = signature.build_full(sets.shingles(load(spark, sf, "documents").select("doc_id", "text")), k=16).select("set_id", "z")
    sig.repartition(2).write.parquet(path)
    return streams.drain(streams.near_duplicate_detector(streams.from_path(spark, path, sig.schema))).distinct()


QUERIES = {f"stream_{f.__name__}": f for f in (tumbling_counts, sliding_counts, session_counts, signature_minima, window_resemblance, late_dropped, dedup_watermark, static_join, interval_join, stateful_detector)}

_CO = lambda k: "(values " + ", ".join(f"({j}, cast({a} as bigint), cast({c} as bigint))" for j, (a, c) in enumerate(coefficients(k))) + ") co(j, ca, cc)"
_S = "cast(epoch(date_trunc('day', ts)) as bigint)"
ORACLES = {
    "stream_tumbling_counts": f"select {_S} as start_s, event_type, count(*) as n from events group by 1, 2",
    "stream_sliding_counts": f"select start_s, event_type, count(*) as n from (select unnest([{_S}, {_S} - 86400]) as start_s, event_type from events) group by 1, 2",
    "stream_session_counts": "with e as (select user_id, ts, case when ts - lag(ts) over w >= interval 30 minutes or lag(ts) over w is null then 1 else 0 end as s from events window w as (partition by user_id order by ts, event_id)), g as (select user_id, ts, sum(s) over (partition by user_id order by ts rows unbounded preceding) as k from e) select cast(floor(epoch(min(ts))) as bigint) as start_s, user_id, count(*) as n from g group by user_id, k",
    "stream_signature_minima": f"select event_type, cast(j as bigint) as j, min((ca*user_id+cc) % {PRIME}) as z from events, {_CO(K)} group by 1, 2",
    "stream_window_resemblance": f"with z as (select event_type, cast(ts as date) as day, j, min((ca*user_id+cc) % {PRIME}) as z from events, {_CO(16)} group by 1, 2, 3) select a.event_type, cast(a.day as varchar) as day, round(sum(case when a.z = b.z then 1 else 0 end)/cast(16 as double), 6) as r_hat from z a join z b on a.event_type = b.event_type and a.j = b.j and b.day = a.day + 1 group by 1, 2",
    "stream_late_dropped": "select cast(0 as bigint) as late_windows, cast(count(*) as bigint) as late_rows from events where cast(ts as date) = (select min(cast(ts as date)) from events)",
    "stream_dedup_watermark": "select distinct user_id, event_type, cast(cast(ts as date) as varchar) as day from events",
    "stream_static_join": "select event_type, c_mktsegment, count(*) as n from events join customer on c_custkey = user_id group by 1, 2",
    "stream_interval_join": "select v.event_id as view_id, p.event_id as purchase_id from events v join events p on v.user_id = p.user_id and v.event_type = 'view' and p.event_type = 'purchase' and p.ts >= v.ts and p.ts <= v.ts + interval 1 hour",
}
