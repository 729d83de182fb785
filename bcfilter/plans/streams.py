"""Streaming queries: each runs over the events file to its end and is compared with the batch result."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.hashing import FilterSpec, hashed, sql_positions
from ..operators import filters
from ..sources.tables import new_path, table, written
from ..streaming import stream
from .base import query

c = F.col

_US = f"""WITH us AS (SELECT DISTINCT user_id AS key FROM events), sp AS (SELECT 6 * count(*) AS m FROM us WHERE key % 5 = 0),
h AS (SELECT key, {sql_positions('key', 3, 'm')} AS positions FROM us, sp), v AS (SELECT list(DISTINCT p) AS ps FROM (SELECT unnest(positions) AS p FROM h WHERE key % 5 = 0)),
e AS (SELECT event_id, ts, user_id, event_type, list_has_all(ps, positions) AS maybe FROM events JOIN h ON key = user_id, v)"""


def _users(spark, sf_dir):
    a = table(spark, sf_dir, "events", ["user_id"]).select(c("user_id").alias("key")).where("key % 5 = 0").distinct()
    spec = FilterSpec(6 * max(1, a.count()), 3)
    return a, spec, written(filters.build_positions(a, spec), "pos")


def _probed(spark, sf_dir):
    _, spec, pos = _users(spark, sf_dir)
    return stream.probe(stream.events(spark, sf_dir), pos, spec, "user_id")


@query("st_probe", _US + " SELECT event_id, user_id, maybe FROM e")
def st_probe(spark, sf_dir):
    return stream.run_available(_probed(spark, sf_dir).select("event_id", "user_id", "maybe"))


@query("st_tumbling", _US + " SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, count(*) AS n, count(*) FILTER (maybe) AS hits FROM e GROUP BY 1")
def st_tumbling(spark, sf_dir):
    return stream.run_available(stream.windowed(_probed(spark, sf_dir), "1 day"), "complete").withColumn("start", c("start").cast("timestamp_ntz"))


@query("st_sliding", _US + ", w AS (SELECT *, unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR, time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 12 HOUR, time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 18 HOUR]) AS start FROM e) SELECT start, count(*) AS n, count(*) FILTER (maybe) AS hits FROM w GROUP BY 1")
def st_sliding(spark, sf_dir):
    return stream.run_available(stream.windowed(_probed(spark, sf_dir), "1 day", "6 hours"), "complete").withColumn("start", c("start").cast("timestamp_ntz"))


@query("st_session", "WITH l AS (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events), g AS (SELECT user_id, ts, sum(CASE WHEN p IS NULL OR ts - p >= INTERVAL 6 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM l) SELECT user_id, min(ts) AS start, count(*) AS n FROM g GROUP BY user_id, s")
def st_session(spark, sf_dir):
    return stream.run_available(stream.sessions(stream.events(spark, sf_dir), "6 hours", "user_id"), "complete").withColumn("start", c("start").cast("timestamp_ntz"))


_LATE = "event_id % 10 = 0 AND ts < (SELECT max(ts) - INTERVAL 3 DAY FROM events)"


@query("st_watermark", f"WITH e AS (SELECT date_trunc('day', ts) AS d, ts, event_id, {_LATE} AS late FROM events), w AS (SELECT max(ts) FILTER (NOT late AND event_id % 10 <> 9) - INTERVAL 1 HOUR AS first, max(ts) - INTERVAL 1 HOUR AS last FROM e) SELECT strftime(d, '%Y-%m-%d') AS day, count(*) AS n FROM e, w WHERE d + INTERVAL 1 DAY <= w.last AND NOT (late AND d + INTERVAL 1 DAY <= w.first) GROUP BY 1")
def st_watermark(spark, sf_dir):
    """Daily counts of three arrivals: every tenth row of more than three days ago comes last, too late for its day.

    A batch drops rows by the watermark of the batch before it, so the second arrival lets that of the first take hold.
    """
    e = table(spark, sf_dir, "events")
    top = e.agg((F.max("ts") - F.expr("interval 3 days")).alias("edge"))
    marked = e.crossJoin(F.broadcast(top)).withColumn("late", (c("event_id") % 10 == 0) & (c("ts") < c("edge"))).drop("edge")
    at = new_path(spark, "arrivals")
    for part in (~c("late") & (c("event_id") % 10 != 9), ~c("late") & (c("event_id") % 10 == 9), c("late")):
        marked.where(part).drop("late").coalesce(1).write.mode("append").parquet(at)
    arrivals = spark.readStream.schema(stream.EVENTS).option("maxFilesPerTrigger", 1).parquet(at).withColumn("ts", c("ts").cast("timestamp"))
    return stream.run_available(stream.daily(arrivals))


@query("st_online_b", "WITH d AS (SELECT user_id AS key, count(*) AS degree FROM events WHERE user_id IS NOT NULL GROUP BY 1), o AS (SELECT *, row_number() OVER (ORDER BY degree DESC, key) AS ord FROM d) SELECT key, degree, ord FROM o WHERE ord <= (SELECT greatest(1, CAST(floor(0.1 * count(*) + 0.5) AS BIGINT)) FROM d)")
def st_online_b(spark, sf_dir):
    """The most frequent tenth of the keys, kept up to date by batch."""
    return stream.OnlineTop(spark, 0.1).run(stream.events(spark, sf_dir).where("user_id is not null"), "user_id")


@query("st_degree", "SELECT user_id, count(*) AS degree FROM events GROUP BY 1")
def st_degree(spark, sf_dir):
    return stream.run_available(stream.degree(stream.events(spark, sf_dir), "user_id"), "complete")


@query("st_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def st_dedup(spark, sf_dir):
    return stream.run_available(stream.dedup(stream.events(spark, sf_dir), ["user_id", "event_type"]).select("user_id", "event_type"))


@query("st_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 1800000000 WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def st_join(spark, sf_dir):
    a = stream.events(spark, sf_dir).where("event_type = 'click'").select(c("event_id").alias("a"), "user_id", c("ts").alias("ta"))
    b = stream.events(spark, sf_dir).where("event_type = 'purchase'").select(c("event_id").alias("b"), "user_id", c("ts").alias("tb"))
    return stream.run_available(stream.interval_join(a, b, "user_id", 1800))


@query("st_union", f"WITH us AS (SELECT DISTINCT user_id AS key FROM events WHERE user_id % 5 = 0), sp AS (SELECT 6 * count(*) AS m FROM us) SELECT DISTINCT unnest({sql_positions('key', 3, 'm')}) AS pos FROM us, sp")
def st_union(spark, sf_dir):
    _, spec, _ = _users(spark, sf_dir)
    growing = stream.GrowingFilter(spark, spec)
    stream.by_batch(stream.events(spark, sf_dir).where("user_id % 5 = 0"), lambda df, n: growing.add(df, n, "user_id"))
    return filters.positions_of(growing.bitmap())


@query("st_reclear", _US + " SELECT count(DISTINCT user_id) FILTER (maybe AND user_id % 5 <> 0) AS fp, CAST(0 AS BIGINT) AS fp_left FROM e")
def st_reclear(spark, sf_dir):
    """After a batch with beta 1 no false positive of the stream is left."""
    a, spec, pos = _users(spark, sf_dir)
    state = stream.RunningClear(spark, pos, a, spec, 1.0)
    stream.by_batch(stream.events(spark, sf_dir), lambda df, n: state.add(df, n, "user_id"))
    u = table(spark, sf_dir, "events", ["user_id"]).select(c("user_id").alias("key")).distinct().where("key % 5 <> 0")
    from ..operators import clearing

    before = filters.probe_negative(u, pos, spec).agg(F.count_if("maybe").alias("fp"))
    return before.crossJoin(filters.probe_negative(u, clearing.reset_bits(pos, state.cleared()), spec).agg(F.count_if("maybe").alias("fp_left")))
