"""Structured Streaming forms: probes, windows, degrees, deduplication, clearing and union by micro-batch.

Every function takes a streaming DataFrame and gives one, or a batch function for ``foreachBatch``; ``run_available``
drives a stream over the files at hand to its end and returns the result as a table in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import FilterSpec, hashed
from ..operators import filters
from ..sources.tables import new_path

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str, per_trigger: int = 1) -> DataFrame:
    """The events table as a stream of its files, with event time ``ts``."""
    src = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
    return src.withColumn("ts", F.col("ts").cast("timestamp"))


def run_available(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All files at hand, then stop; results go to Parquet, in complete mode the last batch's over those before."""
    spark = stream.sparkSession
    at = new_path(spark, "stream")
    out = stream.writeStream.option("checkpointLocation", f"{at}/log").outputMode(mode).trigger(availableNow=True)
    if mode == "append":
        out = out.format("parquet").option("path", f"{at}/out")
    else:
        out = out.foreachBatch(lambda batch, number: batch.write.mode("overwrite").parquet(f"{at}/out"))
    out.start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def probe(stream: DataFrame, pos: DataFrame, spec: FilterSpec, key: str) -> DataFrame:
    """Stream-static probe against broadcast bits: no state, no shuffle."""
    udf = filters.contains_udf(stream.sparkSession, filters.packed_bits(pos, spec))
    from ..functions.hashing import positions

    return stream.withColumn("maybe", udf(positions(key, spec)))


def windowed(stream: DataFrame, length: str, slide: str | None = None, late: str = "1 hour", keys: list[str] | None = None) -> DataFrame:
    """Rows and positive probes by tumbling or sliding window."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    out = stream.withWatermark("ts", late).groupBy(w.alias("w"), *(keys or [])).agg(F.count("*").alias("n"), F.count_if("maybe").alias("hits"))
    return out.select(F.col("w.start").alias("start"), *(keys or []), "n", "hits")


def daily(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """Rows by day, given out once the watermark has passed the day; rows of a day that has been passed are dropped."""
    out = stream.withWatermark("ts", late).groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return out.select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n")


class OnlineTop:
    """Degrees of the keys as a stream's state; each batch writes the troublesome share of them, by degree, anew."""

    def __init__(self, spark: SparkSession, beta: float):
        self.path, self.spark, self.beta = new_path(spark, "top"), spark, beta

    def run(self, stream: DataFrame, key: str) -> DataFrame:
        from ..operators import clearing

        def each(batch: DataFrame, number: int) -> None:
            keys = batch.select(F.col(key).alias("key"), "degree")
            top = clearing.troublesome(keys, self.beta, [F.col("degree").desc(), F.col("key")])
            top.select("key", "degree", "ord").write.mode("overwrite").parquet(f"{self.path}/now")

        counted = degree(stream, key).writeStream.outputMode("complete").foreachBatch(each)
        counted.option("checkpointLocation", f"{self.path}/log").trigger(availableNow=True).start().awaitTermination()
        return self.spark.read.schema("key long, degree long, ord long").parquet(f"{self.path}/now")


def sessions(stream: DataFrame, gap: str, key: str, late: str = "1 hour") -> DataFrame:
    out = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), key).agg(F.count("*").alias("n"))
    return out.select(key, F.col("w.start").alias("start"), "n")


def degree(stream: DataFrame, key: str) -> DataFrame:
    """Running count for each key: the troublesomeness degree, kept as state."""
    return stream.groupBy(key).agg(F.count("*").alias("degree"))


def dedup(stream: DataFrame, keys: list[str], late: str = "40 days") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def interval_join(a: DataFrame, b: DataFrame, on: str, seconds: int, late: str = "1 hour") -> DataFrame:
    """Rows of two streams with the same key within ``seconds``; both sides drop state by watermark."""
    a, b = a.withWatermark("ta", late), b.withWatermark("tb", late)
    near = (a[on] == b[on]) & (F.col("ta") >= F.col("tb") - F.expr(f"interval {seconds} seconds")) & (F.col("ta") <= F.col("tb") + F.expr(f"interval {seconds} seconds"))
    return a.join(b, near).select("a", "b")


def by_batch(stream: DataFrame, each) -> None:
    """Run ``each(batch, number)`` over the files at hand."""
    at = new_path(stream.sparkSession, "stream")
    stream.writeStream.foreachBatch(each).option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start().awaitTermination()


class GrowingFilter:
    """Filter that batches add members to: each batch's bitmap is a version directory; the state is their OR."""

    def __init__(self, spark: SparkSession, spec: FilterSpec):
        self.spark, self.spec, self.path, self.versions = spark, spec, new_path(spark, "versions"), 0

    def add(self, batch: DataFrame, number: int, key: str) -> None:
        members = batch.select(F.col(key).alias("key")).where("key is not null").distinct()
        filters.build_bitmap(members, self.spec).write.mode("overwrite").parquet(f"{self.path}/version={number}")
        self.versions = number + 1

    def bitmap(self) -> DataFrame:
        return filters.union(self.spark.read.schema("bucket long, bits binary").parquet(*[f"{self.path}/version={v}" for v in range(self.versions)]))


class RunningClear:
    """Cleared positions that each batch adds to: of the false positives a batch meets, the most frequent share is
    cleared by the random rule; batch number and positions are one version directory, so a replayed batch overwrites
    its own."""

    def __init__(self, spark: SparkSession, pos: DataFrame, members: DataFrame, spec: FilterSpec, beta: float):
        self.spark, self.pos, self.members, self.spec, self.beta = spark, pos, members, spec, beta
        self.path, self.versions = new_path(spark, "cleared"), 0

    def cleared(self) -> DataFrame:
        if not self.versions:
            return self.spark.createDataFrame([], "pos long")
        return self.spark.read.schema("pos long").parquet(*[f"{self.path}/version={v}" for v in range(self.versions)]).distinct()

    def add(self, batch: DataFrame, number: int, key: str) -> None:
        from ..operators import clearing

        met = batch.groupBy(F.col(key).alias("key")).agg(F.count("*").alias("weight")).join(self.members, "key", "left_anti")
        live = clearing.reset_bits(self.pos, self.cleared())
        yes = filters.probe_negative(met, live, self.spec).where("maybe").select("key")
        fp = hashed(met.join(yes, "key"), self.spec)
        b = clearing.troublesome(fp, self.beta, [F.col("weight").desc(), F.col("key")])
        done = clearing.clear(hashed(self.members, self.spec), fp, b, self.spec, "random")
        done.cleared.select("pos").write.mode("overwrite").parquet(f"{self.path}/version={number}")
        self.versions = number + 1
