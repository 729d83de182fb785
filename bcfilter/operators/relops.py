"""Relational helpers around filters: pre-filtered, as-of, interval, salted and band joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import FilterSpec
from . import clearing, filters


def prefilter(df: DataFrame, cheap: Column, pos: DataFrame, spec: FilterSpec, key: str) -> DataFrame:
    """Cheap predicates first (they reach the scan), then the probe; a probe before a join saves its shuffle."""
    return filters.probe(df.where(cheap), pos, spec, key).where("maybe").drop("maybe")


def join_prefiltered(left: DataFrame, right: DataFrame, key: str, spec: FilterSpec, pos: DataFrame, rescue: DataFrame | None = None) -> DataFrame:
    """Inner join on ``key`` of the left rows that pass the filter.

    ``rescue(key)`` holds the right side's keys that the filter lost to clearing: with them the result is exact,
    without it the join misses their rows.
    """
    passed = filters.probe(left, pos, spec, key)
    if rescue is not None:
        saved = rescue.select(F.col("key").alias(key), F.lit(True).alias("saved"))
        passed = passed.join(saved, key, "left").where(F.col("maybe") | F.col("saved")).drop("saved")
    else:
        passed = passed.where("maybe")
    return passed.drop("maybe").join(right, key)


def rescue_keys(members: DataFrame, cleared: DataFrame) -> DataFrame:
    """Members that clearing made negative."""
    return clearing.hit_by(members, cleared).select("key")


def join_salted(left: DataFrame, right: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """Equi-join whose hot keys are spread: left rows draw a salt by hash of the row, right rows are repeated."""
    l_ = left.withColumn("salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    r_ = right.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return l_.join(r_, [key, "salt"]).drop("salt")


def join_asof(left: DataFrame, right: DataFrame, key: str, at: str, since: str, value: str) -> DataFrame:
    """Left rows with the latest right ``value`` at or before ``at``: one pass over the union, ordered by key and time."""
    from pyspark.sql.window import Window

    cols = left.columns
    u = left.withColumn("t", F.col(at)).withColumn("v", F.lit(None).cast(right.schema[value].dataType)).withColumn("side", F.lit(1))
    r = right.select(key, F.col(since).alias("t"), F.col(value).alias("v"), F.lit(0).alias("side"))
    both = u.unionByName(r, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy("t", "side", "v").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last("v", ignorenulls=True).over(w)).where("side = 1").select(*cols, value)


def join_interval(left: DataFrame, right: DataFrame, on: str, t_left: str, t_right: str, seconds: int) -> DataFrame:
    """Pairs of a key whose times lie within ``seconds``: time is cut into cells, right rows go to two neighbours."""
    cell = lambda t: F.floor(F.unix_timestamp(t) / seconds)
    l_ = left.withColumn("cell", cell(t_left))
    r_ = right.withColumn("cell", F.explode(F.array(cell(t_right) - 1, cell(t_right), cell(t_right) + 1)))
    near = F.abs(F.unix_micros(F.col(t_left).cast("timestamp")) - F.unix_micros(F.col(t_right).cast("timestamp"))) <= seconds * 1_000_000
    return l_.join(r_, [on, "cell"]).where(near).drop("cell")
