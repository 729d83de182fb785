"""Sharding by longest-processing-time scheduling over groups of equal texts.

Groups with more than ``1/units`` of all bytes are scheduled one by one; there are fewer than ``units`` of them
whatever the input. The rest, each a vanishing part of a shard, are put together by hash into ``units`` bundles of
whole groups. Both kinds then go, largest first, to the least loaded shard through a heap. What the driver holds is
bounded by ``2 * units`` rows; rows and texts never leave the executors.

Defined results: a null text has size 1 (no bytes plus one), checksum 0 and is a group of its own; empty texts are
one group; repeated rows are kept and counted; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .common import materialize, text_key


def lpt(sizes: list[tuple[int, object]], n_shards: int) -> list[tuple[object, int]]:
    """Largest first to the least loaded shard; ties by key and by shard number."""
    heap = [(0, s) for s in range(n_shards)]
    placed = []
    for size, key in sorted(sizes, key=lambda x: (-x[0], x[1])):
        load, shard = heapq.heappop(heap)
        placed.append((key, shard))
        heapq.heappush(heap, (load + size, shard))
    return placed


def place_groups(rows: DataFrame, n_shards: int = 8, units: int = 65536) -> DataFrame:
    """``rows(gid, size, ...)`` -> the same rows with ``shard``; rows of one ``gid`` stay together."""
    spark = rows.sparkSession
    groups = materialize(rows.groupBy("gid").agg(F.sum("size").alias("bytes")), "shard_groups")
    total = groups.agg(F.sum("bytes")).first()[0] or 0
    heavy = F.col("bytes") * F.lit(units) > F.lit(total)
    bundle = F.pmod(F.xxhash64("gid"), F.lit(units)).cast("string")
    unit = F.when(heavy, F.concat(F.lit("g"), F.col("gid"))).otherwise(F.concat(F.lit("b"), bundle))
    sizes = [(r[1], r[0]) for r in groups.groupBy(unit.alias("unit")).agg(F.sum("bytes")).collect()]
    schema = T.StructType([T.StructField("unit", T.StringType()), T.StructField("shard", T.IntegerType())])
    plan = F.broadcast(spark.createDataFrame(lpt(sizes, n_shards), schema))
    own = F.concat(F.lit("g"), F.col("gid"))
    return (
        rows.withColumn("bundle", F.concat(F.lit("b"), bundle))
        .join(plan.select(F.col("unit").alias("own"), F.col("shard").alias("own_shard")), own == F.col("own"), "left")
        .join(plan.select(F.col("unit").alias("rest"), F.col("shard").alias("rest_shard")), F.col("bundle") == F.col("rest"), "left")
        .withColumn("shard", F.coalesce("own_shard", "rest_shard"))
        .drop("bundle", "own", "own_shard", "rest", "rest_shard")
    )


def number_slots(rows: DataFrame, n_shards: int, id_col: str, buckets: int = 1024) -> DataFrame:
    """Gapless slots from 0 in each shard: hash buckets are numbered on their own and shifted by earlier buckets' counts.

    The driver holds ``n_shards * buckets`` counts at most.
    """
    spark = rows.sparkSession
    rows = rows.withColumn("bucket", F.pmod(F.xxhash64(id_col), F.lit(buckets)).cast("int"))
    counts = sorted((r[0], r[1], r[2]) for r in rows.groupBy("shard", "bucket").count().collect())
    shifts, shard, at = [], None, 0
    for s, b, n in counts:
        at = at if s == shard else 0
        shard = s
        shifts.append((s, b, at))
        at += n
    schema = T.StructType([T.StructField("shard", T.IntegerType()), T.StructField("bucket", T.IntegerType()), T.StructField("shift", T.LongType())])
    w = Window.partitionBy("shard", "bucket").orderBy(id_col, "gid")
    numbered = rows.withColumn("rank", F.row_number().over(w))
    return (
        numbered.join(F.broadcast(spark.createDataFrame(shifts, schema)), ["shard", "bucket"])
        .withColumn("slot", F.col("shift") + F.col("rank") - 1)
        .drop("bucket", "shift", "rank")
    )


def shard_documents(docs: DataFrame, n_shards: int = 8, units: int = 65536, keep: list[str] | None = None) -> DataFrame:
    """Each document's size, checksum, shard and slot under the law ``bytes``; ``keep`` names more columns to carry."""
    raw = docs["text"].cast("binary")
    rows = docs.select(
        *[docs[c] for c in keep or ["doc_id"]],
        (F.coalesce(F.octet_length(docs["text"]), F.lit(0)) + 1).cast("long").alias("size"),
        F.coalesce(F.crc32(raw), F.lit(0)).cast("long").alias("text_crc32"),
        text_key(docs["text"]).alias("gid"),
    )
    if keep is None:
        rows = materialize(rows, "shard_rows")
    placed = number_slots(place_groups(rows, n_shards, units), n_shards, "doc_id")
    return placed.select(
        *(keep or ["doc_id"]), "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard")
    )
