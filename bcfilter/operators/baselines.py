"""What a cleared filter is compared with: lists, larger, compressed, counting and fingerprint filters."""

from __future__ import annotations

import zlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import FilterSpec, hashed


def union_all(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def exact_list(df: DataFrame, members: DataFrame) -> DataFrame:
    """Exact answers and the size of a list of 32-bit keys."""
    listed = members.select("key").distinct()
    size = listed.agg((F.count("*") * 32).alias("size_bits"))
    return df.select("key").join(listed.withColumn("hit", F.lit(True)), "key", "left").crossJoin(F.broadcast(size)).select("key", F.coalesce("hit", F.lit(False)).alias("maybe"), "size_bits")


def bloom_udaf(members: DataFrame, spec: FilterSpec, parts: int | None = None) -> DataFrame:
    """The filter by a grouped-aggregate UDF: one bit string for each slice of keys, for union afterwards.

    Slices grow in number with the keys, so that a group holds about half a million positions at most.
    """
    m = spec.m
    if parts is None:
        parts = max(64, -(-members.count() * spec.k // 500_000))

    @F.pandas_udf("binary")
    def build(p: pd.Series) -> bytes:
        bits = np.zeros(-(-m // 8), dtype=np.uint8)
        at = np.concatenate(p.to_numpy()) - 1
        np.bitwise_or.at(bits, at >> 3, (1 << (at & 7)).astype(np.uint8))
        return bits.tobytes()

    rows = hashed(members, spec).withColumn("slice", F.pmod(F.xxhash64("key"), F.lit(parts)))
    return rows.groupBy("slice").agg(build("positions").alias("bits")).select("slice", F.bitmap_count("bits").alias("bits_set"))


def compressed(bitmap: DataFrame) -> DataFrame:
    """Lossless compression of each 4 KiB row: bucket, raw and packed bytes."""

    @F.pandas_udf("long")
    def packed(bits: pd.Series) -> pd.Series:
        return bits.map(lambda b: len(zlib.compress(bytes(b), 9)))

    return bitmap.select("bucket", F.octet_length("bits").cast("long").alias("raw_bytes"), packed("bits").alias("packed_bytes"))


def counting(inserted: DataFrame, deleted: DataFrame, spec: FilterSpec) -> DataFrame:
    """Counting filter after insertions and deletions: positions with a count above 0."""
    up = hashed(inserted.select("key"), spec).select(F.explode("positions").alias("pos"), F.lit(1).alias("d"))
    down = hashed(deleted.select("key"), spec).select(F.explode("positions").alias("pos"), F.lit(-1).alias("d"))
    return up.unionByName(down).groupBy("pos").agg(F.sum("d").alias("cnt")).where("cnt > 0")


def dleft(df: DataFrame, members: DataFrame, d: int = 4, load: int = 6, bits: int = 12) -> DataFrame:
    """d-left fingerprint filter: a key's fingerprint goes to the least loaded of its d candidate buckets.

    Keys are dealt to independent shards by hash; in a shard the choice is sequential. One row of measures.
    """
    n = max(1, members.count())
    shards = max(1, -(-n // 20_000), -(-df.count() // 1_000_000))
    width = max(1, -(-n // (shards * load * d)) * 4 // 3 + 1)

    def cells(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        x = keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        x ^= x >> np.uint64(29)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(32)
        finger = (x & np.uint64((1 << bits) - 1)).astype(np.int64)
        where = np.stack([((x >> np.uint64(bits)) * np.uint64(2 * i + 3) % np.uint64(width)).astype(np.int64) for i in range(d)], axis=1)
        return finger, where

    def run(a: pd.DataFrame, u: pd.DataFrame) -> pd.DataFrame:
        table = [[set() for _ in range(width)] for _ in range(d)]
        if len(a):
            for f, w in zip(*cells(a["key"].to_numpy())):
                i = min(range(d), key=lambda j: (len(table[j][w[j]]), j))
                table[i][w[i]].add(int(f))
        maybe = np.zeros(len(u), dtype=bool)
        if len(u):
            finger, where = cells(u["key"].to_numpy())
            held = np.array([(j * width + w) << bits | f for j, t in enumerate(table) for w, cell in enumerate(t) for f in cell], dtype=np.int64)
            maybe = np.isin((np.arange(d) * width + where) << bits | finger[:, None], held).any(axis=1)
        member = u["is_member"].to_numpy() if len(u) else maybe
        deepest = max(len(b) for t in table for b in t)
        return pd.DataFrame([(int((maybe & ~member).sum()), int((~maybe & member).sum()), deepest)], columns=["fp", "fn", "deepest"])

    shard = F.pmod(F.xxhash64("key"), F.lit(shards)).cast("int").alias("shard")
    rows = members.select("key", shard).groupBy("shard").cogroup(df.select("key", "is_member", shard).groupBy("shard")).applyInPandas(run, "fp long, fn long, deepest long")
    return rows.agg(F.sum("fp").alias("fp"), F.sum("fn").alias("fn"), F.max("deepest").alias("deepest")).withColumn("size_bits", F.lit(shards * d * width * load * bits))


def jvm_sketch(members: DataFrame, rate: float = 0.01) -> DataFrame:
    """Spark's own Bloom sketch of the members: its size and the expected rate, as a yardstick."""
    n = members.count()
    bloom = members._jdf.stat().bloomFilter("key", n, rate)
    return members.sparkSession.createDataFrame([(n, int(bloom.bitSize()), float(bloom.expectedFpp()))], "members long, bits long, expected_rate double")


def list_measures(s) -> DataFrame:
    """Cells that hold an element and list entries, for members (a) and false positives (b)."""
    out = None
    for side, keys in (("a", s.members), ("b", s.fp)):
        row = keys.select(F.explode("positions").alias("pos")).agg(F.countDistinct("pos").alias("cells"), F.count("*").alias("entries")).withColumn("side", F.lit(side))
        out = row if out is None else out.unionByName(row)
    return out
