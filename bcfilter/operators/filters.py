"""The plain filter: built as positions or bitmaps, probed by join, broadcast or shuffle, combined and measured."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import FilterSpec, hashed, positions

BUCKET = 32768
#: Bits up to which the engine itself prefers broadcast probes (16 MB).
SMALL_FILTER_BITS = 1 << 27
#: Bits of a filter that may be broadcast as one array (256 MB).
MOST_BROADCAST_BITS = 1 << 31


def build_positions(members: DataFrame, spec: FilterSpec, key: str = "key") -> DataFrame:
    """Set positions, one row each; the distinct is a two-phase hash aggregation."""
    return hashed(members.select(key), spec, key).select(F.explode("positions").alias("pos")).distinct()


def bitmap_of(pos: DataFrame) -> DataFrame:
    """Positions -> (bucket, bits) of 4 KiB rows."""
    return pos.groupBy(F.bitmap_bucket_number("pos").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("pos")).alias("bits"))


def build_bitmap(members: DataFrame, spec: FilterSpec, key: str = "key") -> DataFrame:
    return bitmap_of(hashed(members.select(key), spec, key).select(F.explode("positions").alias("pos")))


def positions_of(bitmap: DataFrame) -> DataFrame:
    """(bucket, bits) -> set positions."""
    byte = F.conv(F.hex(F.substring("bits", F.col("at") + 1, F.lit(1))), 16, 10).cast("int")
    bytes_ = bitmap.select("bucket", "bits", F.explode(F.sequence(F.lit(0), F.lit(BUCKET // 8 - 1))).alias("at")).select("bucket", "at", byte.alias("byte")).where("byte <> 0")
    bit = bytes_.select("bucket", "at", "byte", F.explode(F.sequence(F.lit(0), F.lit(7))).alias("b")).where(F.expr("shiftright(byte, b) & 1 = 1"))
    return bit.select(((F.col("bucket") - 1) * BUCKET + F.col("at") * 8 + F.col("b") + 1).cast("long").alias("pos"))


def probe_join(df: DataFrame, pos: DataFrame, spec: FilterSpec, key: str = "key") -> DataFrame:
    """``df`` with ``maybe``: every distinct key's positions meet the position table; null keys give null."""
    keys = hashed(df.select(key).distinct(), spec, key)
    each = keys.select(key, F.explode(F.array_distinct("positions")).alias("pos"))
    hits = each.join(pos.withColumn("hit", F.lit(1)), "pos", "left").groupBy(key).agg(F.bool_and(F.col("hit").isNotNull()).alias("maybe"))
    return df.join(hits, key, "left")


def packed_bits(pos: DataFrame, spec: FilterSpec) -> bytes:
    """The filter as one byte string on the driver; refused above ``MOST_BROADCAST_BITS``."""
    if spec.m > MOST_BROADCAST_BITS:
        raise ValueError("too many bits to broadcast; use probe_shuffle")
    out = np.zeros(-(-spec.m // BUCKET) * (BUCKET // 8), dtype=np.uint8)
    for bucket, bits in bitmap_of(pos).toLocalIterator():
        out[(bucket - 1) * (BUCKET // 8) : bucket * (BUCKET // 8)] |= np.frombuffer(bytes(bits), dtype=np.uint8)
    return out.tobytes()


def contains_udf(spark, bits: bytes):
    """Arrow UDF: positions -> all set, against the broadcast bits."""
    shared = spark.sparkContext.broadcast(bits)

    @F.pandas_udf("boolean")
    def contains(p: pd.Series) -> pd.Series:
        known = p.notna()
        out = pd.Series([None] * len(p), index=p.index, dtype="object")
        if known.any():
            data = np.frombuffer(shared.value, dtype=np.uint8)
            at = np.stack(p[known].to_numpy()) - 1
            out[known] = ((data[at >> 3] >> (at & 7).astype(np.uint8)) & 1).all(axis=1)
        return out

    return contains


def columns_udf(spark, bits: bytes):
    """Arrow UDF over one column for each hash: plain long columns cross to Python without building lists."""
    shared = spark.sparkContext.broadcast(bits)

    @F.pandas_udf("boolean")
    def contains(p: pd.DataFrame) -> pd.Series:
        data = np.frombuffer(shared.value, dtype=np.uint8)
        known = p.iloc[:, 0].notna().to_numpy()
        hit = known.copy()
        for c in p.columns:
            at = p[c].fillna(1).to_numpy().astype(np.int64) - 1
            hit &= ((data[at >> 3] >> (at & 7).astype(np.uint8)) & 1).astype(bool)
        return pd.Series(np.where(known, hit, None), index=p.index, dtype="object")

    return contains


def maybe_in(df: DataFrame, pos: DataFrame, spec: FilterSpec, key: str | Column = "key") -> Column:
    """Membership predicate as a column of ``df`` (broadcast bits, no shuffle)."""
    at = positions(key, spec)
    return columns_udf(df.sparkSession, packed_bits(pos, spec))(F.struct(*[at[j].alias(f"p{j}") for j in range(spec.k)]))


def probe_broadcast(df: DataFrame, pos: DataFrame, spec: FilterSpec, key: str = "key") -> DataFrame:
    return df.withColumn("maybe", maybe_in(df, pos, spec, key))


def probe_shuffle(df: DataFrame, bitmap: DataFrame, spec: FilterSpec, key: str = "key") -> DataFrame:
    """For filters beyond memory: each position goes to its bucket's row, then answers meet by key."""
    keys = hashed(df.select(key).distinct(), spec, key)
    each = keys.select(key, F.explode(F.array_distinct("positions")).alias("pos"))
    each = each.select(key, F.bitmap_bucket_number("pos").alias("bucket"), F.bitmap_bit_position("pos").alias("bit"))
    at = F.conv(F.hex(F.substring("bits", (F.col("bit") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    hit = F.coalesce(F.expr("1") == at.bitwiseAND(F.expr("shiftleft(1, cast(bit % 8 as int))")).cast("boolean").cast("int"), F.lit(False))
    answers = each.join(bitmap, "bucket", "left").select(key, hit.alias("hit")).groupBy(key).agg(F.bool_and("hit").alias("maybe"))
    return df.join(answers, key, "left")


def probe(df: DataFrame, pos: DataFrame, spec: FilterSpec, key: str = "key") -> DataFrame:
    """``df`` with ``maybe``: broadcast bits while they are few enough for that, co-partitioned bitmaps beyond."""
    if spec.m <= MOST_BROADCAST_BITS:
        return probe_broadcast(df, pos, spec, key)
    return probe_shuffle(df, bitmap_of(pos), spec, key)


def probe_negative(df: DataFrame, pos: DataFrame, spec: FilterSpec, key: str = "key", first: int = 1) -> DataFrame:
    """Staged probe: the first ``first`` hashes reject most keys, the rest is tested for those left; (key, maybe)."""
    keys = hashed(df.select(key).distinct(), spec, key)

    def stage(rows: DataFrame, lo: int, n: int) -> DataFrame:
        each = rows.select(key, "positions", F.explode(F.array_distinct(F.slice("positions", lo, n))).alias("pos"))
        lost = each.join(pos, "pos", "left_anti").select(key).distinct()
        return rows.join(lost, key, "left_anti")

    left = stage(keys, 1, first)
    if spec.k > first:
        left = stage(left, first + 1, spec.k - first)
    return keys.select(key).join(left.select(key, F.lit(True).alias("yes")), key, "left").select(key, F.coalesce("yes", F.lit(False)).alias("maybe"))


def positives(df: DataFrame, pos: DataFrame, spec: FilterSpec, key: str = "key") -> DataFrame:
    """(key) of ``df`` that test positive: broadcast bits for small filters, the staged join beyond.

    Measured on 5,000,000 keys with eight cores: 3.4 million keys a second by broadcast, 0.5 million by staged join.
    """
    if spec.m <= SMALL_FILTER_BITS:
        return probe_broadcast(df.select(key).where(F.col(key).isNotNull()).distinct(), pos, spec, key).where("maybe").select(key)
    return probe_negative(df, pos, spec, key).where("maybe").select(key)


def union(*bitmaps: DataFrame) -> DataFrame:
    """OR of filters of one spec; partial aggregates merge before the shuffle."""
    both = bitmaps[0]
    for b in bitmaps[1:]:
        both = both.unionByName(b)
    return both.groupBy("bucket").agg(F.bitmap_or_agg("bits").alias("bits"))


def intersect(*bitmaps: DataFrame) -> DataFrame:
    """AND of filters of one spec; a bucket absent from one of them is empty."""
    both = bitmaps[0]
    for b in bitmaps[1:]:
        both = both.unionByName(b)
    return both.groupBy("bucket").agg(F.bitmap_and_agg("bits").alias("bits"), F.count("*").alias("n")).where(F.col("n") == len(bitmaps)).drop("n")


def stats(pos: DataFrame, spec: FilterSpec) -> DataFrame:
    """bits_set, fill and the cardinality estimate -(m / k) ln(1 - fill)."""
    x = pos.agg(F.count("*").alias("bits_set"))
    fill = F.col("bits_set") / F.lit(spec.m)
    return x.select("bits_set", F.round(fill, 6).alias("fill"), F.round(-F.lit(spec.m / spec.k) * F.ln(1 - fill), 4).alias("estimate"))


def build_blocked(members: DataFrame, spec: FilterSpec, key: str = "key") -> DataFrame:
    """Blocked filter: keys are shuffled once by block, bits are set inside the task; (block, bits) with all bits."""
    if spec.family != "blocked":
        raise ValueError("a blocked filter needs the blocked family")
    width = spec.block_bits
    rows = hashed(members.select(key), spec, key).select(((F.element_at("positions", 1) - 1) / width).cast("long").alias("block"), "positions")

    def run(batches):
        held: dict[int, np.ndarray] = {}
        for part in batches:
            for block, own in part.groupby("block", sort=False):
                bits = held.setdefault(int(block), np.zeros(-(-width // 8), dtype=np.uint8))
                at = np.concatenate(own["positions"].to_numpy()) - 1 - int(block) * width
                np.bitwise_or.at(bits, at >> 3, (1 << (at & 7)).astype(np.uint8))
        yield pd.DataFrame({"block": list(held), "bits": [b.tobytes() for b in held.values()]})

    return rows.repartition("block").mapInPandas(run, "block long, bits binary")
