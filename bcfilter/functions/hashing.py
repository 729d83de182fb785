"""Hash families: a key column to an array of k positions, 1-based as in the model.

Every family also renders itself as DuckDB SQL where that engine has the same arithmetic, so results can be compared
value by value. A null key has null positions.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

P = 2147483647
# Multipliers and shifts of the linear family.
LINEAR = ((1103515245, 12345), (1664525, 1013904223), (69069, 1), (48271, 11), (16807, 7))
FAMILIES = ("linear", "md5", "xxhash", "double", "blocked", "emulated")


@dataclass(frozen=True)
class FilterSpec:
    """Bits, hashes, family and its seed; ``blocks`` divides the bits for the blocked family."""

    m: int
    k: int
    family: str = "linear"
    seed: int = 0
    blocks: int = 1

    def __post_init__(self):
        if self.m < 1 or self.k < 1:
            raise ValueError("a filter needs at least one bit and one hash")
        if self.family not in FAMILIES:
            raise ValueError(f"unknown family {self.family!r}")
        if self.family == "linear" and self.k > len(LINEAR):
            raise ValueError(f"the linear family has {len(LINEAR)} functions")

    @property
    def block_bits(self) -> int:
        return -(-self.m // self.blocks)


def _linear(key: Column, j: int) -> Column:
    a, b = LINEAR[j]
    return F.pmod(F.lit(a) * F.pmod(key + F.lit(1), F.lit(P)) + F.lit(b), F.lit(P))


def positions(key: Column | str, spec: FilterSpec) -> Column:
    """``array<bigint>`` of k positions in 1..m; stays inside code generation for all but the emulated family."""
    key = F.col(key) if isinstance(key, str) else key
    m = F.lit(spec.m).cast("long")
    if spec.family == "linear":
        out = [F.pmod(_linear(key.cast("long"), j), m) + 1 for j in range(spec.k)]
    elif spec.family == "md5":
        text = key.cast("string")
        out = [F.pmod(F.conv(F.substring(F.md5(F.concat(F.lit(f"{j}:"), text).cast("binary")), 1, 15), 16, 10).cast("long"), m) + 1 for j in range(1, spec.k + 1)]
    elif spec.family == "xxhash":
        out = [F.pmod(F.xxhash64(key, F.lit(spec.seed * 1000 + j)), m) + 1 for j in range(spec.k)]
    elif spec.family == "double":
        h1, h2 = _linear(key.cast("long"), 0), _linear(key.cast("long"), 1)
        out = [F.pmod(h1 + F.lit(j) * h2, m) + 1 for j in range(spec.k)]
    elif spec.family == "blocked":
        bits = F.lit(spec.block_bits).cast("long")
        block = F.pmod(_linear(key.cast("long"), 4), F.lit(spec.blocks).cast("long"))
        out = [block * bits + F.pmod(_linear(key.cast("long"), j), bits) + 1 for j in range(spec.k)]
    else:
        return emulated(key, spec)
    return F.when(key.isNotNull(), F.array(*[x.cast("long") for x in out]))


def emulated(key: Column, spec: FilterSpec) -> Column:
    """Positions drawn by a Mersenne Twister seeded with the key; for statistics, not for portable filters."""
    m, k, seed = spec.m, spec.k, spec.seed

    @F.pandas_udf("array<bigint>")
    def draw(keys: pd.Series) -> pd.Series:
        return pd.Series([None if pd.isna(x) else np.random.RandomState([seed, int(x) & 0xFFFFFFFF, int(x) >> 32 & 0xFFFFFFFF]).randint(1, m + 1, k) for x in keys])

    return draw(key.cast("long"))


def sql_positions(key: str, k: int, m: str, family: str = "linear", blocks: int = 1) -> str:
    """The same positions as a DuckDB list; ``m`` may be an expression."""

    def linear(j: int) -> str:
        a, b = LINEAR[j]
        return f"(({a} * (({key} + 1) % {P}) + {b}) % {P})"

    if family == "linear":
        out = [f"{linear(j)} % {m} + 1" for j in range(k)]
    elif family == "md5":
        out = [f"CAST('0x' || substr(md5('{j}:' || CAST({key} AS VARCHAR)), 1, 15) AS BIGINT) % {m} + 1" for j in range(1, k + 1)]
    elif family == "double":
        out = [f"({linear(0)} + {j} * {linear(1)}) % {m} + 1" for j in range(k)]
    elif family == "blocked":
        bits = f"CAST(ceil({m} / {blocks}.0) AS BIGINT)"
        out = [f"({linear(4)} % {blocks}) * {bits} + {linear(j)} % {bits} + 1" for j in range(k)]
    else:
        raise ValueError(family)
    return "[" + ", ".join(f"CAST({x} AS BIGINT)" for x in out) + "]"


def hashed(df: DataFrame, spec: FilterSpec, key: str = "key") -> DataFrame:
    """``df`` with ``positions``; rows of null key are dropped, for they are no elements."""
    return df.where(F.col(key).isNotNull()).withColumn("positions", positions(key, spec))


def uniformity(keys: DataFrame, spec: FilterSpec, cells: int = 64, key: str = "key") -> DataFrame:
    """Hits per range of positions against the uniform expectation: bucket, n, expected, chi2 (the cell's share)."""
    at = hashed(keys, spec, key).select(F.explode("positions").alias("pos"))
    n = at.groupBy(F.floor((F.col("pos") - 1) * cells / F.lit(spec.m)).cast("long").alias("bucket")).agg(F.count("*").alias("n"))
    total = at.agg(F.count("*").alias("total"))
    return n.crossJoin(F.broadcast(total)).select(
        "bucket", "n", F.round(F.col("total") / cells, 6).alias("expected"), F.round(F.pow(F.col("n") - F.col("total") / cells, 2) / (F.col("total") / cells), 6).alias("chi2")
    )
