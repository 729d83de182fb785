"""Sizing formulas as columns: fill, false-positive rate, best number of hashes, survival under random resets."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .hashing import FilterSpec

Num = Column | float | int


def _c(x: Num) -> Column:
    return x.cast("double") if isinstance(x, Column) else F.lit(float(x))


def p_zero(n: Num, m: Num, k: Num, exact: bool = True) -> Column:
    """Probability that a bit is 0 after n keys."""
    n, m, k = _c(n), _c(m), _c(k)
    return F.pow(1 - 1 / m, k * n) if exact else F.exp(-k * n / m)


def p_one(n: Num, m: Num, k: Num, exact: bool = True) -> Column:
    return 1 - p_zero(n, m, k, exact)


def fp_rate(n: Num, m: Num, k: Num, exact: bool = True) -> Column:
    """Probability that all k bits of a foreign key are 1."""
    return F.pow(p_one(n, m, k, exact), _c(k))


def best_k(m: Num, n: Num) -> tuple[Column, Column]:
    """(m / n) ln 2 and the nearest integer, at least 1."""
    real = _c(m) / _c(n) * F.lit(math.log(2))
    return real, F.greatest(F.lit(1), F.round(real).cast("int"))


def min_fp_rate(m: Num, n: Num) -> Column:
    """Rate at the best real k: 2 ** -(m / n * ln 2)."""
    return F.pow(F.lit(2.0), -_c(m) / _c(n) * F.lit(math.log(2)))


def for_target(n: int, rate: float, family: str = "xxhash") -> FilterSpec:
    """Least m, and k, whose minimum rate is at most ``rate``."""
    if not 0 < rate < 1:
        raise ValueError("a rate lies between 0 and 1")
    m = math.ceil(-max(n, 1) * math.log(rate) / math.log(2) ** 2)
    return FilterSpec(m, max(1, round(m / max(n, 1) * math.log(2))), family)


def for_target_columns(n: Num, rate: Num) -> tuple[Column, Column]:
    """m and k of ``for_target`` as columns."""
    n = F.greatest(_c(n), F.lit(1.0))
    m = F.ceil(-n * F.log(_c(rate)) / F.lit(math.log(2) ** 2))
    return m, F.greatest(F.lit(1), F.round(m / n * F.lit(math.log(2))).cast("int"))


def expected_fp_count(universe: Num, n: Num, m: Num, k: Num) -> Column:
    return (_c(universe) - _c(n)) * fp_rate(n, m, k)


def survival(s: Num, n: Num, m: Num, k: Num) -> Column:
    """Share of positives left after s random resets of 1-bits."""
    return F.pow(1 - _c(s) / (p_one(n, m, k) * _c(m)), _c(k))


def curve(spark: SparkSession, var: str, values: list, n: float, m: float, k: float) -> DataFrame:
    """Rate along one variable, the others fixed."""
    if var not in ("k", "m", "n"):
        raise ValueError(var)
    fixed = {"k": k, "m": m, "n": n}
    base = spark.createDataFrame([(float(v),) for v in values], f"{var} double")
    for name, v in fixed.items():
        if name != var:
            base = base.withColumn(name, F.lit(float(v)))
    return base.select("k", "m", "n", F.round(fp_rate(F.col("n"), F.col("m"), F.col("k")), 10).alias("fp_rate"))
