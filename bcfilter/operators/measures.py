"""Cost and accuracy measures over (key, is_member, maybe) before and after clearing, and over clearing logs."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .clearing import Cleared, hit_by, running

# Two-sided 95% quantiles of Student's t for 1 to 30 degrees of freedom.
T95 = (12.7062, 4.3027, 3.1824, 2.7764, 2.5706, 2.4469, 2.3646, 2.3060, 2.2622, 2.2281, 2.2010, 2.1788, 2.1604, 2.1448, 2.1314, 2.1199, 2.1098, 2.1009, 2.0930, 2.0860, 2.0796, 2.0739, 2.0687, 2.0639, 2.0595, 2.0555, 2.0518, 2.0484, 2.0452, 2.0423)


def r6(x: Column) -> Column:
    return F.round(x, 6)


def fp_rate(answers: DataFrame) -> Column:
    """Share of foreign keys that test positive."""
    return F.avg(F.when(~F.col("is_member"), F.col("maybe").cast("double")))


def fn_rate(answers: DataFrame) -> Column:
    """Share of members that test negative."""
    return F.avg(F.when(F.col("is_member"), (~F.col("maybe")).cast("double")))


def removed_share(before: int | Column, after: int | Column) -> Column:
    return F.try_divide((F.lit(before) - F.lit(after)).cast("double"), F.lit(before))


def table_row(members: DataFrame, fp: DataFrame, b: DataFrame, done: Cleared, universe: int, spec, beta: float, algorithm: str, counters: str = "frozen", scope: str = "all", run: int = 0) -> DataFrame:
    """One row of a results table: sizes, removed false positives, lost members, resets, shares and their ratio."""
    gone = done.cleared.select("pos")
    gone_fp = hit_by(fp, gone).select("key")
    row = (
        members.agg(F.count("*").alias("n"))
        .crossJoin(fp.agg(F.count("*").alias("fp")))
        .crossJoin(b.agg(F.count("*").alias("b")))
        .crossJoin(gone_fp.agg(F.count("*").alias("removed")))
        .crossJoin(gone_fp.join(b.select("key"), "key", "left_anti").agg(F.count("*").alias("b_extra")))
        .crossJoin(hit_by(members, gone).agg(F.count("*").alias("fn")))
        .crossJoin(done.cleared.agg(F.count("*").alias("s")))
    )
    dfp, dfn = F.col("removed") / F.col("fp"), F.col("fn") / F.col("n")
    return row.select(
        F.lit(algorithm).alias("algorithm"), F.lit(counters).alias("counters"), F.lit(scope).alias("fp_scope"), F.lit(float(beta)).alias("beta"), F.lit(run).alias("run"),
        "n", F.lit(universe).cast("long").alias("universe"), F.lit(spec.m).cast("long").alias("m"), F.lit(spec.k).alias("k"), "fp", "b", "b_extra", "removed", "fn", "s",
        r6(dfp).alias("dfp"), r6(dfn).alias("dfn"), r6(F.try_divide(dfp, dfn)).alias("chi"),
    )


def confidence(rows: DataFrame, by: list[str], value: str) -> DataFrame:
    """Mean and half-width of the 95% t-interval over runs."""
    t = F.element_at(F.array(*[F.lit(x) for x in T95]), F.least(F.col("runs") - 1, F.lit(len(T95))).cast("int"))
    out = rows.groupBy(*by).agg(F.count(value).alias("runs"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"))
    return out.select(*by, "runs", r6(F.col("mean")).alias("mean"), r6(F.when(F.col("runs") > 1, t * F.col("sd") / F.sqrt(F.col("runs")))).alias("half_width"))


def overall_error(fp: Column, fn: Column, w_p: float = 1.0, w_n: float = 1.0) -> Column:
    return F.lit(w_p) * fp + F.lit(w_n) * fn


def cost_model(sizes: DataFrame, k: int, c: int = 4, d: int = 8, u: int = 32) -> DataFrame:
    """Operations and bits of every rule as the orders of growth give them (constants left out).

    ``sizes(n, b, m)``: members, troublesome keys and bits of one filter.
    """
    a, b, m = (F.col(x).cast("long") for x in ("n", "b", "m"))
    rows = [
        ("random", "frozen", k * b, m + b), ("min_fn", "frozen", k * (a + b), c * m + b), ("max_fp", "frozen", k * b, c * m + b), ("ratio", "frozen", k * (a + b) + m, c * m + d * m + b),
        ("min_fn", "live", k * (a + b), m + b + k * u * a), ("max_fp", "live", k * b, m + k * u * b), ("ratio", "live", k * (a + b) + m, m + k * u * (a + b) + d * m),
    ]
    each = [F.struct(F.lit(x).alias("algorithm"), F.lit(y).alias("counters"), o.alias("operations"), s.alias("bits")) for x, y, o, s in rows]
    return sizes.select(F.explode(F.array(*each)).alias("x")).select("x.*")


def marginal(log: DataFrame, members: DataFrame, fp: DataFrame) -> DataFrame:
    """Per reset in order: degrees of false positives and members it removes first, running net benefit.

    ``fp`` and ``members`` may carry ``weight``; else every key weighs 1.
    """
    gone = log.where("acted").select("pos", "ord")

    def gain(keys: DataFrame, name: str) -> DataFrame:
        w = F.col("weight") if "weight" in keys.columns else F.lit(1)
        first = keys.select("key", w.alias("w"), F.explode("positions").alias("pos")).join(gone, "pos").groupBy("key", "w").agg(F.min("ord").alias("ord"))
        return first.groupBy("ord").agg(F.sum("w").cast("long").alias(name))

    per = gone.join(gain(fp, "benefit"), "ord", "left").join(gain(members, "cost"), "ord", "left")
    per = per.select("ord", "pos", F.coalesce("benefit", F.lit(0)).alias("benefit"), F.coalesce("cost", F.lit(0)).alias("cost"))
    return running(per.withColumn("gain", F.col("benefit") - F.col("cost")), "ord", {"gain": "net"}).drop("gain")


def entropy_bits(m: Column, p1: Column) -> Column:
    """Bits a lossless code needs for m independent bits of density p1."""
    h = -(p1 * F.log2(p1) + (1 - p1) * F.log2(1 - p1))
    return m * F.coalesce(h, F.lit(0.0))


def bits_of_list(n: Column) -> Column:
    return F.lit(32) * n


def ceil_div(a: int, b: int) -> int:
    return math.ceil(a / b)
