"""Connected components as rounds of DataFrame joins and aggregations; links never leave the executors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_table, materialize


def components(links: DataFrame) -> DataFrame:
    """``links(a, b)`` of longs -> ``(v, root)`` for every linked ``v``; ``root`` is the least vertex of its component.

    A round points each vertex to its least neighbour if that is smaller, follows the pointers once more, renames the
    ends of all links and drops loops and repeats. Pointers go to smaller vertices only, so the least vertex of a
    component stays its own; rounds grow as the logarithm of the longest chain. All states are written tables.
    """
    open_ = materialize(links.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "cc_links")
    label = None
    while not open_.isEmpty():
        both = open_.select(F.explode(F.array(F.struct(F.col("a").alias("v"), F.col("b").alias("w")), F.struct(F.col("b").alias("v"), F.col("a").alias("w")))).alias("x"))
        up = materialize(both.groupBy("x.v").agg(F.min("x.w").alias("w")).select("v", F.least("v", "w").alias("p")), "cc_up")
        for _ in range(2):
            far = up.select(F.col("v").alias("p"), F.col("p").alias("pp"))
            jumped = materialize(up.join(far, "p").select("v", F.col("pp").alias("p")), "cc_up")
            drop_table(up)
            up = jumped
        ends = open_
        for c in ("a", "b"):
            ends = ends.join(up.select(F.col("v").alias(c), F.col("p").alias(f"{c}p")), c).drop(c).withColumnRenamed(f"{c}p", c)
        next_ = materialize(ends.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "cc_links")
        if label is None:
            label = up.withColumnRenamed("p", "root")
            label.bcf_path = up.bcf_path
        else:
            moved = label.join(up.select(F.col("v").alias("root"), F.col("p").alias("to")), "root", "left").select("v", F.coalesce("to", "root").alias("root"))
            moved = materialize(moved, "cc_label")
            drop_table(label)
            drop_table(up)
            label = moved
        drop_table(open_)
        open_ = next_
    if label is None:
        return links.select(F.col("a").alias("v"), F.col("b").alias("root")).where(F.lit(False))
    return label
