"""Mixing sources to target weights by the cube method.

Each source gets a target of words; a document is taken ``floor(r)`` times for the source's rate ``r`` and once more
with probability ``r - floor(r)``. Which documents get the extra copy is decided by balanced sampling: within a block
of documents the inclusion probabilities move along a direction that keeps both the number of documents and the
number of words, until all but two of them are 0 or 1. The undecided ones of all blocks of a source meet in fewer
blocks at the next level, until one block is left, where the landing picks the rounding of a dozen units that comes
nearest to the expected words. Blocks hold about ``block`` documents whatever the size of a source.

Defined results: a null text has 0 words; documents of a source without words are taken 0 words; a null source is a
source of its own and comes last; repeated rows are separate units; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import lookup, materialize, word_count

WEIGHTS = (5, 2, 1)
EPS = 1e-9


def targets(sizes: dict, weights: tuple = WEIGHTS, share: float = 1.5, most: float = 2.0) -> dict:
    """Words wanted of each source: shares by weight, none above ``most`` times its size, the excess shared anew."""
    order = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    left, open_, out = share * sum(sizes.values()), list(order), {}
    while open_:
        total = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / total > most * sizes[s]]
        if not over:
            out |= {s: left * weight[s] / total for s in open_}
            break
        for s in over:
            out[s] = most * sizes[s]
        left -= sum(out[s] for s in over)
        open_ = [s for s in open_ if s not in out]
    return out


def fly(p: np.ndarray, size: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """Flight phase over units in the given order; two units at most stay undecided.

    Three undecided units at a time move along the null space of (1, size), so both totals stay as they are.
    """
    p = p.astype(float).copy()
    flips = iter(rng.random(2 * len(p) + 8).tolist())
    s = size.astype(float).tolist()
    v = p.tolist()
    held: list[int] = []

    def move(units: list[int], u: tuple) -> None:
        up = down = np.inf
        for i, d in zip(units, u):
            if d > 0:
                up, down = min(up, (1 - v[i]) / d), min(down, v[i] / d)
            elif d < 0:
                up, down = min(up, v[i] / -d), min(down, (1 - v[i]) / -d)
        step = up if next(flips) * (up + down) < down else -down
        for i, d in zip(units, u):
            x = v[i] + step * d
            v[i] = 0.0 if x < EPS else 1.0 if x > 1 - EPS else x

    for i in range(len(v)):
        if not EPS < v[i] < 1 - EPS:
            v[i] = float(round(v[i]))
            continue
        held.append(i)
        while len(held) == 3:
            a, b, c = (s[j] for j in held)
            u = (c - b, a - c, b - a)
            top = max(map(abs, u))
            move(held, (1.0, -1.0, 0.0) if top == 0 else tuple(x / top for x in u))
            held = [j for j in held if 0 < v[j] < 1]
    return np.array(v)


def land(p: np.ndarray, size: np.ndarray, rng: np.random.Generator, spare: int = 10) -> np.ndarray:
    """Flight with ``spare`` units of evenly spread sizes held back; they and the undecided rest are the landing problem.

    Of its at most 2 ** (spare + 2) roundings the one nearest to the words expected is taken, then to the documents.
    """
    p = p.astype(float).copy()
    open_ = np.flatnonzero((p > EPS) & (p < 1 - EPS))
    by_size = open_[np.argsort(size[open_], kind="stable")]
    held = np.unique(by_size[np.linspace(0, len(by_size) - 1, min(spare, len(by_size))).astype(int)]) if len(by_size) else by_size
    flown = np.setdiff1d(np.arange(len(p)), held)
    p[flown] = fly(p[flown], size[flown], rng)
    last = np.flatnonzero((p > EPS) & (p < 1 - EPS))
    if len(last):
        ways = (np.arange(1 << len(last))[:, None] >> np.arange(len(last))) & 1
        words = np.abs(ways @ size[last] - p[last] @ size[last])
        count = np.abs(ways.sum(1) - p[last].sum())
        p[last] = ways[np.lexsort((count, words))[0]]
    return np.round(p)


def _flight(seed: int, level: int, last: bool):
    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["lot", "doc_id", "size"], kind="stable", na_position="last", ignore_index=True)
        rng = np.random.default_rng([seed, level, int(key[0]), int(key[1])])
        rows["p"] = (land if last else fly)(rows["p"].to_numpy(), rows["size"].to_numpy(), rng)
        return rows

    return run


def mix(docs: DataFrame, weights: tuple = WEIGHTS, share: float = 1.5, most: float = 2.0, block: int = 512, seed: int = 7) -> DataFrame:
    """doc_id, size, source_size, target, taken and ``copies`` (how often the mix takes the document)."""
    spark = docs.sparkSession
    units = materialize(docs.select("doc_id", "source", word_count(docs["text"]).alias("size")), "mix_units")
    found = {r[0]: (r[1], r[2]) for r in units.groupBy("source").agg(F.sum("size"), F.count("*")).collect()}
    want = targets({s: v[0] for s, v in found.items()}, weights, share, most)
    plan, counts = [], {}
    for k, s in enumerate(sorted((s for s in found if s is not None)) + ([None] if None in found else [])):
        rate = min(most, want[s] / found[s][0]) if found[s][0] else 0.0
        base = int(rate + EPS)
        plan.append((s, k, int(found[s][0]), float(want[s]), base, max(0.0, rate - base)))
        counts[k] = found[s][1]
    schema = T.StructType.fromDDL("mix_source string, k int, source_size long, target double, base int, p double")
    open_ = units.join(lookup(spark, plan, schema), units["source"].eqNullSafe(F.col("mix_source"))).select(
        "doc_id", "size", "k", "source_size", "target", "base", "p", F.xxhash64(F.lit(seed), "doc_id").alias("lot")
    )
    done, level = [], 0
    while True:
        blocks = lookup(spark, [(k, max(1, -(-n // block))) for k, n in counts.items()], "k int, blocks int")
        last = all(n <= block for n in counts.values())
        dealt = open_.join(blocks, "k").withColumn("block", F.pmod(F.xxhash64(F.lit(level), "lot"), F.col("blocks")).cast("int")).drop("blocks")
        out = dealt.groupBy("k", "block").applyInPandas(_flight(seed, level, last), dealt.schema).drop("block")
        if last:
            done.append(out)
            break
        out = materialize(out, "mix_level")
        undecided = (F.col("p") > 0) & (F.col("p") < 1)
        done.append(out.where(~undecided))
        open_ = out.where(undecided)
        counts = {r[0]: r[1] for r in open_.groupBy("k").count().collect()}
        level += 1
        if not counts:
            break
    rows = done[0]
    for more in done[1:]:
        rows = rows.unionByName(more)
    copies = (F.col("base") + F.round("p").cast("int")).cast("int")
    return rows.select("doc_id", "size", "source_size", "target", (F.col("size") * copies).alias("taken"), copies.alias("copies"))
