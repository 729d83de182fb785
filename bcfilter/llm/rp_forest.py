"""Near-duplicate vectors by a forest of random-projection trees with spill.

Each tree splits recursively along random directions; the cut lies in the widest gap of the middle half of a bounded
sample of the node, vectors within a margin of it go to both sides, and a node most of whose sampled vectors lie within
half the threshold angle of their mean (nearly all pairs are links) is not cut. Rounds of splitting are distributed: a round fits, for every leaf
above ``LEAF`` rows, a subtree on at most about ``SAMPLE`` of its rows (the bound of the index; every row is placed),
so nothing that grows with the data reaches the driver. Rounds end when no leaf above that size can be cut further.

Vectors of a leaf are compared in blocks: every pair of blocks of about ``BLOCK`` rows is a task. A pair is counted in
the least of its common leaves only; a task emits a count for each vector and a spanning forest of its links. Equal
vectors of a label are one class with a multiplicity, so copies are counted without being compared.

Only equal labels are compared. Defined results: a null label, a null or empty vector, zero length, null or non-finite
components: no links; vectors of other dimension are not compared; repeated rows are separate vectors; an empty table
gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize
from .components import components

TREES, LEAF, SAMPLE, BLOCK, DEPTH = 6, 512, 4096, 512, 6
SPILL, GROWN = 0.05, 12


def classes(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """vec_id with class (null if it links with nothing), and one row for each class."""
    v = F.col("embedding").cast("array<double>")
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(math.inf)))
    some = F.exists(v, lambda x: x != 0)
    fine = F.col("label").isNotNull() & v.isNotNull() & ~F.coalesce(bad, F.lit(True)) & F.coalesce(some, F.lit(False))
    kept = rows.select("vec_id", F.when(fine, F.xxhash64("label", v)).alias("cls"), F.when(fine, F.xxhash64("label", F.size(v))).alias("room"), F.when(fine, v).alias("v"))
    kept = materialize(kept, "forest_rows")
    one = kept.where("cls is not null").groupBy("cls").agg(F.first("room").alias("room"), F.first("v").alias("v"), F.count("*").alias("copies"))
    return kept.select("vec_id", "cls"), materialize(one, "forest_classes")


def unit(rows: pd.Series) -> np.ndarray:
    x = np.stack(rows.to_numpy()).astype(np.float64)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def fit_subtree(x: np.ndarray, rng: np.random.Generator, target: int, tight: float) -> list[tuple]:
    """Nodes (direction, cut, low, high) by position, children of i at 2i+1 and 2i+2; a missing node is a leaf.

    ``target`` is the number of sampled rows that stand for a full leaf.
    """
    nodes: list[tuple] = []

    def grow(at: int, own: np.ndarray, depth: int) -> None:
        if len(own) <= target or len(own) < 8 or depth == DEPTH:
            return
        mean = own.mean(axis=0)
        size = np.linalg.norm(mean)
        if size > 0 and np.quantile(own @ (mean / size), 0.2) >= tight:
            return
        best = None
        for _ in range(4):
            d = rng.standard_normal(own.shape[1])
            p = np.sort(own @ d)
            lo, hi = len(p) // 4, max(len(p) // 4 + 1, 3 * len(p) // 4)
            gap = np.diff(p[lo : hi + 1])
            i = int(gap.argmax()) + lo
            wide = (p[i + 1] - p[i]) / (p[-1] - p[0] + 1e-300)
            if best is None or wide > best[0]:
                best = (wide, d, (p[i] + p[i + 1]) / 2, p)
        _, d, cut, p = best
        at_cut = np.searchsorted(p, cut) / len(p)
        low, high = np.quantile(p, max(0.0, at_cut - SPILL)), np.quantile(p, min(1.0, at_cut + SPILL))
        nodes.append((at, d, float(cut), float(min(low, cut)), float(max(high, cut))))
        q = own @ d
        grow(2 * at + 1, own[q <= high], depth + 1)
        grow(2 * at + 2, own[q >= low], depth + 1)

    grow(0, x, 0)
    return nodes


def descend(x: np.ndarray, nodes: dict) -> list[tuple[int, np.ndarray]]:
    """(leaf position, rows) for all rows; those in a margin appear in both subtrees."""
    out, todo = [], [(0, np.arange(len(x)))]
    while todo:
        at, own = todo.pop()
        if at not in nodes or not len(own):
            if len(own):
                out.append((at, own))
            continue
        d, _, low, high = nodes[at]
        q = x[own] @ d
        todo += [(2 * at + 1, own[q <= high]), (2 * at + 2, own[q >= low])]
    return out


def _fit(seed: int, turn: int, tight: float):
    def fit(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("cls")
        leaf, n = int(part["leaf"].iloc[0]), int(part["n"].iloc[0])
        rng = np.random.default_rng([seed, turn, leaf & 0xFFFFFFFF, leaf >> 32 & 0xFFFFFFFF])
        nodes = fit_subtree(unit(part["v"]), rng, max(1, int(LEAF * len(part) / n)), tight)
        return pd.DataFrame([(leaf, p, d, c, lo, hi) for p, d, c, lo, hi in nodes], columns=["leaf", "node", "d", "cut", "low", "high"])

    return fit


def grow_forest(one: DataFrame, tight: float, seed: int = 5) -> DataFrame:
    """(cls, leaf) for every class and leaf it falls into, over all trees."""
    trees = F.explode(F.array(*[F.lit(t) for t in range(TREES)]))
    at = one.select("cls", trees.alias("tree"), "room").select("cls", F.xxhash64("tree", "room").alias("leaf"))
    at, done = materialize(at, "forest_at"), []
    for turn in range(GROWN):
        sizes = materialize(at.groupBy("leaf").agg(F.count("*").alias("n")), "forest_sizes")
        big = sizes.where(F.col("n") > LEAF)
        if big.isEmpty():
            break
        done.append(at.join(big.hint("merge"), "leaf", "left_anti").select("cls", "leaf"))
        rows = at.join(big.hint("merge"), "leaf").join(one.select("cls", "v").hint("merge"), "cls")
        rows = materialize(rows.select("cls", "leaf", "n", "v"), "forest_big")
        picked = rows.where(F.pmod(F.xxhash64(F.lit(seed + turn), "cls", "leaf"), F.lit(1 << 20)) < F.lit(float(SAMPLE << 20)) / F.col("n"))

        model = picked.groupBy("leaf").applyInPandas(_fit(seed, turn, tight), "leaf long, node long, d array<double>, cut double, low double, high double")
        model = model.groupBy("leaf").agg(F.collect_list(F.struct("node", "d", "cut", "low", "high")).alias("nodes"))
        model = materialize(model, "forest_model")
        done.append(rows.join(model.hint("merge"), "leaf", "left_anti").select("cls", "leaf"))
        if model.isEmpty():
            at = None
            break

        def place(batches):
            for part in batches:
                for leaf, own in part.groupby("leaf", sort=False):
                    nodes = {r["node"]: (np.asarray(r["d"]), r["cut"], r["low"], r["high"]) for r in own["nodes"].iloc[0]}
                    ids = own["cls"].to_numpy()
                    for pos, some in descend(unit(own["v"]), nodes):
                        yield pd.DataFrame({"cls": ids[some], "up": leaf, "pos": pos})

        moved = rows.join(model.hint("merge"), "leaf").select("cls", "leaf", "v", "nodes").mapInPandas(place, "cls long, up long, pos long")
        next_ = materialize(moved.select("cls", F.xxhash64("up", "pos").alias("leaf")), "forest_at")
        at = next_
    if at is not None:
        done.append(at.select("cls", "leaf"))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return materialize(out.distinct(), "forest_leaves")


def compare(one: DataFrame, leaves: DataFrame, least: float) -> DataFrame:
    """(cls, n, root): links of a class found in a task, and the least class that the task's links connect it with."""
    sizes = leaves.groupBy("leaf").agg(F.ceil(F.count("*") / F.lit(BLOCK)).cast("int").alias("blocks"), F.count("*").alias("n")).where("n > 1")
    sizes = materialize(sizes.select("leaf", "blocks"), "forest_blocks")
    all_ = leaves.groupBy("cls").agg(F.array_sort(F.collect_list("leaf")).alias("leaves"))
    full = materialize(one.join(all_, "cls").select("cls", "v", "copies", "leaves"), "forest_full")
    rows = full.withColumn("leaf", F.explode("leaves")).join(sizes.hint("merge"), "leaf")
    own = F.pmod(F.xxhash64(F.lit(3), "cls"), F.col("blocks")).cast("int")
    dealt = rows.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("leaf", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "cls", "v", "copies", "leaves")
    dealt = dealt.repartition("leaf", "i", "j").sortWithinPartitions("leaf", "i", "j")

    def task(rows: pd.DataFrame) -> pd.DataFrame:
        leaf, i, j = rows["leaf"].iloc[0], rows["i"].iloc[0], rows["j"].iloc[0]
        x, ids, copies, own = unit(rows["v"]), rows["cls"].to_numpy(), rows["copies"].to_numpy(), rows["own"].to_numpy()
        hit = np.triu(x @ x.T >= least, 1)
        if i != j:
            hit &= own[:, None] != own[None, :]
        p, q = np.nonzero(hit)
        width = max(map(len, rows["leaves"]))
        table = np.stack([np.pad(np.asarray(v, dtype=np.int64), (0, width - len(v)), mode="edge") for v in rows["leaves"]])
        first = np.zeros(len(p), dtype=bool)
        for a in range(0, len(p), 8192):
            u, w = table[p[a : a + 8192]], table[q[a : a + 8192]]
            shared = (u[:, :, None] == w[:, None, :]).any(axis=2)
            first[a : a + 8192] = np.where(shared, u, np.iinfo(np.int64).max).min(axis=1) == leaf
        n = np.zeros(len(ids), dtype=np.int64)
        np.add.at(n, p[first], copies[q[first]])
        np.add.at(n, q[first], copies[p[first]])
        root = np.arange(len(ids))
        while True:
            low = root.copy()
            np.minimum.at(low, p, root[q])
            np.minimum.at(low, q, root[p])
            low = low[low]
            if (low == root).all():
                break
            root = low
        some = np.union1d(p, q)
        return pd.DataFrame({"cls": ids[some], "n": n[some], "root": ids[root[some]]})

    def run(batches):
        held, key = [], None
        for rows in batches:
            for k, part in rows.groupby(["leaf", "i", "j"], sort=False):
                if k != key:
                    if held:
                        yield task(pd.concat(held))
                    held, key = [], k
                held.append(part)
        if held:
            yield task(pd.concat(held))

    return materialize(dealt.mapInPandas(run, "cls long, n long, root long"), "forest_links")


def near_vectors(rows: DataFrame, least: float = 0.93) -> DataFrame:
    """vec_id, n_links, component_id and kept of every vector; links at cosine >= ``least`` within a label."""
    vectors, one = classes(rows)
    tight = math.cos(math.acos(least) / 2)
    found = compare(one, grow_forest(one, tight), least)
    roots = components(found.select(F.col("cls").alias("a"), F.col("root").alias("b")))
    counts = found.groupBy("cls").agg(F.sum("n").alias("n"))
    facts = one.select("cls", "copies").join(counts, "cls", "left").join(roots.select(F.col("v").alias("cls"), "root"), "cls", "left")
    facts = materialize(facts.select("cls", (F.coalesce("n", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("root", "cls").alias("group")), "forest_facts")
    linked = materialize(vectors.where("cls is not null").join(facts.hint("merge"), "cls").select("vec_id", "n_links", "group"), "forest_linked")
    leasts = materialize(linked.groupBy("group").agg(F.min("vec_id").alias("component_id")), "forest_least")
    out = linked.join(leasts.hint("merge"), "group").select("vec_id", "n_links", "component_id")
    alone = vectors.where("cls is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return out.unionByName(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
