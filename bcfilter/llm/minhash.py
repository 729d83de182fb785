"""Near-duplicate documents by fast similarity sketching, banding and exact verification.

Sketch: in round i every shingle is hashed to one of ``T`` bins with a value that starts with i, so earlier rounds win;
from round T on, each round serves one bin alone. Rounds go on until every bin is full, which takes one or two for
texts with more than some hundred shingles and never more than 2T. Coordinates agree with the Jaccard similarity as
probability and concentrate as well as independent ones.

Banding: as many coordinates to a key as keep the chance that a pair at the threshold shares no key below 1e-4 (8 at
0.85, 6 at 0.8). Documents that share a key, directly or through others, form a cluster. Clusters are cut into blocks
of about ``BLOCK`` documents and every pair of blocks is a task of bounded size, whatever the size of the cluster. In
clusters beyond ``WIDE`` blocks the documents of each key are compared instead, where that takes fewer copies of sets:
a long chain of texts of which each resembles the next costs in proportion to its length. In a task sketches are
compared first: a pair agreeing in five standard deviations less of the 256 coordinates than one at the threshold is
passed over (chance of error below 1e-5). The others are verified on their full sets, most similar first, unless already connected in the task. What leaves a task
is a spanning forest of verified links, not all pairs.

Sets hold 64-bit hashes of shingles. Sets that agree in two independent 64-bit identities are equal and have one
representative from the start, so exact copies are profiled but not compared. Defined results: null or empty texts (or without words) have an empty set and are linked with nothing; fewer
words than the shingle size make one shingle; a document of null doc_id takes part, ids in results are minima over
the ids that are not null; repeated rows share a component; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_table, materialize
from .components import components
from .textbytes import Words, mix64, shingles, slices

T, BLOCK, WIDE = 256, 128, 32
_SEEDS = mix64(np.arange(1, 2 * T + 1, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95))
_LOW = np.uint64((1 << 55) - 1)
SECOND = 0xE7037ED1A0B428DB


def plan(percent: int) -> tuple[int, int, int]:
    """Coordinates to a key, keys, and least agreeing coordinates for a threshold in percent."""
    s = percent / 100
    rows = max(r for r in range(1, 17) if (1 - s**r) ** (T // r) <= 1e-4 or r == 1)
    return rows, T // rows, int(T * s - 5 * (T * s * (1 - s)) ** 0.5)


def sketch(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Sketches (texts x T, uint64) of sets ``values[bounds[i]:bounds[i+1]]``; rows of empty sets stay unfilled."""
    n = len(bounds) - 1
    full = np.uint64(0xFFFFFFFFFFFFFFFF)
    out = np.full(n * T, full, dtype=np.uint64)
    sizes = np.diff(bounds)
    doc = np.repeat(np.arange(n), sizes)
    x = values
    for i in range(2 * T):
        if not len(x):
            break
        h = mix64(x ^ _SEEDS[i])
        bins = (h >> np.uint64(56)).astype(np.int64) if i < T else i - T
        np.minimum.at(out, doc * T + bins, np.uint64(i << 55) | (h & _LOW))
        at = np.unique(doc)
        short = np.zeros(n, dtype=bool)
        short[at] = (out.reshape(n, T)[at] == full).any(axis=1)
        keep = short[doc]
        x, doc = x[keep], doc[keep]
    return out.reshape(n, T)


def band_keys(s: np.ndarray, rows: int, bands: int) -> np.ndarray:
    """(texts x bands) keys as signed longs."""
    part = s[:, : rows * bands].reshape(len(s), bands, rows)
    key = np.broadcast_to(mix64(np.arange(1, bands + 1, dtype=np.uint64)), (len(s), bands)).copy()
    for j in range(rows):
        key = mix64(key * np.uint64(0x9E3779B97F4A7C15) + part[:, :, j])
    return key.view(np.int64)


def set_ids(values: np.ndarray, bounds: np.ndarray, seed: int = 0xA0761D6478BD642F) -> np.ndarray:
    """One 64-bit identity for each set."""
    total = np.concatenate([[np.uint64(0)], np.cumsum(mix64(values ^ np.uint64(seed)), dtype=np.uint64)])
    sums = total[bounds[1:]] - total[bounds[:-1]]
    return mix64(sums + np.diff(bounds).astype(np.uint64)).view(np.int64)


def profile(docs: DataFrame, size: int, percent: int) -> DataFrame:
    """doc_id, tkey, n, rid (null for empty sets), a second identity and band keys of every document."""
    per_key, bands, _ = plan(percent)

    def run(batches):
        for rows in batches:
            texts = rows["text"].tolist()
            for a, b in slices(texts):
                values, bounds = shingles(Words(texts[a:b]), size)
                n = np.diff(bounds)
                keys = band_keys(sketch(values, bounds), per_key, bands)
                ids = set_ids(values, bounds)
                part = rows.iloc[a:b]
                yield pd.DataFrame({"doc_id": part["doc_id"].to_numpy(), "tkey": part["tkey"].to_numpy(), "n": n,
                                    "rid": pd.Series(ids).astype("Int64").where(pd.Series(n > 0)), "second": set_ids(values, bounds, SECOND),
                                    "keys": [k if m else None for k, m in zip(keys, n)]})

    rows = docs.select(docs["doc_id"].cast("string").alias("doc_id"), F.xxhash64(docs["text"]).alias("tkey"), docs["text"])
    out = rows.mapInPandas(run, "doc_id string, tkey long, n long, rid long, second long, keys array<long>")
    return out.withColumn("doc_id", F.col("doc_id").cast("long"))


def representatives(seen: DataFrame) -> DataFrame:
    """rid, the least document that stands for it, its second identity and the greatest second identity met."""
    least = F.min(F.struct("second", "doc_id", "tkey"))
    return materialize(seen.where("n > 0").groupBy("rid").agg(least.alias("x"), F.max("second").alias("most")), "near_first")


def told_apart(seen: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Profiles in which sets of one identity but different second ones have identities of their own, and representatives."""
    first = representatives(seen)
    clash = first.where("x.second < most").select("rid", F.col("x.second").alias("stays"))
    if clash.isEmpty():
        return seen, first
    rid = F.when(F.col("second") > F.col("stays"), F.xxhash64("rid", "second")).otherwise(F.col("rid"))
    apart = seen.join(clash, "rid", "left").withColumn("rid", rid).select(*seen.columns)
    apart = materialize(apart, "near_profile")
    return apart, representatives(apart)


def candidates(profiles: DataFrame) -> DataFrame:
    """(a, b) for every set and the least set of each band key it shares."""
    exploded = profiles.where("n > 0").select("rid", F.explode("keys").alias("key")).distinct()
    keys = exploded.groupBy("key").agg(F.min("rid").alias("a"), F.max("rid").alias("most")).where("a < most")
    keys = materialize(keys.select("key", "a"), "near_keys")
    return exploded.join(keys, "key").where("rid <> a").select("a", F.col("rid").alias("b")).distinct()


def sets_of(docs: DataFrame, wanted: DataFrame, size: int) -> DataFrame:
    """Full sets and sketch bytes of the documents that stand for a clustered set."""

    def run(batches):
        for rows in batches:
            texts = rows["text"].tolist()
            for a, b in slices(texts):
                values, bounds = shingles(Words(texts[a:b]), size)
                part = rows.iloc[a:b].copy()
                ok = set_ids(values, bounds, SECOND) == part["second"].to_numpy()
                part["coords"] = [x.tobytes() for x in mix64(sketch(values, bounds)).astype(np.uint8)]
                part["members"] = [values[bounds[i] : bounds[i + 1]].tobytes() for i in range(b - a)]
                yield part.loc[ok, ["rid", "clusters", "blocks", "coords", "members"]]

    texts = docs.select(docs["doc_id"], F.xxhash64(docs["text"]).alias("tkey"), docs["text"])
    hit = (texts["tkey"] == wanted["tkey"]) & texts["doc_id"].eqNullSafe(wanted["doc_id"])
    joined = texts.join(wanted.hint("merge"), hit).select("text", "rid", "second", "clusters", "blocks")
    return joined.mapInPandas(run, "rid long, clusters array<long>, blocks array<int>, coords binary, members binary")


def _verify(ids: np.ndarray, side: np.ndarray, coords: np.ndarray, members: list, percent: int, cut: int, cross: bool) -> list[tuple[int, int]]:
    """Spanning links among the documents of one task."""
    size = np.array([len(m) // 8 for m in members])
    found = []
    for r in range(len(ids) - 1):
        ok = ((coords[r] == coords[r + 1 :]).sum(axis=1) >= cut) & (100 * np.minimum(size[r], size[r + 1 :]) >= percent * np.maximum(size[r], size[r + 1 :]))
        ok &= ids[r] != ids[r + 1 :]
        if cross:
            ok &= side[r] != side[r + 1 :]
        for c in np.flatnonzero(ok):
            found.append((-int((coords[r] == coords[r + 1 + c]).sum()), r, r + 1 + int(c)))
    parent = list(range(len(ids)))

    def root(v: int) -> int:
        while parent[v] != v:
            parent[v] = parent[parent[v]]
            v = parent[v]
        return v

    sets: dict[int, np.ndarray] = {}
    out = []
    for _, r, c in sorted(found):
        x, y = root(r), root(c)
        if x == y:
            continue
        u = sets.setdefault(r, np.frombuffer(members[r], dtype=np.uint64))
        v = sets.setdefault(c, np.frombuffer(members[c], dtype=np.uint64))
        both = len(np.intersect1d(u, v, assume_unique=True))
        if 100 * both >= percent * (len(u) + len(v) - both):
            parent[max(x, y)] = min(x, y)
            out.append((int(ids[r]), int(ids[c])))
    return out


def verified_links(sets: DataFrame, percent: int) -> DataFrame:
    """(a, b): links that hold on the full sets and connect what the cluster's links connect."""
    cut = plan(percent)[2]

    def run(batches):
        held: list[pd.DataFrame] = []
        key = None

        def close():
            rows = pd.concat(held) if len(held) > 1 else held[0]
            coords = np.frombuffer(b"".join(rows["coords"]), dtype=np.uint8).reshape(len(rows), T)
            i, j = key[1], key[2]
            return pd.DataFrame(_verify(rows["rid"].to_numpy(), rows["own"].to_numpy(), coords, rows["members"].tolist(), percent, cut, i != j), columns=["a", "b"])

        for rows in batches:
            k = rows[["cluster", "i", "j"]].to_numpy()
            cuts = [0, *(np.flatnonzero((k[1:] != k[:-1]).any(axis=1)) + 1).tolist(), len(rows)]
            for a, b in zip(cuts, cuts[1:]):
                if a == b:
                    continue
                now = tuple(k[a])
                if now != key:
                    if held:
                        yield close()
                    held, key = [], now
                held.append(rows.iloc[a:b])
        if held:
            yield close()

    sets = sets.withColumn("g", F.explode(F.arrays_zip("clusters", "blocks"))).select("rid", "coords", "members", F.col("g.clusters").alias("cluster"), F.col("g.blocks").alias("blocks"))
    own = F.pmod(F.xxhash64(F.lit(3), "rid"), F.col("blocks")).cast("int")
    dealt = sets.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("cluster", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "rid", "coords", "members")
    dealt = dealt.repartition("cluster", "i", "j").sortWithinPartitions("cluster", "i", "j", "rid")
    return dealt.mapInPandas(run, "a long, b long")


def groups(seen: DataFrame, clusters: DataFrame) -> DataFrame:
    """rid with the groups (``clusters``, each in so many ``blocks``) in which its set is compared.

    The group is the cluster; in clusters beyond ``WIDE`` blocks it is each band key, where that deals out fewer sets.
    """
    dealt = lambda n: F.ceil(n / F.lit(BLOCK)).cast("int")
    sizes = materialize(clusters.groupBy("root").agg(F.count("*").alias("size"), dealt(F.count("*")).alias("blocks")), "near_blocks")
    whole = clusters.join(sizes.select("root", "blocks"), "root").select(F.col("v").alias("rid"), F.array("root").alias("clusters"), F.array("blocks").alias("blocks"), "root")
    wide = sizes.where(F.col("blocks") > WIDE)
    if wide.isEmpty():
        return whole.drop("root")
    members = clusters.join(wide, "root").select(F.col("v").alias("rid"), "root")
    keyed = seen.where("n > 0").join(members, "rid").select("rid", "root", F.explode("keys").alias("key")).distinct()
    keyed = materialize(keyed, "near_wide")
    by_key = keyed.groupBy("root", "key").agg(F.count("*").alias("n")).where("n > 1").withColumn("blocks", dealt(F.col("n")))
    by_key = materialize(by_key, "near_wide_keys")
    cost = by_key.groupBy("root").agg(F.sum(F.col("n") * F.col("blocks")).alias("cost"))
    narrow = wide.join(cost, "root").where(F.col("cost") < F.col("size") * F.col("blocks")).select("root")
    narrow = materialize(narrow, "near_narrow")
    each = keyed.join(by_key.join(narrow, "root").select("key", "blocks"), "key")
    each = each.groupBy("rid").agg(F.collect_list(F.struct("key", "blocks")).alias("g")).select("rid", F.col("g.key").alias("clusters"), F.col("g.blocks").alias("blocks"))
    return whole.join(narrow, "root", "left_anti").drop("root").unionByName(each)


def near_duplicates(docs: DataFrame, size: int = 3, percent: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every document; links at 100 * both >= percent * either."""
    seen, first = told_apart(materialize(profile(docs, size, percent), "near_profile"))
    clusters = components(candidates(seen))
    wanted = groups(seen, clusters).join(first, "rid")
    wanted = materialize(wanted.select("x.doc_id", "x.tkey", "x.second", "rid", "clusters", "blocks"), "near_wanted")
    links = materialize(verified_links(sets_of(docs, wanted, size), percent), "near_links")
    for done in (wanted, first, clusters):
        drop_table(done)
    return label(seen, components(links))


def label(seen: DataFrame, found: DataFrame) -> DataFrame:
    """Components of sets carried to documents."""
    found = found.select(F.col("v").alias("rid"), "root")
    sets = seen.where("n > 0").select("doc_id", F.col("n").alias("n_shingles"), "rid").join(found, "rid", "left")
    sets = materialize(sets.select("doc_id", "n_shingles", F.coalesce("root", "rid").alias("group")), "near_groups")
    least = materialize(sets.groupBy("group").agg(F.min("doc_id").alias("component_id")), "near_least")
    linked = sets.join(least, "group").select("doc_id", "n_shingles", "component_id")
    alone = seen.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    return linked.unionByName(alone).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))
