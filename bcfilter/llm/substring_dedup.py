"""Substring deduplication by hashing lines, paragraphs or content-defined pieces of lines.

A unit is a line (``unit="line"``), a paragraph between blank lines (``"paragraph"``), or a piece of a line
(``"piece"``): a line is cut after a word when a hash of that word and the next says so (one in four), so a passage is
cut alike wherever in a line it stands. Units are normalised (A-Z as a-z, white space ignored) and hashed; digests are
grouped over the corpus; the row of least rank (doc_id, then row) keeps a unit, and within it the first place. Of the
other occurrences every one goes that fills a whole line (or paragraph) of at least ``least_line`` words (1: all do),
and, of pieces, every run of consecutive repeated ones with at least ``least`` words: shorter runs repeat by chance.
A passage loses all but some words at either end, up to the first and from the last place where it is cut. Removal is
reported as spans of the original text (code points, ends exclusive) beside the text that is left.

Rows get a key of their own first, in a written table, so repeated rows and rows that share a doc_id remove each
other's units like all others. Digests that hold more than one in ``HOT`` of all occurrences are at most ``HOT`` in
number and meet their occurrences by broadcast; the others by shuffle.

Defined results: null or empty texts stay as they are, without spans; a null doc_id ranks last; an empty table gives
an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_table, materialize
from .textbytes import Words, mix64, slices

LAST = (1 << 63) - 1
_B = 0x9E3779B97F4A7C15
_B_INV = pow(_B, -1, 1 << 64)
LONGEST, HOT = 64, 4096
UNITS = ("piece", "line", "paragraph")


class Units:
    """Units of a batch: word ranges ``start``/``end``, ``hash``, ``line`` (or paragraph) and ``first[i]:first[i+1]`` of text i."""

    def __init__(self, texts: list, unit: str = "piece"):
        self.words = w = Words(texts)
        n = len(w.hash)
        if not n:
            self.start = self.end = self.line = np.zeros(0, np.int64)
            self.hash, self.first = np.zeros(0, np.int64), np.zeros(len(texts) + 1, np.int64)
            return
        breaks = np.zeros(len(w.data) + 1, dtype=np.int64)
        np.cumsum(w.data == 10, out=breaks[1:])
        line = breaks[w.start]
        own = np.zeros(n, dtype=bool)
        own[w.first[:-1][w.first[:-1] < n]] = True
        new = own.copy()
        new[1:] |= np.diff(line) >= (2 if unit == "paragraph" else 1)
        line = np.cumsum(new)
        cut = new
        if unit == "piece":
            cut = new.copy()
            cut[1:] |= mix64(w.hash[:-1] + (w.hash[1:] << np.uint64(1))) & np.uint64(3) == 0
        start = np.flatnonzero(cut)
        length = np.diff(np.append(start, n))
        if unit == "piece" and (length > LONGEST).any():
            start = np.concatenate([np.arange(s, s + k, LONGEST) for s, k in zip(start, length)])
        self.start, self.end = start, np.append(start[1:], n)
        up = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n, _B, dtype=np.uint64)]), dtype=np.uint64)
        down = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n, _B_INV, dtype=np.uint64)]), dtype=np.uint64)
        total = np.concatenate([[np.uint64(0)], np.cumsum(w.hash * up[:n], dtype=np.uint64)])
        self.hash = mix64((total[self.end] - total[self.start]) * down[self.start] + (self.end - self.start).astype(np.uint64)).view(np.int64)
        self.line = line[start]
        self.first = np.searchsorted(start, w.first)


def removed_units(hash_: np.ndarray, words: np.ndarray, line: np.ndarray, elsewhere: np.ndarray, least: int, least_line: int) -> np.ndarray:
    """Which units of one text go, given the digests whose first place is in another text."""
    again = np.ones(len(hash_), dtype=bool)
    again[np.unique(hash_, return_index=True)[1]] = False
    again |= np.isin(hash_, elsewhere)
    if not again.any():
        return again
    out = np.zeros(len(hash_), dtype=bool)
    total = np.concatenate([[0], np.cumsum(words)])

    def take(edge_from: np.ndarray, edge_to: np.ndarray, at_least: int) -> None:
        good = total[edge_to] - total[edge_from] >= at_least
        step = np.zeros(len(hash_) + 1, dtype=np.int64)
        np.add.at(step, edge_from[good], 1)
        np.add.at(step, edge_to[good], -1)
        out[np.cumsum(step[:-1]) > 0] = True

    edge = np.flatnonzero(np.diff(np.concatenate([[0], again.astype(np.int8), [0]])))
    take(edge[0::2], edge[1::2], least)
    edge = np.concatenate([[0], np.flatnonzero(np.diff(line)) + 1, [len(line)]])
    kept = np.concatenate([[0], np.cumsum(~again)])
    whole = kept[edge[:-1]] == kept[edge[1:]]
    take(edge[:-1][whole], edge[1:][whole], least_line)
    return out


def _rows(docs: DataFrame) -> DataFrame:
    """Written rows with a key of their own: row, rank, doc_id, text."""
    rank = F.coalesce(docs["doc_id"], F.lit(LAST)).cast("long")
    return materialize(docs.select(F.monotonically_increasing_id().alias("row"), rank.alias("rank"), docs["doc_id"], docs["text"]), "dedup_rows")


def repeated_digests(rows: DataFrame, unit: str = "piece") -> DataFrame:
    """row and the digests in it whose first row is another one."""

    def run(batches):
        for part in batches:
            texts = part["text"].tolist()
            for a, b in slices(texts):
                u = Units(texts[a:b], unit)
                own = part.iloc[a:b]
                yield pd.DataFrame({"row": own["row"].to_numpy(), "rank": own["rank"].to_numpy(), "units": [np.unique(u.hash[u.first[i] : u.first[i + 1]]) for i in range(b - a)]})

    found = materialize(rows.select("row", "rank", "text").mapInPandas(run, "row long, rank long, units array<long>"), "dedup_units")
    each = found.select("row", "rank", F.explode("units").alias("unit"))
    firsts = each.groupBy("unit").agg(F.min("rank").alias("first"), F.count("*").alias("n")).where("n > 1")
    firsts = materialize(firsts, "dedup_firsts")
    total = firsts.agg(F.sum("n")).first()[0] or 0
    hot = F.broadcast(firsts.where(F.col("n") * HOT > F.lit(total)).select("unit", "first"))
    cold = firsts.where(F.col("n") * HOT <= F.lit(total)).select("unit", "first")
    met = each.join(hot, "unit").unionByName(each.join(hot, "unit", "left_anti").join(cold, "unit"))
    met = materialize(met.select("row", "unit", (F.col("rank") > F.col("first")).alias("later")), "dedup_met")
    # Rows that share the least doc_id of a unit: the first of them keeps it.
    tied = met.where("not later").groupBy("unit").agg(F.min("row").alias("keeps"), F.max("row").alias("last")).where("keeps < last")
    tied = materialize(tied.select("unit", "keeps"), "dedup_tied")
    again = met.where("later").select("row", "unit")
    if not tied.isEmpty():
        again = again.unionByName(met.where("not later").join(tied, "unit").where("row > keeps").select("row", "unit"))
    again = materialize(again.groupBy("row").agg(F.collect_list("unit").alias("units")), "dedup_again")
    for done in (found, firsts, met, tied):
        drop_table(done)
    return again


def dedup_substrings(docs: DataFrame, least: int = 8, least_line: int = 1, unit: str = "piece") -> DataFrame:
    """doc_id, text that is left, spans removed (``start:end`` joined by commas), removed_chars and removed_words."""
    if unit not in UNITS:
        raise ValueError(f"unit is one of {UNITS}")

    def run(batches):
        for rows in batches:
            texts, ids, units = rows["text"].tolist(), rows["doc_id"].tolist(), rows["units"].tolist()
            for a, b in slices(texts):
                u = Units(texts[a:b], unit)
                w = u.words
                sizes = u.end - u.start
                # Only texts with a repeated unit, their own or another's, are looked at one by one.
                text_of = np.repeat(np.arange(b - a), np.diff(u.first))
                order = np.lexsort((u.hash, text_of))
                twice = text_of[order][1:][(np.diff(u.hash[order]) == 0) & (np.diff(text_of[order]) == 0)]
                seen = [x is not None for x in units[a:b]]
                for i in twice.tolist():
                    seen[i] = True
                chars = w.chars_before() if any(seen) else None
                out = []
                for i in range(b - a):
                    text = texts[a + i]
                    if not seen[i]:
                        out.append((ids[a + i], text, "", 0, 0))
                        continue
                    p, q = u.first[i], u.first[i + 1]
                    elsewhere = np.array([] if units[a + i] is None else units[a + i], dtype=np.int64)
                    gone = removed_units(u.hash[p:q], sizes[p:q], u.line[p:q], elsewhere, least if unit == "piece" else LAST, least_line)
                    edge = np.flatnonzero(np.diff(np.concatenate([[0], gone.astype(np.int8), [0]]))) + p
                    base = chars[w.offset[i]]
                    spans = []
                    for s, e in zip(edge[0::2], edge[1::2]):
                        lo, hi = w.start[u.start[s]], w.end[u.end[e - 1] - 1]
                        spans.append((int(chars[lo] - base), int(chars[hi] - base)))
                    left, at = [], 0
                    for s, e in spans:
                        left.append(text[at:s])
                        at = e
                    out.append((ids[a + i], text if not spans else "".join(left) + text[at:], ",".join(f"{s}:{e}" for s, e in spans), sum(e - s for s, e in spans), int(sizes[p:q][gone].sum())))
                yield pd.DataFrame(out, columns=["doc_id", "text", "spans", "removed_chars", "removed_words"])

    rows = _rows(docs)
    again = repeated_digests(rows, unit)
    texts = rows.select("row", F.col("doc_id").cast("string").alias("doc_id"), "text")
    out = texts.join(again, "row", "left").select("doc_id", "text", "units").mapInPandas(run, "doc_id string, text string, spans string, removed_chars long, removed_words long")
    return out.withColumn("doc_id", F.col("doc_id").cast("long"))
