"""Benchmark decontamination by latent semantic retrieval, then order and answer checks.

Texts in lower case become word codes once (a written table that all passes read). Passages of ``NARROWEST`` words, scaled by their
words' weights, are the rows of a TF-IDF matrix over ``1 << FEATURE_BITS`` hashed words of the whole corpus; document
frequencies are counted over all documents in ``1 << DF_BITS`` buckets. A single-pass randomised SVD gives the latent
space: tasks sum the product of the Gram matrix with a random matrix, and the Nystroem form of that product holds the
leading ``RANK`` right singular directions. Benchmark items take no part in it, so the space is fitted once, whatever
the benchmark.

Every text is searched in windows of widths that double from ``NARROWEST`` on, stepping by half a width; an item is
searched in the least width that holds it. A window's vector is the weighted sum of its words' rows of the space, so
windows of all widths are sums of the narrowest half windows. Candidates are pairs whose cosine, normalised in the
space, is at least that of a window which shares ``LOOSE`` of the item's words, ``LOOSE * sqrt(length / width)``, and
never below ``COSINE``, where the window is twice as long as the item. Beside them a window that holds ``RUN`` words of an item in a row (a whole shorter item) is a candidate whatever its
cosine, so a verbatim copy is compared at any size of the corpus. A candidate counts as a leak when the longest common
subsequence of the item and the window with half a width on either side covers ``ORDER`` of the item's words, or, for
paraphrases, ``LOOSE`` of them and most of its answer (its last sentence). Candidates with fewer words of the item than
``LOOSE`` asks for are dropped before the subsequence is computed, for it cannot be longer. Items of less than ``RUN``
words have no latent candidates: they leak where they stand word by word.

Items are taken in blocks of at most ``ITEMS``, so what is broadcast is bounded whatever the benchmark; the space
(``1 << FEATURE_BITS`` by ``RANK`` floats) is the largest of it. Defined results: null and empty texts hold no window;
items with fewer than ``SHORTEST`` words are not searched, for one or two words stand in clean texts too; repeated rows
of a document or of an item are reported once for each pair of ids; empty tables give an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize
from .textbytes import _BASE, PUNCTUATION, Words, mix64, slices

NARROWEST = 32
ORDER, LOOSE, ANSWER = 0.6, 0.45, 0.8
COSINE = LOOSE / 2**0.5
RANK, SPARE = 28, 4
ITEMS, RUN, SHORTEST = 1024, 5, 3
FEATURE_BITS, DF_BITS, GATE_BITS = 16, 18, 22
#: Words a task sums before its part of the Gram product is shuffled.
TASK_WORDS = 1 << 24
#: Windows that are compared with the items at once; words of pieces, words of terms and pairs that are worked on at once (a cache holds them).
CHUNK, SUMMED, TERMS, PAIRS = 2048, 4096, 8192, 8192
#: Hashed words of the vocabulary, for the bound on the common subsequence, and how often their bits are folded in turn.
BELONGS, FOLDS = 4096, (16, 4, 1)


def codes(words: Words) -> np.ndarray:
    """Words as 32-bit codes."""
    return (words.hash >> np.uint64(32)).astype(np.uint32)


def feature(code: np.ndarray) -> np.ndarray:
    return code >> np.uint32(32 - FEATURE_BITS)


def place(code: np.ndarray) -> np.ndarray:
    """Bucket of the document frequencies."""
    return code >> np.uint32(32 - DF_BITS)


class Items:
    """A block of items: words as positions in the sorted vocabulary, width, and how many last words are the answer."""

    def __init__(self, rows: list[tuple]):
        words = Words([t.lower() for _, t in rows], PUNCTUATION)
        code = codes(words)
        keep = [i for i in range(len(rows)) if words.first[i + 1] - words.first[i] >= SHORTEST]
        self.ids = [rows[i][0] for i in keep]
        spans = [(words.first[i], words.first[i + 1]) for i in keep]
        self.codes = [code[a:b] for a, b in spans]
        self.vocabulary = np.unique(np.concatenate(self.codes)) if keep else np.zeros(0, np.uint32)
        self.words = [np.searchsorted(self.vocabulary, c).astype(np.int32) for c in self.codes]
        self.size = np.array([len(w) for w in self.words], dtype=np.int64)
        self.width = np.array([max(NARROWEST, 1 << int(n - 1).bit_length()) for n in self.size], dtype=np.int64)
        count = np.concatenate([[0], np.cumsum((words.data == 46) | (words.data == 63) | (words.data == 33))])
        self.answer = []
        for a, b in spans:
            sentence = count[words.start[a:b]]
            self.answer.append(max(1, int((sentence == sentence[-1]).sum())))
        self.where = [places(w.tolist()) for w in self.words]
        self.where_answer = [places(w[-n:].tolist()) for w, n in zip(self.words, self.answer)]
        self._index()

    def __getstate__(self) -> dict:
        """Without the tables, which are many times larger than what they are made from."""
        return {k: v for k, v in vars(self).items() if k not in ("masks", "table", "crowded", "runs")}

    def __setstate__(self, state: dict) -> None:
        vars(self).update(state)
        self._index()

    def _index(self) -> None:
        # Places of each hashed word in an item of up to 64 words, as bits of one number.
        self.masks = np.zeros((len(self.ids), BELONGS + 1), dtype=np.uint64)
        for q, w in enumerate(self.words):
            if len(w) <= 64:
                np.bitwise_or.at(self.masks[q], w % BELONGS, np.uint64(1) << np.arange(len(w), dtype=np.uint64))
        at = (self.vocabulary >> np.uint32(32 - GATE_BITS)).astype(np.int64)
        self.table = np.full(1 << GATE_BITS, -1, dtype=np.int32)
        self.table[at[::-1]] = np.arange(len(at), dtype=np.int32)[::-1]
        self.crowded = np.zeros(1 << GATE_BITS, dtype=bool)
        self.crowded[at[1:][at[1:] == at[:-1]]] = True
        self.runs = {}
        for n in range(SHORTEST, RUN + 1):
            held = [(q, runs(w, np.arange(len(w) - n + 1), n)) for q, w in enumerate(self.words) if min(RUN, len(w)) == n]
            if held:
                run = np.concatenate([r for _, r in held])
                item = np.repeat([q for q, _ in held], [len(r) for _, r in held])
                order = np.argsort(run, kind="stable")
                own, first = np.unique(run[order], return_index=True)
                gate = np.zeros(1 << GATE_BITS, dtype=bool)
                gate[(own >> np.uint64(64 - GATE_BITS)).astype(np.int64)] = True
                self.runs[n] = own, np.split(item[order], first[1:]), gate

    def lookup(self, code: np.ndarray) -> np.ndarray:
        """Position in the vocabulary, -1 for other words."""
        at = (code >> np.uint32(32 - GATE_BITS)).astype(np.int64)
        out = self.table[at]
        some = np.flatnonzero(out >= 0)
        wrong = some[self.vocabulary[out[some]] != code[some]]
        out[wrong] = -1
        again = wrong[self.crowded[at[wrong]]]
        if len(again):
            near = np.minimum(np.searchsorted(self.vocabulary, code[again]), len(self.vocabulary) - 1)
            hit = self.vocabulary[near] == code[again]
            out[again[hit]] = near[hit]
        return out

    def held(self, term: np.ndarray, first: np.ndarray) -> list[tuple[np.ndarray, np.ndarray, list]]:
        """For each run length: starts of runs of an item in the texts, which run, and the items of each run."""
        out = []
        of = np.repeat(np.arange(len(first) - 1), np.diff(first))
        known = np.concatenate([[0], np.cumsum(term >= 0)])
        for n, (own, items, gate) in self.runs.items():
            some = np.flatnonzero(known[n:] - known[:-n] == n) if len(term) >= n else np.zeros(0, np.int64)
            some = some[of[some] == of[some + n - 1]]
            run = runs(term, some, n)
            near = gate[(run >> np.uint64(64 - GATE_BITS)).astype(np.int64)]
            some, run = some[near], run[near]
            at = np.minimum(np.searchsorted(own, run), len(own) - 1)
            hit = own[at] == run
            out.append((n, some[hit], at[hit], items))
        return out


def runs(term: np.ndarray, start: np.ndarray, size: int = RUN) -> np.ndarray:
    """Hash of the ``size`` terms from each start on."""
    out = np.zeros(len(start), dtype=np.uint64)
    for j in range(size):
        out = mix64(out * _BASE + term[start + j].astype(np.uint64) + np.uint64(1))
    return out


def places(a: list) -> dict:
    """Where each word of ``a`` stands, as bits."""
    where: dict = {}
    for i, x in enumerate(a):
        where[x] = where.get(x, 0) | 1 << i
    return where


def lcs(size: int, where: dict, b: list) -> int:
    """Length of the longest common subsequence of ``b`` and a list of ``size`` words at ``where``, bit-parallel."""
    full = (1 << size) - 1
    v = full
    for m in map(where.get, b):
        if m:
            u = v & m
            v = ((v + u) | (v - u)) & full
    return size - v.bit_count()


def lcs_bound(items: Items, which: np.ndarray, near: np.ndarray) -> np.ndarray:
    """Common subsequence of items of up to 64 words and columns of hashed words; words that share a hash count as equal."""
    full = ~np.uint64(0) >> (64 - items.size[which]).astype(np.uint64)
    masks, row = items.masks.ravel(), which * items.masks.shape[1]
    v = full.copy()
    for word in near:
        u = v & masks.take(row + word)
        v = ((v + u) | (v - u)) & full
    return items.size[which] - np.bitwise_count(v)


def fold(bits: np.ndarray, times: int) -> np.ndarray:
    """Rows of bits laid on each other ``times`` over (a power of two), so that they are as many times shorter."""
    while times > 1:
        half = bits.shape[1] // 2
        bits, times = bits[:, :half] | bits[:, half:], times // 2
    return bits


def common(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Bits that rows of ``a`` and ``b`` have in common."""
    n = np.bitwise_count(a & b)
    if n.shape[1] == 4:  # four counts stand in one number
        n = n.view(np.uint32)[:, 0]
        n = (n & np.uint32(0xFF00FF)) + (n >> np.uint32(8) & np.uint32(0xFF00FF))
        return (n + (n >> np.uint32(16)) & np.uint32(0xFFFF)).astype(np.int64)
    return n.sum(axis=1, dtype=np.int64)


def tokens(docs: DataFrame) -> DataFrame:
    """doc_id, n words and their codes as 4 bytes each; and for each task a row of n = -1 - its documents, with ``counts``
    of documents by bucket in ``places``, so that the document frequencies need no pass of their own."""

    def run(batches):
        total, seen = np.zeros(1 << DF_BITS, dtype=np.int32), 0
        for rows in batches:
            texts = rows["text"].tolist()
            seen += len(texts)
            for a, b in slices(texts):
                w = Words([None if t is None else t.lower() for t in texts[a:b]], PUNCTUATION)
                code, n = codes(w), np.diff(w.first)
                held = np.repeat(np.arange(b - a, dtype=np.int64), n) << DF_BITS | place(code).astype(np.int64)
                held.sort()
                once = held[np.diff(held, prepend=-1) != 0]
                total += np.bincount(once & ((1 << DF_BITS) - 1), minlength=1 << DF_BITS).astype(np.int32)
                raw, at = code.tobytes(), (4 * w.first).tolist()
                yield pd.DataFrame({"doc_id": rows["doc_id"].iloc[a:b].to_numpy(), "n": n, "terms": [raw[i:j] for i, j in zip(at, at[1:])], "places": None, "counts": None})
        at = np.flatnonzero(total).astype(np.int32)
        yield pd.DataFrame({"doc_id": [None], "n": [-1 - seen], "terms": [None], "places": [at], "counts": [total[at]]})

    rows = docs.select(docs["doc_id"].cast("string").alias("doc_id"), docs["text"])
    return materialize(rows.mapInPandas(run, "doc_id string, n long, terms binary, places array<int>, counts array<int>"), "leak_tokens")


def flat(rows: pd.DataFrame, most: int = 1 << 18):
    """(from, codes, first) of slices with about ``most`` words or a single longer text."""
    n = rows["terms"].map(len).to_numpy() // 4
    a = 0
    while a < len(n):
        b = max(a + 1, a + int(np.searchsorted(np.cumsum(n[a:]), most, side="right")))
        first = np.concatenate([[0], np.cumsum(n[a:b])])
        yield a, np.frombuffer(b"".join(rows["terms"].iloc[a:b]), dtype=np.uint32), first
        a = b


def inverse_frequencies(found: DataFrame) -> np.ndarray:
    """ln((1 + N) / (1 + df)) over all documents, by bucket."""

    def pack(batches):
        for rows in batches:
            yield pd.DataFrame({"place": [rows["place"].to_numpy(np.int64).tobytes()], "n": [rows["n"].to_numpy(np.int64).tobytes()]})

    parts = found.where("n < 0")
    each = parts.select(F.explode(F.arrays_zip(F.col("places").alias("place"), F.col("counts").alias("n"))).alias("x")).select("x.place", "x.n")
    counts = each.groupBy(F.col("place").cast("long").alias("place")).agg(F.sum("n").alias("n"))
    df, n = np.zeros(1 << DF_BITS), parts.agg(F.sum(-1 - F.col("n"))).first()[0] or 0
    for r in counts.mapInPandas(pack, "place binary, n binary").toLocalIterator():
        df[np.frombuffer(r["place"], np.int64)] = np.frombuffer(r["n"], np.int64)
    return (np.log((1 + n) / (1 + df)) + 1e-3).astype(np.float32)


def cuts(first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts of the pieces of ``size`` that each text is cut into, and the first piece of each text."""
    pieces = -(-np.diff(first) // size)
    bounds = np.concatenate([[0], np.cumsum(pieces)])
    step = np.arange(bounds[-1]) - np.repeat(bounds[:-1], pieces)
    return np.repeat(first[:-1], pieces) + size * step, bounds


def sums(matrix: np.ndarray, row: np.ndarray, weight: np.ndarray, start: np.ndarray, size: int) -> np.ndarray:
    """Weighted sums of rows of ``matrix`` over the pieces that begin at ``start``, none of them longer than ``size``."""
    out = np.zeros((len(start), matrix.shape[1]), dtype=np.float32)
    matrix, row = np.ascontiguousarray(matrix), row.astype(np.intp)
    end, step = np.append(start[1:], len(row)), np.arange(size)
    pieces = max(1, SUMMED // size)
    for a in range(0, len(start), pieces):
        b = min(a + pieces, len(start))
        at = start[a:b, None] + step
        inside = at < end[a:b, None]
        np.minimum(at, len(row) - 1, out=at)
        own = np.where(inside, weight.take(at), np.float32(0))
        out[a:b] = np.matmul(own[:, None, :], matrix.take(row.take(at), axis=0))[:, 0]
    return out


def gram_times(found: DataFrame, idf: np.ndarray, right: np.ndarray) -> np.ndarray:
    """(A'A) times ``right`` for the matrix of all passages."""
    shared = found.sparkSession.sparkContext.broadcast((idf, right.astype(np.float32)))

    def run(batches):
        idf, right = shared.value
        total = np.zeros(right.shape, dtype=np.float32)
        seen = np.zeros(len(right), dtype=bool)
        for rows in batches:
            for _, code, first in flat(rows):
                if not len(code):
                    continue
                start, _ = cuts(first, NARROWEST)
                weight, term = idf[place(code)], feature(code)
                scale = 1 / np.sqrt(np.add.reduceat(weight * weight, start))
                of = np.repeat(np.arange(len(start)), np.diff(np.append(start, len(code))))
                weight = weight * scale[of]
                y = sums(right, term, weight, start, NARROWEST)
                order = np.argsort(term.astype(np.uint16), kind="stable")
                term, weight, of = term[order], weight[order], of[order]
                at = np.flatnonzero(np.append(True, term[1:] != term[:-1]))
                own, end, a = term[at].astype(np.intp), np.append(at[1:], len(order)), 0
                while a < len(own):
                    b = max(a + 1, int(np.searchsorted(end, at[a] + TERMS, side="right")))
                    lo, hi = at[a], end[b - 1]
                    parts = y.take(of[lo:hi], axis=0)
                    parts *= weight[lo:hi, None]
                    total[own[a:b]] += np.add.reduceat(parts, at[a:b] - lo, axis=0)
                    a = b
                seen[own] = True
        at = np.flatnonzero(seen)
        yield pd.DataFrame({"term": at, "v": [x.tobytes() for x in total[at]]})

    def add(batches):
        held: dict[int, np.ndarray] = {}
        for rows in batches:
            for t, v in zip(rows["term"], rows["v"]):
                v = np.frombuffer(v, dtype=np.float32)
                if t in held:
                    held[t] += v
                else:
                    held[t] = v.astype(np.float64)
        yield pd.DataFrame({"term": list(held), "v": [x.astype(np.float32).tobytes() for x in held.values()]})

    # Few tasks with many words each: a task's part is as large as its words are many kinds, whatever their number.
    found = found.where("n > 0")
    words = found.agg(F.sum("n")).first()[0] or 0
    tasks = max(found.sparkSession.sparkContext.defaultParallelism, -(-words // TASK_WORDS))
    parts = found.select("terms").coalesce(tasks).mapInPandas(run, "term long, v binary")
    total = np.zeros(right.shape)
    for r in parts.repartition("term").mapInPandas(add, "term long, v binary").toLocalIterator():
        total[r["term"]] = np.frombuffer(r["v"], dtype=np.float32)
    return total


def latent_space(found: DataFrame, idf: np.ndarray, seed: int = 11) -> np.ndarray:
    """Leading right singular directions (hashed words x rank) over their singular values, from one pass.

    A text's product with it is where that text would stand among the left singular vectors.
    """
    right = np.random.default_rng(seed).standard_normal((1 << FEATURE_BITS, RANK + SPARE))
    product = gram_times(found, idf, right)
    middle = right.T @ product
    value, vector = np.linalg.eigh((middle + middle.T) / 2)
    good = value > max(1e-12, 1e-9 * value[-1])
    half = product @ (vector[:, good] / np.sqrt(value[good]))
    directions, size, _ = np.linalg.svd(half, full_matrices=False)
    good = size[:RANK] > 1e-6 * size.max(initial=1.0)
    return np.ascontiguousarray(directions[:, :RANK][:, good] / size[:RANK][good], dtype=np.float32)


def unit(rows: np.ndarray) -> np.ndarray:
    size = np.linalg.norm(rows, axis=1, keepdims=True)
    return np.divide(rows, size, out=np.zeros_like(rows), where=size > 0)


class Search:
    """Items with their place in the space, for one block."""

    def __init__(self, items: Items, idf: np.ndarray, space: np.ndarray):
        self.items, self.idf, self.space = items, idf, space
        code = np.concatenate(items.codes)
        start = np.concatenate([[0], np.cumsum(items.size)[:-1]])
        self.latent = unit(sums(space, feature(code), idf[place(code)], start, int(items.size.max()))) if space.shape[1] else np.zeros((len(start), 0), np.float32)
        self.latent[items.size < RUN] = 0
        self.least = np.maximum(COSINE, LOOSE * np.sqrt(items.size / items.width)).astype(np.float32)

    def found(self, code: np.ndarray, first: np.ndarray) -> list[tuple]:
        """(text, item, cosine, order share, answer share) of leaks in a slice of texts."""
        out: list[tuple] = []
        if not len(code):
            return out
        items = self.items
        term = items.lookup(code)
        held = items.held(term, first)
        half = NARROWEST // 2
        start, bounds = cuts(first, half)
        block = sums(self.space, feature(code), self.idf[place(code)], start, half)
        # The words of the items that a half window holds, as bits.
        known = np.flatnonzero(term >= 0)
        of = np.repeat(np.arange(len(start)), np.diff(np.append(start, len(term))))[known]
        bits = np.zeros(len(start) * (BELONGS // 64), dtype=np.uint64)
        np.bitwise_or.at(bits, of * (BELONGS // 64) + (term[known] % BELONGS >> 6), np.uint64(1) << (term[known] & 63).astype(np.uint64))
        bits = bits.reshape(len(start), -1)
        hashed = np.where(term >= 0, term % BELONGS, BELONGS)
        while True:
            if (items.width == 2 * half).any():
                self._level(out, term, hashed, bits, first, held, start, bounds, block, half)
            if 2 * half >= items.width.max():
                return out
            half *= 2
            pair, bounds = cuts(bounds, 2)
            two = np.flatnonzero(np.diff(np.append(pair, len(start))) == 2)
            more = pair[two] + 1
            start, add, also = start[pair], block[more], bits[more]
            block, bits = block[pair], bits[pair]
            block[two] += add
            bits[two] |= also

    def _level(self, out, term, hashed, bits, first, held, start, bounds, block, half) -> None:
        """Windows of two half windows that follow each other (one, in a text that has no more)."""
        items = self.items
        own = np.flatnonzero(items.width == 2 * half)
        mine = np.zeros((len(own), BELONGS // 64), dtype=np.uint64)
        for i, q in enumerate(own):
            np.bitwise_or.at(mine[i], items.words[q] % BELONGS >> 6, np.uint64(1) << (items.words[q] & 63).astype(np.uint64))
        # Words of an item beyond its distinct hashed ones may all be met, so they are taken as met.
        sieves = []
        for times in FOLDS:
            theirs = fold(mine, times)
            spare = items.size[own] - np.bitwise_count(theirs).sum(axis=1, dtype=np.int64)
            sieves.append((fold(bits, times), theirs, np.ceil(LOOSE * items.size[own] - 1e-9).astype(np.int64) - spare))
        local = np.full(len(items.ids), -1)
        local[own] = np.arange(len(own))
        n = np.diff(bounds)
        text = np.repeat(np.arange(len(n)), n)
        last = bounds[1:][text] - 1
        at = np.flatnonzero((np.arange(len(text)) < last) | (n[text] == 1))
        text, lo = text[at], start[at]
        hi = np.minimum(lo + 2 * half, first[text + 1])
        runs_of: dict[int, list] = {}
        for size, begin, which, of in held:
            a, b = np.searchsorted(begin, lo), np.searchsorted(begin, hi - size, side="right")
            for p in np.flatnonzero(a < b):
                q = np.unique(np.concatenate([of[x] for x in np.unique(which[a[p] : b[p]])]))
                q = local[q[items.width[q] == 2 * half]]
                if len(q):
                    runs_of.setdefault(int(p), []).append(q)
        ran = np.array(sorted(runs_of), dtype=np.int64)

        def around(rows: np.ndarray, which: np.ndarray) -> np.ndarray:
            """Bits of windows with half a width on either side, from those of half windows."""
            i = at[which]
            near, begin, end = rows[i], bounds[text[which]], bounds[text[which] + 1]
            for step in (-1, 1, 2):
                inside = np.flatnonzero((i + step >= begin) & (i + step < end))
                near[inside] |= rows[i[inside] + step]
            return near

        chunk = max(1, CHUNK * NARROWEST // half)
        for a in range(0, len(at), chunk):
            b = min(a + chunk, len(at))
            z = block[at[a:b]] + np.where((n[text[a:b]] > 1)[:, None], block[np.minimum(at[a:b] + 1, len(block) - 1)], 0)
            cosine = unit(z) @ self.latent[own].T
            close = cosine >= self.least[own]
            for p in ran[np.searchsorted(ran, a) : np.searchsorted(ran, b)]:
                for q in runs_of[int(p)]:
                    close[p - a, q] = True
            cell = np.flatnonzero(close)
            some = np.arange(b - a)
            for rows, theirs, need in sieves:
                # The words near those windows that are still in a pair.
                there = around(rows, a + some)
                row = np.zeros(b - a, dtype=np.int64)
                row[some] = np.arange(len(some))
                kept = [np.zeros(0, np.int64)]
                for i in range(0, len(cell), PAIRS):
                    pair = cell[i : i + PAIRS]
                    p = pair // len(own)
                    q = pair - p * len(own)
                    kept.append(pair[common(there.take(row.take(p), axis=0), theirs.take(q, axis=0)) >= need.take(q)])
                cell = np.concatenate(kept)
                some = np.unique(cell // len(own))
            p, q = np.divmod(cell, len(own))
            some = np.arange(len(cell))
            left, right = np.maximum(first[text[a:b]], lo[a:b] - half)[p], np.minimum(first[text[a:b] + 1], hi[a:b] + half)[p]
            if 2 * half <= 64:
                fits = [np.zeros(0, np.int64)]
                for i in range(0, len(some), PAIRS):
                    k = some[i : i + PAIRS]
                    spot = left[k] + np.arange(4 * half)[:, None]
                    word = np.where(spot < right[k], hashed.take(np.minimum(spot, len(hashed) - 1)), BELONGS)
                    fits.append(k[lcs_bound(items, own[q[k]], word) >= LOOSE * items.size[own[q[k]]] - 1e-9])
                some = np.concatenate(fits)
            for k in some:
                i = own[q[k]]
                near, size = term[left[k] : right[k]].tolist(), int(items.size[i])
                order = lcs(size, items.where[i], near) / size
                if order < LOOSE or (size < RUN and order < 1):
                    continue
                answer = lcs(items.answer[i], items.where_answer[i], near) / items.answer[i]
                if order >= ORDER or answer >= ANSWER:
                    out.append((int(text[a + p[k]]), items.ids[i], float(cosine[p[k], q[k]]), order, answer))


def _block(found: DataFrame, idf: np.ndarray, space: np.ndarray, rows: list[tuple]) -> DataFrame | None:
    items = Items(rows)
    if not items.ids:
        return None
    shared = found.sparkSession.sparkContext.broadcast(Search(items, idf, space))

    def run(batches):
        search = shared.value
        for rows in batches:
            ids = rows["doc_id"].to_numpy()
            for a, code, first in flat(rows):
                hits = [(ids[a + t], *more) for t, *more in search.found(code, first)]
                yield pd.DataFrame(hits, columns=["doc_id", "item_id", "cosine", "order_share", "answer_share"])

    out = found.where("n > 0").select("doc_id", "terms").mapInPandas(run, "doc_id string, item_id long, cosine double, order_share double, answer_share double")
    return out.withColumn("doc_id", F.col("doc_id").cast("long"))


def leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id and the best cosine, order share and answer share of every leak."""
    found = tokens(docs)
    idf = inverse_frequencies(found)
    space = latent_space(found, idf)
    rows, out, block = benchmark.select("item_id", "text").where("text is not null").orderBy("item_id"), None, []

    def more(out, block):
        own = _block(found, idf, space, block)
        return own if out is None else out if own is None else out.unionByName(own)

    for r in rows.toLocalIterator():
        block.append((r[0], r[1]))
        if len(block) == ITEMS:
            out, block = more(out, block), []
    if block:
        out = more(out, block)
    if out is None:
        out = docs.sparkSession.createDataFrame([], "doc_id long, item_id long, cosine double, order_share double, answer_share double")
    return out.groupBy("doc_id", "item_id").agg(*[F.max(c).alias(c) for c in ("cosine", "order_share", "answer_share")])
