"""Toxic passages as maximal scoring segments of token log-odds.

Tokens are runs of letters and digits, lower-cased, hashed into ``1 << BITS`` buckets. A token's share of toxic use has
a Dirichlet prior centred on the share of its first five bytes, which has one centred on the corpus share; the score
is the log-odds against the corpus share less a drift, so that ordinary text scores below zero. One linear scan per
text finds all maximal scoring segments. The sum of their scores, against the length of the text, is calibrated by an
extreme-value (Gumbel) law fitted to harmless training texts; a logistic curve turns the tail probability into a
score. Segments are reported with offsets and their own tail probability.

Learning uses only labelled rows given as training, at most about ``LABELLED`` of them, chosen by a hash of their id (a
documented bound of the classifier alone, so that ids and labels can be broadcast and no text is shuffled). What the
driver gets is bounded by the bucket numbers. Defined results: null and empty texts have no segments and the score of
no evidence; labels that are null teach nothing; with one class only, or no labels, every score is the share of that
class or 0; repeated rows are scored alike.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize
from .textbytes import PUNCTUATION, Words, slices

BITS, PREFIX_BITS = 20, 18
#: Chosen among 36 settings by halves of the training rows of sf0.1 alone (tests/llm/toxicity_settings.py).
TOKEN_PRIOR, PREFIX_PRIOR, DRIFT = 10.0, 2.0, 1.0
LEAST_TOXIC = 3
LABELLED = 500_000
GRID = 0.05


def _buckets(words: Words) -> tuple[np.ndarray, np.ndarray]:
    return (words.hash >> np.uint64(64 - BITS)).astype(np.int64), (words.prefix_hash(5) >> np.uint64(64 - PREFIX_BITS)).astype(np.int64)


def token_counts(train: DataFrame) -> DataFrame:
    """kind (0 token, 1 prefix), bucket, n texts and toxic texts that hold it, over ``train(text, toxic)``."""

    def run(batches):
        n = [np.zeros(1 << bits, dtype=np.int64) for bits in (BITS, PREFIX_BITS)]
        bad = [np.zeros(1 << bits, dtype=np.int64) for bits in (BITS, PREFIX_BITS)]
        for rows in batches:
            texts, toxic = rows["text"].tolist(), rows["toxic"].to_numpy()
            for a, b in slices(texts):
                w = Words(texts[a:b], PUNCTUATION)
                doc = np.repeat(np.arange(b - a), np.diff(w.first))
                for kind, code in enumerate(_buckets(w)):
                    once = np.unique(doc << BITS | code)
                    code = once & ((1 << BITS) - 1)
                    np.add.at(n[kind], code, 1)
                    np.add.at(bad[kind], code[toxic[a:b][once >> BITS] > 0], 1)
        for kind in (0, 1):
            at = np.flatnonzero(n[kind])
            yield pd.DataFrame({"kind": kind, "bucket": at, "n": n[kind][at], "bad": bad[kind][at]})

    rows = train.select("text", F.col("toxic").cast("int").alias("toxic")).mapInPandas(run, "kind int, bucket long, n long, bad long")
    return rows.groupBy("kind", "bucket").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))


class Model:
    """Counts by token bucket and toxic share by prefix bucket; scores are log-odds against ``share`` less the drift."""

    def __init__(self, share: float):
        self.share, self.prior, self.drift = share, TOKEN_PRIOR, DRIFT
        self.n = np.zeros(1 << BITS, np.float32)
        self.bad = np.zeros(1 << BITS, np.float32)
        self.prefix = np.full(1 << PREFIX_BITS, share, np.float32)

    def score(self, words: Words) -> np.ndarray:
        if not 0 < self.share < 1:
            return np.full(len(words.hash), -self.drift)
        token, prefix = _buckets(words)
        q = (self.bad[token] + self.prior * self.prefix[prefix]) / (self.n[token] + self.prior)
        return np.log(q / (1 - q)) - math.log(self.share / (1 - self.share)) - self.drift


def fit(train: DataFrame) -> Model:
    """Grouped counts of all training rows; the driver gets those of buckets in three toxic or twenty texts."""
    counts = materialize(token_counts(train), "tox_counts")
    n, bad = counts.where("kind = 0").agg(F.sum("n"), F.sum("bad")).first()
    model = Model(bad / n if n else 0.0)
    held = counts.where((F.col("bad") >= LEAST_TOXIC) | (F.col("n") >= 20)).toPandas()
    token, prefix = held[held["kind"] == 0], held[held["kind"] == 1]
    model.n[token["bucket"]], model.bad[token["bucket"]] = token["n"], token["bad"]
    model.prefix[prefix["bucket"]] = (prefix["bad"] + PREFIX_PRIOR * model.share) / (prefix["n"] + PREFIX_PRIOR)
    return model


def segments(score: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (start, end, score), left to right, in time linear in the text.

    Runs of positive scores are the starting pieces. Each new piece looks for the nearest earlier candidate whose left
    sum is lower; if that one's right sum is lower too, both become one piece and the search goes on from there.
    """
    up = score > 0
    edge = np.flatnonzero(np.diff(np.concatenate([[0], up.astype(np.int8), [0]])))
    if not len(edge):
        return []
    total = np.concatenate([[0.0], np.cumsum(score, dtype=np.float64)])
    held: list[list] = []
    for a, b in zip(edge[0::2].tolist(), edge[1::2].tolist()):
        left, right = float(total[a]), float(total[b])
        back = len(held) - 1
        while True:
            while back >= 0 and held[back][2] >= left:
                back = held[back][4]
            if back < 0 or held[back][3] >= right:
                held.append([a, b, left, right, back])
                break
            a, left = held[back][0], held[back][2]
            link = held[back][4]
            del held[back:]
            back = link
    return [(a, b, right - left) for a, b, left, right, _ in held]


def scan(docs: DataFrame, model: Model, least: float = 1.0) -> DataFrame:
    """doc_id, n tokens, total score of segments and the segments of at least ``least`` (code points, ends exclusive)."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(model)

    def run(batches):
        model = shared.value
        for rows in batches:
            texts = rows["text"].tolist()
            for a, b in slices(texts):
                w = Words(texts[a:b], PUNCTUATION)
                score = model.score(w)
                chars = w.chars_before()
                out = []
                for i in range(b - a):
                    p, q = w.first[i], w.first[i + 1]
                    found = [x for x in segments(score[p:q]) if x[2] >= least]
                    base = chars[w.offset[i]]
                    out.append([{"start": int(chars[w.start[p + s]] - base), "end": int(chars[w.end[p + e - 1]] - base), "score": float(v)} for s, e, v in found])
                yield pd.DataFrame({"doc_id": rows["doc_id"].iloc[a:b].to_numpy(), "n": np.diff(w.first), "total": [sum(x["score"] for x in o) for o in out], "segments": out})

    rows = docs.select(docs["doc_id"].cast("string").alias("doc_id"), docs["text"])
    out = rows.mapInPandas(run, "doc_id string, n long, total double, segments array<struct<start:int,end:int,score:double>>")
    return out.withColumn("doc_id", F.col("doc_id").cast("long"))


def logistic(grid: list[tuple[float, int, int]], steps: int = 100) -> tuple[float, float]:
    """Intercept and slope by damped Newton steps on (x, harmless, toxic) counts, with a unit normal prior on a scale."""
    x, n0, n1 = (np.array(v, dtype=float) for v in zip(*grid))
    mid = float((x * (n0 + n1)).sum() / (n0 + n1).sum())
    x = x - mid
    ridge = np.array([1e-6, 0.01])

    def loss(t):
        z = t[0] + t[1] * x
        return float((n0 * np.logaddexp(0, z) + n1 * np.logaddexp(0, -z)).sum() + (ridge * t * t).sum() / 2)

    t = np.zeros(2)
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(t[0] + t[1] * x, -500, 500)))
        w, r = (n0 + n1) * p * (1 - p), n1 - (n0 + n1) * p
        g = np.array([r.sum(), (r * x).sum()]) - ridge * t
        h = np.array([[w.sum(), (w * x).sum()], [(w * x).sum(), (w * x * x).sum()]]) + np.diag(ridge + 1e-9)
        step, size, now = np.linalg.solve(h, g), 1.0, loss(t)
        while size > 1e-8 and loss(t + size * step) > now:
            size /= 2
        t = t + size * step
        if np.abs(size * step).max() < 1e-9:
            break
    return float(t[0] - t[1] * mid), float(t[1])


def score_documents(docs: DataFrame, labels: DataFrame, training) -> DataFrame:
    """doc_id, score, segments with tail probability; ``training`` is a condition on doc_id for rows to learn from."""
    known = labels.where(F.col("toxic").isNotNull()).select(F.col("doc_id"), F.col("toxic").cast("int").alias("toxic")).where(training)
    known = materialize(known.groupBy("doc_id").agg(F.max("toxic").alias("toxic")), "tox_labels")
    share = min(1.0, LABELLED / max(1, known.count()))
    known = F.broadcast(known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < F.lit(int(share * (1 << 30)))))
    train = docs.select("doc_id", "text").join(known, "doc_id").select("text", "toxic")
    found = materialize(scan(docs, fit(train)), "tox_segments")
    seen = found.select("doc_id", "n", "total").join(known, "doc_id")
    # The location of a maximum grows with the log of the length: its slope over harmless training rows.
    cov, var = seen.where("toxic = 0").agg(F.covar_pop(F.log1p("n"), "total"), F.var_pop(F.log1p("n"))).first()
    slope = max(0.0, cov / var) if var else 0.0
    x = F.col("total") - F.lit(slope) * F.log1p("n")
    seen = seen.withColumn("x", x)
    grid = seen.groupBy(F.floor(F.col("x") / GRID).alias("bin")).agg(F.sum(1 - F.col("toxic")), F.sum("toxic")).collect()
    grid = [((b + 0.5) * GRID, n0, n1) for b, n0, n1 in grid]
    clean, bad = sum(g[1] for g in grid), sum(g[2] for g in grid)
    if not clean or not bad:
        flat = F.lit(bad / (clean + bad) if clean + bad else 0.0)
        return found.select("doc_id", flat.alias("score"), F.expr("transform(segments, s -> named_struct('start', s.start, 'end', s.end, 'score', s.score, 'tail', 1D))").alias("segments"))
    mean = sum(v * n for v, n, _ in grid) / clean
    sd = math.sqrt(max(0.01, sum(n * (v - mean) ** 2 for v, n, _ in grid) / clean))
    scale = sd * math.sqrt(6) / math.pi
    place = mean - 0.5772156649015329 * scale

    def evidence(v):
        """Log of one minus the log of P(X >= v) under the Gumbel law (whose tail far out is exp(-z))."""
        z = (v - place) / scale
        return math.log1p(z if z > 30 else -math.log(-math.expm1(-math.exp(-z))) if z > -6 else 0.0)

    a, b = logistic([(evidence(v), n0, n1) for v, n0, n1 in grid])
    z = lambda v: (v - F.lit(place)) / F.lit(scale)
    tail = lambda v: F.when(z(v) > 30, F.exp(-z(v))).when(z(v) > -6, -F.expm1(-F.exp(-z(v)))).otherwise(F.lit(1.0))
    g = F.log1p(F.when(z(x) > 30, z(x)).otherwise(-F.ln(tail(x))))
    score = F.lit(1.0) / (1 + F.exp(-(F.lit(a) + F.lit(b) * g)))
    marked = F.transform("segments", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["score"].alias("score"), tail(s["score"] - F.lit(slope) * F.log1p("n")).alias("tail")))
    return found.select("doc_id", score.alias("score"), marked.alias("segments"))
