"""How the priors and the drift of the toxicity operator were chosen: ``python tests/llm/toxicity_settings.py [folder]``.

Only labelled rows whose checksum leaves remainder 0 or 2 are read. Each half is scored by counts of the other one;
a setting is worth the mean of the best F1 of the two. Rows of remainder 1 take no part.
"""

import itertools
import math
import os
import sys
import zlib

import duckdb
import numpy as np

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__)))))
from bcfilter.llm import toxicity as T  # noqa: E402
from bcfilter.llm.textbytes import PUNCTUATION, Words  # noqa: E402

TOKEN, PREFIX, DRIFT = (1.0, 3.0, 10.0), (2.0, 5.0, 20.0), (0.5, 1.0, 2.0, 3.0)


class Half:
    def __init__(self, rows: list):
        self.words = Words([t for t, _ in rows], PUNCTUATION)
        self.toxic = np.array([y for _, y in rows])
        self.buckets = T._buckets(self.words)
        doc = np.repeat(np.arange(len(rows)), np.diff(self.words.first))
        self.counts = []
        for code, bits in zip(self.buckets, (T.BITS, T.PREFIX_BITS)):
            once = np.unique(doc << T.BITS | code)
            code = once & ((1 << T.BITS) - 1)
            n = np.bincount(code, minlength=1 << bits).astype(float)
            bad = np.bincount(code, weights=self.toxic[once >> T.BITS], minlength=1 << bits)
            held = (bad >= T.LEAST_TOXIC) | (n >= 20)
            self.counts.append((n * held, bad * held))
        self.share = self.counts[0][1].sum() / self.counts[0][0].sum()


def best_f1(train: Half, other: Half, token: float, prefix: float, drift: float) -> float:
    (n, bad), (pn, pbad) = train.counts
    near = (pbad + prefix * train.share) / (pn + prefix)
    t, p = other.buckets
    q = (bad[t] + token * near[p]) / (n[t] + token)
    score = np.log(q / (1 - q)) - math.log(train.share / (1 - train.share)) - drift
    first = other.words.first
    total = np.array([sum(x[2] for x in T.segments(score[a:b]) if x[2] >= 1.0) for a, b in zip(first[:-1], first[1:])])
    length, clean = np.log1p(np.diff(first)), other.toxic == 0
    slope = max(0.0, np.cov(length[clean], total[clean])[0, 1] / max(1e-9, length[clean].var()))
    found = np.cumsum(other.toxic[np.argsort(-(total - slope * length), kind="stable")])
    return float((2 * found / (np.arange(1, len(found) + 1) + found[-1])).max())


def main(folder: str) -> None:
    docs = f"SELECT d.doc_id, d.text, max(l.toxic)::INT FROM '{folder}/documents.parquet' d JOIN '{folder}/labels.parquet' l USING (doc_id) WHERE l.toxic IS NOT NULL GROUP BY 1, 2 ORDER BY 1"
    halves: dict[int, list] = {0: [], 1: [], 2: []}
    for i, text, toxic in duckdb.sql(docs).fetchall():
        halves[zlib.crc32(str(i).encode()) % 3].append((text, toxic))
    a, b = Half(halves[0]), Half(halves[2])
    worth = sorted(((best_f1(a, b, *s) + best_f1(b, a, *s)) / 2, s) for s in itertools.product(TOKEN, PREFIX, DRIFT))
    for f1, setting in reversed(worth):
        print(f"{f1:.4f} token prior {setting[0]:g}, prefix prior {setting[1]:g}, drift {setting[2]:g}")


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.1")
