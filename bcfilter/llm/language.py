"""Language identification by Bayesian fusion of text, markup, address and host evidence.

Text: byte trigrams hashed into ``1 << BITS`` buckets, one multinomial per language with a uniform Dirichlet prior,
fitted to at most about ``PER_LANGUAGE`` labelled rows of each language (chosen by hash; a documented bound of the
classifier alone). The log-likelihood is tempered, for trigrams of one text are not independent. Markup: the language
that an ``html`` element declares. Address: the country suffix or the first path part of the URL. Host: a prior for
each host, smoothed towards its domain, which is smoothed towards the corpus, from grouped sums of the text's
posteriors over all rows. The posterior is the product of the four.

A row is rejected if it has no letters, or if no language explains its letters: its best mean log-likelihood a
trigram is below that of the uniform distribution over the buckets. The floor is fixed: it depends neither on the
text's length nor on the training rows. Defined results: null and empty texts are
rejected with a null language; null markup, address or host are no evidence; repeated rows count each; without
labelled rows every language is null and nothing but empty text is rejected.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize
from .textbytes import slices

BITS, PER_LANGUAGE = 16, 4000
#: Cells of the table of languages by buckets; beyond 256 languages it has fewer buckets for each.
ROOM = 1 << 24
TEMPER, HOST_PRIOR, DOMAIN_PRIOR = 0.25, 10.0, 10.0
DECLARED_RIGHT, SUFFIX_RIGHT = 0.9, 0.8
# Country suffixes that name a language.
SUFFIXES = {"de": "de", "at": "de", "fr": "fr", "es": "es", "mx": "es", "ar": "es", "uk": "en", "us": "en", "au": "en", "it": "it", "pt": "pt", "br": "pt", "nl": "nl"}
_LOWER = np.arange(256, dtype=np.uint32)
_LOWER[65:91] += 32
_LETTER = np.array([b >= 128 or chr(b).isalpha() for b in range(256)])


def trigrams(texts: list, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of every trigram with a letter in its middle, and ``first[i]:first[i+1]`` of text i."""
    raw = [b"" if t is None else t.encode("utf-8", "surrogatepass") for t in texts]
    data = np.frombuffer(b"  " + b"  ".join(raw) + b"  ", dtype=np.uint8)
    low = np.where(_LETTER[data], _LOWER[data], 32).astype(np.uint32)
    code = (low[:-2] * np.uint32(0x9E3779B1) ^ low[1:-1] * np.uint32(0x85EBCA77) ^ low[2:] * np.uint32(0xC2B2AE3D)) * np.uint32(0x27D4EB2F) >> np.uint32(32 - bits)
    keep = np.flatnonzero(_LETTER[data[1:-1]])
    edges = np.concatenate([[1], 2 + np.cumsum([len(r) + 2 for r in raw]) - 1])
    return code[keep].astype(np.int64), np.searchsorted(keep, edges)


def fit(rows: DataFrame, room: int = ROOM) -> tuple[list[str], np.ndarray]:
    """Languages and log-probabilities (languages x buckets) from ``rows(id, text, lang)``."""
    rows = rows.where("lang is not null and text is not null")
    sizes = {r[0]: r[1] for r in rows.groupBy("lang").count().collect()}
    langs = sorted(sizes)
    if not langs:
        return [], np.zeros((0, 1 << BITS), np.float32)
    bits = max(1, min(BITS, (room // len(langs)).bit_length() - 1))
    share = F.lit(0.0)
    for k in langs:
        share = F.when(F.col("lang") == k, F.lit(min(1.0, PER_LANGUAGE / sizes[k]))).otherwise(share)
    sample = rows.where(F.pmod(F.xxhash64("id", "text"), F.lit(1_000_000)) < share * 1_000_000)

    def run(batches):
        total = {}
        for part in batches:
            for lang, own in part.groupby("lang"):
                texts = own["text"].tolist()
                for a, b in slices(texts):
                    n = np.bincount(trigrams(texts[a:b], bits)[0], minlength=1 << bits)
                    total[lang] = total[lang] + n if lang in total else n
        for lang, n in total.items():
            at = np.flatnonzero(n)
            yield pd.DataFrame({"lang": lang, "bucket": at, "n": n[at]})

    counts = sample.select("lang", "text").mapInPandas(run, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
    table = np.full((len(langs), 1 << bits), 0.1)
    table[[langs.index(x) for x in counts["lang"]], counts["bucket"]] += counts["n"]
    return langs, np.log(table / table.sum(axis=1, keepdims=True)).astype(np.float32)


def likelihoods(rows: DataFrame, langs: list[str], table: np.ndarray, keep: list[str]) -> DataFrame:
    """``keep`` columns, n trigrams and tempered log-likelihoods per language (array in the order of ``langs``)."""
    spark = rows.sparkSession
    shared = spark.sparkContext.broadcast(table)

    def run(batches):
        table = shared.value
        bits = table.shape[1].bit_length() - 1
        for part in batches:
            texts = part["text"].tolist()
            for a, b in slices(texts):
                code, first = trigrams(texts[a:b], bits)
                n = np.diff(first)
                ll = np.zeros((b - a, len(table)))
                some = np.flatnonzero(n)
                if len(some):
                    for k in range(len(table)):
                        ll[some, k] = np.add.reduceat(table[k][code].astype(np.float64), first[some])
                out = part[keep].iloc[a:b].copy()
                out["n"], out["ll"] = n, list(ll * TEMPER)
                yield out

    types = dict(rows.dtypes)
    rows = rows.select(*[F.col(c).cast("string").alias(c) for c in keep], "text")
    out = rows.mapInPandas(run, ", ".join(f"`{c}` string" for c in keep) + ", n long, ll array<double>")
    return out.withColumns({c: F.col(c).cast(types[c]) for c in keep if types[c] != "string"})


def _normal(logs: Column) -> Column:
    """Array of logs -> array of probabilities."""
    top = F.array_max(logs)
    raw = F.transform(logs, lambda v: F.exp(v - top))
    total = F.aggregate(raw, F.lit(0.0), lambda a, v: a + v)
    return F.transform(raw, lambda v: v / total)


def _named(name: Column, langs: list[str], right: float) -> Column:
    """Log-evidence of a named language for each language; none if the name is unknown."""
    wrong = (1 - right) / max(1, len(langs) - 1)
    known = F.coalesce(name.isin(langs), F.lit(False))
    return F.array(*[F.when(~known, F.lit(0.0)).when(name == k, F.lit(float(np.log(right)))).otherwise(F.lit(float(np.log(wrong)))) for k in langs])


def declared_language(html: Column) -> Column:
    return F.nullif(F.lower(F.regexp_extract(html, r"(?i)<html[^>]{0,200}?\slang\s*=\s*[\"']?([a-z]{2})", 1)), F.lit(""))


def address_language(url: Column) -> Column:
    host = F.regexp_extract(url, r"^[a-zA-Z]+://([^/:?#]+)", 1)
    suffix = F.regexp_extract(host, r"\.([a-z]{2})$", 1)
    path = F.regexp_extract(url, r"^[a-zA-Z]+://[^/]+/([a-z]{2})(?:[/?#]|$)", 1)
    named = None
    for k, v in SUFFIXES.items():
        named = F.when(suffix == k, F.lit(v)) if named is None else named.when(suffix == k, F.lit(v))
    return F.coalesce(F.nullif(path, F.lit("")), named)


def host_of(url: Column) -> Column:
    return F.nullif(F.lower(F.regexp_extract(url, r"^[a-zA-Z]+://([^/:?#]+)", 1)), F.lit(""))


def domain_of(host: Column) -> Column:
    """The last two labels of a host name."""
    return F.substring_index(host, ".", -2)


def identify(rows: DataFrame, labelled: DataFrame, id_col: str, least: float | None = None) -> DataFrame:
    """``rows(id, text, declared, address, host)`` -> id, lang, confidence, kept.

    ``labelled(id, text, lang)`` fits the text model. Host priors are sums over all of ``rows``.
    """
    langs, table = fit(labelled)
    if not langs:
        letters = F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False))
        return rows.select(id_col, F.lit(None).cast("string").alias("lang"), F.lit(0.0).alias("confidence"), letters.alias("kept"))
    seen = likelihoods(rows, langs, table, [id_col, "declared", "address", "host"])
    own = F.when(F.col("n") > 0, _normal(F.col("ll"))).otherwise(F.array(*[F.lit(1.0 / len(langs))] * len(langs)))
    seen = materialize(seen.withColumn("own", own).withColumn("domain", domain_of(F.col("host"))), "lang_text")
    sums = [F.sum(F.when(F.col("n") > 0, F.col("own")[k])).alias(f"s{k}") for k in range(len(langs))]
    hosts = seen.where("host is not null").groupBy("host", "domain").agg(*sums)
    hosts = materialize(hosts, "lang_hosts")
    cols = [f"s{k}" for k in range(len(langs))]
    total = hosts.agg(*[F.coalesce(F.sum(c), F.lit(0.0)) for c in cols]).first()
    base = (np.array(total, dtype=float) + 1) / (sum(total) + len(langs))
    domains = hosts.groupBy("domain").agg(*[F.coalesce(F.sum(c), F.lit(0.0)).alias(f"d{k}") for k, c in enumerate(cols)])
    d_sum = sum((F.col(f"d{k}") for k in range(len(langs))), F.lit(0.0))
    d = [(F.col(f"d{k}") + F.lit(DOMAIN_PRIOR * float(base[k]))) / (d_sum + DOMAIN_PRIOR) for k in range(len(langs))]
    h_sum = sum((F.coalesce(F.col(c), F.lit(0.0)) for c in cols), F.lit(0.0))
    h = [(F.coalesce(F.col(c), F.lit(0.0)) + HOST_PRIOR * d[k]) / (h_sum + HOST_PRIOR) for k, c in enumerate(cols)]
    prior = materialize(hosts.join(domains, "domain").select("host", F.array(*[F.ln(x) for x in h]).alias("prior")), "lang_prior")
    fused = seen.join(prior, "host", "left")
    flat = F.array(*[F.lit(float(np.log(b))) for b in base])
    parts = [F.coalesce(F.col("prior"), flat), _named(F.col("declared"), langs, DECLARED_RIGHT), _named(F.col("address"), langs, SUFFIX_RIGHT)]
    logs = F.col("ll")
    for p in parts:
        logs = F.zip_with(logs, p, lambda a, b: a + b)
    fused = fused.withColumn("post", _normal(logs))
    best = F.array_max("post")
    name = F.element_at(F.array(*[F.lit(x) for x in langs]), F.array_position("post", best).cast("int"))
    floor = F.lit(np.log(1.0 / table.shape[1]) * TEMPER if least is None else least * TEMPER)
    explained = F.array_max("ll") >= floor * F.col("n")
    return fused.select(
        id_col, F.when(F.col("n") > 0, name).alias("lang"), F.when(F.col("n") > 0, best).otherwise(F.lit(0.0)).alias("confidence"), ((F.col("n") > 0) & explained).alias("kept")
    )


def identify_documents(docs: DataFrame) -> DataFrame:
    """Documents: the source is the host; markup and address count where the text or the source holds them."""
    named = F.when(F.col("source").rlike(r"^[a-zA-Z]+://"), F.col("source"))
    rows = docs.select("doc_id", "text", declared_language(F.col("text")).alias("declared"), address_language(named).alias("address"), F.coalesce(host_of(named), F.col("source")).alias("host"))
    return identify(rows, docs.select(F.col("doc_id").alias("id"), "text", "lang"), "doc_id")


def identify_pages(pages: DataFrame, labelled: DataFrame) -> DataFrame:
    """Pages: tags are cut for the text likelihood; markup, address and host come from html and url."""
    text = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style)\b.*?</\1>", " "), r"<[^>]*>|&[a-zA-Z#0-9]+;", " ")
    rows = pages.select("page_id", text.alias("text"), declared_language(F.col("html")).alias("declared"), address_language(F.col("url")).alias("address"), host_of(F.col("url")).alias("host"))
    return identify(rows, labelled, "page_id")
