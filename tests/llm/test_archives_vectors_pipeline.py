"""ARC and WARC files, vectors, and the pipeline."""

import gzip
import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from bcfilter.llm import queries, rp_forest, warc
from bcfilter.llm.common import new_path


def test_archive_query_matches_duckdb(spark, sf, duck):
    cols = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"]
    got = sorted(map(str, (tuple(r) for r in queries.op4_arc_to_warc(spark, sf).select(*cols).collect())))
    want = sorted(map(str, duck.execute(f"SELECT {', '.join(cols)} FROM ({queries.ORACLE_SQL['op4_arc_to_warc']})").fetchall()))
    assert got == want


def test_odd_pages(spark):
    rows = [(1, "http://a b/\n", "x"), (2, None, "x"), (3, "u", None), (4, "u", ""), (5, "u", "é" * 200000), (None, "u", "x"), (1, "http://a b/\n", "x")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("payload", F.lit(1))
    got = warc.archive_pages(pages).collect()
    assert len(got) == 7
    x = [r for r in got if r.payload_digest == warc.digest32(b"x")]
    assert sorted((str(r.page_id), r.record_type, r.refers_to) for r in x) == [("1", "response", None), ("1", "revisit", 1), ("2", "revisit", 1), ("None", "revisit", 1)]
    assert sorted((r.page_id, r.record_type, r.refers_to) for r in got if r.payload_bytes == 0) == [(3, "response", None), (4, "revisit", 3)]
    assert [r.payload_bytes for r in got if r.page_id == 5] == [400000]
    assert warc.archive_pages(pages.limit(0)).count() == 0


def test_payload_comes_back_byte_for_byte(spark, sf):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    want = {r.page_id: r.html.encode() for r in pages.collect()}
    got = {r.page_id: bytes(r.payload) for r in warc.archive_pages(pages).where("record_type = 'response'").collect()}
    assert got and all(want[i] == b for i, b in got.items())


@pytest.mark.parametrize("version", [1, 2])
@pytest.mark.parametrize("packed", [False, True])
def test_arc_versions_plain_and_packed(tmp_path, version, packed):
    name = tmp_path / ("a.arc.gz" if packed else "a.arc")
    blocks = [warc.http_block(7, b"one\n\n"), warc.http_block(None, b""), b"HTTP/1.0 200 OK\n\nplain"]
    body = f"{version} 0 test\n{warc.ARC_FIELDS[version]}\n\n".encode()
    records = [f"filedesc://a.arc 0.0.0.0 19990101000000 text/plain {len(body)}\n".encode() + body + b"\n"]
    records += [warc.arc_header(version, f"http://h/{i} x", "19990102030405", b, "a.arc", 0) + b + b"\n" for i, b in enumerate(blocks)]
    name.write_bytes(b"".join(map(gzip.compress if packed else bytes, records)))
    got = list(warc.arc_records(str(name)))
    assert [b for _, _, b in got] == blocks and [m["URL"] for _, m, _ in got] == [f"http://h/{i} x" for i in range(3)]
    assert {m["Archive-date"] for _, m, _ in got} == {"19990102030405"} and warc.iso_date("19990102030405") == "1999-01-02T03:04:05Z"


def test_broken_arc_is_refused(tmp_path):
    name = tmp_path / "b.arc"
    body = f"1 0 t\n{warc.ARC_FIELDS[1]}\n\n".encode()
    name.write_bytes(f"filedesc://b 0 0 t {len(body)}\n".encode() + body + b"\nhttp://x 0 1 text/html 50\nshort")
    with pytest.raises(ValueError):
        list(warc.arc_records(str(name)))


def test_warc_records_carry_their_fields(spark, tmp_path):
    pages = spark.createDataFrame([(1, "http://h/", "same"), (2, "http://i/", "same")], "page_id long, url string, html string")
    files = warc.arc_to_warc(warc.write_arc(pages, new_path(spark, "arc")), new_path(spark, "warc"))
    records = [x for r in files.collect() for x in warc.warc_records(r.path)]
    kinds = {f["warc-type"] for f, _ in records}
    assert kinds == {"warcinfo", "response", "revisit"}
    response = next(f for f, _ in records if f["warc-type"] == "response")
    revisit = next(f for f, _ in records if f["warc-type"] == "revisit")
    assert revisit["warc-refers-to"] == response["warc-record-id"] and revisit["warc-profile"] == warc.PROFILE
    assert response["warc-payload-digest"] == "sha1:" + warc.digest32(b"same") and hashlib.sha1(b"same").hexdigest()


# --- vectors ----------------------------------------------------------------------------------------------------


def brute_links(rows, least=0.93):
    n, parent = {}, {}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ok = [(i, np.array(v, dtype=float), lab) for i, v, lab in rows if v is not None and lab is not None and len(v) and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    for i, *_ in rows:
        n[i], parent[i] = 0, i
    for k, (i, v, a) in enumerate(ok):
        for j, w, b in ok[:k]:
            if a == b and len(v) == len(w) and v @ w / np.linalg.norm(v) / np.linalg.norm(w) >= least:
                n[i] += 1
                n[j] += 1
                x, y = root(i), root(j)
                parent[max(x, y)] = min(x, y)
    return {i: (n[i], root(i)) for i, *_ in rows}


def test_vectors_equal_brute_force(spark):
    rng = np.random.default_rng(1)
    rows = []
    centre = rng.standard_normal((40, 16))
    for i in range(1500):
        c = centre[i % 40] if i % 3 else rng.standard_normal(16)
        rows.append((i, (c + 0.12 * rng.standard_normal(16)).tolist(), int(i % 2)))
    rows += [(2000 + i, rows[0][1], 0) for i in range(5)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    want = brute_links(rows)
    got = {r.vec_id: r for r in rp_forest.near_vectors(df).collect()}
    assert sum(g.n_links for g in got.values()) >= 0.97 * sum(w[0] for w in want.values())
    assert all(got[i].n_links <= want[i][0] for i in want)
    assert sum(got[i].component_id == want[i][1] for i in want) >= 0.99 * len(want)


def test_odd_vectors(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(1, [1.0, 0.0], 0), (2, [2.0, 0.0], 0), (3, [1.0, 0.0], 1), (4, [0.0, 0.0], 0), (5, None, 0), (6, [1.0, None], 0), (7, [nan, 1.0], 0), (8, [inf, 1.0], 0), (9, [1.0, 0.0], None), (10, [], 0), (11, [1.0, 0.0, 0.0], 0), (12, [1.0, 0.0], 0), (13, [1e200, 1.0], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").withColumn("copies", F.lit("x"))
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in rp_forest.near_vectors(df).collect()}
    assert got[1] == (3, 1, True) and got[2] == (3, 1, False) and got[12] == (3, 1, False) and got[13] == (3, 1, False)
    assert all(got[i] == (0, i, True) for i in (3, 4, 5, 6, 7, 8, 9, 10, 11))
    assert rp_forest.near_vectors(df.limit(0)).count() == 0


# --- pipeline ---------------------------------------------------------------------------------------------------


def test_stages_keep_columns_and_take_effect(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    sizes, at = [docs.count()], docs
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, at, sf)
        if k < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns
        path = new_path(spark, "test_stage")
        out.write.parquet(path)
        at = spark.read.parquet(path)
        sizes.append(at.count())
    assert sizes[1] == sizes[0] and sizes[2] < sizes[1] and sizes[3] < sizes[2] and sizes[5] == sizes[4] > 0
    assert at.groupBy("doc_id").count().agg(F.max("count")).first()[0] <= 2


def test_stages_on_odd_and_empty_rows(spark, odd, none, sf):
    for docs in (odd, none):
        docs = docs.select("doc_id", "text", "lang", "source", "n_chars", "size")
        for _, stage in corpus_pipeline.STAGES:
            stage(spark, docs, sf).count()


def test_stages_decide_by_row_not_by_id(spark, sf):
    leak = spark.read.parquet(f"{sf}/benchmark.parquet").first()["text"]
    a, b = (" ".join(f"{x}{i}" for i in range(40)) for x in ("left", "right"))
    cols = "doc_id long, text string, lang string, source string, n_chars long"
    docs = spark.createDataFrame([(i, t, "en", "s", 1) for i in (None, 5) for t in (a, b, leak)], cols)
    kept = corpus_pipeline.keep_one_of_near_duplicates(spark, docs, sf).collect()
    assert sorted((r.doc_id, r.text) for r in kept) == sorted((5, t) for t in (a, b, leak))
    kept = corpus_pipeline.keep_clean_of_benchmarks(spark, docs, sf).collect()
    assert sorted(map(str, ((r.doc_id, r.text) for r in kept))) == sorted(map(str, ((i, t) for i in (None, 5) for t in (a, b))))
    many = spark.createDataFrame([(None, " ".join(["word"] * (1 + i % 5)), "en", "ab"[i % 2], 1) for i in range(200)], cols)
    total = many.count()
    taken = corpus_pipeline.mix_sources(spark, many, sf)
    words = taken.agg(F.sum(F.size(F.split("text", " ")))).first()[0]
    assert taken.count() > total and abs(words - 1.5 * 600) < 20
