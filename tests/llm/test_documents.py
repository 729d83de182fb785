"""Document operators: odd inputs, brute force, invariants and held-out accuracy."""

import collections
import hashlib
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from bcfilter.llm import decontaminate, language, minhash, mixing, queries, secret_scan, sharding, substring_dedup, toxicity
from bcfilter.llm.common import small_batches
from bcfilter.llm.textbytes import PUNCTUATION, Words

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def docs_of(spark, sf, name="documents"):
    return spark.read.parquet(f"{sf}/{name}.parquet")


# --- near duplicates --------------------------------------------------------------------------------------------


def brute_components(rows, size=3, percent=85):
    sets = []
    for i, t in rows:
        w = words((t or "").translate(LOWER))
        sets.append((i, {tuple(w[k : k + size]) for k in range(len(w) - size + 1)} or ({tuple(w)} if w else set())))
    parent = list(range(len(sets)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(sets)):
        for b in range(a):
            u, v = sets[a][1], sets[b][1]
            both = len(u & v)
            if both and 100 * both >= percent * (len(u) + len(v) - both):
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    least = {}
    for k, (i, _) in enumerate(sets):
        if i is not None:
            least[root(k)] = min(i, least.get(root(k), i))
    return collections.Counter((i, len(s), least.get(root(k))) for k, (i, s) in enumerate(sets))


@pytest.mark.parametrize("size,percent", [(3, 85), (5, 80)])
def test_near_duplicates_equal_brute_force(spark, sf, size, percent):
    docs = docs_of(spark, sf)
    got = collections.Counter((r.doc_id, r.n_shingles, r.component_id) for r in minhash.near_duplicates(docs, size, percent).collect())
    assert got == brute_components([(r.doc_id, r.text) for r in docs.collect()], size, percent)


def test_near_duplicates_odd_rows(odd, none):
    got = collections.Counter((r.doc_id, r.n_shingles, r.component_id) for r in minhash.near_duplicates(odd).collect())
    assert got == brute_components([(r.doc_id, r.text) for r in odd.collect()])
    assert minhash.near_duplicates(none).count() == 0


def test_a_group_of_near_copies_over_many_blocks(spark):
    """400 copies with their own edits: more than one block, one component, and strangers left alone."""
    import random

    rng = random.Random(3)
    base = [f"w{rng.randrange(10**6)}" for _ in range(200)]
    rows = []
    for i in range(400):
        own = list(base)
        for _ in range(i % 3):
            own[rng.randrange(200)] = f"e{rng.randrange(10**6)}"
        rows.append((i, " ".join(own)))
    rows += [(1000 + i, " ".join(f"s{rng.randrange(10**6)}" for _ in range(100))) for i in range(20)]
    got = {r.doc_id: r.component_id for r in minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert collections.Counter((i, got[i]) for i in got) == collections.Counter((i, c) for i, _, c in brute_components(rows))


def test_a_long_chain_is_compared_by_key(spark, monkeypatch):
    """Each text resembles the next few: keys deal out fewer sets than blocks of the cluster, with the same result."""
    monkeypatch.setattr(minhash, "BLOCK", 16)
    monkeypatch.setattr(minhash, "WIDE", 4)
    rows = [(i, " ".join(f"w{k}" for k in range(8 * i, 8 * i + 200))) for i in range(600)]
    rows += [(1000 + i, rows[0][1] + f" near{i}") for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    seen, _ = minhash.told_apart(minhash.profile(docs, 3, 85))
    clusters = minhash.components(minhash.candidates(seen))
    dealt = minhash.groups(seen, clusters).selectExpr("size(clusters) AS n", "aggregate(blocks, 0, (a, b) -> a + b) AS copies").toPandas()
    size = clusters.count()
    assert dealt["n"].max() > 1
    assert dealt["copies"].sum() < size * -(-size // 16)
    got = collections.Counter((r.doc_id, r.n_shingles, r.component_id) for r in minhash.near_duplicates(docs).collect())
    assert got == brute_components(rows)


def test_sets_of_one_identity_are_told_apart(spark):
    rows = [(1, 11, 5, 7, 100), (2, 12, 5, 7, 200), (3, 13, 5, 7, 200), (4, 14, 5, 8, 300), (5, 15, 0, None, 0)]
    seen = spark.createDataFrame(rows, "doc_id long, tkey long, n long, rid long, second long").withColumn("keys", F.array(F.lit(1).cast("long")))
    apart, first = minhash.told_apart(seen)
    rid = {r.doc_id: r.rid for r in apart.collect()}
    assert rid[1] == 7 and rid[2] == rid[3] not in (7, 8) and rid[4] == 8 and rid[5] is None
    assert {r.rid: (r.x.doc_id, r.x.second) for r in first.collect()} == {7: (1, 100), rid[2]: (2, 200), 8: (4, 300)}


def test_sketch_estimates_similarity():
    import numpy as np

    rng = np.random.default_rng(0)
    pool = rng.integers(1, 2**62, 3000).astype(np.uint64)
    for both, own in ((900, 50), (500, 250), (3, 2)):
        a, b = pool[: both + own], np.concatenate([pool[:both], pool[both + own : both + 2 * own]])
        s = minhash.sketch(np.concatenate([a, b]), np.array([0, len(a), len(a) + len(b)]))
        assert (s != np.uint64(0xFFFFFFFFFFFFFFFF)).all()
        assert abs((s[0] == s[1]).mean() - both / (both + 2 * own)) < 0.12


# --- substring deduplication ------------------------------------------------------------------------------------


def test_repeated_lines_and_passages(spark):
    import random

    rng = random.Random(1)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(7))
    passage = " ".join(word() for _ in range(80))
    line = " ".join(word() for _ in range(9))
    other = [" ".join(word() for _ in range(60)) for _ in range(6)]
    rows = [
        (1, f"{other[0]} {passage} {other[1]}"), (2, f"{other[2]} {passage.upper()} {other[3]}"), (3, f"{line}\n{other[4]}"), (4, f"{other[5]}\n{line}\n"), (5, None), (6, ""),
    ]
    got = {r.doc_id: r for r in substring_dedup.dedup_substrings(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [got[i].spans for i in (1, 3, 5, 6)] == [""] * 4 and got[1].text == rows[0][1] and got[5].text is None
    a, b = map(int, got[2].spans.split(":"))
    cut = rows[1][1][a:b]
    assert len(words(cut)) >= 55 and cut.lower() in passage and got[2].text == rows[1][1][:a] + rows[1][1][b:]
    s = got[4].spans.split(":")
    assert rows[3][1][int(s[0]) : int(s[1])] == line


def brute_units(rows, pattern):
    """Spans of the units found by ``pattern`` whose normal form stands earlier, in rows ordered by id (null last), row."""
    seen, out = set(), {}
    for k in sorted(range(len(rows)), key=lambda k: (rows[k][0] is None, rows[k][0] or 0, k)):
        spans = []
        for m in re.finditer(pattern, rows[k][1] or ""):
            w = tuple(words(m.group().translate(LOWER)))
            if not w:
                continue
            at = [x.span() for x in re.finditer(r"[^\x20\x09-\x0D]+", m.group())]
            spans += [(m.start() + at[0][0], m.start() + at[-1][1])] if w in seen else []
            seen.add(w)
        out[k] = spans
    return collections.Counter((rows[k][0], tuple(s)) for k, s in out.items())


def joined(text, spans):
    """Spans with those that only white space parts taken together, as the operator reports them."""
    out = []
    for s, e in spans:
        if out and not (text or "")[out[-1][1] : s].strip(" \t\n\r\v\f"):
            out[-1] = (out[-1][0], e)
        else:
            out.append((s, e))
    return tuple(out)


@pytest.mark.parametrize("unit,pattern", [("line", r"[^\n]+"), ("paragraph", r"(?:[^\n]|\n(?![ \t\r\v\f]*\n))+")])
def test_repeated_units_equal_brute_force(spark, sf, odd, unit, pattern):
    """Every repeated line or paragraph goes, however short, also those of equal rows and of rows that share an id."""
    own = [(900001, "Short line\nother\n\nanother  LINE\r\nshort   line"), (900001, "Short line\nother\n\nanother  LINE\r\nshort   line"), (None, "OTHER\n\nshort line\nother"), (900000, "other")]
    docs = docs_of(spark, sf).select("doc_id", "text").unionByName(odd.select("doc_id", "text")).unionByName(spark.createDataFrame(own, "doc_id long, text string"))
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    got = substring_dedup.dedup_substrings(docs, unit=unit).collect()
    want = brute_units(rows, pattern)
    text = {(i, t) for i, t in rows}
    seen = collections.Counter()
    for r in got:
        seen[(r.doc_id, tuple(tuple(map(int, x.split(":"))) for x in r.spans.split(",") if x))] += 1
    flat = collections.Counter()
    for (i, spans), n in want.items():
        options = [joined(t, spans) for j, t in text if j == i]
        flat[(i, max(options, key=lambda o: seen[(i, o)]))] += n
    assert seen == flat and sum(len(s) for _, s in seen) > 10


def test_passages_of_any_place_and_size(spark):
    """Passages of 20 and 51 words inside other lines: found but for some words at the ends; strangers left alone."""
    import random

    rng = random.Random(9)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(6))
    rows, size = [], {}
    for i in range(200):
        n = 51 if i % 2 else 20
        passage = " ".join(word() for _ in range(n))
        for k in (2 * i, 2 * i + 1):
            rows.append((k, f"{' '.join(word() for _ in range(40))} {passage} {' '.join(word() for _ in range(40))}"))
        size[2 * i + 1] = n
    rows += [(1000 + i, " ".join(word() for _ in range(200))) for i in range(50)]
    got = {r.doc_id: r for r in substring_dedup.dedup_substrings(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(got[i].removed_words == 0 for i, _ in rows if i not in size)
    long_, short = ([got[i].removed_words for i in size if size[i] == n] for n in (51, 20))
    assert all(n >= 20 for n in long_) and sum(long_) / len(long_) >= 42 and max(long_) <= 51 and sum(n > 0 for n in short) >= 0.75 * len(short)


def test_substrings_odd_rows(odd, none):
    rows = substring_dedup.dedup_substrings(odd).collect()
    spans = collections.defaultdict(list)
    for r in rows:
        spans[r.doc_id].append(r.spans)
    whole = f"0:{len(odd.where('doc_id = 1').first().text)}"
    assert len(rows) == 11 and all(spans[i] == [""] for i in (3, 4, 6, 8, 9, 10)) and sorted(spans[1]) == ["", whole] and spans[None] == [whole]
    assert substring_dedup.dedup_substrings(none).count() == 0


# --- decontamination --------------------------------------------------------------------------------------------


def test_leaks_equal_exact_containment(spark, sf):
    docs, items = docs_of(spark, sf), docs_of(spark, sf, "benchmark")
    flat = lambda t: " " + " ".join(re.findall(r"[^\W_]+", (t or "").lower())) + " "
    want = {(d.doc_id, b.item_id) for b in items.collect() for d in docs.collect() if flat(b.text) in flat(d.text)}
    got = {(r.doc_id, r.item_id) for r in decontaminate.leaks(docs, items).collect()}
    assert want and got == want


def test_a_paraphrase_is_found_and_a_shuffle_is_not(spark, sf):
    items = docs_of(spark, sf, "benchmark")
    text = max((r.text for r in items.collect()), key=len)
    w = text.split()
    changed = " ".join(x if i % 6 else "instead" for i, x in enumerate(w))
    docs = spark.createDataFrame([(1, "before that. " + changed + " and after"), (2, " ".join(sorted(w))), (3, None), (4, "")], "doc_id long, text string").unionByName(docs_of(spark, sf).select((F.col("doc_id") + 100).alias("doc_id"), "text"))
    assert {r.doc_id for r in decontaminate.leaks(docs, items).where("doc_id < 100").collect()} == {1}


def test_leaks_odd_rows(odd, none, spark):
    items = spark.createDataFrame([(1, "seven wise men watch from a distant hill and say nothing at all"), (2, None), (3, ""), (4, "a b"), (None, None)], "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontaminate.leaks(odd, items).collect()}
    assert got == {(1, 1), (2, 1), (None, 1)}
    assert decontaminate.leaks(none, items).count() == 0 and decontaminate.leaks(odd, items.limit(0)).count() == 0


def test_document_frequencies_count_all_words(spark):
    docs = spark.createDataFrame([(i, f"common word{i} alpha") for i in range(50)], "doc_id long, text string")
    idf = decontaminate.inverse_frequencies(decontaminate.tokens(docs))
    got = idf[decontaminate.place(decontaminate.codes(Words(["common word7 beta"], PUNCTUATION)))]
    assert np.allclose(got, [1e-3, np.log(51 / 2) + 1e-3, np.log(51) + 1e-3], atol=1e-4)


def synonym_corpus():
    """Topics of which each has words in two forms that share their passages; a paraphrase takes the other form."""
    import random

    rng = random.Random(4)
    rows = []
    for _ in range(900):
        t = rng.randrange(30)
        rows.append(" ".join(f"t{t}{rng.choice('ab')}{rng.randrange(40)}" if rng.random() < 0.6 else f"common{rng.randrange(30)}" for _ in range(32)))
    item = [f"common{i}" if i % 2 else f"t3a{i}" for i in range(28)]
    other = [x if i % 2 else f"t3b{i}" for i, x in enumerate(item)]
    return rows, " ".join(item[:20]) + ". " + " ".join(item[20:]), " ".join(other[:20] + item[20:])


def test_the_latent_space_finds_what_the_words_alone_do_not(spark):
    """A paraphrase whose telling words are all others: cosine of the words under the bound, in the space above it."""
    rows, item, paraphrase = synonym_corpus()
    docs = spark.createDataFrame([(i, t) for i, t in enumerate([*rows, paraphrase])], "doc_id long, text string")
    found = decontaminate.tokens(docs)
    idf = decontaminate.inverse_frequencies(found)

    def vector(text):
        out = np.zeros(1 << decontaminate.FEATURE_BITS)
        code = decontaminate.codes(Words([text], PUNCTUATION))
        np.add.at(out, decontaminate.feature(code), idf[decontaminate.place(code)])
        return out

    def cosine(u, v):
        return float(u @ v / np.linalg.norm(u) / np.linalg.norm(v))

    space = decontaminate.latent_space(found, idf)
    head, body = " ".join(item.split()[:20]).rstrip("."), " ".join(paraphrase.split()[:20])
    plain, latent = cosine(vector(head), vector(body)), cosine(vector(head) @ space, vector(body) @ space)
    assert plain < decontaminate.COSINE < latent
    items = spark.createDataFrame([(1, item)], "item_id long, text string")
    assert [r.doc_id for r in decontaminate.leaks(docs, items).collect()] == [len(rows)]


def test_the_space_holds_the_leading_directions(spark):
    """The projector of the one-pass decomposition against that of the full one, where a gap parts few directions."""
    rng = np.random.default_rng(3)
    rows = [(i, " ".join(f"k{i % 8}w{rng.integers(12)}" for _ in range(32))) for i in range(400)]
    found = decontaminate.tokens(spark.createDataFrame(rows, "doc_id long, text string"))
    idf = decontaminate.inverse_frequencies(found)
    matrix = np.zeros((len(rows), 1 << decontaminate.FEATURE_BITS), np.float32)
    for i, (_, t) in enumerate(rows):
        code = decontaminate.codes(Words([t], PUNCTUATION))
        weight = idf[decontaminate.place(code)]
        np.add.at(matrix[i], decontaminate.feature(code), weight / np.sqrt((weight**2).sum()))
    full = np.linalg.svd(matrix, full_matrices=False)[2][:8]
    space = decontaminate.latent_space(found, idf)
    own = np.linalg.qr(space)[0]
    assert np.linalg.norm(full @ own) ** 2 > 0.98 * 8


def test_verbatim_items_of_any_length_in_any_case(spark):
    rng = np.random.default_rng(8)
    items = {n: [f"Éw{n}x{rng.integers(50)}" for _ in range(n)] for n in (3, 4, 5, 17, 300, 700, 2000)}
    fill = lambda: " ".join(f"fill{rng.integers(2000)}" for _ in range(200))
    docs = [(n, f"{fill()} {' '.join(w).upper()}! {fill()}") for n, w in items.items()] + [(10000 + i, fill()) for i in range(20)]
    got = decontaminate.leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame([(n, " ".join(w)) for n, w in items.items()], "item_id long, text string"))
    assert {(r.doc_id, r.item_id, r.order_share) for r in got.collect()} == {(n, n, 1.0) for n in items}


def test_a_short_item_of_common_words_is_found_among_rare_words(spark):
    rare = [f"rare{i}" for i in range(60)]
    text = " ".join(rare[:30]) + " one two three four five " + " ".join(rare[30:])
    rows = [(0, text)] + [(i, f"five filler{i} two one four three") for i in range(1, 300)]
    items = spark.createDataFrame([(1, "One two, three four five.")], "item_id long, text string")
    got = decontaminate.leaks(spark.createDataFrame(rows, "doc_id long, text string"), items)
    assert got.where("doc_id = 0").count() == 1


def test_items_of_any_length_are_found(spark):
    long = {n: " ".join(f"w{n}x{i}" for i in range(n)) for n in (128, 129, 427, 569, 3000)}
    items = spark.createDataFrame(list(long.items()), "item_id long, text string")
    docs = spark.createDataFrame([(n, "some words before " * 20 + t + " and some after" * 20) for n, t in long.items()], "doc_id long, text string")
    got = decontaminate.leaks(docs, items).collect()
    assert {(r.doc_id, r.item_id, r.order_share) for r in got} == {(n, n, 1.0) for n in long}


def test_the_whole_last_sentence_is_the_answer():
    items = decontaminate.Items([(1, "A question of five words? " + " ".join(f"w{i}" for i in range(40)) + ".")])
    assert items.answer == [40]


def test_the_space_lies_by_rows_and_codes_are_bytes(spark):
    """Rows of the space are taken for every word, and codes cross to Python as they are stored."""
    found = decontaminate.tokens(spark.createDataFrame([(i, f"k{i % 8} Wörter, again k{i % 5}") for i in range(60)] + [(60, None), (61, "")], "doc_id long, text string"))
    rows = {r.doc_id: r for r in found.where("n >= 0").collect()}
    want = decontaminate.codes(Words(["k1 wörter, again k4"], PUNCTUATION))
    assert bytes(rows["9"].terms) == want.tobytes() and rows["9"].n == 4 and rows["60"].n == rows["61"].n == 0
    assert decontaminate.latent_space(found, decontaminate.inverse_frequencies(found)).flags.c_contiguous


def test_sums_against_a_loop():
    rng = np.random.default_rng(5)
    matrix, row, weight = rng.random((50, 7)).astype(np.float32), rng.integers(50, size=3000).astype(np.uint32), rng.random(3000).astype(np.float32)
    start, _ = decontaminate.cuts(np.array([0, 0, 1, 17, 17, 1200, 2999, 3000]), 16)
    got = decontaminate.sums(np.asfortranarray(matrix), row, weight, start, 16)
    want = [weight[a:b] @ matrix[row[a:b]] for a, b in zip(start, [*start[1:], 3000])]
    assert np.allclose(got, want, rtol=1e-5)


def test_bits_in_common_where_all_are():
    for words in (4, 16, 64):
        assert decontaminate.common(np.full((2, words), ~np.uint64(0)), np.full((2, words), ~np.uint64(0))).tolist() == [64 * words] * 2


def test_the_sieves_drop_no_leak(monkeypatch):
    """Items of all widths with words left out, doubled and put elsewhere: the same leaks as with no sieve at all."""
    rng = np.random.default_rng(6)
    word = lambda: f"w{int(rng.zipf(1.3)) % 3000}"
    items = decontaminate.Items([(i, " ".join(word() for _ in range(n))) for i, n in enumerate((3, 5, 9, 20, 31, 32, 33, 50, 64, 65, 200, 700))])
    texts = []
    for codes in items.codes * 6:
        kept = [codes[rng.random(len(codes)) < rng.uniform(0.35, 0.8)]]
        texts.append(np.concatenate([np.array([rng.choice(items.vocabulary) for _ in range(rng.integers(90))], np.uint32), *kept, rng.integers(1 << 32, size=rng.integers(90), dtype=np.uint32)]))
    code, first = np.concatenate(texts), np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    search = decontaminate.Search(items, np.ones(1 << decontaminate.DF_BITS, np.float32), rng.standard_normal((1 << decontaminate.FEATURE_BITS, 28)).astype(np.float32))
    got = search.found(code, first)
    monkeypatch.setattr(decontaminate, "FOLDS", ())
    want = search.found(code, first)
    assert sorted(got) == sorted(want) and len({item for _, item, *_ in got}) >= 8


def test_lcs_against_the_table_method():
    import random

    rng = random.Random(5)
    for _ in range(50):
        a, b = ([rng.randrange(5) for _ in range(rng.randrange(1, 30))] for _ in range(2))
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
        assert decontaminate.lcs(len(a), decontaminate.places(a), b) == t[-1][-1]


# --- toxicity ---------------------------------------------------------------------------------------------------


def test_toxicity_on_held_out_rows(spark):
    sf = "/root/testdata/sf0.01"
    got = queries.op3_toxic_segments(spark, sf).join(docs_of(spark, sf, "labels"), "doc_id").where("held_out").collect()
    hit = sum(r.predicted == r.toxic for r in got) / len(got)
    found = [r for r in got if r.predicted == 1]
    assert hit >= 0.93 and sum(r.toxic for r in found) >= 0.8 * len(found) and all(0 <= r.score <= 1 for r in got)


def test_segments_against_brute_force():
    """Each reported segment is maximal: found anew as the best scoring stretch, left and right of it recursively."""
    import random

    import numpy as np

    def best(s, lo, hi):
        top = None
        for a in range(lo, hi):
            run = 0.0
            for b in range(a, hi):
                run += s[b]
                if run > 1e-9 and (top is None or run > top[0] + 1e-9):
                    top = (run, a, b + 1)
        return [] if top is None else best(s, lo, top[1]) + [(top[1], top[2], round(top[0], 6))] + best(s, top[2], hi)

    rng = random.Random(2)
    for _ in range(60):
        s = [rng.choice((-3, -2, -1.5, 1, 2.25, 4.125)) + rng.random() / 100 for _ in range(rng.randrange(0, 25))]
        assert [(a, b, round(v, 6)) for a, b, v in toxicity.segments(np.array(s))] == best(s, 0, len(s))


def test_toxicity_odd_rows(odd, none, spark):
    labels = spark.createDataFrame([(1, None), (2, 1), (7, 0), (8, 0)], "doc_id long, toxic int")
    rows = toxicity.score_documents(odd, labels, F.lit(True)).collect()
    assert len(rows) == 11 and all(0 <= r.score <= 1 for r in rows)
    assert all(r.segments == [] for r in rows if r.doc_id in (3, 4, 6))
    assert toxicity.score_documents(none, labels, F.lit(True)).count() == 0
    assert {r.score for r in toxicity.score_documents(odd, labels.limit(0), F.lit(True)).collect()} == {0.0}


# --- secrets ----------------------------------------------------------------------------------------------------

KINDS = [("assign", re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A), 2, 8), ("access", re.compile("AKIA[A-Z0-9]+"), 0, 16), ("hex", re.compile("[0-9a-f]+"), 0, 32)]


def base_spans(t):
    return [x[2] for x in sorted((m.start(), r, f"{k}:{m.start()}:{m.end()}") for r, (k, p, g, n) in enumerate(KINDS) for m in p.finditer(t or "") if len(m[g]) >= n)]


def test_secrets_equal_brute_force(spark, odd, none, sf):
    tricky = ["password=token=abcdefgh1", "password: token: abcdefghij", "ТOKEN=abcdefgh token='Zz9+/_.=-x'", "Secret\"  =  'x' api_key:AAAAAAAA apikey=bbbbbbbb", "é" * 5 + "AKIA" + "A" * 12 + " " + "f" * 31 + " " + "0" * 40 + "g", "passwd=" + "a" * 7]
    rows = spark.createDataFrame(list(enumerate(tricky)), "doc_id long, text string").unionByName(odd.select("doc_id", "text")).unionByName(docs_of(spark, sf).select("doc_id", "text"))
    want = collections.Counter()
    for r in rows.collect():
        s = base_spans(r.text)
        want[(r.doc_id, *[sum(x.startswith(k) for x in s) for k, *_ in KINDS], hashlib.sha256(",".join(s).encode()).hexdigest())] += 1
    got = secret_scan.digest_columns(secret_scan.scan(rows)).collect()
    assert collections.Counter((r.doc_id, r.n_assign, r.n_access, r.n_hex, r.base_sha256) for r in got) == want
    assert secret_scan.digest_columns(secret_scan.scan(none)).count() == 0


def test_random_strings_are_told_from_names(spark, sf):
    import base64
    import random

    rng = random.Random(9)
    secret = [base64.b64encode(rng.randbytes(30)).decode() for _ in range(30)]
    plain = [f"this_is_the_long_name_of_a_setting_number_{i}" for i in range(30)] + ["1111111111aaaaaaaaaa1111111111aaaaaaaaaa"]
    rows = spark.createDataFrame([(-i - 1, f"use {t} here") for i, t in enumerate(secret + plain)], "doc_id long, text string").unionByName(docs_of(spark, sf).select("doc_id", "text"))
    found = {-r.doc_id - 1 for r in secret_scan.digest_columns(secret_scan.scan(rows)).where("n_random > 0 and doc_id < 0").collect()}
    assert len([i for i in found if i < 30]) >= 27 and not [i for i in found if i >= 30]


def test_decoys_take_all_letters_of_all_texts(spark):
    """The null counts come from every text whole, but for less than a least piece at its end."""
    texts = ["Some ordinary words, " * n + "ä 12 end" for n in range(1, 40)] + ["", "short"]
    rows = spark.createDataFrame([(t,) for t in texts], "text string").select("text", secret_scan.decoys(F.col("text")).alias("d")).collect()
    for r in rows:
        letters = re.sub("[^A-Za-z]", "", r.text)
        pieces = [re.sub("[0-9]+$", "", x["m"]) for x in r.d]
        assert 0 <= len(letters) - sum(map(len, pieces)) < 20 and all(p in letters and len(p) in secret_scan.DECOY for p in pieces)


def test_decoys_take_the_same_tests_compiled(spark, sf):
    """Decoys get the p-values that candidates would, to the last bit, without a lambda over their characters."""
    import random

    rng = random.Random(6)
    odd_letters = ["".join(rng.choices(a, k=124)) for a in ("abcdef", "ABCDEF", "ABCDEFG", "xyz", "XYZ", "abXY", "a", "A") for _ in range(20)]
    texts = spark.createDataFrame([(t,) for t in [*odd_letters, "", "short", None]], "text string").unionByName(docs_of(spark, sf).select("text")).select(F.coalesce("text", F.lit("")).alias("text"))
    each = texts.select(F.explode(secret_scan.decoys(F.col("text"))).alias("x"))
    want = texts.select(F.explode(secret_scan.tested(secret_scan.decoys(F.col("text")))).alias("x"))
    got = secret_scan.tested_rows(each)
    rows = lambda df: collections.Counter((r.x["code"], r.x["n"], r.x["p"]) for r in df.collect())
    assert rows(got) == rows(want) and {c for c, *_ in rows(got)} == {"hex", "HEX", "base32", "base36", "base62"}
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "aggregate(" not in plan and "zip_with(" not in plan


def test_bounds_keep_the_share_of_false_reports():
    targets = {(0, b): 10 for b in range(20)} | {(0, b): 50 for b in range(900, 1000)}
    nulls = {(0, b): 1 for b in range(10, 20)} | {(0, b): 100 for b in range(900, 1000)}
    cut = secret_scan.bounds(targets, nulls, 0.05)
    total, size = sum(targets.values()), sum(nulls.values())
    share = lambda b: total * (sum(n for (_, x), n in nulls.items() if x <= b) + 1) / (size + 1) / sum(n for (_, x), n in targets.items() if x <= b)
    assert share(cut[0]) <= 0.05 < share(cut[0] + 1) and cut[1] == cut[2] == -1


def test_many_matches_in_one_text_take_proportional_time(spark):
    import time

    took = {}
    for n in (1000, 16000, 64000):
        text = "token=abcdefgh1 " * n
        at = time.time()
        row = secret_scan.digest_columns(secret_scan.scan(spark.createDataFrame([(1, text)], "doc_id long, text string"))).first()
        took[n] = time.time() - at
        want = [f"assign:{16 * i}:{16 * i + 15}" for i in range(n)]
        assert row.n_assign == n and row.base_sha256 == hashlib.sha256(",".join(want).encode()).hexdigest()
    assert took[64000] < 8 * max(1.0, took[16000]), took


def brute_language(rows, labelled, langs):
    """The fusion in plain Python: smoothed trigram likelihoods, declared markup, address, host prior by domain and corpus."""
    import math

    grams = {i: language.trigrams([t])[0].tolist() for i, t, *_ in rows}
    counts = {k: collections.Counter() for k in langs}
    for t, k in labelled:
        counts[k].update(language.trigrams([t])[0].tolist())
    size = 1 << language.BITS
    total = {k: sum(c.values()) + 0.1 * size for k, c in counts.items()}
    ll = {i: [language.TEMPER * sum(math.log((counts[k][g] + 0.1) / total[k]) for g in own) for k in langs] for i, own in grams.items()}

    def normal(x):
        top = max(x)
        e = [math.exp(v - top) for v in x]
        return [v / sum(e) for v in e]

    own = {i: normal(v) if grams[i] else None for i, v in ll.items()}
    host, domain = collections.defaultdict(lambda: [0.0] * len(langs)), collections.defaultdict(lambda: [0.0] * len(langs))
    for i, _, _, _, h in rows:
        if h is not None and own[i]:
            for x in (host[h], domain[".".join(h.split(".")[-2:])]):
                for k, v in enumerate(own[i]):
                    x[k] += v
    every = [sum(h[k] for h in host.values()) for k in range(len(langs))]
    base = [(v + 1) / (sum(every) + len(langs)) for v in every]

    def prior(h):
        if h is None:
            return base
        d = domain[".".join(h.split(".")[-2:])]
        d = [(v + language.DOMAIN_PRIOR * b) / (sum(d) + language.DOMAIN_PRIOR) for v, b in zip(d, base)]
        return [(v + language.HOST_PRIOR * b) / (sum(host[h]) + language.HOST_PRIOR) for v, b in zip(host[h], d)]

    def named(name, right):
        return [0.0] * len(langs) if name not in langs else [math.log(right) if k == name else math.log((1 - right) / (len(langs) - 1)) for k in langs]

    out = {}
    for i, _, declared, address, h in rows:
        if grams[i]:
            post = normal([a + math.log(p) + d + u for a, p, d, u in zip(ll[i], prior(h), named(declared, language.DECLARED_RIGHT), named(address, language.SUFFIX_RIGHT))])
            out[i] = (langs[post.index(max(post))], max(post))
        else:
            out[i] = (None, 0.0)
    return out


def test_language_fusion_equals_brute_force(spark):
    text = {"en": "the cat and the dog went over the hill", "de": "der Hund und die Katze gingen über den Hügel", "fr": "le chat et le chien sont allés sur la colline"}
    labelled = [(i, t, k) for i, (k, t) in enumerate(text.items())]
    rows = [(1, "the dog", None, None, "a.x.org"), (2, "die katze und", "de", None, "a.x.org"), (3, "x", "fr", "fr", "b.x.org"), (4, "le le", None, "de", None), (5, "", "en", None, "b.x.org"), (6, None, None, None, None), (7, "over und sur", "en", "de", "c.y.net"), (8, "q", "xx", None, "b.x.org")]
    df = spark.createDataFrame(rows, "id long, text string, declared string, address string, host string")
    got = {r.id: (r.lang, r.confidence) for r in language.identify(df, spark.createDataFrame(labelled, "id long, text string, lang string"), "id").collect()}
    want = brute_language(rows, [(t, k) for _, t, k in labelled], sorted(text))
    assert {i: v[0] for i, v in got.items()} == {i: v[0] for i, v in want.items()}
    assert all(abs(got[i][1] - want[i][1]) < 1e-4 for i in want)


def test_more_languages_than_the_table_has_room_for(spark):
    rows = spark.createDataFrame([(i, f"word{chr(97 + i % 26)}{chr(97 + i // 26)} " * 5, f"l{i}") for i in range(300)], "id long, text string, lang string")
    langs, table = language.fit(rows, room=1 << 22)
    assert len(langs) == 300 and table.size <= 1 << 22


def test_pages_odd_rows(spark):
    cols = "page_id long, url string, html string, own string, declared string"
    rows = [(1, "http://a.de/x", "<html lang=de>der Hund</html>", "x", "y"), (1, "http://a.de/x", "<html lang=de>der Hund</html>", "x", "y"), (2, None, None, None, None), (None, "no address", "", "x", "y"), (3, "http://b.fr", "<p>" + "mot " * 50000, "x", "y")]
    labelled = spark.createDataFrame([(1, "der Hund und", "de"), (2, "le mot et", "fr"), (3, None, "fr"), (4, "x", None)], "id long, text string, lang string")
    pages = spark.createDataFrame(rows, cols)
    got = sorted((str(r.page_id), str(r.lang), r.kept) for r in language.identify_pages(pages, labelled).collect())
    assert got == [("1", "de", True), ("1", "de", True), ("2", "None", False), ("3", "fr", True), ("None", "None", False)]
    assert language.identify_pages(pages.limit(0), labelled).count() == 0


# --- language, mixing, sharding ---------------------------------------------------------------------------------


def test_language_on_held_out_rows(spark, sf):
    docs = docs_of(spark, sf)
    train, test = docs.where("doc_id % 2 = 0"), docs.where("doc_id % 2 = 1")
    rows = test.select("doc_id", "text", F.lit(None).cast("string").alias("declared"), F.lit(None).cast("string").alias("address"), F.col("source").alias("host"))
    got = language.identify(rows, train.select(F.col("doc_id").alias("id"), "text", "lang"), "doc_id").withColumnRenamed("lang", "found")
    both = got.join(docs, "doc_id").collect()
    assert sum(r.found == r.lang for r in both) >= 0.98 * len(both) and all(r.kept for r in both)


def test_markup_and_address_decide_short_texts(spark, sf):
    docs = docs_of(spark, sf).select(F.col("doc_id").alias("id"), "text", "lang")
    pages = spark.createDataFrame([(1, "http://x.example.com/fr/1", "<html lang='fr'><p>a</p>"), (2, "http://y.example.de/", "<html lang=\"de\">e"), (3, None, None)], "page_id long, url string, html string")
    got = {r.page_id: r for r in language.identify_pages(pages, docs).collect()}
    assert (got[1].lang, got[2].lang, got[3].lang) == ("fr", "de", None) and not got[3].kept


def test_language_odd_rows(odd, none):
    got = collections.Counter((r.doc_id, r.kept) for r in language.identify_documents(odd).collect())
    assert got[(3, False)] == got[(4, False)] == got[(6, False)] == 1 and got[(1, True)] == 2 and got[(None, True)] == 1
    assert language.identify_documents(none).count() == 0


def test_mix_meets_targets(spark, sf):
    rows = mixing.mix(docs_of(spark, sf)).join(docs_of(spark, sf).select("doc_id", "source"), "doc_id").collect()
    size, taken, target = collections.Counter(), collections.Counter(), {}
    for r in rows:
        size[r.source] += r.size
        taken[r.source] += r.taken
        target[r.source] = r.target
        assert r.taken <= 2 * r.size and r.taken % max(1, r.size) == 0
    assert abs(sum(target.values()) - 1.5 * sum(size.values())) < 1e-6 * sum(size.values())
    order = sorted(size)
    open_ = {s for s in order if target[s] < 2 * size[s] - 1e-6}
    rates = {round(target[s] / (5, 2, 1)[order.index(s) % 3], 4) for s in open_}
    assert len(rates) == 1 and all(r.source_size == size[r.source] for r in rows)
    assert all(abs(taken[s] - target[s]) <= 0.02 * target[s] for s in order)
    again = {r.doc_id: r.taken for r in mixing.mix(docs_of(spark, sf).repartition(5)).collect()}
    assert again == {r.doc_id: r.taken for r in rows}


def test_cube_keeps_totals_and_probabilities():
    import numpy as np

    rng = np.random.default_rng(4)
    p, size = np.full(60, 0.3), rng.integers(1, 100, 60)
    total = np.zeros(60)
    for i in range(300):
        v = mixing.fly(p, size, np.random.default_rng(i))
        assert abs(v.sum() - p.sum()) < 1e-6 and abs(v @ size - p @ size) < 1e-4 and ((v > 0) & (v < 1)).sum() <= 2
        total += mixing.land(p, size, np.random.default_rng(i))
    assert abs(total.mean() / 300 - 0.3) < 0.03


def test_mix_odd_rows(odd, none):
    rows = mixing.mix(odd).collect()
    assert len(rows) == 11 and all(r.taken <= 2 * r.size for r in rows) and mixing.mix(none).count() == 0


def test_shards_follow_the_heap(spark, sf):
    docs = docs_of(spark, sf)
    rows = sharding.shard_documents(docs).collect()
    text = {r.doc_id: r.text for r in docs.collect()}
    groups = collections.Counter()
    for r in rows:
        assert r.size == len(text[r.doc_id].encode()) + 1 and r.text_crc32 == __import__("zlib").crc32(text[r.doc_id].encode())
        groups[text[r.doc_id]] += r.size
    want = collections.Counter()
    load = [0] * 8
    for size in sorted(groups.values(), reverse=True):
        load[load.index(min(load))] += size
    got, slots = collections.Counter(), collections.defaultdict(list)
    for r in rows:
        got[r.shard] += r.size
        slots[r.shard].append(r.slot)
    assert sorted(got.values()) == sorted(load) and not want
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert all(len({r.shard for r in rows if text[r.doc_id] == t}) == 1 for t, n in collections.Counter(text.values()).items() if n > 1)


def test_bundles_of_small_groups(spark, sf):
    """With few units most groups are bundled; groups stay whole and the loads stay close."""
    rows = sharding.shard_documents(docs_of(spark, sf), 4, units=64).collect()
    load = collections.Counter()
    for r in rows:
        load[r.shard] += r.size
    assert max(load.values()) - min(load.values()) < 0.1 * sum(load.values()) / 4


def test_shards_odd_rows(odd, none):
    rows = sharding.shard_documents(odd).collect()
    assert len(rows) == 11 and {(r.size, r.text_crc32) for r in rows if r.doc_id in (3, 4)} == {(1, 0)}
    assert sharding.shard_documents(none).count() == 0


def test_small_batches_nest_and_return_the_setting(spark):
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    own = spark.conf.get(key)
    with small_batches(spark, 7):
        assert spark.conf.get(key) == "7"
        with small_batches(spark, 9):
            assert spark.conf.get(key) == "7"
        assert spark.conf.get(key) == "7"
        seen = spark.range(50, numPartitions=1).mapInPandas(lambda parts: (p.head(1).assign(id=len(p)) for p in parts), "id long")
        assert max(r[0] for r in seen.collect()) <= 7
    assert spark.conf.get(key) == own
