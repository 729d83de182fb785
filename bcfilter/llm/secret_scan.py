"""Secret scan: base patterns plus a randomness test battery, all in built-in expressions.

Base spans come from three patterns (matches found left to right per kind, failing ones dropped). Further candidates
are runs of at least ``least`` base64 or URL-safe characters with both a letter and a digit. For each the narrowest
encoding that holds its characters is inferred (hex, base32, base36, base62, base64) and three tests ask whether it
looks like uniform draws from that alphabet: chi-squared over the alphabet, runs above and below its middle, serial
correlation of neighbours. Fisher's method joins the three into the p-value of being random.

What is controlled is the share of false reports. The null hypothesis is an ordinary token; its distribution is that
of decoys, strings with no secret in them that every text gives: its letters without the characters between words,
cut from front to back into pieces of ``DECOY`` letters in turn, each followed by a number. Every letter of every text
stands in one decoy, but for a rest below the least size. Decoys go through the same inference and tests; as their
length is bounded, the sums behind these are compiled for them (``fixed_sums``), with equal results, in a pass over the
texts of its own. For each class of length the candidates reported are those at least as random as the lowest bound where the share of decoys beyond it, times the number of candidates, is at most
``alpha`` of the candidates beyond it (a step-up over a grid of bounds); longer strings of words look less random, so
their bound is lower. Only bounded histograms leave the executors.

Candidates that lie within a base span are not reported again.

Offsets are code points, ends exclusive. Defined results: a null or empty text has no spans and the digest of the
empty string; repeated rows are scanned each for itself; without candidates or decoys beyond a bound nothing is
reported; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

# The base kinds, their patterns, the group whose length counts and its least length.
KINDS = (
    ("assign", r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    ("access", r"AKIA[A-Z0-9]+", 0, 16),
    ("hex", r"[0-9a-f]{32,}", 0, 32),
)
CANDIDATE = r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{%d,}+"
# Alphabets in the order in which they are tried.
ALPHABETS = (
    ("hex", "0123456789abcdef"),
    ("HEX", "0123456789ABCDEF"),
    ("base32", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"),
    ("base36", "0123456789abcdefghijklmnopqrstuvwxyz"),
    ("base62", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"),
    ("base64", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz+/"),
    ("base64url", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz-_"),
)
BINS = 3000
#: Matches whose offsets are added up one by one; longer lists go in blocks of as many.
BLOCK = 64
#: Letters of a decoy by class of length, and the least length of each class.
DECOY, LENGTHS = (20, 36, 68), (0, 32, 64)
#: Characters of the longest decoy, with its number.
WIDTH = max(DECOY) + 4


def spans_of(text: Column, pattern: str, group: int = 0, least: int = 0) -> Column:
    """``array<struct<s, e, m>>`` of matches whose ``group`` has ``least`` characters.

    The pieces between the matches and the matches themselves are cut by the same engine, so their lengths add up to
    the offsets.
    """
    gaps = F.split(text, pattern, -1)
    whole = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    part = whole if group == 0 else F.regexp_extract_all(text, F.lit(pattern), F.lit(group))
    kind = "array<struct<s:int,e:int,m:string,n:int>>"
    zero = F.struct(F.lit(0).alias("at"), F.array().cast(kind).alias("out"))

    def step(acc: Column, x: Column) -> Column:
        s = acc["at"] + F.length(x["gap"])
        e = s + F.length(x["whole"])
        one = F.struct(s.alias("s"), e.alias("e"), x["whole"].alias("m"), F.length(x["part"]).alias("n"))
        return F.struct(e.alias("at"), F.concat(acc["out"], F.array(one)).alias("out"))

    def shifted(acc: Column, x: Column) -> Column:
        at = F.concat(acc["starts"], F.array(acc["at"]))
        return F.struct((acc["at"] + x["at"]).alias("at"), at.alias("starts"))

    # Appending copies an array, so a long list is added up in blocks, and the blocks after that.
    zipped = F.arrays_zip(F.slice(gaps, F.lit(1), F.size(whole)).alias("gap"), whole.alias("whole"), part.alias("part"))
    cut = lambda z: F.transform(F.sequence(F.lit(0), F.floor((F.size(z) - 1) / BLOCK).cast("int")), lambda b: F.aggregate(F.slice(z, b * BLOCK + 1, BLOCK), zero, step))
    first = F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("starts"))
    place = lambda y: F.struct(y.alias("blocks"), F.aggregate(y, first, shifted, lambda acc: acc["starts"]).alias("starts"))
    moved = lambda b, at: F.transform(b["out"], lambda x: F.struct((x["s"] + at).alias("s"), (x["e"] + at).alias("e"), x["m"].alias("m"), x["n"].alias("n")))
    joined = F.transform(F.transform(F.transform(F.array(zipped), cut), place), lambda p: F.flatten(F.zip_with(p["blocks"], p["starts"], moved)))
    found = F.element_at(joined, 1)
    kept = F.transform(F.filter(found, lambda x: x["n"] >= least), lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["m"].alias("m")))
    none = F.array().cast("array<struct<s:int,e:int,m:string>>")
    return F.when(text.rlike(pattern), kept).otherwise(none)


def tail_scale(z: Column) -> Column:
    """1 / (1 + 0.2316419 z), in whose powers ``normal_tail`` is a polynomial."""
    return F.lit(1.0) / (F.lit(1.0) + F.lit(0.2316419) * z)


def normal_tail(z: Column, t: Column) -> Column:
    """P(Z > z) for z >= 0, by the five-term polynomial in ``t``, the scale of z."""
    poly = F.lit(0.0)
    for c in (1.330274429, -1.821255978, 1.781477937, -0.356563782, 0.319381530):
        poly = (poly + F.lit(c)) * t
    return F.greatest(F.lit(1e-300), F.exp(-z * z / 2) * F.lit(0.3989422804014327) * poly)


def keep(x: Column, *names: str) -> list[Column]:
    return [x[c].alias(c) for c in names]


def code_of(core: Column) -> Column:
    pick = None
    for name, letters in ALPHABETS:
        fits = core.rlike("^[" + letters.replace("-", "\\-") + "]*$")
        pick = F.when(fits, F.lit(name)) if pick is None else pick.when(fits, F.lit(name))
    return F.coalesce(pick, F.lit("base64"))


def by_code(code: Column, value) -> Column:
    pick = None
    for name, letters in ALPHABETS:
        pick = F.when(code == name, value(letters)) if pick is None else pick.when(code == name, value(letters))
    return pick


def values(letters: str) -> Column:
    """The value of every ASCII character in an alphabet, -1 outside it."""
    return F.lit([float(letters.find(chr(c))) for c in range(128)])


def with_core(x: Column) -> Column:
    return F.struct(x["s"].alias("s"), x["e"].alias("e"), F.when(x["m"].endswith("="), F.regexp_replace(x["m"], "=+$", "")).otherwise(x["m"]).alias("core"))


def with_code(x: Column) -> Column:
    return F.struct(x["s"].alias("s"), x["e"].alias("e"), x["core"].alias("core"), code_of(x["core"]).alias("code"))


# A stage for each value that is read often: nothing is kept between two readings within one.
def with_letters(x: Column) -> Column:
    chars = F.slice(F.split(x["core"], ""), F.lit(1), F.length(x["core"]))
    return F.struct(*keep(x, "s", "e", "core", "code"), F.length(x["core"]).alias("n"), by_code(x["code"], lambda a: F.lit(float(len(a)))).alias("k"), by_code(x["code"], values).alias("values"), chars.alias("chars"))


def with_values(x: Column) -> Column:
    at = lambda c: F.get(x["values"], F.ascii(c))
    count = lambda c: (x["n"] - F.length(F.replace(x["core"], c, F.lit("")))).cast("double")
    return F.struct(*keep(x, "s", "e", "code", "k"), x["n"].cast("double").alias("n"), (x["k"] / 2).alias("mid"),
                    F.transform(F.array_distinct(x["chars"]), lambda c: F.struct(at(c).alias("v"), count(c).alias("n"))).alias("each"),
                    F.transform(x["chars"], at).alias("v"))


def with_pairs(x: Column) -> Column:
    size = x["n"].cast("int") - 1
    return F.struct(*keep(x, "s", "e", "code", "k", "n", "mid", "each", "v"), F.slice(x["v"], F.lit(1), size).alias("left"), F.slice(x["v"], F.lit(2), size).alias("right"))


def with_sums(x: Column) -> Column:
    zero, mid = F.lit(0.0), x["mid"]
    none = F.struct(zero.alias("squares"), zero.alias("sx"), zero.alias("sxx"), zero.alias("high"))
    # Plain numbers are added up: a struct for each character would take most of the time.
    total = lambda values: F.aggregate(values, zero, lambda a, b: a + b)
    products = F.zip_with(x["left"], x["right"], lambda a, b: F.when(a >= 0, a * b).otherwise(zero))
    breaks = F.size(F.filter(F.zip_with(x["left"], x["right"], lambda a, b: (a < 0) | ((a >= mid) != (b >= mid))), lambda new: new))

    def add(a: Column, c: Column) -> Column:
        one = c["n"] * c["v"]
        return F.struct((a["squares"] + c["n"] * c["n"]).alias("squares"), (a["sx"] + one).alias("sx"), (a["sxx"] + one * c["v"]).alias("sxx"), F.when(c["v"] >= mid, a["high"] + c["n"]).otherwise(a["high"]).alias("high"))

    return F.struct(*keep(x, "s", "e", "code", "k", "n"), F.element_at(x["v"], 1).alias("first"), F.element_at(x["v"], -1).alias("last"), total(products).alias("sxy"),
                    (breaks + 1).cast("double").alias("runs"), F.aggregate(x["each"], none, add).alias("t"))


def with_moments(x: Column) -> Column:
    k, n, t = x["k"], x["n"], x["t"]
    free = k - 1
    chi = F.greatest(F.lit(0.0), t["squares"] * k / n - n)
    avg = t["sx"] / n
    below = t["sxx"] - n * avg * avg
    above = x["sxy"] + x["last"] * x["first"] - n * avg * avg
    return F.struct(*keep(x, "s", "e", "code", "n"), chi.alias("chi"), free.alias("free"), (F.lit(2.0) / (free * 9)).alias("spread"), x["runs"].alias("runs"),
                    (t["high"] * 2 * (n - t["high"]) / n + 1).alias("mean"), below.alias("below"), above.alias("above"))


def with_z(x: Column) -> Column:
    n = x["n"]
    var = (x["mean"] - 1) * (x["mean"] - 2) / F.greatest(n - 1, F.lit(1.0))
    chi = (F.pow(x["chi"] / x["free"], F.lit(1.0 / 3)) - (F.lit(1.0) - x["spread"])) / F.sqrt(x["spread"])
    runs = F.when(var > 0, F.abs(x["runs"] - x["mean"]) / F.sqrt(var))
    serial = F.when(x["below"] > 0, F.abs(x["above"] / x["below"] + F.lit(1.0) / (n - 1)) * F.sqrt(n))
    return F.struct(*keep(x, "s", "e", "code", "n"), chi.alias("z"), F.abs(chi).alias("chi"), runs.alias("runs"), serial.alias("serial"))


def with_scales(x: Column) -> Column:
    names = ("chi", "runs", "serial")
    return F.struct(*keep(x, "s", "e", "code", "n", "z", *names), *[tail_scale(x[c]).alias("t_" + c) for c in names])


def with_tails(x: Column) -> Column:
    return F.struct(*keep(x, "s", "e", "code", "n", "z"), *[F.when(x[c].isNotNull(), normal_tail(x[c], x["t_" + c])).alias(c) for c in ("chi", "runs", "serial")])


def with_log(x: Column) -> Column:
    # Without spread (a single letter, one half of the alphabet only) a test counts as failed; a null tail means that.
    p_chi = F.when(x["z"] >= 0, x["chi"]).otherwise(F.lit(1.0) - x["chi"])
    both = [F.coalesce(x[c] * 2, F.lit(1e-6)) for c in ("runs", "serial")]
    ln = lambda p: F.ln(F.least(F.lit(1.0), p))
    return F.struct(*keep(x, "s", "e", "code", "n"), (-(ln(p_chi) + ln(both[0]) + ln(both[1]))).alias("log"))


def with_p(x: Column) -> Column:
    log = x["log"]
    joint = F.exp(-log) * (F.lit(1.0) + log + log * log / 2)
    return F.struct(*keep(x, "s", "e", "code"), F.greatest(F.lit(1e-300), joint).alias("p"), x["n"].alias("n"))


#: From a string to its sums, and from the sums to the p-value; ``fixed_sums`` does for decoys what ``LETTERS`` do.
READ, LETTERS, NUMBERS = (with_core, with_code), (with_letters, with_values, with_pairs, with_sums), (with_moments, with_z, with_scales, with_tails, with_log, with_p)


def tested(spans: Column) -> Column:
    """``array<struct<s, e, code, p, n>>``: each candidate's encoding and joint p-value of being random."""
    out = F.filter(spans, lambda x: x["m"].rlike("[0-9]") & x["m"].rlike("[A-Za-z]"))
    for f in (*READ, *LETTERS, *NUMBERS):
        out = F.transform(out, f)
    return out


def fixed_sums(coded: DataFrame) -> DataFrame:
    """What the stages in ``LETTERS`` give, for strings ``x`` of at most ``WIDTH`` letters and digits, a row each.

    The sums are written out over the positions, so they are compiled, where a lambda is interpreted at every character.
    Beyond a string's end a position is null and adds nothing. A character's count is what is lost in length without
    it. The lambda that hands on ``n`` keeps a selection out of whole-stage code, where it would be one method, too long
    for the JVM to compile; the sums stay outside its arguments, which are interpreted.
    """

    def offset(letters: str, kind: str) -> int:
        """What to take from a code point of this kind for its value."""
        return next((ord(c) - letters.index(c) for c in kind if c in letters), 0)

    kinds = {"digit": "0123456789", "upper": "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "lower": "abcdefghijklmnopqrstuvwxyz"}
    several = lambda each: f"array({', '.join(each)})"
    n = "transform(array(n), c -> c)[0] n"
    at, v = ([f"get({name}, {i})" for i in range(WIDTH)] for name in ("at", "v"))
    value = lambda c: f"{c} - if({c} < 58, digit, if({c} < 91, upper, lower))"
    counts = [f"n - octet_length(replace(x.core, '{c}', ''))" for kind in kinds.values() for c in kind]
    count = [f"counts[{i}]" for i in range(len(counts))]
    sums = [
        " + ".join(f"coalesce({c}, 0)" for c in v), " + ".join(f"coalesce({c} * {c}, 0)" for c in v), " + ".join(f"if(2 * {c} >= k, 1, 0)" for c in v),
        " + ".join(f"coalesce({c} * {d}, 0)" for c, d in zip(v, v[1:])), " + ".join(f"if((2 * {c} >= k) != (2 * {d} >= k), 1, 0)" for c, d in zip(v, v[1:])),
    ]
    coding = [by_code(F.col("x.code"), lambda a, kind=kind: F.lit(offset(a, kind))).alias(name) for name, kind in kinds.items()]
    row = coded.select("x", F.slice(F.split("x.core", ""), F.lit(1), F.length("x.core")).alias("chars"), *coding, by_code(F.col("x.code"), lambda a: F.lit(len(a))).alias("k"), F.length("x.core").alias("n"))
    row = row.selectExpr("x", "k", n, *kinds, several([f"ascii(get(chars, {i}))" for i in range(WIDTH)]) + " at")
    row = row.selectExpr("x", "k", n, "at", several([value(c) for c in at]) + " v")
    row = row.selectExpr("x", "k", n, "v", several(sums) + " sums", several(counts) + " counts")
    row = row.selectExpr("x", "k", n, "v", "sums", " + ".join(f"{c} * {c}" for c in count) + " squares")
    real = lambda c, name: F.expr(c).cast("double").alias(name)
    t = F.struct(real("squares", "squares"), real("sums[0]", "sx"), real("sums[1]", "sxx"), real("sums[2]", "high"))
    return row.select(F.struct(*keep(F.col("x"), "s", "e", "code"), real("k", "k"), real("n", "n"), real("v[0]", "first"), real("v[n - 1]", "last"), real("sums[3]", "sxy"), real("sums[4] + 1", "runs"), t.alias("t")).alias("x"))


def tested_rows(strings: DataFrame) -> DataFrame:
    """``tested`` for decoys, one in each row of the column ``x``."""
    staged = lambda rows, fs: rows if not fs else staged(rows.select(fs[0](F.col("x")).alias("x")), fs[1:])
    return staged(fixed_sums(staged(strings, READ)), NUMBERS)


def bin_of(p: Column) -> Column:
    """Where a p-value of being random lies on the grid; larger is smaller."""
    return F.least(F.lit(BINS), F.floor(-F.log10(F.least(F.lit(1.0), p)) * 100)).cast("int")


def class_of(n: Column) -> Column:
    pick = F.lit(0)
    for k, least in enumerate(LENGTHS[1:], 1):
        pick = F.when(n >= least, F.lit(k)).otherwise(pick)
    return pick


def decoys(text: Column) -> Column:
    """``array<struct<s, e, m>>``: strings of a text's own words, without their gaps, with a number behind."""
    first, *more = (f"([A-Za-z]{{{n}}})" for n in DECOY)
    letters = F.regexp_replace(text, "[^A-Za-z]+", "")
    cut = [F.regexp_extract_all(letters, F.lit(first + "".join(f"{p}?" for p in more)), F.lit(i + 1)) for i in range(len(DECOY))]
    numbered = lambda m: F.struct(F.lit(0).alias("s"), F.lit(0).alias("e"), F.concat(m, F.pmod(F.xxhash64(m), F.lit(10000)).cast("string")).alias("m"))
    return F.transform(F.filter(F.concat(*cut), lambda m: m != ""), numbered)


def bounds(targets: dict, nulls: dict, alpha: float) -> dict[int, int]:
    """For each class of length the last bin of the grid that is reported, from counts by (class, bin); -1 for none."""
    out = {}
    for k in range(len(LENGTHS)):
        own, null = ({b: n for (c, b), n in counts.items() if c == k} for counts in (targets, nulls))
        total, size = sum(own.values()), sum(null.values())
        cut, reported, false = -1, 0, 0
        for b in range(BINS + 1):
            reported += own.get(b, 0)
            false += null.get(b, 0)
            if reported and size and total * (false + 1) / (size + 1) <= alpha * reported:
                cut = b
        out[k] = cut
    return out


def scan(docs: DataFrame, least: int = 20, alpha: float = 0.05) -> DataFrame:
    """doc_id, the base spans by kind, all spans with kind and, of random ones, encoding and p-value."""
    text = F.coalesce(F.col("text"), F.lit(""))
    base = [spans_of(text, p, g, n).alias(k) for k, p, g, n in KINDS]
    found = docs.select("doc_id", *base, spans_of(text, CANDIDATE % least).alias("more"))
    plain = [F.transform(k, lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"))).alias(k) for k, *_ in KINDS]
    place = lambda x: F.struct(class_of(x["n"]).alias("k"), bin_of(x["p"]).alias("bin"))
    found = materialize(found.select("doc_id", *plain, tested(F.col("more")).alias("more")), "secret_spans")
    null = tested_rows(docs.select(F.explode(decoys(text)).alias("x")))

    def counts(rows: DataFrame) -> dict:
        each = rows.select(place(F.col("x")).alias("c"))
        return {(r[0], r[1]): r[2] for r in each.groupBy("c.k", "c.bin").count().collect()}

    cut = bounds(counts(found.select(F.explode("more").alias("x"))), counts(null), alpha)
    last = lambda c: F.element_at(F.array(*[F.lit(cut[k]) for k in range(len(LENGTHS))]), class_of(c["n"]) + 1)
    base = F.concat(*[k for k, *_ in KINDS])
    random = F.filter("more", lambda c: (bin_of(c["p"]) <= last(c)) & ~F.exists(base, lambda x: (x["s"] <= c["s"]) & (c["e"] <= x["e"])))
    return found.select("doc_id", *[k for k, *_ in KINDS], random.alias("random"))


def digest_columns(found: DataFrame) -> DataFrame:
    """Counts, the digest of the base spans, and all spans as one string."""
    names = [k for k, *_ in KINDS]

    def tagged(name: str, rank: int) -> Column:
        return F.transform(name, lambda x: F.struct(x["s"].alias("s"), F.lit(rank).alias("rank"), F.concat_ws(":", F.lit(name), x["s"].cast("string"), x["e"].cast("string")).alias("t")))

    def joined(spans: Column) -> Column:
        return F.array_join(F.transform(F.array_sort(spans), lambda x: x["t"]), ",")

    base = F.concat(*[tagged(k, i) for i, k in enumerate(names)])
    every = F.concat(*[tagged(k, i) for i, k in enumerate([*names, "random"])])
    return found.select(
        "doc_id", *[F.size(k).cast("long").alias(f"n_{k}") for k in names], F.sha2(joined(base).cast("binary"), 256).alias("base_sha256"),
        joined(every).alias("spans"), F.size("random").cast("long").alias("n_random"),
    )
