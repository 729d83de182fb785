"""Queries of hashing, sizing, filters, clearing, baselines and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import sizing
from ..functions.hashing import FilterSpec, hashed, positions, sql_positions, uniformity
from ..operators import baselines, clearing, filters, measures
from ..operators.measures import r6
from ..sources import wire
from ..sources.tables import new_path, table, written
from .base import ORACLE_SQL, U_SQL, VISIT_SQL, b_sql, choice_sql, frozen_sql, live_sql, query, row_sql, run, setting, setting_sql, universe, with_sql

BETAS = (0.01, 0.02, 0.05, 0.10, 0.25, 0.50, 0.75, 1.0)

# --- hashing ----------------------------------------------------------------------------------------------------


def _hash(family: str, k: int = 3, blocks: int = 1):
    def f(spark, sf_dir):
        spec = FilterSpec(15000, k, family, blocks=blocks)
        return hashed(universe(spark, sf_dir), spec).select("key", *[F.col("positions")[j].alias(f"p{j + 1}") for j in range(k)])

    return f


for _name, _family, _k, _blocks in (("hash_linear", "linear", 5, 1), ("hash_md5", "md5", 3, 1), ("hash_double", "double", 4, 1), ("hash_blocked", "blocked", 3, 16)):
    query(_name, f"WITH {U_SQL}, h AS (SELECT key, {sql_positions('key', _k, '15000', _family, _blocks)} AS p FROM u) SELECT key, " + ", ".join(f"p[{j + 1}] AS p{j + 1}" for j in range(_k)) + " FROM h")(_hash(_family, _k, _blocks))
query("hash_xxhash")(_hash("xxhash", 3))
query("hash_emulated")(_hash("emulated", 3))


@query(
    "hash_uniformity",
    f"""WITH {U_SQL}, e AS (SELECT unnest({sql_positions('key', 3, '15000')}) AS pos FROM u), t AS (SELECT count(*) AS total FROM e)
SELECT bucket, n, round(total / 64.0, 6) AS expected, round(power(n - total / 64.0, 2) / (total / 64.0), 6) AS chi2
FROM (SELECT CAST(floor((pos - 1) * 64 / 15000.0) AS BIGINT) AS bucket, count(*) AS n FROM e GROUP BY 1), t""",
)
def hash_uniformity(spark, sf_dir):
    return uniformity(universe(spark, sf_dir), FilterSpec(15000, 3))


# --- sizing -----------------------------------------------------------------------------------------------------

_GRID = [(1000.0, float(b * 1000), float(k)) for b in (2, 5, 10, 16) for k in (1, 3, 5, 8)]


def _grid(spark):
    return spark.createDataFrame(_GRID, "n double, m double, k double")


def _size(name: str, spark_cols, sql_cols: str):
    sql = f"SELECT n, m, k, {sql_cols} FROM (VALUES " + ", ".join(f"(CAST({n} AS DOUBLE), CAST({m} AS DOUBLE), CAST({k} AS DOUBLE))" for n, m, k in _GRID) + ") t(n, m, k)"
    query(name, sql)(lambda spark, sf_dir: _grid(spark).select("n", "m", "k", *spark_cols(F.col("n"), F.col("m"), F.col("k"))))


#: Filters of the order keys of each priority: n distinct keys, some bits to a key and numbers of hashes.
_KEYS_SQL = "kn AS (SELECT o_orderpriority, CAST(count(DISTINCT o_orderkey) AS DOUBLE) AS n FROM orders GROUP BY 1)"
_GIVEN_SQL = f"WITH {_KEYS_SQL}, t AS (SELECT o_orderpriority, n, b * n AS m, k FROM kn, (SELECT unnest([2.0::DOUBLE, 5, 10, 16]) AS b), (SELECT unnest([1.0::DOUBLE, 3, 5, 8]) AS k))"


def _keys(spark, sf_dir):
    """(o_orderpriority, n): distinct order keys of each priority."""
    o = table(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority"]).distinct()
    return o.groupBy("o_orderpriority").agg(F.count("o_orderkey").cast("double").alias("n"))


def _given(name: str, spark_cols, sql_cols: str):
    def f(spark, sf_dir):
        grid = spark.createDataFrame([(b, k) for b in (2.0, 5.0, 10.0, 16.0) for k in (1.0, 3.0, 5.0, 8.0)], "b double, k double")
        t = _keys(spark, sf_dir).crossJoin(F.broadcast(grid)).withColumn("m", F.col("b") * F.col("n"))
        return t.select("o_orderpriority", "n", "m", "k", *spark_cols(F.col("n"), F.col("m"), F.col("k")))

    query(name, f"{_GIVEN_SQL} SELECT o_orderpriority, n, m, k, {sql_cols} FROM t")(f)


_P0 = "power(1 - 1 / m, k * n)"
_size("size_p0", lambda n, m, k: [r6(sizing.p_zero(n, m, k)).alias("exact"), r6(sizing.p_zero(n, m, k, False)).alias("approx")], f"round({_P0}, 6) AS exact, round(exp(-k * n / m), 6) AS approx")
_size("size_p1", lambda n, m, k: [r6(sizing.p_one(n, m, k)).alias("p1")], f"round(1 - {_P0}, 6) AS p1")
_given("size_fp_rate", lambda n, m, k: [r6(sizing.fp_rate(n, m, k)).alias("exact"), r6(sizing.fp_rate(n, m, k, False)).alias("approx")], f"round(power(1 - {_P0}, k), 6) AS exact, round(power(1 - exp(-k * n / m), k), 6) AS approx")
_given("size_best_k", lambda n, m, k: [r6(sizing.best_k(m, n)[0]).alias("real_k"), sizing.best_k(m, n)[1].alias("best_k")], "round(m / n * ln(2), 6) AS real_k, CAST(greatest(1, round(m / n * ln(2))) AS INTEGER) AS best_k")
_size("size_min_fp", lambda n, m, k: [r6(sizing.min_fp_rate(m, n)).alias("rate")], "round(power(2, -m / n * ln(2)), 6) AS rate")
# The universe is 20 times the keys, as in the simulation's small grid (20,000 over 1,000).
_given("size_fp_count", lambda n, m, k: [F.round(sizing.expected_fp_count(20 * n, n, m, k), 4).alias("expected")], f"round((20 * n - n) * power(1 - {_P0}, k), 4) AS expected")
_size("size_survival", lambda n, m, k: [r6(sizing.survival(F.lit(s), n, m, k)).alias(f"s{s}") for s in (1, 100)], ", ".join(f"round(power(1 - {s} / ((1 - {_P0}) * m), k), 6) AS s{s}" for s in (1, 100)))


@query("size_for_target", f"WITH {_KEYS_SQL}, t AS (SELECT *, CAST(ceil(-n * ln(rate) / power(ln(2), 2)) AS BIGINT) AS m FROM kn, (SELECT unnest([0.1::DOUBLE, 0.01, 0.001]) AS rate)) SELECT o_orderpriority, n, rate, m, CAST(greatest(1, round(m / n * ln(2))) AS INTEGER) AS k FROM t")
def size_for_target(spark, sf_dir):
    rates = spark.createDataFrame([(0.1,), (0.01,), (0.001,)], "rate double")
    m, k = sizing.for_target_columns(F.col("n"), F.col("rate"))
    return _keys(spark, sf_dir).crossJoin(F.broadcast(rates)).select("o_orderpriority", "n", "rate", m.alias("m"), k.alias("k"))


#: Each curve in shares of the urgent orders' n keys: m = 10 n and k = 5 where they don't vary.
_CURVES = {"k": list(range(1, 21)), "m": [2 * i for i in range(1, 11)], "n": [i / 5 for i in range(1, 11)]}


@query(
    "fig_fp_curves",
    "WITH z AS (SELECT CAST(count(DISTINCT o_orderkey) AS DOUBLE) AS n0 FROM orders WHERE o_orderpriority = '1-URGENT'), "
    "t AS ("
    + " UNION ALL ".join(
        f"SELECT '{v}' AS var, {'x' if v == 'k' else '5::DOUBLE'} AS k, {'x' if v == 'm' else '10'} * n0 AS m, {'x * ' if v == 'n' else ''}n0 AS n FROM z, (SELECT unnest([{', '.join(f'{x}::DOUBLE' for x in xs)}]) AS x)"
        for v, xs in _CURVES.items()
    )
    + ") SELECT var, k, m, n, round(power(1 - power(1 - 1 / m, k * n), k), 10) AS fp_rate FROM t",
)
def fig_fp_curves(spark, sf_dir):
    keys = table(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority"]).where("o_orderpriority = '1-URGENT'").agg(F.countDistinct("o_orderkey").cast("double").alias("n0"))
    rows = [(v, float(x) if v == "k" else 5.0, float(x) if v == "m" else 10.0, float(x) if v == "n" else 1.0) for v, xs in _CURVES.items() for x in xs]
    t = spark.createDataFrame(rows, "var string, k double, m double, n double").crossJoin(F.broadcast(keys)).select("var", "k", (F.col("m") * F.col("n0")).alias("m"), (F.col("n") * F.col("n0")).alias("n"))
    return t.withColumn("fp_rate", F.round(sizing.fp_rate(F.col("n"), F.col("m"), F.col("k")), 10))


# --- plain filter -----------------------------------------------------------------------------------------------


def _small(spark, sf_dir, bits=5, k=3, **kw):
    u = universe(spark, sf_dir)
    n = u.where("is_member").count()
    spec = FilterSpec(int(bits * n), k, **kw)
    return u, u.where("is_member").select("key"), spec


@query("bf_positions", with_sql(setting_sql(), select="SELECT pos FROM v", recursive=False))
def bf_positions(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return filters.build_positions(a, spec)


@query("bf_bitmap", with_sql(setting_sql(), select="SELECT (pos - 1) // 32768 + 1 AS bucket, count(*) AS bits_set FROM v GROUP BY 1", recursive=False))
def bf_bitmap(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return filters.build_bitmap(a, spec).select("bucket", F.bitmap_count("bits").alias("bits_set"))


@query("bf_udaf")
def bf_udaf(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return baselines.bloom_udaf(a, spec)


_PROBE = with_sql(setting_sql(), select="SELECT key, is_member, maybe FROM pr", recursive=False)


@query("bf_probe_join", _PROBE)
def bf_probe_join(spark, sf_dir):
    u, a, spec = _small(spark, sf_dir)
    return filters.probe_join(u, filters.build_positions(a, spec), spec).select("key", "is_member", "maybe")


@query("bf_probe_broadcast", _PROBE)
def bf_probe_broadcast(spark, sf_dir):
    u, a, spec = _small(spark, sf_dir)
    return filters.probe_broadcast(u, filters.build_positions(a, spec), spec).select("key", "is_member", "maybe")


@query("bf_probe_shuffle", _PROBE)
def bf_probe_shuffle(spark, sf_dir):
    u, a, spec = _small(spark, sf_dir)
    return filters.probe_shuffle(u, filters.build_bitmap(a, spec), spec).select("key", "is_member", "maybe")


@query("bf_probe_negative", with_sql(setting_sql(), select="SELECT key, maybe FROM pr", recursive=False))
def bf_probe_negative(spark, sf_dir):
    u, a, spec = _small(spark, sf_dir)
    return filters.probe_negative(u, filters.build_positions(a, spec), spec)


def _halves(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return [filters.build_bitmap(a.where(F.col("key") % 2 == r), spec) for r in (0, 1)], spec


@query("bf_union", with_sql(setting_sql(), select="SELECT pos FROM v", recursive=False))
def bf_union(spark, sf_dir):
    parts, _ = _halves(spark, sf_dir)
    return filters.positions_of(filters.union(*parts))


@query("bf_intersect", with_sql(setting_sql(), select="SELECT unnest(positions) AS pos FROM a WHERE key % 2 = 0 INTERSECT SELECT unnest(positions) FROM a WHERE key % 2 = 1", recursive=False))
def bf_intersect(spark, sf_dir):
    parts, _ = _halves(spark, sf_dir)
    return filters.positions_of(filters.intersect(*parts))


@query("bf_stats", with_sql(setting_sql(), select="SELECT x AS bits_set, round(x / CAST(m AS DOUBLE), 6) AS fill, round(-(m / 3.0) * ln(1 - x / CAST(m AS DOUBLE)), 4) AS estimate FROM (SELECT count(*) AS x FROM v), sp", recursive=False))
def bf_stats(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return filters.stats(filters.build_positions(a, spec), spec)


@query("bf_roundtrip", with_sql(setting_sql(), select="SELECT pos, m, 3 AS k, 'linear' AS family FROM v, sp", recursive=False))
def bf_roundtrip(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    path = new_path(spark, "filter")
    wire.save(filters.build_bitmap(a, spec), spec, path)
    bitmap, back = wire.load(spark, path)
    return filters.positions_of(bitmap).select("pos", F.lit(back.m).cast("long").alias("m"), F.lit(back.k).alias("k"), F.lit(back.family).alias("family"))


@query("wire_roundtrip", with_sql(setting_sql(), select="SELECT pos FROM v", recursive=False))
def wire_roundtrip(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return filters.positions_of(wire.decode(wire.encode(filters.build_bitmap(a, spec), spec, compress=True))).select("pos")


@query("bf_incremental", with_sql(setting_sql(), select="SELECT pos FROM v", recursive=False))
def bf_incremental(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    old = filters.build_bitmap(a.where("key % 10 <> 0"), spec)
    return filters.positions_of(filters.union(old, filters.build_bitmap(a.where("key % 10 = 0"), spec)))


@query("bf_no_fn", with_sql(setting_sql(), select="SELECT count(*) FILTER (NOT maybe) AS false_negatives, count(*) AS members FROM pr WHERE is_member", recursive=False))
def bf_no_fn(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return filters.probe_join(a, filters.build_positions(a, spec), spec).agg(F.count_if(~F.col("maybe")).alias("false_negatives"), F.count("*").alias("members"))


@query("bf_blocked", with_sql(setting_sql(5, 3, "blocked", 16), select="SELECT (pos - 1) // CAST(ceil(m / 16.0) AS BIGINT) AS block, count(*) AS bits_set FROM v, sp GROUP BY 1", recursive=False))
def bf_blocked(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir, family="blocked", blocks=16)
    return filters.build_blocked(a, spec).select("block", F.bitmap_count("bits").alias("bits_set"))


# --- clearing ---------------------------------------------------------------------------------------------------


@query("clear_bits", with_sql(setting_sql(), select="SELECT pos FROM v WHERE pos % 7 <> 0", recursive=False))
def clear_bits(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    pos = filters.build_positions(a, spec)
    return clearing.reset_bits(pos, pos.where("pos % 7 = 0"))


def _randomized(s: int):
    def f(spark, sf_dir):
        st = setting(spark, sf_dir)
        gone = written(clearing.randomized(filters.build_positions(st.members.select("key"), st.spec), s), "gone")
        lost = clearing.hit_by(st.members, gone).agg(F.count("*").alias("fn"))
        return clearing.hit_by(st.fp, gone).agg(F.count("*").alias("removed")).crossJoin(lost).select(F.lit(s).alias("s"), "removed", "fn")

    return f


def _randomized_sql(s: int) -> str:
    return with_sql(
        setting_sql(), f"g AS (SELECT list(pos) AS ps FROM (SELECT pos FROM v ORDER BY md5('0:' || CAST(pos AS VARCHAR)), pos LIMIT {s}))",
        select=f"SELECT {s} AS s, (SELECT count(*) FROM fp, g WHERE list_has_any(positions, ps)) AS removed, (SELECT count(*) FROM a, g WHERE list_has_any(positions, ps)) AS fn", recursive=False,
    )


query("clear_randomized", _randomized_sql(500))(_randomized(500))
query("clear_randomized_one", _randomized_sql(1))(_randomized(1))


def _clear(rule: str, beta: float = 0.1, live: bool = False, scope: str = "all", engine: str = "auto"):
    def f(spark, sf_dir):
        s = setting(spark, sf_dir)
        b, done = run(s, rule, beta, live, scope, engine)
        return measures.table_row(s.members, s.fp, b, done, s.n_universe, s.spec, beta, rule, "live" if live else "frozen", scope)

    return f


for _rule in clearing.RULES:
    query(f"clear_{_rule}", frozen_sql(_rule))(_clear(_rule, engine="rounds" if _rule == "ratio" else "auto"))
for _rule in ("min_fn", "max_fp", "ratio"):
    query(f"clear_{_rule}_live", with_sql(setting_sql(), b_sql(), live_sql(_rule), select=row_sql(_rule, "live")))(_clear(_rule, live=True))
for _rule in ("max_fp", "ratio"):
    query(f"clear_{_rule}_scope_b", frozen_sql(_rule, scope="troublesome"))(_clear(_rule, scope="troublesome"))


@query("clear_skipped_keys", frozen_sql("ratio", select="SELECT ch.key, ch.ord FROM ch WHERE ch.ord NOT IN (SELECT ord FROM c)"))
def clear_skipped_keys(spark, sf_dir):
    _, done = run(setting(spark, sf_dir), "ratio")
    return done.log.where("not acted").select("key", "ord")


@query("clear_beta_full", with_sql(setting_sql(), select="SELECT count(*) AS fp, CAST(0 AS BIGINT) AS fp_left FROM fp", recursive=False))
def clear_beta_full(spark, sf_dir):
    s = setting(spark, sf_dir)
    _, done = run(s, "ratio", 1.0)
    gone = clearing.hit_by(s.fp, done.cleared).select("key")
    return s.fp.agg(F.count("*").alias("fp")).crossJoin(s.fp.join(gone, "key", "left_anti").agg(F.count("*").alias("fp_left")))


_COUNT = "SELECT pos, count(*) AS cnt FROM (SELECT unnest(positions) AS pos FROM {}) GROUP BY pos"


@query("counter_members", with_sql(setting_sql(), select=_COUNT.format("a"), recursive=False))
def counter_members(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return clearing.counters(hashed(a, spec))


@query("counter_false_pos", with_sql(setting_sql(), select=_COUNT.format("fp"), recursive=False))
def counter_false_pos(spark, sf_dir):
    return clearing.counters(setting(spark, sf_dir).fp)


@query("counter_pruned", with_sql(setting_sql(), b_sql(), select=_COUNT.format("a") .replace("GROUP BY", "WHERE pos IN (SELECT unnest(positions) FROM b) GROUP BY"), recursive=False))
def counter_pruned(spark, sf_dir):
    s = setting(spark, sf_dir)
    b = clearing.troublesome(s.fp, 0.1, count=s.n_fp)
    return clearing.counters(s.members, b.select(F.explode("positions").alias("pos")).distinct())


@query("ratio_vector", with_sql(setting_sql(), f"ca AS ({_COUNT.format('a')}), cb AS ({_COUNT.format('fp')})", select="SELECT coalesce(ca.pos, cb.pos) AS pos, coalesce(ca.cnt, 0) AS cnt_a, coalesce(cb.cnt, 0) AS cnt_b, round(CAST(coalesce(ca.cnt, 0) AS DOUBLE) / cb.cnt, 6) AS ratio FROM ca FULL JOIN cb ON ca.pos = cb.pos", recursive=False))
def ratio_vector(spark, sf_dir):
    s = setting(spark, sf_dir)
    return clearing.ratio_vector(clearing.counters(s.members, name="cnt_a"), clearing.counters(s.fp, name="cnt_b")).withColumn("ratio", r6(F.col("ratio")))


@query("element_list", with_sql(setting_sql(), select="SELECT unnest(positions) AS pos, key FROM fp", recursive=False))
def element_list(spark, sf_dir):
    return clearing.element_lists(setting(spark, sf_dir).fp)


@query("element_list_drop", with_sql(setting_sql(), select="SELECT unnest(positions) AS pos, key FROM fp WHERE key % 3 <> 0", recursive=False))
def element_list_drop(spark, sf_dir):
    fp = setting(spark, sf_dir).fp
    return clearing.drop_elements(clearing.element_lists(fp), fp.where("key % 3 = 0"))


_DEGREE_SQL = "dg AS (SELECT l_orderkey AS key, count(*) AS weight FROM lineitem GROUP BY 1)"
_WEIGHTED = with_sql(
    setting_sql(), _DEGREE_SQL, b_sql(), choice_sql("ratio", weight="weight").replace("unnest(positions) AS pos, weight AS w FROM fp", "unnest(positions) AS pos, coalesce(weight, 1) AS w FROM fp LEFT JOIN dg USING (key)"), VISIT_SQL, select=row_sql("ratio", scope="weighted")
)


@query("clear_ratio_weighted", _WEIGHTED)
def clear_ratio_weighted(spark, sf_dir):
    s = setting(spark, sf_dir)
    degree = table(spark, sf_dir, "lineitem", ["l_orderkey"]).groupBy(F.col("l_orderkey").alias("key")).agg(F.count("*").alias("weight"))
    s.fp = written(s.fp.join(degree, "key", "left").withColumn("weight", F.coalesce("weight", F.lit(1))), "fp")
    b, done = run(s, "ratio", weight="weight")
    return measures.table_row(s.members, s.fp, b, done, s.n_universe, s.spec, 0.1, "ratio", scope="weighted")


_LOST_SQL = """f1 AS (SELECT key, min(ord) AS ord FROM (SELECT key, unnest(positions) AS pos FROM a) x JOIN c USING (pos) GROUP BY key),
pe AS (SELECT c.pos, c.ord, coalesce(l.lost, 0) AS lost FROM c LEFT JOIN (SELECT ord, count(*) AS lost FROM f1 GROUP BY ord) l USING (ord)),
cu AS (SELECT pos, ord, count(*) OVER (ORDER BY ord) AS resets, CAST(sum(lost) OVER (ORDER BY ord) AS BIGINT) AS fn FROM pe)"""


@query("clear_budget", with_sql(setting_sql(), b_sql(), choice_sql("ratio"), VISIT_SQL, _LOST_SQL, select="SELECT pos, ord, resets, fn FROM cu WHERE resets <= 60 AND fn <= 50"))
def clear_budget(spark, sf_dir):
    s = setting(spark, sf_dir)
    _, done = run(s, "ratio")
    return clearing.budget(done.log, s.members, max_resets=60, max_fn=50)


@query("engine_agreement", "SELECT r AS rule, l AS counters, CAST(0 AS BIGINT) AS differing FROM (VALUES ('random', 'frozen'), ('min_fn', 'frozen'), ('max_fp', 'frozen'), ('ratio', 'frozen'), ('min_fn', 'live'), ('max_fp', 'live'), ('ratio', 'live'), ('ratio', 'blocked, frozen'), ('ratio', 'blocked, live')) t(r, l)")
def engine_agreement(spark, sf_dir):
    """Rows of the log that differ between the engines, for frozen and live counters; ``blocked`` on a blocked filter."""
    s, blocked = setting(spark, sf_dir), setting(spark, sf_dir, family="blocked", blocks=16)
    cases = [(s, "random", False), (s, "min_fn", False), (s, "max_fp", False), (s, "ratio", False), (s, "min_fn", True), (s, "max_fp", True), (s, "ratio", True), (blocked, "ratio", False), (blocked, "ratio", True)]
    out = None
    for x, rule, live in cases:
        second = "blocked" if x is blocked else "single_task"
        logs = [run(x, rule, 0.05, live, engine=e)[1].log.where("acted").select("key", "ord", "pos", "j") for e in ("rounds", second)]
        n = logs[0].exceptAll(logs[1]).unionByName(logs[1].exceptAll(logs[0])).agg(F.count("*").alias("differing"))
        row = n.select(F.lit(rule).alias("rule"), F.lit(("blocked, " if x is blocked else "") + ("live" if live else "frozen")).alias("counters"), "differing")
        out = row if out is None else out.unionByName(row)
    return out


# --- measures ---------------------------------------------------------------------------------------------------

_AFTER = frozen_sql("ratio", select="SELECT {} FROM (SELECT count(*) AS fp FROM fp), (SELECT count(*) AS n FROM a), (SELECT count(*) AS foreign_keys FROM u WHERE NOT is_member), (SELECT count(*) AS removed FROM gp), (SELECT count(*) AS fn FROM gn), (SELECT count(*) AS s FROM c), (SELECT count(*) AS b FROM b), (SELECT m FROM sp)")


def _measure(name: str, column, sql: str):
    """A measure over one row: fp, n, foreign_keys, removed, fn, s, b, m after the ratio rule at beta 10%."""

    def f(spark, sf_dir):
        s = setting(spark, sf_dir)
        b, done = run(s, "ratio")
        row = measures.table_row(s.members, s.fp, b, done, s.n_universe, s.spec, 0.1, "ratio")
        return row.select("fp", "n", (F.col("universe") - F.col("n")).alias("foreign_keys"), "removed", "fn", "s", "b", "m").select(*column())

    query(name, _AFTER.replace("{}", sql))(f)


c = F.col
_measure("m_fp_rate", lambda: [r6(c("fp") / c("foreign_keys")).alias("fp_rate")], "round(fp / foreign_keys, 6) AS fp_rate")
_measure("m_fp_rate_after", lambda: [r6((c("fp") - c("removed")) / c("foreign_keys")).alias("fp_rate_after")], "round((fp - removed) / foreign_keys, 6) AS fp_rate_after")
_measure("m_fn_rate", lambda: [r6(c("fn") / c("n")).alias("fn_rate")], "round(fn / n, 6) AS fn_rate")
_measure("m_delta_fp", lambda: [r6(c("removed") / c("fp")).alias("delta_fp")], "round(removed / fp, 6) AS delta_fp")
_measure("m_delta_fn", lambda: [r6(c("fn") / c("n")).alias("delta_fn")], "round(fn / n, 6) AS delta_fn")
_measure("m_chi", lambda: [r6((c("removed") / c("fp")) / (c("fn") / c("n"))).alias("chi")], "round((removed / fp) / (fn / n), 6) AS chi")
_measure("m_bits_reset", lambda: [c("s"), r6(c("s") / c("b")).alias("per_key")], "s, round(s / b, 6) AS per_key")
_measure("m_beta", lambda: [r6(c("b") / c("fp")).alias("beta")], "round(b / fp, 6) AS beta")
_measure("m_overall_error", lambda: [measures.overall_error(c("fp") - c("removed"), c("fn")).alias("after"), measures.overall_error(c("fp"), F.lit(0.0)).alias("before")], "CAST(fp - removed + fn AS DOUBLE) AS after, CAST(fp AS DOUBLE) AS before")
query("m_table_row", frozen_sql("ratio"))(_clear("ratio"))


@query("m_skipped_share", frozen_sql("ratio", select="SELECT round(1 - (SELECT count(*) FROM c) / (SELECT CAST(count(*) AS DOUBLE) FROM b), 6) AS skipped_share"))
def m_skipped_share(spark, sf_dir):
    _, done = run(setting(spark, sf_dir), "ratio")
    return done.log.agg(r6(F.avg((~F.col("acted")).cast("double"))).alias("skipped_share"))


@query("m_list_occupancy", with_sql(setting_sql(), select="SELECT 'a' AS side, round(count(DISTINCT pos) / CAST(any_value(m) AS DOUBLE), 6) AS occupancy FROM (SELECT unnest(positions) AS pos FROM a), sp UNION ALL SELECT 'b', round(count(DISTINCT pos) / CAST(any_value(m) AS DOUBLE), 6) FROM (SELECT unnest(positions) AS pos FROM fp), sp", recursive=False))
def m_list_occupancy(spark, sf_dir):
    s = setting(spark, sf_dir)
    return baselines.list_measures(s).select("side", r6(c("cells") / s.spec.m).alias("occupancy"))


@query("m_list_length", with_sql(setting_sql(), select="SELECT 'a' AS side, round(count(*) / CAST(count(DISTINCT pos) AS DOUBLE), 6) AS mean_length FROM (SELECT unnest(positions) AS pos FROM a) UNION ALL SELECT 'b', round(count(*) / CAST(count(DISTINCT pos) AS DOUBLE), 6) FROM (SELECT unnest(positions) AS pos FROM fp)", recursive=False))
def m_list_length(spark, sf_dir):
    return baselines.list_measures(setting(spark, sf_dir)).select("side", r6(c("entries") / c("cells")).alias("mean_length"))


_COSTS = {
    ("random", "frozen"): ("k * b", "m + b"), ("min_fn", "frozen"): ("k * (n + b)", "4 * m + b"), ("max_fp", "frozen"): ("k * b", "4 * m + b"), ("ratio", "frozen"): ("k * (n + b) + m", "12 * m + b"),
    ("min_fn", "live"): ("k * (n + b)", "m + b + k * 32 * n"), ("max_fp", "live"): ("k * b", "m + k * 32 * b"), ("ratio", "live"): ("k * (n + b) + m", "9 * m + k * 32 * (n + b)"),
}


@query("m_cost_model", with_sql(setting_sql(), b_sql(), "z AS (SELECT n, (SELECT count(*) FROM b) AS b, m, 3 AS k FROM sp)", select=" UNION ALL ".join(f"SELECT '{x}' AS algorithm, '{y}' AS counters, CAST({o} AS BIGINT) AS operations, CAST({s} AS BIGINT) AS bits FROM z" for (x, y), (o, s) in _COSTS.items()), recursive=False))
def m_cost_model(spark, sf_dir):
    """The costs of clearing the filter over the order keys at beta 10%."""
    s = setting(spark, sf_dir)
    take = min(s.n_fp, max(1, clearing.round_half_up(0.1 * s.n_fp)))
    return measures.cost_model(spark.createDataFrame([(s.n, take, s.spec.m)], "n long, b long, m long"), s.spec.k)


_MARGIN = """f2 AS (SELECT key, min(ord) AS ord FROM (SELECT key, unnest(positions) AS pos FROM fp) x JOIN c USING (pos) GROUP BY key),
f1 AS (SELECT key, min(ord) AS ord FROM (SELECT key, unnest(positions) AS pos FROM a) x JOIN c USING (pos) GROUP BY key)"""


@query("m_marginal", with_sql(setting_sql(), b_sql(), choice_sql("ratio"), VISIT_SQL, _MARGIN, select="SELECT ord, pos, benefit, cost, CAST(sum(benefit - cost) OVER (ORDER BY ord) AS BIGINT) AS net FROM (SELECT c.ord, c.pos, coalesce(x.n, 0) AS benefit, coalesce(y.n, 0) AS cost FROM c LEFT JOIN (SELECT ord, count(*) AS n FROM f2 GROUP BY 1) x USING (ord) LEFT JOIN (SELECT ord, count(*) AS n FROM f1 GROUP BY 1) y USING (ord))"))
def m_marginal(spark, sf_dir):
    s = setting(spark, sf_dir)
    _, done = run(s, "ratio")
    return measures.marginal(done.log, s.members, s.fp)


# --- baselines --------------------------------------------------------------------------------------------------

query("baseline_bloom", _PROBE)(bf_probe_broadcast)


@query("baseline_list", f"WITH {U_SQL} SELECT key, is_member AS maybe, 32 * (SELECT count(*) FROM u WHERE is_member) AS size_bits FROM u")
def baseline_list(spark, sf_dir):
    u = universe(spark, sf_dir)
    return baselines.exact_list(u, u.where("is_member").select("key"))


@query("baseline_randomized", _randomized_sql(200))
def baseline_randomized(spark, sf_dir):
    return _randomized(200)(spark, sf_dir)


@query("baseline_larger_m", " UNION ALL ".join("SELECT * FROM (" + with_sql(setting_sql(b), select=f"SELECT CAST({b} AS DOUBLE) AS bits_per_key, (SELECT m FROM sp) AS m, (SELECT count(*) FROM fp) AS fp", recursive=False) + ")" for b in (2, 5, 10)))
def baseline_larger_m(spark, sf_dir):
    out = None
    for bits in (2, 5, 10):
        s = setting(spark, sf_dir, bits)
        row = s.fp.agg(F.count("*").alias("fp")).select(F.lit(float(bits)).alias("bits_per_key"), F.lit(s.spec.m).cast("long").alias("m"), "fp")
        out = row if out is None else out.unionByName(row)
    return out


@query("baseline_compressed")
def baseline_compressed(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return baselines.compressed(filters.build_bitmap(a, spec))


@query("compressed_entropy", with_sql(setting_sql(), select="SELECT bits_set, round(CAST(m AS DOUBLE) * -(p * log2(p) + (1 - p) * log2(1 - p)), 2) AS entropy_bits FROM (SELECT count(*) AS bits_set, count(*) / CAST(any_value(m) AS DOUBLE) AS p, any_value(m) AS m FROM v, sp)", recursive=False))
def compressed_entropy(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    set_ = filters.build_positions(a, spec).agg(F.count("*").alias("bits_set"))
    return set_.select("bits_set", F.round(measures.entropy_bits(F.lit(float(spec.m)), c("bits_set") / F.lit(spec.m)), 2).alias("entropy_bits"))


@query("baseline_counting", with_sql(setting_sql(), select="SELECT pos, count(*) AS cnt FROM (SELECT unnest(positions) AS pos FROM a WHERE key % 4 <> 0) GROUP BY pos", recursive=False))
def baseline_counting(spark, sf_dir):
    _, a, spec = _small(spark, sf_dir)
    return baselines.counting(a, a.where("key % 4 = 0"), spec)


@query("baseline_dleft")
def baseline_dleft(spark, sf_dir):
    u, a, _ = _small(spark, sf_dir)
    return baselines.dleft(u, a)


query("frozen_vs_live", " UNION ALL ".join(f"SELECT * FROM ({x})" for r in ("min_fn", "max_fp", "ratio") for x in (frozen_sql(r, 0.05), with_sql(setting_sql(), b_sql(0.05), live_sql(r), select=row_sql(r, "live", beta=0.05)))))(
    lambda spark, sf_dir: baselines.union_all([_clear(r, 0.05, live)(spark, sf_dir) for r in ("min_fn", "max_fp", "ratio") for live in (False, True)])
)


@query("exact_fp_fn", frozen_sql("ratio", select="SELECT count(*) AS universe, count(*) FILTER (maybe AND NOT pr.is_member) AS fp, count(*) FILTER (maybe AND NOT pr.is_member AND NOT list_has_any(h.positions, cleared)) AS fp_after, count(*) FILTER (pr.is_member AND list_has_any(h.positions, cleared)) AS fn_after FROM pr JOIN h ON h.key = pr.key, fin"))
def exact_fp_fn(spark, sf_dir):
    """Brute force: the whole universe is probed again on the sealed filter."""
    s = setting(spark, sf_dir)
    _, done = run(s, "ratio")
    pos = written(filters.build_positions(s.members.select("key"), s.spec), "pos")
    before = filters.probe_join(s.u, pos, s.spec)
    after = filters.probe_join(s.u.select("key"), clearing.reset_bits(pos, done.cleared), s.spec).select("key", c("maybe").alias("after"))
    both = before.join(after, "key")
    return both.agg(F.count("*").alias("universe"), F.count_if(c("maybe") & ~c("is_member")).alias("fp"), F.count_if(c("after") & ~c("is_member")).alias("fp_after"), F.count_if(~c("after") & c("is_member")).alias("fn_after"))


@query("baseline_jvm_sketch")
def baseline_jvm_sketch(spark, sf_dir):
    u, a, _ = _small(spark, sf_dir)
    return baselines.jvm_sketch(a)


@query("baseline_exception_list", with_sql(setting_sql(), b_sql(), select="SELECT pr.key, pr.maybe AND b.key IS NULL AS maybe, (SELECT m FROM sp) + 32 * (SELECT count(*) FROM b) AS size_bits FROM pr LEFT JOIN b ON pr.key = b.key", recursive=False))
def baseline_exception_list(spark, sf_dir):
    s = setting(spark, sf_dir)
    b = written(clearing.troublesome(s.fp, 0.1, count=s.n_fp), "b")
    answers = filters.probe_join(s.u.select("key"), filters.build_positions(s.members.select("key"), s.spec), s.spec)
    marked = answers.join(b.select("key", F.lit(True).alias("listed")), "key", "left")
    return marked.select("key", (c("maybe") & c("listed").isNull()).alias("maybe"), (F.lit(s.spec.m) + 32 * F.lit(b.count())).cast("long").alias("size_bits"))
