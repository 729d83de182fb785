"""Experiment workloads: the key-universe simulation, the route replay and other places where hot keys matter."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import sizing
from ..functions.hashing import FilterSpec, hashed, sql_positions
from ..operators import clearing, filters, measures, tracing
from ..operators.baselines import union_all
from ..operators.measures import r6
from ..sources.tables import table, written
from .base import ORACLE_SQL, QUERIES, U_SQL, VISIT_SQL, Setting, b_sql, choice_sql, frozen_sql, live_sql, query, row_sql, run, setting, setting_sql, with_sql

BETAS = (0.01, 0.02, 0.05, 0.10, 0.25, 0.50, 0.75, 1.0)
RUNS = 15
SHIFT = 40
c = F.col


# --- simulation over the key universe ---------------------------------------------------------------------------


def composite(keys: DataFrame, group: str) -> DataFrame:
    """Keys and positions of several independent visits side by side: the group stands above bit ``SHIFT``."""
    up = F.shiftleft(c(group).cast("long"), SHIFT)
    return keys.withColumn("positions", F.transform("positions", lambda p: p + up)).withColumn("key", c("key") + up).drop(group)


def group_of(x: str):
    return F.shiftright(c(x), SHIFT).cast("int")


def low(x: str):
    return c(x).bitwiseAND(F.lit((1 << SHIFT) - 1))


def visits(s: Setting, rule: str, runs: int, live: bool = False) -> tuple[DataFrame, DataFrame]:
    """Visits of all false positives in ``runs`` orders: keys (run, key, ord) and resets (run, pos, ord).

    With frozen counters the choice of a key is the same in every order (but for the random rule), so it is made once
    and the orders are visited side by side. Live counters take one order.
    """
    keys = s.fp.select("key", "positions")
    if live:
        ordered = written(clearing.troublesome(s.fp, 1.0, count=s.n_fp), "ordered")
        done = written(clearing.clear(s.members, s.fp, ordered, s.spec, rule, True).log, "log")
        return ordered.select(F.lit(0).alias("run"), "key", "ord"), done.where("acted").select(F.lit(0).alias("run"), "pos", "ord")
    run = F.explode(F.sequence(F.lit(0), F.lit(runs - 1)))
    text = c("key").cast("string") if runs == 1 else F.concat(c("run").cast("string"), F.lit(":"), c("key").cast("string"))
    ordered = clearing.numbered(keys.withColumn("run", run), [c("run"), F.md5(text.cast("binary")), c("key")])
    ordered = written(ordered.withColumn("ord", c("ord") - c("run") * s.n_fp), "ordered")
    if rule == "random":
        digest = F.md5(F.concat(c("run").cast("string"), F.lit(":"), c("key").cast("string")).cast("binary"))
        j = F.pmod(F.conv(F.substring(digest, 1, 15), 16, 10).cast("long"), F.lit(s.spec.k)).cast("int")
        chosen = ordered.withColumn("j", j).withColumn("pos", F.element_at("positions", c("j") + 1))
    else:
        once = clearing.choose(keys.withColumn("ord", F.lit(0).cast("long")), rule, s.members, s.fp, k=s.spec.k).select("key", "pos", "j")
        chosen = ordered.join(once, "key")
    chosen = composite(chosen.withColumn("pos", c("pos") + F.shiftleft(c("run").cast("long"), SHIFT)), "run").select("key", "ord", "positions", "pos", "j")
    done = written(clearing.visit_frozen(chosen).log, "log")
    return ordered.select("run", "key", "ord"), done.where("acted").select(group_of("pos").alias("run"), low("pos").alias("pos"), "ord")


def sweep(s: Setting, rule: str, betas, runs: int = 1, live: bool = False) -> DataFrame:
    """All betas in one visit: the counters do not depend on beta, so a smaller beta is a prefix of the visit.

    A position is cleared from the order of its reset on; a key is lost from the least such order on.
    """
    ordered, gone = visits(s, rule, runs, live)

    def first(keys: DataFrame) -> DataFrame:
        return keys.select("key", F.explode("positions").alias("pos")).join(gone, "pos").groupBy("run", "key").agg(F.min("ord").alias("at"))

    lost_fp = first(s.fp).join(ordered.select("run", "key", c("ord").alias("own")), ["run", "key"])
    last = [(r, float(b), min(s.n_fp, max(1, clearing.round_half_up(b * s.n_fp)))) for b in betas for r in range(runs)]
    steps = s.fp.sparkSession.createDataFrame(last, "run int, beta double, last long")

    def count(rows: DataFrame, name: str, *conds) -> DataFrame:
        """Rows up to a step, added up from what each order adds: the steps never multiply the rows."""
        per = rows.groupBy("run", "at").agg(F.count("*").alias("n"))
        return F.broadcast(steps).join(per, (steps["run"] == per["run"]) & (per["at"] <= steps["last"]), "left").groupBy(steps["run"], "beta", "last").agg(F.coalesce(F.sum("n"), F.lit(0)).alias(name))

    removed = count(lost_fp, "removed")
    # Removed though not visited by then: lost at ``at``, visited only at ``own``.
    before = count(lost_fp.select("run", F.greatest("at", "own").alias("at")), "visited")
    fn = count(first(s.members), "fn")
    resets = count(gone.select("run", c("ord").alias("at")), "s")
    by = ["run", "beta", "last"]
    out = removed.join(before, by).join(fn, by).join(resets, by).withColumn("b_extra", c("removed") - c("visited"))
    dfp, dfn = c("removed") / F.lit(s.n_fp), c("fn") / F.lit(s.n)
    return out.select("run", F.lit(rule).alias("algorithm"), "beta", c("last").alias("b"), "b_extra", "removed", "fn", "s", r6(F.try_divide(dfp, dfn)).alias("chi"))


def averaged(rows: DataFrame) -> DataFrame:
    """One row for each rule and beta: means over the runs, and chi with the half-width of its 95% interval."""
    from functools import reduce

    by = ["algorithm", "beta"]
    means = rows.groupBy(*by, "b").agg(*[r6(F.avg(x)).alias(x) for x in ("b_extra", "removed", "fn", "s")])
    chi = measures.confidence(rows, by, "chi").withColumnsRenamed({"mean": "chi"})
    return reduce(lambda a, b: a.join(b, by), [means, chi])


def _visits_sql(rule: str, runs: int) -> list[str]:
    """CTEs bo(run, key, ord) and c(run, pos, ord): the visits of all runs with frozen counters."""
    text = "CAST(key AS VARCHAR)" if runs == 1 else "CAST(run AS VARCHAR) || ':' || CAST(key AS VARCHAR)"
    order = f"bo AS (SELECT run, key, positions, row_number() OVER (PARTITION BY run ORDER BY md5({text}), key) AS ord FROM fp, (SELECT unnest(range(0, {runs})) AS run))"
    if rule == "random":
        chosen = ["cr AS (SELECT run, ord, positions, positions[CAST('0x' || substr(md5(CAST(run AS VARCHAR) || ':' || CAST(key AS VARCHAR)), 1, 15) AS BIGINT) % 3 + 1] AS pos FROM bo)"]
    else:
        chosen = ["b AS (SELECT key, positions, 0 AS ord FROM fp)", choice_sql(rule), "cr AS (SELECT bo.run, bo.ord, bo.positions, ch.pos FROM bo JOIN ch USING (key))"]
    return [
        order, *chosen,
        """vis AS (SELECT DISTINCT run, 0::BIGINT AS step, []::BIGINT[] AS cleared, []::BIGINT[] AS acting FROM cr
  UNION ALL SELECT vis.run, vis.step + 1, CASE WHEN list_has_any(vis.cleared, cr.positions) THEN vis.cleared ELSE list_append(vis.cleared, cr.pos) END,
  CASE WHEN list_has_any(vis.cleared, cr.positions) THEN vis.acting ELSE list_append(vis.acting, cr.ord) END FROM vis JOIN cr ON cr.run = vis.run AND cr.ord = vis.step + 1)""",
        "c AS (SELECT run, unnest(cleared) AS pos, unnest(acting) AS ord FROM (SELECT run, arg_max(cleared, step) AS cleared, arg_max(acting, step) AS acting FROM vis GROUP BY run))",
    ]


def _sweep_sql(rule: str, cols: str = "algorithm, beta, b, b_extra, removed, fn, s, chi", runs: int = 1, live: bool = False, betas=BETAS, averaged: bool = False) -> str:
    visit = _visits_sql(rule, runs)
    if live:
        visit = [b_sql(1.0), live_sql(rule).replace("c AS (SELECT unnest(cleared) AS pos", "c AS (SELECT 0 AS run, unnest(cleared) AS pos")]
    order = "bx AS (SELECT 0 AS run, key, ord FROM bo)" if live else "bx AS (SELECT run, key, ord FROM bo)"
    lost = "(SELECT run, key, min(ord) AS hit_at FROM (SELECT key, unnest(positions) AS pos FROM {}) x JOIN c USING (pos) GROUP BY run, key)"
    upto = "(SELECT count(*) FROM {0} x WHERE x.run = st.run AND x.{1} <= st.b{2})"
    parts = [
        setting_sql(), *visit, order, f"lf AS (SELECT l.run, l.key, hit_at, bx.ord AS own FROM {lost.format('fp')} l JOIN bx ON bx.run = l.run AND bx.key = l.key)", f"la AS {lost.format('a')}",
        f"st AS (SELECT run, beta, least(nf, greatest(1, CAST(floor(beta * nf + 0.5) AS BIGINT))) AS b, nf FROM (SELECT unnest([{', '.join(f'CAST({x} AS DOUBLE)' for x in betas)}]) AS beta), (SELECT unnest(range(0, {runs})) AS run), (SELECT count(*) AS nf FROM fp))",
        f"rw AS (SELECT '{rule}' AS algorithm, run, beta, b, nf, {upto.format('lf', 'hit_at', ' AND x.own > st.b')} AS b_extra, {upto.format('lf', 'hit_at', '')} AS removed, {upto.format('la', 'hit_at', '')} AS fn, {upto.format('c', 'ord', '')} AS s FROM st)",
        "rx AS (SELECT *, round((removed / nf) / nullif(fn / (SELECT CAST(n AS DOUBLE) FROM sp), 0), 6) AS chi FROM rw)",
    ]
    if averaged:
        means = ", ".join(f"round(avg({x}), 6) AS {x}" for x in ("b_extra", "removed", "fn", "s"))
        parts.append(f"ra AS (SELECT algorithm, beta, b, {means}, count(chi) AS runs, round(avg(chi), 6) AS chi, round(CASE WHEN count(chi) > 1 THEN {measures.T95[runs - 2]} * stddev_samp(chi) / sqrt(count(chi)) END, 6) AS half_width FROM rx GROUP BY algorithm, beta, b)")
    return with_sql(*parts, select=f"SELECT {cols} FROM {'ra' if averaged else 'rx'}")


_AVERAGED = "algorithm, beta, b, b_extra, removed, fn, s, runs, chi, half_width"
for _rule in clearing.RULES:
    query(f"w_sim_table_{_rule}", _sweep_sql(_rule, _AVERAGED, RUNS, averaged=True))(lambda spark, sf_dir, r=_rule: averaged(sweep(setting(spark, sf_dir), r, BETAS, RUNS)))
query("m_confidence", _sweep_sql("ratio", "algorithm, beta, runs, chi AS mean, half_width", RUNS, betas=(0.1,), averaged=True))(
    lambda spark, sf_dir: measures.confidence(sweep(setting(spark, sf_dir), "ratio", (0.1,), RUNS), ["algorithm", "beta"], "chi")
)


def _four(cols: list[str]):
    def f(spark, sf_dir):
        s = setting(spark, sf_dir)
        return union_all([sweep(s, r, BETAS).select("algorithm", "beta", *cols) for r in clearing.RULES])

    return f


query("w_sim_bits_reset", " UNION ALL ".join(f"SELECT * FROM ({_sweep_sql(r, 'algorithm, beta, b, s')})" for r in clearing.RULES))(_four(["b", "s"]))
query("w_sim_chi", " UNION ALL ".join(f"SELECT * FROM ({_sweep_sql(r, 'algorithm, beta, chi')})" for r in clearing.RULES))(_four(["chi"]))


_PAIR = "beta, b, b_extra, removed, fn, s, chi"


def _pairs(spark, sf_dir, rule: str) -> DataFrame:
    s = setting(spark, sf_dir)
    return union_all([sweep(s, rule, BETAS, live=live).select("algorithm", F.lit("live" if live else "frozen").alias("counters"), *_PAIR.split(", ")) for live in (False, True)])


for _rule in ("min_fn", "max_fp", "ratio"):
    _sql = " UNION ALL ".join(f"SELECT * FROM ({_sweep_sql(_rule, f'algorithm, {chr(39)}{n}{chr(39)} AS counters, {_PAIR}', live=n == 'live')})" for n in ("frozen", "live"))
    query(f"w_live_{_rule}", _sql)(lambda spark, sf_dir, r=_rule: _pairs(spark, sf_dir, r))

_LIST_BITS = tuple(range(1, 11))


def _lists(spark, sf_dir) -> DataFrame:
    out = []
    from ..operators.baselines import list_measures

    for bits in _LIST_BITS:
        s = setting(spark, sf_dir, bits)
        out.append(list_measures(s).select(F.lit(s.spec.m).cast("long").alias("m"), "side", "cells", "entries"))
    return union_all(out)


def _lists_sql(expr: str) -> str:
    return " UNION ALL ".join(
        "SELECT * FROM (" + with_sql(setting_sql(b), select=" UNION ALL ".join(f"SELECT (SELECT m FROM sp) AS m, '{side}' AS side, {expr} FROM (SELECT unnest(positions) AS pos FROM {t})" for side, t in (("a", "a"), ("b", "fp"))), recursive=False) + ")" for b in _LIST_BITS
    )


query("w_list_occupancy", _lists_sql("round(count(DISTINCT pos) / CAST((SELECT m FROM sp) AS DOUBLE), 6) AS occupancy"))(lambda spark, sf_dir: _lists(spark, sf_dir).select("m", "side", r6(c("cells") / c("m")).alias("occupancy")))
query("w_list_length", _lists_sql("round(count(*) / nullif(CAST(count(DISTINCT pos) AS DOUBLE), 0), 6) AS mean_length"))(lambda spark, sf_dir: _lists(spark, sf_dir).select("m", "side", r6(F.try_divide(c("entries").cast("double"), c("cells"))).alias("mean_length")))


@query(
    "w_fp_measured_vs_model",
    " UNION ALL ".join(
        "SELECT * FROM (" + with_sql(setting_sql(b, k), select=f"SELECT {k} AS k, m, round((SELECT count(*) FROM fp) / (SELECT CAST(count(*) AS DOUBLE) FROM u WHERE NOT is_member), 6) AS measured, round(power(1 - power(1 - 1 / CAST(m AS DOUBLE), {k} * n), {k}), 6) AS model FROM sp", recursive=False) + ")"
        for b in (2, 5, 10) for k in (1, 3, 5)
    ),
)
def w_fp_measured_vs_model(spark, sf_dir):
    out = []
    for bits in (2, 5, 10):
        for k in (1, 3, 5):
            s = setting(spark, sf_dir, bits, k)
            row = s.fp.agg(F.count("*").alias("fp"))
            out.append(row.select(F.lit(k).alias("k"), F.lit(s.spec.m).cast("long").alias("m"), r6(c("fp") / F.lit(float(s.n_universe - s.n))).alias("measured"), r6(sizing.fp_rate(s.n, s.spec.m, k)).alias("model")))
    return union_all(out)


_LAW = (1, 100, 500, 1000, 2000)


@query(
    "w_random_law",
    with_sql(
        setting_sql(), "g AS (SELECT pos, row_number() OVER (ORDER BY md5('0:' || CAST(pos AS VARCHAR)), pos) AS ord FROM v)",
        "lf AS (SELECT key, min(ord) AS hit_at FROM (SELECT key, unnest(positions) AS pos FROM fp) x JOIN g USING (pos) GROUP BY key)",
        "la AS (SELECT key, min(ord) AS hit_at FROM (SELECT key, unnest(positions) AS pos FROM a) x JOIN g USING (pos) GROUP BY key)",
        select=f"SELECT s, round((SELECT count(*) FROM lf WHERE hit_at <= s) / (SELECT CAST(count(*) AS DOUBLE) FROM fp), 6) AS fp_removed, round((SELECT count(*) FROM la WHERE hit_at <= s) / (SELECT CAST(n AS DOUBLE) FROM sp), 6) AS members_lost, round(1 - (SELECT power(1 - s / ((1 - power(1 - 1 / CAST(m AS DOUBLE), 3 * n)) * m), 3) FROM sp), 6) AS law FROM (SELECT unnest({list(_LAW)}) AS s)",
        recursive=False,
    ),
)
def w_random_law(spark, sf_dir):
    s = setting(spark, sf_dir)
    pos = filters.build_positions(s.members.select("key"), s.spec)
    gone = written(clearing.numbered(pos, [F.md5(F.concat(F.lit("0:"), c("pos").cast("string")).cast("binary")), c("pos")]), "gone")

    def first(keys):
        return keys.select("key", F.explode("positions").alias("pos")).join(gone, "pos").groupBy("key").agg(F.min("ord").alias("at"))

    steps = F.broadcast(spark.createDataFrame([(x,) for x in _LAW], "s int"))
    x = steps.join(first(s.fp), c("at") <= c("s"), "left").groupBy("s").agg(F.count("at").alias("p"))
    y = steps.join(first(s.members), c("at") <= c("s"), "left").groupBy("s").agg(F.count("at").alias("q"))
    law = 1 - sizing.survival(c("s"), s.n, s.spec.m, s.spec.k)
    return x.join(y, "s").select("s", r6(c("p") / float(s.n_fp)).alias("fp_removed"), r6(c("q") / float(s.n)).alias("members_lost"), r6(law).alias("law"))


# --- route replay -----------------------------------------------------------------------------------------------

HOPS_SQL = """li AS (SELECT o_custkey AS dest, o_orderdate, l_orderkey, l_linenumber, l_partkey, l_suppkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey),
rk AS (SELECT cycle, dest, l_partkey, l_suppkey, row_number() OVER (PARTITION BY cycle, dest ORDER BY o_orderdate DESC, l_orderkey DESC, l_linenumber DESC, l_partkey DESC, l_suppkey DESC) AS rn
  FROM li, (SELECT unnest({cycles}) AS cycle) WHERE o_orderdate < TIMESTAMP '2000-01-01' + to_days(CAST(60 * cycle AS INTEGER))),
cu AS (SELECT cycle, dest, max(l_partkey) FILTER (rn = 1) AS part, max(l_suppkey) FILTER (rn = 1) AS supp, max(l_partkey) FILTER (rn = 2) AS prev FROM rk WHERE rn <= 2 GROUP BY cycle, dest),
tr AS (SELECT cycle, m.n_nationkey AS monitor, dest, list_filter([1000000000 + m.n_nationkey, 2000000000 + 10 * m.n_regionkey + d.n_regionkey, 3000000000 + 100 * m.n_nationkey + c_nationkey, 4000000000 + supp,
  CASE WHEN dest % 10 = 0 AND prev <> part THEN 5000000000 + prev END, 5000000000 + part], lambda x: x IS NOT NULL) AS path
  FROM cu JOIN customer ON c_custkey = dest JOIN nation d ON d.n_nationkey = c_nationkey CROSS JOIN nation m WHERE m.n_nationkey < 10),
hp AS (SELECT cycle, monitor, dest, ttl, node, ttl = len(path) AS is_penultimate, len(path) AS hops FROM (SELECT *, unnest(path) AS node, unnest(range(1, len(path) + 1)) AS ttl FROM tr)),
ss AS (SELECT DISTINCT node AS key FROM hp WHERE cycle = 0 AND is_penultimate),
kn AS (SELECT node AS key, count(*) AS weight FROM hp WHERE cycle = 0 GROUP BY node)"""


def hops_sql(cycles) -> str:
    return HOPS_SQL.replace("{cycles}", str(list(cycles)))


def route_filter_sql(factor: float, beta: float | None, k: int = 5, live: bool = False) -> str:
    """CTEs for one filter over the stop set: sp, a, fp (with weight), b by degree, and the visit unless beta is null."""
    pos = sql_positions("kn.key", k, "sp.m")
    base = f"""sp AS (SELECT CAST(ceil({factor} * count(*)) AS BIGINT) AS m, count(*) AS n FROM ss),
h AS (SELECT kn.key, weight, ss.key IS NOT NULL AS is_member, {pos} AS positions FROM kn LEFT JOIN ss ON ss.key = kn.key, sp),
a AS (SELECT key, positions FROM h WHERE is_member),
v AS (SELECT DISTINCT unnest(positions) AS pos FROM a),
vs AS (SELECT list(pos) AS ps FROM v),
fp AS (SELECT key, weight, positions FROM h WHERE NOT is_member AND (SELECT bool_and(x IN (SELECT pos FROM v)) FROM (SELECT unnest(h.positions) AS x)))"""
    if beta is None:
        return base
    b = f"""bo AS (SELECT key, positions, row_number() OVER (ORDER BY weight DESC, key) AS ord FROM fp),
b AS (SELECT * FROM bo WHERE ord <= (SELECT least(count(*), greatest(1, CAST(floor({beta} * count(*) + 0.5) AS BIGINT))) FROM fp))"""
    return ",\n".join([base, b, *([live_sql("ratio", k)] if live else [choice_sql("ratio", k), VISIT_SQL])])


#: Outcome rows of the node set ``pz(key)``.
_REPLAY = """fs AS (SELECT cycle, monitor, dest, min((ttl, is_penultimate)) AS x FROM hp JOIN pz ON pz.key = hp.node WHERE cycle IN ({cycles}) GROUP BY ALL),
oc AS (SELECT e.cycle, e.monitor, e.dest, e.hops, x[1] AS stop_ttl, CASE WHEN x IS NULL THEN 'collision' WHEN x[2] THEN 'success' ELSE 'short' END AS outcome
  FROM (SELECT cycle, monitor, dest, max(ttl) AS hops FROM hp WHERE cycle IN ({cycles}) GROUP BY ALL) e LEFT JOIN fs USING (cycle, monitor, dest)),
ou AS (SELECT cycle, count(*) AS traces, round(avg(CAST(outcome = 'success' AS DOUBLE)), 6) AS success, round(avg(CAST(outcome = 'short' AS DOUBLE)), 6) AS short, round(avg(CAST(outcome = 'collision' AS DOUBLE)), 6) AS collision FROM oc GROUP BY cycle)"""
_NODES = "nd AS (SELECT DISTINCT node AS key FROM hp)"


def positive_sql(kind: str) -> str:
    """CTE pz(key): nodes of any cycle that test positive."""
    if kind == "list":
        return "pz AS (SELECT key FROM ss)"
    pos = sql_positions("key", 5, "sp.m")
    left = "(SELECT pos FROM v)" if kind == "bloom" else "(SELECT pos FROM v WHERE pos NOT IN (SELECT pos FROM c))"
    return f"nd AS (SELECT DISTINCT node AS key FROM hp),\nnh AS (SELECT key, unnest({pos}) AS pos FROM nd, sp),\nlv AS {left},\npz AS (SELECT key FROM nh LEFT JOIN lv USING (pos) GROUP BY key HAVING bool_and(lv.pos IS NOT NULL))"


def replay_sql(kind: str, factor: float = 2.5, beta: float | None = 0.25, cycles=(0, 1), shown=(1,), live: bool = False, select: str = "SELECT * FROM ou") -> str:
    parts = [hops_sql(cycles)]
    if kind != "list":
        parts.append(route_filter_sql(factor, beta if kind == "cleared" else None, live=live))
    return with_sql(*parts, positive_sql(kind), _REPLAY.replace("{cycles}", ", ".join(map(str, shown))), select=select)


class Routes:
    """Written hops, stop set and known nodes with degrees; filters over the stop set."""

    def __init__(self, spark: SparkSession, sf_dir: str, cycles=(0, 1)):
        self.hops = written(tracing.hops(spark, sf_dir, list(cycles)), "hops")
        self.stop = written(tracing.stop_set(self.hops), "stop")
        self.known = written(tracing.degrees(self.hops), "known")
        self.nodes = written(self.hops.select(c("node").alias("key")).distinct(), "nodes")
        self.n = self.stop.count()

    def spec(self, factor: float, k: int = 5) -> FilterSpec:
        return FilterSpec(int(-(-factor * self.n // 1)), k)

    def positive(self, kind: str, factor: float = 2.5, beta: float = 0.25, live: bool = False) -> DataFrame:
        """(key) of all nodes that test positive."""
        if kind == "list":
            return self.stop
        spec = self.spec(factor)
        pos = written(filters.build_positions(self.stop, spec), "pos")
        if kind == "cleared":
            _, done = self.cleared(spec, beta, live)
            pos = clearing.reset_bits(pos, done.cleared)
        return filters.positives(self.nodes, pos, spec)

    def cleared(self, spec: FilterSpec, beta: float, live: bool = False):
        members = hashed(self.stop, spec)
        fp = written(clearing.false_positives(self.known.select("key"), self.stop, spec).join(self.known, "key"), "fp")
        b = clearing.troublesome(fp, beta, [c("weight").desc(), c("key")])
        done = clearing.clear(members, fp, b, spec, "ratio", live)
        done.log = written(done.log, "log")
        return fp, done

    def replayed(self, kind: str, factor: float = 2.5, beta: float = 0.25, cycles=(1,), live: bool = False) -> DataFrame:
        return tracing.replay(self.hops.where(c("cycle").isin(list(cycles))), self.positive(kind, factor, beta, live))


FACTORS = (1.25, 2.5, 3.75, 5.0, 6.25, 7.5, 8.75, 10.0, 11.25, 12.5)
TRACE_BETAS = (0.01, 0.05, 0.10, 0.25)


class Grid:
    """Filters of several sizes over one stop set, built, probed and cleared side by side.

    Keys and positions of size i carry i above bit ``SHIFT``, so one join, one numbering and one visit serve all sizes.
    ``until(key, i, gone)`` tells for every node and size how many visits leave it positive; i = 0 is the list.
    """

    def __init__(self, r: Routes, factors=FACTORS, live: bool = False):
        self.r, self.factors = r, factors
        specs = [(i, r.spec(f)) for i, f in enumerate(factors, 1)]

        def spread(df: DataFrame) -> DataFrame:
            return union_all([composite(hashed(df, spec).withColumn("i", F.lit(i)), "i") for i, spec in specs])

        members = written(spread(r.stop), "members")
        pos = written(members.select(F.explode("positions").alias("pos")).distinct(), "pos")
        nodes = spread(r.nodes)
        lost = nodes.select("key", F.explode("positions").alias("pos")).join(pos, "pos", "left_anti").select("key").distinct()
        positive = written(nodes.join(lost, "key", "left_anti"), "positive")
        known = r.known.select(c("key").alias("node"), "weight")
        fp = positive.withColumn("node", low("key")).join(known, "node").drop("node").join(members.select("key"), "key", "left_anti")
        fp = written(fp, "fp")
        ordered = written(clearing.numbered(fp, [group_of("key"), c("weight").desc(), c("key")]), "ordered")
        self.count = {x[0]: x[1] for x in fp.groupBy(group_of("key").alias("i")).count().collect()}
        self.before = {i: sum(self.count.get(j, 0) for j in range(1, i)) for i, _ in specs}
        done = clearing.clear(members, fp, ordered, specs[0][1], "ratio", live)
        done.log = written(done.log, "log")
        gone = done.cleared.select("pos", "ord")
        until = positive.select("key", F.explode("positions").alias("pos")).join(gone, "pos", "left").groupBy("key").agg(F.min(F.coalesce("ord", F.lit(tracing.NEVER))).alias("gone"))
        listed = r.stop.select("key", F.lit(0).alias("i"), F.lit(tracing.NEVER).alias("gone"))
        self.until = written(until.select(low("key").alias("key"), group_of("key").alias("i"), "gone").unionByName(listed), "until")

    def paths(self, cycles=(1,)) -> DataFrame:
        return written(tracing.paths(self.r.hops.where(c("cycle").isin(list(cycles))), self.until, len(self.factors) + 1), "paths")

    def last(self, i: int, beta: float) -> int:
        """Visits made at ``beta``, counted over all sizes up to i."""
        n = self.count.get(i, 0)
        return self.before[i] + (min(n, max(1, clearing.round_half_up(beta * n))) if beta > 0 else 0)

    def steps(self, betas=TRACE_BETAS, plain: bool = True, listed: bool = True) -> DataFrame:
        """(i, last, representation, factor, beta) of the list, the plain filters and the cleared ones."""
        rows = [(0, 0, "list", 0.0, 0.0)] if listed else []
        for i, f in enumerate(self.factors, 1):
            rows += [(i, self.last(i, 0.0), "bloom", float(f), 0.0)] if plain else []
            rows += [(i, self.last(i, b), "cleared", float(f), float(b)) for b in betas]
        return self.r.hops.sparkSession.createDataFrame(rows, "i int, last long, representation string, factor double, beta double")


def grid_sql(factors=FACTORS, cycles=(0, 1), shown=(1,), live: bool = False) -> str:
    """CTEs of the same: sp by size, node visits nx(i, key, gone), hops ht(i, cycle, monitor, dest, ttl, gone)."""
    one = 1 << SHIFT
    sizes = ", ".join(f"({i}, {f})" for i, f in enumerate(factors, 1))
    spread = lambda key: f"list_transform({sql_positions(key, 5, 'sp.m')}, lambda p: p + sp.i * {one})"
    visit = """vis AS (SELECT DISTINCT key >> {shift} AS i, min(ord) OVER (PARTITION BY key >> {shift}) - 1 AS step, []::BIGINT[] AS cleared, []::BIGINT[] AS acting FROM ch
  UNION ALL SELECT vis.i, vis.step + 1, CASE WHEN list_has_any(vis.cleared, ch.positions) THEN vis.cleared ELSE list_append(vis.cleared, ch.pos) END,
  CASE WHEN list_has_any(vis.cleared, ch.positions) THEN vis.acting ELSE list_append(vis.acting, ch.ord) END
  FROM vis JOIN ch ON ch.key >> {shift} = vis.i AND ch.ord = vis.step + 1)""".replace("{shift}", str(SHIFT))
    if live:
        visit = live_sql("ratio", 5)
        visit = visit[: visit.index("fin AS")].rstrip().rstrip(",")
        visit = visit.replace("SELECT 0::BIGINT AS step,", f"SELECT DISTINCT key >> {SHIFT} AS i, min(ord) OVER (PARTITION BY key >> {SHIFT}) - 1 AS step,").replace("AS acting\n  UNION ALL SELECT s.step + 1", "AS acting FROM b\n  UNION ALL SELECT s.i, s.step + 1").replace("JOIN b ON b.ord = s.step + 1", f"JOIN b ON b.key >> {SHIFT} = s.i AND b.ord = s.step + 1")
    return ",\n".join([
        hops_sql(cycles),
        f"sp AS (SELECT i, f, CAST(ceil(f * n) AS BIGINT) AS m FROM (VALUES {sizes}) z(i, f), (SELECT count(*) AS n FROM ss))",
        f"a AS (SELECT ss.key + sp.i * {one} AS key, {spread('ss.key')} AS positions FROM ss, sp)",
        "v AS (SELECT DISTINCT unnest(positions) AS pos FROM a)",
        f"nd AS (SELECT sp.i, d.key, {spread('d.key')} AS positions FROM (SELECT DISTINCT node AS key FROM hp) d, sp)",
        "ok AS (SELECT i, key FROM (SELECT i, key, unnest(positions) AS pos FROM nd) x LEFT JOIN v USING (pos) GROUP BY i, key HAVING bool_and(v.pos IS NOT NULL))",
        f"fp AS (SELECT nd.key + nd.i * {one} AS key, weight, positions FROM nd JOIN ok ON ok.i = nd.i AND ok.key = nd.key JOIN kn ON kn.key = nd.key WHERE nd.key NOT IN (SELECT key FROM ss))",
        f"b AS (SELECT key, positions, row_number() OVER (ORDER BY key >> {SHIFT}, weight DESC, key) AS ord FROM fp)",
        *([visit] if live else [choice_sql("ratio", 5), visit]),
        "c AS (SELECT unnest(cleared) AS pos, unnest(acting) AS ord FROM (SELECT arg_max(cleared, step) AS cleared, arg_max(acting, step) AS acting FROM vis GROUP BY i))",
        "nx AS (SELECT i, key, min(coalesce(ord, 9000000000000)) AS gone FROM (SELECT nd.i, nd.key, unnest(positions) AS pos FROM nd JOIN ok ON ok.i = nd.i AND ok.key = nd.key) x LEFT JOIN c USING (pos) GROUP BY i, key UNION ALL SELECT 0, key, 9000000000000 FROM ss)",
        f"ht AS (SELECT i, cycle, monitor, dest, ttl, is_penultimate, gone FROM hp JOIN nx ON nx.key = hp.node WHERE cycle IN ({', '.join(map(str, shown))}))",
        f"nf AS (SELECT sp.i, sp.f, (SELECT count(*) FROM fp WHERE key >> {SHIFT} = sp.i) AS n, (SELECT count(*) FROM fp WHERE key >> {SHIFT} < sp.i) AS before FROM sp)",
    ])


def steps_sql(betas=TRACE_BETAS, plain: bool = True, listed: bool = True) -> str:
    """CTE st(i, last, representation, factor, beta)."""
    rows = ["SELECT 0 AS i, 0::BIGINT AS last, 'list' AS representation, 0::DOUBLE AS factor, 0::DOUBLE AS beta"] if listed else []
    if plain:
        rows.append("SELECT i, before, 'bloom', CAST(f AS DOUBLE), 0::DOUBLE FROM nf")
    rows.append(f"SELECT i, before + CASE WHEN beta = 0 THEN 0 ELSE least(n, greatest(1, CAST(floor(beta * n + 0.5) AS BIGINT))) END AS last, 'cleared' AS representation, CAST(f AS DOUBLE) AS factor, beta FROM nf, (SELECT unnest([{', '.join(f'CAST({b} AS DOUBLE)' for b in betas)}]) AS beta)")
    return "st AS (" + " UNION ALL ".join(rows) + ")"


#: First stop of every trace at every step, and the shares.
_STOPS = """te AS (SELECT cycle, monitor, dest, max(ttl) AS hops FROM hp WHERE cycle IN (SELECT DISTINCT cycle FROM ht) GROUP BY ALL),
ff AS (SELECT representation, factor, beta, cycle, monitor, dest, min((ttl, is_penultimate)) AS x FROM st JOIN ht ON ht.i = st.i AND gone > last GROUP BY ALL),
sh AS (SELECT st.representation, st.factor, st.beta, te.cycle, count(*) AS traces, round(count(*) FILTER (x[2]) / CAST(count(*) AS DOUBLE), 6) AS success,
  round(count(*) FILTER (NOT x[2]) / CAST(count(*) AS DOUBLE), 6) AS short, round(count(*) FILTER (x IS NULL) / CAST(count(*) AS DOUBLE), 6) AS collision
  FROM st CROSS JOIN te LEFT JOIN ff ON ff.representation = st.representation AND ff.factor = st.factor AND ff.beta = st.beta AND ff.cycle = te.cycle AND ff.monitor = te.monitor AND ff.dest = te.dest
  GROUP BY st.representation, st.factor, st.beta, te.cycle)"""


def _shares(col: str):
    def f(spark, sf_dir):
        g = Grid(Routes(spark, sf_dir))
        return tracing.shares(g.paths(), g.steps()).select("representation", "factor", "beta", "traces", col)

    return f


for _name in ("success", "short", "collision"):
    query(f"w_trace_{_name}", with_sql(grid_sql(), steps_sql(), _STOPS, select=f"SELECT representation, factor, beta, traces, {_name} FROM sh"))(_shares(_name))
    query(f"m_{_name}", replay_sql("cleared", select=f"SELECT cycle, {_name} FROM ou"))(lambda spark, sf_dir, x=_name: tracing.outcomes(Routes(spark, sf_dir).replayed("cleared")).select("cycle", x))


@query("w_trace_trouble", with_sql(hops_sql((0,)), route_filter_sql(2.5, None), select="SELECT weight AS degree, count(*) AS keys FROM fp GROUP BY 1", recursive=False))
def w_trace_trouble(spark, sf_dir):
    r = Routes(spark, sf_dir, (0,))
    fp = clearing.false_positives(r.known.select("key"), r.stop, r.spec(2.5)).join(r.known, "key")
    return fp.groupBy(c("weight").alias("degree")).agg(F.count("*").alias("keys"))


query("m_trouble_hist", ORACLE_SQL["w_trace_trouble"])(QUERIES["w_trace_trouble"])


@query("m_centrality", with_sql(hops_sql((0,)), select="SELECT key, weight FROM kn", recursive=False))
def m_centrality(spark, sf_dir):
    return tracing.degrees(tracing.hops(spark, sf_dir, [0]))


_SEEN = """sn AS (SELECT DISTINCT node FROM hp JOIN oc USING (cycle, monitor, dest) WHERE stop_ttl IS NULL OR ttl <= stop_ttl),
sl AS (SELECT DISTINCT prev AS a, node AS b FROM (SELECT node, ttl, stop_ttl, lag(node) OVER (PARTITION BY cycle, monitor, dest ORDER BY ttl) AS prev FROM hp JOIN oc USING (cycle, monitor, dest) WHERE stop_ttl IS NULL OR ttl <= stop_ttl) WHERE prev IS NOT NULL)"""


def _missed_sql(what: str, kind: str) -> str:
    ref = replay_sql("list", select="SELECT * FROM {}").replace("SELECT * FROM {}", "").rstrip() + ",\n" + _SEEN
    own = replay_sql(kind, select="").rstrip() + ",\n" + _SEEN
    t, on = ("sn", "r.node = o.node") if what == "nodes" else ("sl", "r.a = o.a AND r.b = o.b")
    return f"SELECT '{kind}' AS representation, round(avg(CAST(o.{'node' if what == 'nodes' else 'b'} IS NULL AS DOUBLE)), 6) AS {what}_missed FROM ({ref} SELECT * FROM {t}) r LEFT JOIN ({own} SELECT * FROM {t}) o ON {on}"


def _missed(what: str):
    def f(spark, sf_dir):
        r = Routes(spark, sf_dir)
        trace = r.hops.where("cycle = 1")
        see = tracing.seen_nodes if what == "nodes" else tracing.seen_links
        ref = written(see(trace, r.replayed("list")), "ref")
        return union_all([tracing.missed(ref, see(trace, r.replayed(k)), f"{what}_missed").withColumn("representation", F.lit(k)) for k in ("bloom", "cleared")])

    return f


_SEEN_BY = {
    "nodes": "sn AS (SELECT DISTINCT st.representation, st.factor, st.beta, node AS k FROM st JOIN hp ON cycle = 1 LEFT JOIN ff ON ff.representation = st.representation AND ff.factor = st.factor AND ff.beta = st.beta AND ff.monitor = hp.monitor AND ff.dest = hp.dest WHERE x IS NULL OR ttl <= x[1])",
    "links": "lk AS (SELECT monitor, dest, ttl, (lag(node) OVER (PARTITION BY monitor, dest ORDER BY ttl), node) AS k FROM hp WHERE cycle = 1),\nsn AS (SELECT DISTINCT st.representation, st.factor, st.beta, k FROM st JOIN lk ON k[1] IS NOT NULL LEFT JOIN ff ON ff.representation = st.representation AND ff.factor = st.factor AND ff.beta = st.beta AND ff.monitor = lk.monitor AND ff.dest = lk.dest WHERE x IS NULL OR ttl <= x[1])",
}
_MISSED_BY = "SELECT st.representation, st.factor, st.beta, round(avg(CAST(sn.k IS NULL AS DOUBLE)), 6) AS missed FROM st CROSS JOIN (SELECT k FROM sn WHERE representation = 'list') r LEFT JOIN sn ON sn.representation = st.representation AND sn.factor = st.factor AND sn.beta = st.beta AND sn.k = r.k WHERE st.representation <> 'list' GROUP BY ALL"


def _missed_by(what: str):
    def f(spark, sf_dir):
        g = Grid(Routes(spark, sf_dir))
        return tracing.missed_shares(g.paths(), g.steps(listed=False), what == "links")

    return f


for _what in ("nodes", "links"):
    query(f"w_trace_{_what}_missed", with_sql(grid_sql(), steps_sql(), _STOPS, _SEEN_BY[_what], select=_MISSED_BY))(_missed_by(_what))
    query(f"m_{_what}_missed", " UNION ALL ".join(_missed_sql(_what, k) for k in ("bloom", "cleared")))(_missed(_what))

_SWEEP = tuple(round(i / 100, 2) for i in range(101))
_SWEEP_SIZES = (2.5, 7.5)


@query("w_trace_beta_sweep", with_sql(grid_sql(_SWEEP_SIZES), steps_sql(_SWEEP, False, False), _STOPS, select="SELECT factor, beta, traces, success, short, collision FROM sh"))
def w_trace_beta_sweep(spark, sf_dir):
    """All betas of two sizes from one visit; the places where outcomes change are added up, not the traces of each beta."""
    g = Grid(Routes(spark, sf_dir), _SWEEP_SIZES)
    return tracing.shares(g.paths(), g.steps(_SWEEP, False, False)).select("factor", "beta", "traces", "success", "short", "collision")


_CYCLES = tuple(range(11))


@query("w_trace_cycles", with_sql(grid_sql(_SWEEP_SIZES, _CYCLES, _CYCLES[1:]), steps_sql((0.25,), False), _STOPS, select="SELECT representation, factor, cycle, traces, success, short, collision FROM sh"))
def w_trace_cycles(spark, sf_dir):
    """Ten probing cycles after one learning cycle: the list and cleared filters of two sizes at beta 25%."""
    g = Grid(Routes(spark, sf_dir, _CYCLES), _SWEEP_SIZES)
    return tracing.shares(g.paths(_CYCLES[1:]), g.steps((0.25,), False)).select("representation", "factor", "cycle", "traces", "success", "short", "collision")


class Legs:
    """What ``Routes`` holds of the learning cycle, from the two legs of the traces instead of a row for each hop."""

    def __init__(self, spark: SparkSession, sf_dir: str, cycles=(0, 1)):
        self.approach, tail = tracing.legs(spark, sf_dir, list(cycles))
        self.tail = written(tail, "tail")
        learnt = self.tail.where("cycle = 0")
        self.stop = written(tracing.ends(self.approach, learnt), "stop")
        self.known = written(tracing.known_nodes(self.approach, learnt), "known")
        self.nodes = written(tracing.known_nodes(self.approach, self.tail).select("key"), "nodes")
        self.n = self.stop.count()

    spec = Routes.spec


def _live_shares(spark: SparkSession, sf_dir: str, factors=FACTORS, betas=(0.01, 0.25)) -> DataFrame:
    """Outcome shares of every size and beta with frozen and with live counters.

    Filters are built and probed once for both counters. A smaller beta is a prefix of the visit, so the visits end at
    the greatest one. A node's answers at all steps are the bits of one number, and the traces are walked once.
    """
    r = Legs(spark, sf_dir)
    specs = [(i, r.spec(f)) for i, f in enumerate(factors, 1)]

    def spread(df: DataFrame) -> DataFrame:
        return union_all([composite(hashed(df, spec).withColumn("i", F.lit(i)), "i") for i, spec in specs])

    members = written(spread(r.stop), "members")
    pos = members.select(F.explode("positions").alias("pos")).distinct()
    others = spread(r.nodes.join(r.stop, "key", "left_anti"))
    lost = others.select("key", F.explode("positions").alias("pos")).join(pos, "pos", "left_anti").select("key").distinct()
    foreign = written(others.join(lost, "key", "left_anti"), "positive")
    fp = written(foreign.withColumn("node", low("key")).join(r.known.select(c("key").alias("node"), "weight"), "node").drop("node"), "fp")
    count = {x[0]: x[1] for x in fp.groupBy(group_of("key").alias("i")).count().collect()}
    last, before, rows = {}, 0, []
    for i, f in enumerate(factors, 1):
        n = count.get(i, 0)
        for beta in betas:
            last[i, beta] = before + (min(n, max(1, clearing.round_half_up(beta * n))) if beta > 0 else 0)
            rows += [(i, last[i, beta], float(f), float(beta), live) for live in ("frozen", "live")]
        before += n
    steps = spark.createDataFrame([(*x, bit) for bit, x in enumerate(rows)], "i int, last long, factor double, beta double, counters string, bit int")
    ends = spark.createDataFrame([(i, max(last[i, beta] for beta in betas)) for i, _ in specs], "i int, last long")
    ordered = clearing.numbered(fp, [group_of("key"), c("weight").desc(), c("key")]).withColumn("i", group_of("key"))
    b = written(ordered.join(F.broadcast(ends), "i").where("ord <= last").drop("i", "last"), "ordered")
    gone = []
    for counters in ("frozen", "live"):
        done = clearing.clear(members, fp, b, specs[0][1], "ratio", counters == "live", group=group_of)
        gone.append(done.cleared.select("pos", "ord", F.lit(counters).alias("counters")))
    gone = written(union_all(gone), "gone")

    # Bits of the sizes under which a node tests positive, less those of the steps that have reset one of its positions.
    bits = lambda x: F.bit_or(F.expr("shiftleft(1L, bit)")).alias(x)
    by_size = F.broadcast(steps.groupBy("i").agg(bits("mask")))
    every = r.stop.select("key", F.lit((1 << len(rows)) - 1).cast("long").alias("mask"))
    some = foreign.select(low("key").alias("key"), group_of("key").alias("i")).join(by_size, "i").select("key", "mask")
    positive = every.unionByName(some).groupBy("key").agg(F.bit_or("mask").alias("mask"))
    holders = members.select("key", "positions").unionByName(foreign.select("key", "positions")).select("key", F.explode("positions").alias("pos"))
    reset = holders.join(gone, "pos").groupBy("key", "counters").agg(F.min("ord").alias("ord")).withColumn("i", group_of("key"))
    cleared = reset.join(F.broadcast(steps), ["i", "counters"]).where("ord <= last").groupBy(low("key").alias("key")).agg(bits("off"))
    masks = positive.join(cleared, "key", "left").select("key", c("mask").bitwiseAND(F.bitwise_not(F.coalesce("off", F.lit(0).cast("long")))).alias("mask"))
    return tracing.mask_shares(r.approach, r.tail.where("cycle = 1"), written(masks, "masks"), steps.select("bit", "factor", "beta", "counters"))


def _live_trace(col: str):
    return lambda spark, sf_dir: _live_shares(spark, sf_dir).select("factor", "beta", "counters", col)


for _col in ("success", "short", "collision"):
    _sql = " UNION ALL ".join("SELECT * FROM (" + with_sql(grid_sql(live=live), steps_sql((0.01, 0.25), False, False), _STOPS, select=f"SELECT factor, beta, '{'live' if live else 'frozen'}' AS counters, {_col} FROM sh") + ")" for live in (False, True))
    query(f"w_trace_live_{_col}", _sql)(_live_trace(_col))


@query("w_trace_merge", with_sql(hops_sql((0,)), "sp AS (SELECT CAST(ceil(2.5 * count(*)) AS BIGINT) AS m FROM ss)", select=f"SELECT DISTINCT unnest({sql_positions('key', 5, 'sp.m')}) AS pos FROM ss, sp", recursive=False))
def w_trace_merge(spark, sf_dir):
    """Each monitor learns its own filter; OR of all is the filter of the union."""
    r = Routes(spark, sf_dir, (0,))
    spec = r.spec(2.5)
    own = hashed(r.hops.where("is_penultimate").select("monitor", c("node").alias("key")).distinct(), spec)
    each = own.select("monitor", F.explode("positions").alias("pos")).groupBy("monitor", F.bitmap_bucket_number("pos").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("pos")).alias("bits"))
    return filters.positions_of(filters.union(each.select("bucket", "bits")))


@query("m_probe_load", " UNION ALL ".join(f"SELECT '{k}' AS representation, * FROM ({replay_sql(k, select='SELECT cycle, CAST(sum(coalesce(stop_ttl, hops + 1)) AS BIGINT) AS sent, CAST(sum(hops + 1 - coalesce(stop_ttl, hops + 1)) AS BIGINT) AS saved FROM oc GROUP BY cycle')})" for k in ("list", "bloom", "cleared")))
def m_probe_load(spark, sf_dir):
    r = Routes(spark, sf_dir)
    return union_all([tracing.probe_load(r.replayed(k)).withColumn("representation", F.lit(k)) for k in ("list", "bloom", "cleared")])


@query("m_destination_hits", replay_sql("list", cycles=(0, 1, 2, 3), shown=(0, 1, 2, 3), select="SELECT cycle, hits, CAST(sum(hits) OVER (ORDER BY cycle) AS BIGINT) AS total FROM (SELECT cycle, count(*) FILTER (cycle = 0 OR outcome = 'collision') AS hits FROM oc GROUP BY cycle)"))
def m_destination_hits(spark, sf_dir):
    r = Routes(spark, sf_dir, (0, 1, 2, 3))
    return tracing.destination_hits(r.replayed("list", cycles=(0, 1, 2, 3)))


@query("m_compression", with_sql(hops_sql((0,)), select="SELECT factor, m, round(32.0 * n / m, 6) AS ratio FROM (SELECT factor, n, CAST(ceil(factor * n) AS BIGINT) AS m FROM (SELECT unnest([1.25::DOUBLE, 2.5, 5.0, 7.5, 10.0, 12.5]) AS factor), (SELECT count(*) AS n FROM ss))", recursive=False))
def m_compression(spark, sf_dir):
    stop = tracing.stop_set(tracing.hops(spark, sf_dir, [0])).agg(F.count("*").alias("n"))
    f = spark.createDataFrame([(x,) for x in (1.25, 2.5, 5.0, 7.5, 10.0, 12.5)], "factor double")
    return f.crossJoin(stop).select("factor", F.ceil(c("factor") * c("n")).alias("m"), "n").select("factor", "m", r6(32.0 * c("n") / c("m")).alias("ratio"))


@query("m_comm_cost", with_sql(hops_sql((0,)), select="SELECT r AS representation, CAST(10 * CASE r WHEN 'list' THEN 32 * n WHEN 'bloom' THEN CAST(ceil(2.5 * n) AS BIGINT) ELSE CAST(ceil(2.5 * n) AS BIGINT) END AS BIGINT) AS bits FROM (SELECT unnest(['list', 'bloom', 'cleared']) AS r), (SELECT count(*) AS n FROM ss)", recursive=False))
def m_comm_cost(spark, sf_dir):
    """Bits sent to all monitors; clearing does not change the size of a filter."""
    stop = tracing.stop_set(tracing.hops(spark, sf_dir, [0])).agg(F.count("*").alias("n"))
    kinds = spark.createDataFrame([("list",), ("bloom",), ("cleared",)], "representation string")
    bits = F.when(c("representation") == "list", 32 * c("n")).otherwise(F.ceil(2.5 * c("n")))
    return kinds.crossJoin(stop).select("representation", (10 * bits).cast("long").alias("bits"))


_ASPECTS = ("success", "topology_found", "compression", "no_collision", "topology_missed", "load", "collision")


def _aspects_sql() -> str:
    found = f"fd AS (SELECT representation, count(*) AS found FROM sn GROUP BY 1),\nmi AS ({_MISSED_BY}),\nal AS (SELECT count(DISTINCT node) AS every FROM hp WHERE cycle = 1)"
    size = "CASE representation WHEN 'list' THEN 32 * (SELECT count(*) FROM ss) ELSE (SELECT m FROM sp) END"
    value = f"""CASE a WHEN 'success' THEN success WHEN 'collision' THEN collision WHEN 'no_collision' THEN round(1 - collision, 6) WHEN 'topology_missed' THEN coalesce(missed, 0)
 WHEN 'topology_found' THEN round(found / CAST(every AS DOUBLE), 6) WHEN 'compression' THEN round(32 * (SELECT count(*) FROM ss) / CAST({size} AS DOUBLE), 6) ELSE CAST(10 * {size} AS DOUBLE) END"""
    rows = f"va AS (SELECT a AS aspect, representation, {value} AS value FROM sh JOIN fd USING (representation) LEFT JOIN mi USING (representation), al, (SELECT unnest({list(_ASPECTS)}) AS a))"
    return with_sql(grid_sql((2.5,)), steps_sql((0.25,)), _STOPS, _SEEN_BY["nodes"], found, rows, select="SELECT aspect, max(value) FILTER (representation = 'list') AS list, max(value) FILTER (representation = 'bloom') AS bloom, max(value) FILTER (representation = 'cleared') AS cleared FROM va GROUP BY aspect")


@query("m_aspect_matrix", _aspects_sql())
def m_aspect_matrix(spark, sf_dir):
    """The seven aspects by representation, recomputed from one replay and pivoted; load is what all monitors are sent, in bits."""
    r = Routes(spark, sf_dir)
    g = Grid(r, (2.5,))
    path, steps = g.paths(), g.steps((0.25,))
    outcome = tracing.shares(path, steps).select("representation", "success", "collision")
    missed = tracing.missed_shares(path, steps.where("i > 0"), False).select("representation", "missed")
    seen = path.select("i", F.explode("hits").alias("h")).groupBy("i", "h.node").agg(F.min("h.reach").alias("reach"))
    found = seen.join(F.broadcast(steps), (seen["i"] == steps["i"]) & (c("reach") <= c("last"))).groupBy("representation").agg(F.count("*").alias("found"))
    every = seen.where("i = 0").agg(F.count("*").alias("every"))
    size = F.when(c("representation") == "list", F.lit(32 * r.n)).otherwise(F.lit(r.spec(2.5).m)).cast("double")
    rows = outcome.join(found, "representation").join(missed, "representation", "left").crossJoin(F.broadcast(every)).select(
        "representation", "success", r6(c("found") / c("every").cast("double")).alias("topology_found"), r6(F.lit(32.0 * r.n) / size).alias("compression"), r6(1 - c("collision")).alias("no_collision"),
        F.coalesce("missed", F.lit(0.0)).alias("topology_missed"), (10 * size).alias("load"), "collision",
    )
    long = rows.unpivot(["representation"], list(_ASPECTS), "aspect", "value")
    return long.groupBy("aspect").pivot("representation", ["list", "bloom", "cleared"]).agg(F.first("value"))


@query("baseline_full_trace", with_sql(hops_sql((0, 1)), select="SELECT cycle, count(*) AS traces, count(*) AS hits, CAST(sum(hops + 1) AS BIGINT) AS sent FROM (SELECT cycle, monitor, dest, max(ttl) AS hops FROM hp GROUP BY ALL) GROUP BY cycle", recursive=False))
def baseline_full_trace(spark, sf_dir):
    t = tracing.hops(spark, sf_dir, [0, 1]).groupBy("cycle", "monitor", "dest").agg(F.max("ttl").alias("hops"))
    return t.groupBy("cycle").agg(F.count("*").alias("traces"), F.count("*").alias("hits"), F.sum(c("hops") + 1).alias("sent"))


@query("baseline_cooperative", with_sql(hops_sql((0, 1)), "lw AS (SELECT node, min(monitor) AS lowest FROM hp WHERE cycle = 1 GROUP BY node)", "fo AS (SELECT monitor, dest, min(ttl) AS stop_ttl FROM hp JOIN lw USING (node) WHERE cycle = 1 AND lowest < monitor GROUP BY ALL)", select="SELECT monitor, count(*) AS traces, count(stop_ttl) AS stopped, CAST(sum(coalesce(stop_ttl, hops + 1)) AS BIGINT) AS sent FROM (SELECT monitor, dest, max(ttl) AS hops FROM hp WHERE cycle = 1 GROUP BY ALL) LEFT JOIN fo USING (monitor, dest) GROUP BY monitor", recursive=False))
def baseline_cooperative(spark, sf_dir):
    t = tracing.cooperative(written(tracing.hops(spark, sf_dir, [0, 1]), "hops"))
    return t.groupBy("monitor").agg(F.count("*").alias("traces"), F.count("stop_ttl").alias("stopped"), F.sum(F.coalesce("stop_ttl", c("hops") + 1)).cast("long").alias("sent"))


# --- other places where hot keys matter -------------------------------------------------------------------------


@query("w_join_prefilter", with_sql(setting_sql(), b_sql(), choice_sql("ratio"), VISIT_SQL, "lf AS (SELECT list(pos) AS ps FROM v WHERE pos NOT IN (SELECT pos FROM c))", "hit AS (SELECT h.key, is_member, list_has_all(ps, positions) AS after, list_has_all((SELECT list(pos) FROM v), positions) AS before FROM h, lf)", select="SELECT count(*) AS lines, count(*) FILTER (before AND NOT is_member) AS false_before, count(*) FILTER (after AND NOT is_member) AS false_after, count(*) FILTER (is_member AND NOT after) AS lost FROM lineitem JOIN hit ON key = l_orderkey"))
def w_join_prefilter(spark, sf_dir):
    """Lines let through to a join with urgent orders, before and after clearing."""
    s = setting(spark, sf_dir)
    _, done = run(s, "ratio")
    pos = written(filters.build_positions(s.members.select("key"), s.spec), "pos")
    before = filters.probe_negative(s.u, pos, s.spec).select("key", c("maybe").alias("before"))
    after = filters.probe_negative(s.u, clearing.reset_bits(pos, done.cleared), s.spec).select("key", c("maybe").alias("after"))
    keys = s.u.join(before, "key").join(after, "key")
    li = table(spark, sf_dir, "lineitem", ["l_orderkey"])
    j = li.join(keys, c("l_orderkey") == c("key"))
    return j.agg(F.count("*").alias("lines"), F.count_if(c("before") & ~c("is_member")).alias("false_before"), F.count_if(c("after") & ~c("is_member")).alias("false_after"), F.count_if(c("is_member") & ~c("after")).alias("lost"))


_GRAM = "list_filter(string_split_regex(lower(text), '\\s+'), lambda x: x <> '')"


def _grams_sql(src: str, key: str) -> str:
    return f"SELECT {key}, unnest(list_transform(range(1, greatest(len(w) - 3, 1)), lambda i: array_to_string(w[i:i + 4], ' '))) AS g FROM (SELECT {key}, {_GRAM} AS w FROM {src})"


@query("w_contamination", f"WITH bg AS (SELECT DISTINCT g FROM ({_grams_sql('benchmark', 'item_id')})), dg AS (SELECT doc_id, g FROM ({_grams_sql('documents', 'doc_id')})), ht AS (SELECT g, count(*) AS uses, count(DISTINCT doc_id) AS degree FROM dg WHERE g IN (SELECT g FROM bg) GROUP BY g) SELECT (SELECT count(*) FROM dg) AS grams, count(*) AS in_benchmark, CAST(sum(uses) AS BIGINT) AS hits, max(degree) AS top_degree FROM ht")
def w_contamination(spark, sf_dir):
    """Benchmark 5-grams as members, document 5-grams as probes. Grams stay 64-bit hashes until the filter has rejected
    nearly all of them; only what passes is written out, checked exactly and counted by document."""

    def grams(df: DataFrame) -> DataFrame:
        words = F.filter(F.split(F.lower("text"), r"\s+"), lambda x: x != "")
        starts = F.when(F.size("w") >= 5, F.sequence(F.lit(1), F.size("w") - 4)).otherwise(F.array().cast("array<int>"))
        each = df.withColumn("w", words).select(df.columns[0], F.explode(F.transform(starts, lambda i: F.array_join(F.slice("w", i, 5), " "))).alias("gram"))
        return each.withColumn("key", F.xxhash64("gram"))

    a = written(grams(table(spark, sf_dir, "benchmark", ["item_id", "text"])).select("gram", "key").distinct(), "members")
    spec = FilterSpec(10 * max(1, a.count()), 7, "xxhash")
    text = table(spark, sf_dir, "documents", ["doc_id", "text"])
    passed = filters.probe(grams(text), filters.build_positions(a, spec), spec).where("maybe").select("doc_id", "gram")
    hit = passed.join(a.select("gram"), "gram", "left_semi").groupBy("gram", "doc_id").agg(F.count("*").alias("n")).groupBy("gram").agg(F.sum("n").alias("uses"), F.count("*").alias("degree"))
    n = F.size(F.filter(F.split(F.lower("text"), r"\s+"), lambda x: x != ""))
    every = text.agg(F.sum(F.greatest(n - 4, F.lit(0))).alias("grams"))
    return hit.agg(F.count("*").alias("in_benchmark"), F.sum("uses").alias("hits"), F.max("degree").alias("top_degree")).crossJoin(every).select("grams", "in_benchmark", "hits", "top_degree")


_HOT_BETAS = (0.01, 0.1, 0.25, 1.0)


def hot_traffic(u: DataFrame, bits: int = 5, k: int = 3, betas=_HOT_BETAS) -> DataFrame:
    """What clearing the most frequent false positives saves: u(key, weight, is_member) are keys and their traffic.

    By share of false positives cleared, most frequent first, ratio rule with counters weighted by traffic: false
    traffic let through before and after, members lost and theirs.
    """
    u = written(u, "traffic")
    spec = FilterSpec(max(1, bits * u.where("is_member").count()), k)
    a = hashed(u.where("is_member"), spec)
    fp = written(hashed(filters.positives(u.where(~c("is_member")), filters.build_positions(a, spec), spec).join(u, "key"), spec), "fp")
    n_fp, before = fp.agg(F.count("*"), F.coalesce(F.sum("weight"), F.lit(0))).first()
    b = clearing.troublesome(fp, 1.0, [c("weight").desc(), c("key")], n_fp)
    done = clearing.clear(a, fp, b, spec, "ratio", weight="weight")
    gone = written(done.log, "log").where("acted").select("pos", "ord")

    def lost(keys: DataFrame, names: tuple) -> DataFrame:
        at = keys.select("key", "weight", F.explode("positions").alias("pos")).join(gone, "pos").groupBy("key", "weight").agg(F.min("ord").alias("at"))
        each = at.groupBy("at").agg(F.count("*").alias("n"), F.sum("weight").alias("w"))
        met = F.broadcast(steps).join(each, c("at") <= c("last"), "left").groupBy("beta", "last")
        return met.agg(F.coalesce(F.sum("n"), F.lit(0)).alias(names[0]), F.coalesce(F.sum("w"), F.lit(0)).alias(names[1]))

    steps = u.sparkSession.createDataFrame([(float(x), min(n_fp, max(1, clearing.round_half_up(x * n_fp)))) for x in betas], "beta double, last long")
    out = lost(fp, ("removed", "saved")).join(lost(a, ("members_lost", "traffic_lost")), ["beta", "last"])
    return out.select("beta", c("last").alias("b"), "removed", F.lit(before).cast("long").alias("false_before"), (F.lit(before) - c("saved")).cast("long").alias("false_after"), "members_lost", "traffic_lost")


def _hot_sql(u: str, bits: int = 5, k: int = 3) -> str:
    lost = "(SELECT key, weight, min(ord) AS hit_at FROM (SELECT key, weight, unnest(positions) AS pos FROM {}) x JOIN c USING (pos) GROUP BY key, weight)"
    return with_sql(
        f"u AS ({u})", f"sp AS (SELECT greatest(1, {bits} * count(*)) AS m FROM u WHERE is_member)", f"h AS (SELECT key, weight, is_member, {sql_positions('key', k, 'sp.m')} AS positions FROM u, sp)",
        "a AS (SELECT key, weight, positions FROM h WHERE is_member)", "v AS (SELECT DISTINCT unnest(positions) AS pos FROM a)",
        "ok AS (SELECT key FROM (SELECT key, unnest(positions) AS pos FROM h WHERE NOT is_member) x LEFT JOIN v USING (pos) GROUP BY key HAVING bool_and(v.pos IS NOT NULL))",
        "fp AS (SELECT key, weight, positions FROM h JOIN ok USING (key))", "b AS (SELECT key, positions, row_number() OVER (ORDER BY weight DESC, key) AS ord FROM fp)",
        choice_sql("ratio", k, weight="weight"), VISIT_SQL, f"lf AS {lost.format('fp')}", f"la AS {lost.format('a')}",
        f"st AS (SELECT beta, least(n, greatest(1, CAST(floor(beta * n + 0.5) AS BIGINT))) AS b FROM (SELECT unnest([{', '.join(f'CAST({x} AS DOUBLE)' for x in _HOT_BETAS)}]) AS beta), (SELECT count(*) AS n FROM fp))",
        select="SELECT beta, b, (SELECT count(*) FROM lf WHERE hit_at <= b) AS removed, (SELECT CAST(coalesce(sum(weight), 0) AS BIGINT) FROM fp) AS false_before, (SELECT CAST(coalesce(sum(weight), 0) AS BIGINT) FROM fp) - (SELECT CAST(coalesce(sum(weight), 0) AS BIGINT) FROM lf WHERE hit_at <= b) AS false_after, (SELECT count(*) FROM la WHERE hit_at <= b) AS members_lost, (SELECT CAST(coalesce(sum(weight), 0) AS BIGINT) FROM la WHERE hit_at <= b) AS traffic_lost FROM st",
    )


def text_key_of(x):
    """A string as a key of 60 bits."""
    return F.conv(F.substring(F.md5(x.cast("binary")), 1, 15), 16, 10).cast("long")


_TEXT_KEY_SQL = "CAST('0x' || substr(md5({}), 1, 15) AS BIGINT)"


@query("w_hot_urls", _hot_sql(f"SELECT {_TEXT_KEY_SQL.format('url')} AS key, CAST(sum(length(html)) AS BIGINT) AS weight, bool_or(page_id % 4 = 0) AS is_member FROM pages GROUP BY url"))
def w_hot_urls(spark, sf_dir):
    """Seen addresses as members; a false positive costs the page that is skipped, so its size is its traffic."""
    p = table(spark, sf_dir, "pages", ["page_id", "url", "html"])
    return hot_traffic(p.groupBy("url").agg(F.sum(F.length("html")).alias("weight"), F.bool_or(c("page_id") % 4 == 0).alias("is_member")).select(text_key_of(c("url")).alias("key"), "weight", "is_member"))


@query("w_hot_users", _hot_sql("SELECT user_id AS key, count(*) AS weight, user_id % 5 = 0 AS is_member FROM events WHERE user_id IS NOT NULL GROUP BY user_id", 3))
def w_hot_users(spark, sf_dir):
    """Allowed users as members, their events as traffic."""
    e = table(spark, sf_dir, "events", ["user_id"]).where("user_id is not null")
    return hot_traffic(e.groupBy(c("user_id").alias("key")).agg(F.count("*").alias("weight")).withColumn("is_member", c("key") % 5 == 0), 3)


_WORDS_SQL = "SELECT w, count(*) AS weight FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents) GROUP BY w"


@query("w_blocked_words", _hot_sql(f"SELECT {_TEXT_KEY_SQL.format('w')} AS key, weight, substr(md5(w), 32, 1) = '0' AS is_member FROM ({_WORDS_SQL})"))
def w_blocked_words(spark, sf_dir):
    """A list of blocked words (those whose digest ends in 0) against all words of the documents, by their uses."""
    text = table(spark, sf_dir, "documents", ["text"])
    words = text.select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("w")).groupBy("w").agg(F.count("*").alias("weight"))
    return hot_traffic(words.select(text_key_of(c("w")).alias("key"), "weight", (F.substring(F.md5(c("w").cast("binary")), 32, 1) == "0").alias("is_member")))


@query("w_url_seen", f"WITH sp AS (SELECT 8 * count(*) AS m FROM pages WHERE page_id % 2 = 0), h AS (SELECT page_id, url, {sql_positions('url', 3, 'm', 'md5')} AS positions FROM pages, sp), v AS (SELECT list(DISTINCT p) AS ps FROM (SELECT unnest(positions) AS p FROM h WHERE page_id % 2 = 0)) SELECT page_id, list_has_all(ps, positions) AS seen FROM h, v")
def w_url_seen(spark, sf_dir):
    p = table(spark, sf_dir, "pages", ["page_id", "url"])
    a = p.where("page_id % 2 = 0").select(c("url").alias("key"))
    spec = FilterSpec(8 * a.count(), 3, "md5")
    return filters.probe_join(p.withColumnRenamed("url", "key"), filters.build_positions(a, spec), spec).select("page_id", c("maybe").alias("seen"))


@query("w_event_allowlist", f"WITH us AS (SELECT DISTINCT user_id AS key FROM events), sp AS (SELECT 6 * count(*) AS m FROM us WHERE key % 5 = 0), h AS (SELECT key, {sql_positions('key', 3, 'm')} AS positions FROM us, sp), v AS (SELECT list(DISTINCT p) AS ps FROM (SELECT unnest(positions) AS p FROM h WHERE key % 5 = 0)) SELECT event_type, count(*) AS events, count(*) FILTER (list_has_all(ps, positions)) AS let_through, count(*) FILTER (key % 5 = 0) AS allowed FROM events JOIN h ON key = user_id, v GROUP BY event_type")
def w_event_allowlist(spark, sf_dir):
    e = table(spark, sf_dir, "events", ["user_id", "event_type"]).withColumnRenamed("user_id", "key")
    a = e.where("key % 5 = 0").select("key").distinct()
    spec = FilterSpec(6 * a.count(), 3)
    hit = filters.probe(e, filters.build_positions(a, spec), spec)
    return hit.groupBy("event_type").agg(F.count("*").alias("events"), F.count_if(c("maybe")).alias("let_through"), F.count_if(c("key") % 5 == 0).alias("allowed"))
