"""Registry, the shared fixtures as DataFrames, and the same fixtures as SQL."""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import FilterSpec, hashed, sql_positions
from ..operators import clearing
from ..sources.tables import table, written

QUERIES: dict = {}
ORACLE_SQL: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        if name in QUERIES:
            raise ValueError(f"{name} is registered twice")
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


def universe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order keys; urgent orders are the members."""
    o = table(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority"])
    return o.select(F.col("o_orderkey").alias("key"), (F.col("o_orderpriority") == "1-URGENT").alias("is_member"))


@dataclass
class Setting:
    """Universe, members and false positives (with positions) of one filter."""

    u: DataFrame
    members: DataFrame
    fp: DataFrame
    spec: FilterSpec
    n: int
    n_universe: int
    n_fp: int


def setting(spark: SparkSession, sf_dir: str, bits: float = 5, k: int = 3, family: str = "linear", blocks: int = 1) -> Setting:
    """The order-key universe under m = bits * n; members and false positives are written once and reused."""
    u = universe(spark, sf_dir)
    n_universe, n = u.agg(F.count("*"), F.count_if("is_member")).first()
    spec = FilterSpec(int(bits * n), k, family, blocks=blocks)
    members = hashed(u.where("is_member").select("key"), spec)
    fp = written(clearing.false_positives(u, members, spec), "fp")
    return Setting(u, members, fp, spec, n, n_universe, fp.count())


def run(s: Setting, rule: str, beta: float = 0.1, live: bool = False, scope: str = "all", engine: str = "auto", order=None, seed: int = 0, weight=None):
    """Troublesome keys and the cleared log (written, since measures read it several times)."""
    b = clearing.troublesome(s.fp, beta, order, s.n_fp)
    done = clearing.clear(s.members, s.fp, b, s.spec, rule, live, scope, engine, seed, weight)
    done.log = written(done.log, "log")
    return b, done


# --- SQL of the same fixtures -----------------------------------------------------------------------------------

U_SQL = "u AS (SELECT o_orderkey AS key, o_orderpriority = '1-URGENT' AS is_member FROM orders)"


def setting_sql(bits: float = 5, k: int = 3, family: str = "linear", blocks: int = 1) -> str:
    """CTEs u, sp(m, n), h(key, is_member, positions), v(pos), a, fp."""
    pos = sql_positions("key", k, "sp.m", family, blocks)
    return f"""{U_SQL},
sp AS (SELECT CAST(floor({bits} * count(*)) AS BIGINT) AS m, count(*) AS n FROM u WHERE is_member),
h AS (SELECT key, is_member, {pos} AS positions FROM u, sp),
a AS (SELECT key, positions FROM h WHERE is_member),
v AS (SELECT DISTINCT unnest(positions) AS pos FROM a),
pr AS (SELECT key, is_member, bool_and(hit) AS maybe FROM (SELECT x.key, x.is_member, v.pos IS NOT NULL AS hit
  FROM (SELECT key, is_member, unnest(positions) AS pos FROM h) x LEFT JOIN v ON x.pos = v.pos) GROUP BY key, is_member),
fp AS (SELECT h.key, h.positions FROM h JOIN pr ON h.key = pr.key WHERE pr.maybe AND NOT pr.is_member)"""


def b_sql(beta: float = 0.1, prefix: str = "") -> str:
    """CTE b(key, positions, ord)."""
    text = f"'{prefix}' || CAST(key AS VARCHAR)" if prefix else "CAST(key AS VARCHAR)"
    return f"""bo AS (SELECT key, positions, row_number() OVER (ORDER BY md5({text}), key) AS ord FROM fp),
b AS (SELECT * FROM bo WHERE ord <= (SELECT least(count(*), greatest(1, CAST(floor({beta} * count(*) + 0.5) AS BIGINT))) FROM fp))"""


def choice_sql(rule: str, k: int = 3, scope: str = "all", seed: int = 0, weight: str = "") -> str:
    """CTE ch(key, ord, positions, pos, j): frozen choices."""
    if rule == "random":
        return f"""ch AS (SELECT key, ord, positions, positions[j + 1] AS pos, j FROM (SELECT *,
  CAST(CAST('0x' || substr(md5('{seed}:' || CAST(key AS VARCHAR)), 1, 15) AS BIGINT) % {k} AS INTEGER) AS j FROM b))"""
    src = "fp" if scope == "all" else "b"
    summed = weight or "1"
    score = {"min_fn": "coalesce(ca.c, 0)", "max_fp": "-cb.c", "ratio": "CAST(coalesce(ca.c, 0) AS DOUBLE) / cb.c"}[rule]
    return f"""ca AS (SELECT pos, count(*) AS c FROM (SELECT unnest(positions) AS pos FROM a) GROUP BY pos),
cb AS (SELECT pos, CAST(sum(w) AS BIGINT) AS c FROM (SELECT unnest(positions) AS pos, {summed} AS w FROM {src}) GROUP BY pos),
be AS (SELECT key, ord, positions, unnest(positions) AS pos, unnest(range(0, {k})) AS j FROM b),
sc AS (SELECT be.*, {score} AS score FROM be LEFT JOIN ca ON be.pos = ca.pos LEFT JOIN cb ON be.pos = cb.pos),
ch AS (SELECT key, ord, positions, pos, CAST(j AS INTEGER) AS j FROM (SELECT *, row_number() OVER (PARTITION BY key ORDER BY score, j) AS rn FROM sc WHERE score IS NOT NULL) WHERE rn = 1)"""


VISIT_SQL = """vis AS (SELECT 0::BIGINT AS step, []::BIGINT[] AS cleared, []::BIGINT[] AS acting
  UNION ALL SELECT vis.step + 1, CASE WHEN list_has_any(vis.cleared, ch.positions) THEN vis.cleared ELSE list_append(vis.cleared, ch.pos) END,
  CASE WHEN list_has_any(vis.cleared, ch.positions) THEN vis.acting ELSE list_append(vis.acting, ch.ord) END
  FROM vis JOIN ch ON ch.ord = vis.step + 1),
fin AS (SELECT cleared, acting FROM vis ORDER BY step DESC LIMIT 1),
c AS (SELECT unnest(cleared) AS pos, unnest(acting) AS ord FROM fin),
gp AS (SELECT fp.key FROM fp, fin WHERE list_has_any(fp.positions, fin.cleared)),
gn AS (SELECT a.key FROM a, fin WHERE list_has_any(a.positions, fin.cleared))"""


def live_sql(rule: str, k: int = 3, scope: str = "all") -> str:
    """CTEs as ``VISIT_SQL`` with counters that follow the resets."""
    src = "fp" if scope == "all" else "b"
    score = {"min_fn": "coalesce(xa.c, 0)", "max_fp": "-coalesce(xb.c, 0)", "ratio": "CAST(coalesce(xa.c, 0) AS DOUBLE) / nullif(xb.c, 0)"}[rule]
    alive = lambda t: f"(SELECT count(*) FROM {t} WHERE p = q.pos AND NOT list_has_any(positions, s.cleared))"
    best = score.replace("coalesce(xa.c, 0)", alive("near_a")).replace("coalesce(xb.c, 0)", alive("near_b")).replace("nullif(xb.c, 0)", f"nullif({alive('near_b')}, 0)")
    return f"""pb AS (SELECT list(DISTINCT p) AS ps FROM (SELECT unnest(positions) AS p FROM b)),
near_a AS (SELECT p, positions FROM (SELECT unnest(positions) AS p, positions FROM a), pb WHERE list_contains(ps, p)),
near_b AS (SELECT p, positions FROM (SELECT unnest(positions) AS p, positions FROM {src}), pb WHERE list_contains(ps, p)),
vis AS (SELECT 0::BIGINT AS step, []::BIGINT[] AS cleared, []::BIGINT[] AS acting
  UNION ALL SELECT s.step + 1, CASE WHEN list_has_any(s.cleared, b.positions) THEN s.cleared ELSE list_append(s.cleared,
    (SELECT arg_min(pos, (score, j)) FROM (SELECT q.pos, q.j, {best} AS score FROM (SELECT unnest(b.positions) AS pos, unnest(range(0, {k})) AS j) q) WHERE score IS NOT NULL)) END,
  CASE WHEN list_has_any(s.cleared, b.positions) THEN s.acting ELSE list_append(s.acting, b.ord) END
  FROM vis s JOIN b ON b.ord = s.step + 1),
{VISIT_SQL[VISIT_SQL.index("fin AS"):]}"""


def row_sql(algorithm: str, counters: str = "frozen", scope: str = "all", beta: float = 0.1, k: int = 3, run_: int = 0) -> str:
    """SELECT of one results-table row over the CTEs above."""
    return f"""SELECT '{algorithm}' AS algorithm, '{counters}' AS counters, '{scope}' AS fp_scope, CAST({beta} AS DOUBLE) AS beta, {run_} AS run, n, universe, m, {k} AS k,
 fp, b, b_extra, removed, fn, s, round(removed / fp, 6) AS dfp, round(fn / n, 6) AS dfn, round((removed / fp) / nullif(fn / n, 0), 6) AS chi FROM (
SELECT (SELECT n FROM sp) AS n, (SELECT count(*) FROM u) AS universe, (SELECT m FROM sp) AS m, (SELECT count(*) FROM fp) AS fp, (SELECT count(*) FROM b) AS b,
 (SELECT count(*) FROM gp WHERE key NOT IN (SELECT key FROM b)) AS b_extra, (SELECT count(*) FROM gp) AS removed, (SELECT count(*) FROM gn) AS fn, (SELECT count(*) FROM c) AS s)"""


def with_sql(*parts: str, select: str, recursive: bool = True) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}" + ",\n".join(parts) + "\n" + select


@lru_cache
def frozen_sql(rule: str, beta: float = 0.1, scope: str = "all", select: str = "", bits: float = 5, k: int = 3, prefix: str = "", seed: int = 0) -> str:
    return with_sql(setting_sql(bits, k), b_sql(beta, prefix), choice_sql(rule, k, scope, seed), VISIT_SQL, select=select or row_sql(rule, "frozen", scope, beta, k))
