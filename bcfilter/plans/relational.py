"""Scans, sources, predicates, joins, aggregations, windows, sets and functions on filter data."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import FilterSpec, hashed, positions, sql_positions
from ..operators import clearing, filters, measures, relops
from ..sources import io
from ..sources.tables import NAMES, new_path, table, written
from .base import U_SQL, VISIT_SQL, b_sql, choice_sql, query, run, setting, setting_sql, universe, with_sql

c = F.col
_KEYS = {
    "region": "r_regionkey, r_name", "nation": "n_nationkey, n_regionkey", "customer": "c_custkey, c_nationkey", "supplier": "s_suppkey, s_nationkey", "part": "p_partkey, p_size", "orders": "o_orderkey, o_orderpriority",
    "lineitem": "l_orderkey, l_partkey, l_suppkey, l_linenumber", "events": "event_id, user_id, event_type", "documents": "doc_id, lang, source, n_chars", "embeddings": "vec_id, label", "pages": "page_id, url", "benchmark": "item_id, text", "labels": "doc_id, quality, toxic", "conversations": "conv_id, turn, role",
}

for _t in NAMES:
    query(f"scan_{_t}", f"SELECT {_KEYS[_t]} FROM {_t}")(lambda spark, sf_dir, t=_t: table(spark, sf_dir, t, _KEYS[t].split(", ")))


def _roundtrip(fmt: str):
    def f(spark, sf_dir):
        df = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderpriority"])
        path = new_path(spark, fmt)
        io.write(df, fmt, path)
        return io.read(spark, fmt, path, "o_orderkey long, o_custkey long, o_orderpriority string")

    return f


for _f in ("csv", "json", "orc"):
    query(f"src_{_f}_roundtrip", "SELECT o_orderkey, o_custkey, o_orderpriority FROM orders")(_roundtrip(_f))


@query("sink_parquet_partitioned", "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderpriority = '1-URGENT'")
def sink_parquet_partitioned(spark, sf_dir):
    path = new_path(spark, "sink")
    io.write(table(spark, sf_dir, "orders", ["o_orderkey", "o_orderpriority"]), "parquet", path, partition_by=["o_orderpriority"])
    return spark.read.parquet(path).where("o_orderpriority = '1-URGENT'").select("o_orderkey", "o_orderpriority")


@query("src_filter_datasource")
def src_filter_datasource(spark, sf_dir):
    spark.dataSource.register(io.FilterKeys)
    return spark.read.format("filter_keys").option("n", 1000).option("m", 5000).option("k", 3).load()


def _setup(spark, sf_dir):
    s = setting(spark, sf_dir)
    return s, written(filters.build_positions(s.members.select("key"), s.spec), "pos")


_IN = with_sql(setting_sql(), select="SELECT key FROM pr WHERE maybe", recursive=False)


@query("sql_contains", _IN)
def sql_contains(spark, sf_dir):
    """SQL functions over a registered filter."""
    s, pos = _setup(spark, sf_dir)
    io.register_sql(spark, "bcf", pos, s.spec)
    s.u.createOrReplaceTempView("bcf_universe")
    return spark.sql("SELECT key FROM bcf_universe WHERE bcf_contains(bcf_positions(key))")


@query("proj_keys", "SELECT o_orderkey * 10 + 1 AS k2, {'a': o_custkey, 'b': o_orderstatus}.b AS st, CAST(floor(o_totalprice) AS BIGINT) AS price FROM orders")
def proj_keys(spark, sf_dir):
    o = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice"])
    return o.select((c("o_orderkey") * 10 + 1).alias("k2"), F.struct(c("o_custkey").alias("a"), c("o_orderstatus").alias("b"))["b"].alias("st"), F.floor("o_totalprice").cast("long").alias("price"))


@query("pred_maybe_in", _IN)
def pred_maybe_in(spark, sf_dir):
    s, pos = _setup(spark, sf_dir)
    return s.u.where(filters.maybe_in(s.u, pos, s.spec)).select("key")


@query("pred_not_in", _IN.replace("WHERE maybe", "WHERE NOT maybe"))
def pred_not_in(spark, sf_dir):
    s, pos = _setup(spark, sf_dir)
    return s.u.where(~filters.maybe_in(s.u, pos, s.spec)).select("key")


_O = ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"]


def _orders(name: str, cond: str, sql: str | None = None):
    query(name, f"SELECT o_orderkey FROM orders WHERE {sql or cond}")(lambda spark, sf_dir: table(spark, sf_dir, "orders", _O).where(cond).select("o_orderkey"))


_orders("pred_range", "o_orderdate BETWEEN timestamp '1996-01-01' AND timestamp '1996-12-31' AND o_totalprice < 100000")
_orders("pred_in", "o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_custkey IN (1, 2, 3, 5, 8)")
_orders("pred_like", "o_orderpriority LIKE '%URG%' OR o_orderpriority RLIKE '^[45]-'", "o_orderpriority LIKE '%URG%' OR regexp_matches(o_orderpriority, '^[45]-')")
_orders("pred_nullsafe", "nullif(o_orderstatus, 'F') <=> NULL", "nullif(o_orderstatus, 'F') IS NOT DISTINCT FROM NULL")


@query("pred_case", "SELECT CASE WHEN o_totalprice < 50000 THEN 'low' WHEN o_totalprice < 200000 THEN 'mid' ELSE 'high' END AS band, count(*) AS n FROM orders GROUP BY 1")
def pred_case(spark, sf_dir):
    p = c("o_totalprice")
    return table(spark, sf_dir, "orders", ["o_totalprice"]).groupBy(F.when(p < 50000, "low").when(p < 200000, "mid").otherwise("high").alias("band")).agg(F.count("*").alias("n"))


_HIT = with_sql(setting_sql(), "hit AS (SELECT key FROM pr WHERE maybe)", select="SELECT l_orderkey, count(*) AS n FROM lineitem JOIN hit ON key = l_orderkey WHERE l_quantity > 40 GROUP BY 1", recursive=False)


@query("pred_prefilter", _HIT)
def pred_prefilter(spark, sf_dir):
    s, pos = _setup(spark, sf_dir)
    li = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_quantity"])
    return relops.prefilter(li, c("l_quantity") > 40, pos, s.spec, "l_orderkey").groupBy("l_orderkey").agg(F.count("*").alias("n"))


@query("sample_hash", f"WITH {U_SQL} SELECT key FROM u WHERE CAST('0x' || substr(md5(CAST(key AS VARCHAR)), 1, 8) AS BIGINT) % 100 < 10")
def sample_hash(spark, sf_dir):
    h = F.conv(F.substring(F.md5(c("key").cast("string").cast("binary")), 1, 8), 16, 10).cast("long")
    return universe(spark, sf_dir).where(F.pmod(h, F.lit(100)) < 10).select("key")


# --- joins ------------------------------------------------------------------------------------------------------

_INNER = "SELECT l_orderkey, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM lineitem JOIN orders ON o_orderkey = l_orderkey WHERE o_orderpriority = '1-URGENT' GROUP BY 1"


def _inner(hint: str):
    def f(spark, sf_dir):
        o = table(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice", "o_orderpriority"]).where("o_orderpriority = '1-URGENT'")
        j = table(spark, sf_dir, "lineitem", ["l_orderkey"]).join(o.hint(hint), c("o_orderkey") == c("l_orderkey"))
        return j.groupBy("l_orderkey").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))

    return f


for _h, _n in (("broadcast", "broadcast"), ("merge", "merge"), ("shuffle_hash", "shuffle_hash")):
    query(f"join_inner_{_n}", _INNER)(_inner(_h))


@query("join_left", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1")
def join_left(spark, sf_dir):
    j = table(spark, sf_dir, "customer", ["c_custkey"]).join(table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), c("c_custkey") == c("o_custkey"), "left")
    return j.groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


_CA = "SELECT pos, count(*) AS cnt FROM (SELECT unnest(positions) AS pos FROM {}) GROUP BY pos"


@query("join_full", with_sql(setting_sql(), f"x AS ({_CA.format('a')}), y AS ({_CA.format('fp')})", select="SELECT coalesce(x.pos, y.pos) AS pos, x.cnt AS a, y.cnt AS b FROM x FULL JOIN y ON x.pos = y.pos", recursive=False))
def join_full(spark, sf_dir):
    s = setting(spark, sf_dir)
    return clearing.counters(s.members, name="a").join(clearing.counters(s.fp, name="b"), "pos", "full").select("pos", "a", "b")


@query("join_semi", "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity = 50)")
def join_semi(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", ["l_partkey", "l_quantity"]).where("l_quantity = 50")
    return table(spark, sf_dir, "part", ["p_partkey"]).join(li, c("p_partkey") == c("l_partkey"), "left_semi")


@query("join_anti", "SELECT p_partkey FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity = 50)")
def join_anti(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", ["l_partkey", "l_quantity"]).where("l_quantity = 50")
    return table(spark, sf_dir, "part", ["p_partkey"]).join(li, c("p_partkey") == c("l_partkey"), "left_anti")


@query("join_cross", "SELECT beta, r AS run, n_nationkey AS monitor FROM (SELECT unnest([0.01::DOUBLE, 0.1, 1.0]) AS beta), (SELECT unnest(range(0, 3)) AS r), nation WHERE n_nationkey < 10")
def join_cross(spark, sf_dir):
    """Small grids only: betas, runs and monitors."""
    betas = spark.createDataFrame([(0.01,), (0.1,), (1.0,)], "beta double")
    return betas.crossJoin(spark.range(3).withColumnRenamed("id", "run")).crossJoin(table(spark, sf_dir, "nation", ["n_nationkey"]).where("n_nationkey < 10")).withColumnRenamed("n_nationkey", "monitor")


_BANDS = [(1, 3, "few"), (4, 6, "some"), (7, 1000000, "many")]


@query("join_range", "WITH d AS (SELECT l_orderkey, count(*) AS n FROM lineitem GROUP BY 1), b AS (SELECT * FROM (VALUES (1, 3, 'few'), (4, 6, 'some'), (7, 1000000, 'many')) t(lo, hi, band)) SELECT band, count(*) AS keys FROM d JOIN b ON n BETWEEN lo AND hi GROUP BY band")
def join_range(spark, sf_dir):
    d = table(spark, sf_dir, "lineitem", ["l_orderkey"]).groupBy("l_orderkey").agg(F.count("*").alias("n"))
    b = F.broadcast(spark.createDataFrame(_BANDS, "lo int, hi int, band string"))
    return d.join(b, c("n").between(c("lo"), c("hi"))).groupBy("band").agg(F.count("*").alias("keys"))


@query("join_asof", "SELECT c_custkey, cut, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS o_orderkey FROM (SELECT c_custkey, TIMESTAMP '1998-01-01' AS cut FROM customer) LEFT JOIN orders ON o_custkey = c_custkey AND o_orderdate <= cut GROUP BY 1, 2")
def join_asof(spark, sf_dir):
    left = table(spark, sf_dir, "customer", ["c_custkey"]).withColumn("cut", F.lit("1998-01-01").cast("timestamp"))
    right = table(spark, sf_dir, "orders", ["o_custkey", "o_orderdate", "o_orderkey"]).withColumnRenamed("o_custkey", "c_custkey")
    return relops.join_asof(left, right, "c_custkey", "cut", "o_orderdate", "o_orderkey")


_IV = "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 1800000000 WHERE a.event_type = 'click' AND b.event_type = 'purchase'"


@query("join_interval", _IV)
def join_interval(spark, sf_dir):
    e = table(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type"])
    a = e.where("event_type = 'click'").select(c("event_id").alias("a"), "user_id", c("ts").alias("ta"))
    b = e.where("event_type = 'purchase'").select(c("event_id").alias("b"), "user_id", c("ts").alias("tb"))
    return relops.join_interval(a, b, "user_id", "ta", "tb", 1800).select("a", "b")


def _assisted(exact: bool):
    def f(spark, sf_dir):
        s, pos = _setup(spark, sf_dir)
        _, done = run(s, "ratio")
        left = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber"]).withColumnRenamed("l_orderkey", "key")
        rescue = relops.rescue_keys(s.members, done.cleared) if exact else None
        j = relops.join_prefiltered(left, s.members.select("key"), "key", s.spec, written(clearing.reset_bits(pos, done.cleared), "pos"), rescue)
        return j.groupBy("key").agg(F.count("*").alias("n"))

    return f


query("join_prefilter_exact", f"WITH {U_SQL} SELECT key, count(*) AS n FROM lineitem JOIN u ON key = l_orderkey WHERE is_member GROUP BY 1")(_assisted(True))
query("join_prefilter_lossy", with_sql(setting_sql(), b_sql(), choice_sql("ratio"), VISIT_SQL, select="SELECT a.key, count(*) AS n FROM lineitem JOIN a ON a.key = l_orderkey WHERE a.key NOT IN (SELECT key FROM gn) GROUP BY 1"))(_assisted(False))


@query("join_salted", "SELECT user_id, count(*) AS n FROM events JOIN (SELECT DISTINCT user_id FROM events WHERE user_id % 5 = 0) USING (user_id) GROUP BY 1")
def join_salted(spark, sf_dir):
    e = table(spark, sf_dir, "events", ["event_id", "user_id"])
    return relops.join_salted(e, e.where("user_id % 5 = 0").select("user_id").distinct(), "user_id").groupBy("user_id").agg(F.count("*").alias("n"))


@query("join_lateral", f"WITH {U_SQL} SELECT key, unnest({sql_positions('key', 3, '15000')}) AS pos FROM u")
def join_lateral(spark, sf_dir):
    hashed(universe(spark, sf_dir), FilterSpec(15000, 3)).createOrReplaceTempView("bcf_lateral")
    return spark.sql("SELECT key, pos FROM bcf_lateral LATERAL VIEW explode(positions) t AS pos")


# --- aggregations -----------------------------------------------------------------------------------------------


@query("agg_basic", "SELECT l_returnflag, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS q, round(avg(l_discount), 6) AS d, min(l_shipdate) AS lo, max(l_shipdate) AS hi, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY 1")
def agg_basic(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", ["l_returnflag", "l_quantity", "l_discount", "l_shipdate"])
    return li.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("q"), F.round(F.avg("l_discount"), 6).alias("d"), F.min("l_shipdate").alias("lo"), F.max("l_shipdate").alias("hi"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"))


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", ["l_returnflag", "l_partkey", "l_suppkey"]).groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps"))


@query("agg_approx_distinct")
def agg_approx_distinct(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", ["l_returnflag", "l_partkey"]).groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


def _sets(name: str, f, sql: str):
    query(name, f"SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY {sql}")(f)


_two = ["o_orderstatus", "o_orderpriority"]
_sets("agg_cube", lambda spark, sf_dir: table(spark, sf_dir, "orders", _two).cube(*_two).agg(F.count("*").alias("n")), "CUBE (o_orderstatus, o_orderpriority)")
_sets("agg_rollup", lambda spark, sf_dir: table(spark, sf_dir, "orders", _two).rollup(*_two).agg(F.count("*").alias("n")), "ROLLUP (o_orderstatus, o_orderpriority)")
_sets("agg_grouping_sets", lambda spark, sf_dir: table(spark, sf_dir, "orders", _two).groupingSets([["o_orderstatus"], ["o_orderpriority"]], *_two).agg(F.count("*").alias("n")), "GROUPING SETS ((o_orderstatus), (o_orderpriority))")


@query("agg_pivot", "SELECT o_orderstatus, " + ", ".join(f"nullif(count(*) FILTER (o_orderpriority = '{p}'), 0) AS \"{p}\"" for p in ("1-URGENT", "2-HIGH")) + " FROM orders GROUP BY 1")
def agg_pivot(spark, sf_dir):
    return table(spark, sf_dir, "orders", _two).groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "2-HIGH"]).count()


@query("agg_unpivot", "SELECT l_orderkey, l_linenumber, unnest(['part', 'supp']) AS what, unnest([l_partkey, l_suppkey]) AS k FROM lineitem")
def agg_unpivot(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"])
    return li.select("l_orderkey", "l_linenumber", c("l_partkey").alias("part"), c("l_suppkey").alias("supp")).unpivot(["l_orderkey", "l_linenumber"], ["part", "supp"], "what", "k")


@query("agg_argmin", "SELECT l_orderkey, arg_min(l_partkey, (l_extendedprice, l_linenumber, l_partkey)) AS part FROM lineitem GROUP BY 1")
def agg_argmin(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_extendedprice", "l_linenumber"]).groupBy("l_orderkey").agg(F.min_by("l_partkey", F.struct("l_extendedprice", "l_linenumber", "l_partkey")).alias("part"))


@query("agg_lists", with_sql(setting_sql(), select="SELECT pos, array_to_string(list_sort(list(key)), ',') AS keys FROM (SELECT unnest(positions) AS pos, key FROM fp) GROUP BY pos", recursive=False))
def agg_lists(spark, sf_dir):
    return clearing.element_lists(setting(spark, sf_dir).fp).groupBy("pos").agg(F.array_join(F.array_sort(F.collect_list("key")), ",").alias("keys"))


_DEG = "SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1"


def _deg(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", ["l_partkey"]).groupBy("l_partkey").agg(F.count("*").alias("n"))


@query("agg_percentile", f"SELECT quantile_cont(n, 0.5) AS p50, quantile_cont(n, 0.99) AS p99, CAST(median(n) AS DOUBLE) AS med, round(skewness_pop(n), 6) AS skew FROM ({_DEG.replace('SELECT', 'SELECT', 1)})".replace("skewness_pop(n)", "(avg(n * n * n) - 3 * avg(n) * avg(n * n) + 2 * power(avg(n), 3)) / power(stddev_pop(n), 3)"))
def agg_percentile(spark, sf_dir):
    return _deg(spark, sf_dir).agg(F.expr("percentile(n, 0.5)").alias("p50"), F.expr("percentile(n, 0.99)").alias("p99"), F.median("n").alias("med"), F.round(F.skewness("n"), 6).alias("skew"))


@query("agg_histogram", f"SELECT CAST(floor(n / 10.0) AS BIGINT) AS bucket, count(*) AS keys FROM ({_DEG}) GROUP BY 1")
def agg_histogram(spark, sf_dir):
    return _deg(spark, sf_dir).groupBy(F.floor(c("n") / 10).alias("bucket")).agg(F.count("*").alias("keys"))


@query("agg_filter", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, CAST(sum(o_custkey) FILTER (o_orderstatus = 'O') AS BIGINT) AS o FROM orders GROUP BY 1")
def agg_filter(spark, sf_dir):
    table(spark, sf_dir, "orders", ["o_orderpriority", "o_orderstatus", "o_custkey"]).createOrReplaceTempView("bcf_orders")
    return spark.sql("SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, sum(o_custkey) FILTER (WHERE o_orderstatus = 'O') AS o FROM bcf_orders GROUP BY 1")


@query("agg_bool", "SELECT l_orderkey, bool_and(l_quantity > 5) AS every_, bool_or(l_quantity > 45) AS some_, count_if(l_discount > 0.05) AS n FROM lineitem GROUP BY 1")
def agg_bool(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_quantity", "l_discount"])
    return li.groupBy("l_orderkey").agg(F.bool_and(c("l_quantity") > 5).alias("every_"), F.bool_or(c("l_quantity") > 45).alias("some_"), F.count_if(c("l_discount") > 0.05).alias("n"))


@query("agg_bitmap", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def agg_bitmap(spark, sf_dir):
    """Distinct counts by mergeable bitmaps: per bucket and flag, then added up."""
    li = table(spark, sf_dir, "lineitem", ["l_returnflag", "l_partkey"]).withColumn("p", c("l_partkey") + 1)
    per = li.groupBy("l_returnflag", F.bitmap_bucket_number("p").alias("bucket")).agg(F.bitmap_count(F.bitmap_construct_agg(F.bitmap_bit_position("p"))).alias("n"))
    return per.groupBy("l_returnflag").agg(F.sum("n").alias("parts"))


@query("agg_count_min")
def agg_count_min(spark, sf_dir):
    """Heavy hitters' sketch of degrees: its size."""
    li = table(spark, sf_dir, "lineitem", ["l_partkey"])
    return li.agg(F.octet_length(F.count_min_sketch("l_partkey", F.lit(0.001), F.lit(0.99), F.lit(7))).alias("bytes"))


# --- windows, sorts, sets ---------------------------------------------------------------------------------------

_W = "OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)"
_w = lambda: Window.partitionBy("o_custkey").orderBy(c("o_totalprice").desc(), "o_orderkey")


def _windows(name: str, cols, sql: str):
    query(name, f"SELECT o_orderkey, {sql} FROM orders")(lambda spark, sf_dir: table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_totalprice", "o_orderdate"]).select("o_orderkey", *cols()))


_windows(
    "win_ranking",
    lambda: [F.row_number().over(_w()).alias("rn"), F.rank().over(_w()).alias("rk"), F.dense_rank().over(_w()).alias("dr"), F.round(F.percent_rank().over(_w()), 6).alias("pr"), F.ntile(4).over(_w()).alias("nt"), F.round(F.cume_dist().over(_w()), 6).alias("cd")],
    f"row_number() {_W} AS rn, rank() {_W} AS rk, dense_rank() {_W} AS dr, round(percent_rank() {_W}, 6) AS pr, ntile(4) {_W} AS nt, round(cume_dist() {_W}, 6) AS cd",
)
_windows("win_lag_lead", lambda: [F.lag("o_orderkey").over(_w()).alias("before"), F.lead("o_orderkey").over(_w()).alias("after")], f"lag(o_orderkey) {_W} AS before, lead(o_orderkey) {_W} AS after")
_FULL = _W[:-1] + " ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
_windows(
    "win_first_last",
    lambda: [f.over(_w().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias(n) for n, f in (("top", F.first("o_orderkey")), ("low", F.last("o_orderkey")), ("second", F.nth_value("o_orderkey", 2)))],
    f"first_value(o_orderkey) {_FULL} AS top, last_value(o_orderkey) {_FULL} AS low, nth_value(o_orderkey, 2) {_FULL} AS second",
)
_windows("win_rows", lambda: [F.sum("o_orderkey").over(_w().rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.round(F.avg("o_orderkey").over(_w().rowsBetween(-2, 0)), 4).alias("moving")], f"CAST(sum(o_orderkey) {_W[:-1]} ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running, round(avg(o_orderkey) {_W[:-1]} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving")
_windows(
    "win_range",
    lambda: [F.count("*").over(Window.partitionBy("o_custkey").orderBy(F.unix_date(c("o_orderdate").cast("date"))).rangeBetween(-90, 0)).alias("in_90_days")],
    "count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS in_90_days",
)


@query("win_first_stop", "SELECT user_id, arg_min(event_id, (ts, event_id)) AS first_click FROM events WHERE event_type = 'click' GROUP BY 1")
def win_first_stop(spark, sf_dir):
    e = table(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type"]).where("event_type = 'click'")
    return e.groupBy("user_id").agg(F.min_by("event_id", F.struct("ts", "event_id")).alias("first_click"))


@query("sort_topk", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def sort_topk(spark, sf_dir):
    return table(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).orderBy(c("o_totalprice").desc(), "o_orderkey").limit(20)


@query("sort_topk_group", f"SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() {_W} AS rn FROM orders) WHERE rn <= 2")
def sort_topk_group(spark, sf_dir):
    return table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_totalprice"]).withColumn("rn", F.row_number().over(_w())).where("rn <= 2").select("o_custkey", "o_orderkey")


@query("sort_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
def sort_limit_offset(spark, sf_dir):
    return table(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).orderBy(c("o_totalprice").desc(), "o_orderkey").offset(5).limit(10).select("o_orderkey")


def _setop(name: str, op: str, method: str):
    def f(spark, sf_dir):
        a = table(spark, sf_dir, "orders", ["o_custkey"]).select(c("o_custkey").alias("k"))
        b = table(spark, sf_dir, "customer", ["c_custkey"]).where("c_custkey % 2 = 0").select(c("c_custkey").alias("k"))
        out = getattr(a, method)(b)
        return out.distinct() if op == "UNION" else out

    query(name, f"SELECT o_custkey AS k FROM orders {op} SELECT c_custkey FROM customer WHERE c_custkey % 2 = 0")(f)


for _n, _op, _m in (("set_union", "UNION", "unionByName"), ("set_intersect", "INTERSECT", "intersect"), ("set_except", "EXCEPT", "subtract"), ("set_except_all", "EXCEPT ALL", "exceptAll"), ("set_intersect_all", "INTERSECT ALL", "intersectAll")):
    _setop(_n, _op, _m)


@query("set_distinct", "SELECT DISTINCT o_orderstatus, o_orderpriority FROM orders")
def set_distinct(spark, sf_dir):
    return table(spark, sf_dir, "orders", _two).dropDuplicates()


def _view_sql(name: str, sql: str, duck: str | None = None):
    def f(spark, sf_dir):
        for t in ("orders", "customer", "lineitem"):
            table(spark, sf_dir, t).createOrReplaceTempView(t)
        return spark.sql(sql)

    query(name, duck or sql)(f)


_view_sql("sub_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)")
_view_sql("sub_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
_view_sql("cte_chain", "WITH RECURSIVE r(step, v) AS (SELECT 1, CAST(1 AS BIGINT) UNION ALL SELECT step + 1, v * 3 FROM r WHERE step < 12), o AS (SELECT o_orderkey AS k FROM orders) SELECT step, v, count(k) AS n FROM r LEFT JOIN o ON k % v = 0 GROUP BY step, v")


# --- functions and UDFs -----------------------------------------------------------------------------------------


@query("fn_string", r"SELECT p_partkey, lower(p_name) AS l, substr(p_name, 2, 4) AS s, regexp_replace(p_type, '[A-Z]+', 'x', 'g') AS r, concat_ws('|', p_brand, p_type) AS j, md5(p_name) AS h, levenshtein(p_brand, 'Brand#11') AS d FROM part")
def fn_string(spark, sf_dir):
    p = table(spark, sf_dir, "part", ["p_partkey", "p_name", "p_type", "p_brand"])
    return p.select("p_partkey", F.lower("p_name").alias("l"), F.substring("p_name", 2, 4).alias("s"), F.regexp_replace("p_type", "[A-Z]+", "x").alias("r"), F.concat_ws("|", "p_brand", "p_type").alias("j"), F.md5(c("p_name").cast("binary")).alias("h"), F.levenshtein("p_brand", F.lit("Brand#11")).alias("d"))


@query("fn_ngrams", "SELECT item_id, unnest(list_transform(range(1, greatest(len(w) - 1, 1)), lambda i: array_to_string(w[i:i + 2], ' '))) AS g FROM (SELECT item_id, string_split(lower(text), ' ') AS w FROM benchmark)")
def fn_ngrams(spark, sf_dir):
    w = table(spark, sf_dir, "benchmark").select("item_id", F.split(F.lower("text"), " ").alias("w"))
    return w.where(F.size("w") >= 3).select("item_id", F.explode(F.transform(F.sequence(F.lit(1), F.size("w") - 2), lambda i: F.array_join(F.slice("w", i, 3), " "))).alias("g"))


@query("fn_date", "SELECT o_orderkey, date_trunc('month', o_orderdate) AS m, date_diff('day', CAST(o_orderdate AS DATE), DATE '2001-12-31') AS d, CAST(year(o_orderdate) AS INTEGER) AS y, epoch_us(o_orderdate) AS us FROM orders")
def fn_date(spark, sf_dir):
    o = table(spark, sf_dir, "orders", ["o_orderkey", "o_orderdate"])
    ts = c("o_orderdate").cast("timestamp")
    return o.select("o_orderkey", F.date_trunc("month", "o_orderdate").alias("m"), F.date_diff(F.lit("2001-12-31").cast("date"), c("o_orderdate").cast("date")).alias("d"), F.year("o_orderdate").alias("y"), F.unix_micros(ts).alias("us"))


@query("fn_interval", "SELECT o_orderkey, o_orderdate + to_days(CAST(60 * (o_orderkey % 11) AS INTEGER)) AS cut, o_orderdate + to_months(CAST(o_orderkey % 11 AS INTEGER)) AS month_cut FROM orders")
def fn_interval(spark, sf_dir):
    """Each order's date moved on by 0 to 10 cycles of 60 days, and by as many months."""
    cycle = "cast(o_orderkey % 11 as int)"
    o = table(spark, sf_dir, "orders", ["o_orderkey", "o_orderdate"])
    return o.select("o_orderkey", F.expr(f"o_orderdate + make_interval(0, 0, 0, 60 * {cycle})").cast("timestamp").alias("cut"), F.expr(f"o_orderdate + make_interval(0, {cycle})").cast("timestamp").alias("month_cut"))


@query("fn_math", "SELECT p_partkey, round(ln(p_size), 6) AS l, round(exp(p_size / 50.0), 6) AS e, round(power(p_size, 1.5), 4) AS p, round(sqrt(p_retailprice), 6) AS s, p_partkey % 7 AS m FROM part")
def fn_math(spark, sf_dir):
    p = table(spark, sf_dir, "part", ["p_partkey", "p_size", "p_retailprice"])
    return p.select("p_partkey", F.round(F.ln("p_size"), 6).alias("l"), F.round(F.exp(c("p_size") / 50), 6).alias("e"), F.round(F.pow(c("p_size"), F.lit(1.5)), 4).alias("p"), F.round(F.sqrt("p_retailprice"), 6).alias("s"), F.pmod("p_partkey", F.lit(7)).alias("m"))


@query("fn_bits", "SELECT p_partkey, p_partkey & 255 AS a, p_partkey | 256 AS o, xor(p_partkey, 77::BIGINT) AS x, p_partkey << 3 AS l, p_partkey >> 2 AS r, bit_count(p_partkey) AS n FROM part")
def fn_bits(spark, sf_dir):
    k = c("p_partkey")
    return table(spark, sf_dir, "part", ["p_partkey"]).select(k, k.bitwiseAND(F.lit(255)).alias("a"), k.bitwiseOR(F.lit(256)).alias("o"), k.bitwiseXOR(F.lit(77)).alias("x"), F.shiftleft(k, 3).alias("l"), F.shiftright(k, 2).alias("r"), F.bit_count(k).alias("n"))


_P3 = f"WITH {U_SQL}, h AS (SELECT key, {sql_positions('key', 3, '15000')} AS p FROM u) "
_p3 = lambda spark, sf_dir: hashed(universe(spark, sf_dir), FilterSpec(15000, 3)).select("key", c("positions").alias("p"))


@query("fn_array", _P3 + "SELECT key, list_max(p) AS hi, len(list_distinct(p)) AS d, list_sort(p)[1] AS lo, array_to_string(p[1:2], ',') AS two, list_has_any(p, [CAST(1 AS BIGINT), 2, 3]) AS hit FROM h")
def fn_array(spark, sf_dir):
    return _p3(spark, sf_dir).select("key", F.array_max("p").alias("hi"), F.size(F.array_distinct("p")).alias("d"), F.sort_array("p")[0].alias("lo"), F.array_join(F.slice("p", 1, 2), ",").alias("two"), F.arrays_overlap("p", F.array(*[F.lit(x).cast("long") for x in (1, 2, 3)])).alias("hit"))


@query("fn_higher_order", _P3 + "SELECT key, CAST(list_sum(list_transform(p, lambda x: x % 10)) AS BIGINT) AS s, len(list_filter(p, lambda x: x > 7500)) AS n, len(list_filter(p, lambda x: x > 7500)) > 0 AS some_, len(list_filter(p, lambda x: x > 100)) = 3 AS every_ FROM h")
def fn_higher_order(spark, sf_dir):
    return _p3(spark, sf_dir).select("key", F.aggregate(F.transform("p", lambda x: x % 10), F.lit(0).cast("long"), lambda a, x: a + x).alias("s"), F.size(F.filter("p", lambda x: x > 7500)).alias("n"), F.exists("p", lambda x: x > 7500).alias("some_"), F.forall("p", lambda x: x > 100).alias("every_"))


@query("fn_map", _P3 + "SELECT key, p[2] AS second, 3 AS n FROM h")
def fn_map(spark, sf_dir):
    m = F.map_from_arrays(F.array(F.lit(1), F.lit(2), F.lit(3)), c("p"))
    return _p3(spark, sf_dir).select("key", F.element_at(m, 2).alias("second"), F.size(F.map_entries(m)).alias("n"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def fn_json(spark, sf_dir):
    return table(spark, sf_dir, "events", ["event_id", "props"]).select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("fn_url", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS chars FROM pages")
def fn_url(spark, sf_dir):
    p = table(spark, sf_dir, "pages")
    return p.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("chars"))


@query("fn_vector_key", "SELECT vec_id, CAST(list_sum(list_transform(range(1, 33), lambda i: CASE WHEN embedding[i] > 0 THEN CAST(1 AS BIGINT) << CAST(i - 1 AS BIGINT) ELSE 0 END)) AS BIGINT) AS key FROM embeddings")
def fn_vector_key(spark, sf_dir):
    bit = F.transform(F.sequence(F.lit(1), F.lit(32)), lambda i: F.when(F.element_at("embedding", i) > 0, F.expr("1L") * F.pow(F.lit(2), i - 1).cast("long")).otherwise(F.lit(0).cast("long")))
    return table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]).select("vec_id", F.aggregate(bit, F.lit(0).cast("long"), lambda a, x: a + x).alias("key"))


query("udf_probe", _IN)(pred_maybe_in)


@query("udaf_build")
def udaf_build(spark, sf_dir):
    from .core import bf_udaf

    return bf_udaf(spark, sf_dir)


@query("udtf_positions", f"WITH {U_SQL} SELECT key, CAST(unnest(range(1, 4)) AS INTEGER) AS j, unnest({sql_positions('key', 3, '15000')}) AS pos FROM u WHERE is_member")
def udtf_positions(spark, sf_dir):
    spark.udtf.register("bcf_positions_of", io.positions_udtf())
    universe(spark, sf_dir).where("is_member").createOrReplaceTempView("bcf_members")
    return spark.sql("SELECT key, t.j, t.pos FROM bcf_members, LATERAL bcf_positions_of(key, 15000, 3) t")


_BLOCKED = with_sql(setting_sql(2, 3, "blocked", 16), b_sql(), choice_sql("ratio"), VISIT_SQL, select="SELECT key, ord, c.pos FROM c JOIN ch USING (ord)")


@query("udf_block_clear", _BLOCKED)
def udf_block_clear(spark, sf_dir):
    """Blocked engine: a key's positions lie in one block, so blocks clear independently and exactly."""
    s = setting(spark, sf_dir, 2, 3, "blocked", 16)
    _, done = run(s, "ratio", engine="blocked")
    return done.log.where("acted").select("key", "ord", "pos")
