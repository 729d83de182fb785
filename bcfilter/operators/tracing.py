"""Route replay: traces that should stop one hop before their destination, under a list, a filter or a cleared filter.

Traces are rows (cycle, monitor, dest, ttl, node, is_penultimate). Nodes are classified once, not hops; replay is one
aggregation by trace over hops joined with the positive nodes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..sources.tables import table

G = 1_000_000_000


def lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with customer and date, the columns routes are made of."""
    o = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
    li = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"])
    return o.join(li, o["o_orderkey"] == li["l_orderkey"]).select(F.col("o_custkey").alias("dest"), "o_orderdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def current_lines(spark: SparkSession, sf_dir: str, cycles: list[int]) -> DataFrame:
    """As-of: for each cycle and customer the latest line before the cut, and the part of the one before it.

    One window for each customer gives every line the time up to which it is the latest; a cycle then picks the one
    line that is valid at its cut. Lines are not multiplied by the cycles, and those from the last cut on are in no cycle.
    """
    cuts = spark.createDataFrame([(c,) for c in cycles], "cycle int").withColumn("cut", F.expr("timestamp '2000-01-01' + make_interval(0, 0, 0, 60 * cycle)"))
    w = Window.partitionBy("dest").orderBy("o_orderdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    last = F.expr(f"timestamp '2000-01-01' + make_interval(0, 0, 0, {60 * max(cycles)})")
    at = lines(spark, sf_dir).where(F.col("o_orderdate") < last).select("dest", "o_orderdate", F.col("l_partkey").alias("part"), F.col("l_suppkey").alias("supp"), F.lag("l_partkey").over(w).alias("prev"), F.lead("o_orderdate").over(w).alias("until"))
    valid = (F.col("o_orderdate") < F.col("cut")) & (F.col("until").isNull() | (F.col("until") >= F.col("cut")))
    return at.join(F.broadcast(cuts), valid).select("cycle", "dest", "part", "supp", "prev")


def legs(spark: SparkSession, sf_dir: str, cycles: list[int]) -> tuple[DataFrame, DataFrame]:
    """The two parts of every trace: ``approach(monitor, nation, path)``, which the destinations of a nation share, and
    ``tail(cycle, dest, nation, path)``, which the monitors share; a trace is a pair of equal nation."""
    nation = table(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    monitors = nation.where("n_nationkey < 10").select(F.col("n_nationkey").alias("monitor"), F.col("n_regionkey").alias("m_region"))
    home = table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]).where("c_nationkey is not null").select(F.col("c_custkey").alias("dest"), F.col("c_nationkey").alias("nation"))
    known = lambda *nodes: F.filter(F.array(*nodes).cast("array<bigint>"), lambda x: x.isNotNull()).alias("path")
    region, at = F.col("n_regionkey"), F.col("n_nationkey")
    approach = monitors.crossJoin(F.broadcast(nation)).select("monitor", at.alias("nation"), known(1 * G + F.col("monitor"), 2 * G + 10 * F.col("m_region") + region, 3 * G + 100 * F.col("monitor") + at))
    via = F.when((F.col("dest") % 10 == 0) & (F.col("prev") != F.col("part")), 5 * G + F.col("prev"))
    tail = current_lines(spark, sf_dir, cycles).join(home, "dest").select("cycle", "dest", "nation", known(4 * G + F.col("supp"), via, 5 * G + F.col("part")))
    return approach, tail


def hops(spark: SparkSession, sf_dir: str, cycles: list[int]) -> DataFrame:
    """All hops of all traces of the given cycles."""
    approach, tail = legs(spark, sf_dir, cycles)
    t = tail.join(F.broadcast(approach.withColumnRenamed("path", "before")), "nation").select("cycle", "monitor", "dest", F.concat("before", "path").alias("path"))
    return t.select("cycle", "monitor", "dest", F.size("path").alias("len"), F.posexplode("path").alias("at", "node")).select(
        "cycle", "monitor", "dest", (F.col("at") + 1).alias("ttl"), "node", (F.col("at") + 1 == F.col("len")).alias("is_penultimate")
    )


def known_nodes(approach: DataFrame, tail: DataFrame) -> DataFrame:
    """(key, weight) of the traces that the legs make up: nodes and how many traces pass each, without a row for each trace."""
    tails = tail.groupBy("nation").agg(F.count("*").alias("weight"))
    monitors = approach.groupBy("nation").agg(F.count("*").alias("weight"))
    near = approach.join(tails, "nation").select(F.explode("path").alias("key"), "weight")
    far = tail.join(F.broadcast(monitors), "nation").select(F.explode("path").alias("key"), "weight")
    return near.unionByName(far).groupBy("key").agg(F.sum("weight").alias("weight"))


def ends(approach: DataFrame, tail: DataFrame) -> DataFrame:
    """(key): the distinct last nodes of the traces."""
    pairs = tail.select("nation", F.try_element_at("path", F.lit(-1)).alias("key")).distinct().join(approach.select("nation", F.try_element_at("path", F.lit(-1)).alias("bare")).distinct(), "nation")
    return pairs.select(F.coalesce("key", "bare").alias("key")).distinct()


def mask_shares(approach: DataFrame, tail: DataFrame, masks: DataFrame, steps: DataFrame) -> DataFrame:
    """Outcome shares as ``shares`` gives them, at up to 63 steps at once.

    ``masks(key, mask)``: bit b is set where the node tests positive at the step of that ``bit``. The first hop that
    holds a bit ends the traces of its step. Tails are walked once for all monitors and approaches once for all
    destinations of a nation; an approach that holds a bit ends every trace behind it.
    """
    by = [c for c in steps.columns if c != "bit"]
    zero = F.lit(0).cast("long")

    def walked(legs: DataFrame, *key: str) -> DataFrame:
        each = legs.select(*key, F.size("path").alias("n"), F.posexplode_outer("path").alias("at", "key")).join(masks, "key", "left")
        hit = F.struct("at", (F.col("at") + 1 == F.col("n")).alias("last"), F.coalesce("mask", zero).alias("mask"))
        start = F.struct(zero.alias("good"), zero.alias("early"))

        def step(acc, h):
            new = h["mask"].bitwiseAND(F.bitwise_not(acc["good"].bitwiseOR(acc["early"])))
            return F.struct(acc["good"].bitwiseOR(F.when(h["last"], new).otherwise(zero)).alias("good"), acc["early"].bitwiseOR(F.when(h["last"], zero).otherwise(new)).alias("early"))

        return each.groupBy(*key).agg(F.aggregate(F.array_sort(F.collect_list(hit)), start, step).alias("x"), (F.max("n") == 0).alias("bare")).select(*key, "bare", "x.good", "x.early")

    bit = lambda mask: F.col(mask).bitwiseAND(F.expr("shiftleft(1L, bit)")) != 0
    count = lambda what: F.sum(F.when(what, F.col("n")).otherwise(zero))
    alike = walked(tail, "cycle", "dest", "nation").groupBy("cycle", "nation", "bare", "good", "early").agg(F.count("*").alias("n"))
    far = alike.crossJoin(F.broadcast(steps)).groupBy("cycle", "nation", "bare", *by, "bit").agg(F.sum("n").alias("n"), count(bit("good")).alias("good"), count(bit("early")).alias("early"))
    near = walked(approach, "monitor", "nation").select("nation", F.col("good").alias("last"), F.col("good").bitwiseOR(F.col("early")).alias("ended"))
    met = far.join(F.broadcast(near), "nation")
    # Without a tail the approach's last hop is the penultimate one; with a tail none of its hops is.
    ended, met_last = bit("ended"), F.col("bare") & bit("last")
    good = F.when(met_last, F.col("n")).when(ended, zero).otherwise(F.col("good"))
    early = F.when(met_last, zero).when(ended, F.col("n")).otherwise(F.col("early"))
    out = met.groupBy(*by, "cycle").agg(F.sum("n").alias("traces"), F.sum(good).alias("good"), F.sum(early).alias("early"))
    share = lambda x: F.round(x / F.col("traces").cast("double"), 6)
    return out.select(*by, "cycle", "traces", share(F.col("good")).alias("success"), share(F.col("early")).alias("short"), share(F.col("traces") - F.col("good") - F.col("early")).alias("collision"))


def stop_set(trace: DataFrame, cycle: int = 0) -> DataFrame:
    return trace.where((F.col("cycle") == cycle) & F.col("is_penultimate")).select(F.col("node").alias("key")).distinct()


def degrees(trace: DataFrame, how: str = "encountered", cycle: int = 0) -> DataFrame:
    """(key, weight): traces of the learning cycle that pass a node, or that would stop at it first."""
    own = trace.where(F.col("cycle") == cycle)
    if how == "first_stop":
        own = own.groupBy("cycle", "monitor", "dest").agg(F.min_by("node", "ttl").alias("node"))
    return own.groupBy(F.col("node").alias("key")).agg(F.count("*").alias("weight"))


#: Order from which no reset ever clears a node: members' nodes of a list, and positives that no visit touches.
NEVER = 1 << 62


def paths(trace: DataFrame, until: DataFrame, filters: int) -> DataFrame:
    """One row for each trace and filter: ``hits``, its hops in order as (ttl, node, is_penultimate, until, reach).

    ``until(key, i, gone)``: node ``key`` tests positive under filter i while fewer than ``gone`` visits have been made
    (0: never). A trace stops at its first hop whose ``gone`` is above the number of visits made, so a hop is reached
    from ``reach`` visits on, the greatest ``gone`` before it: one row answers for every number of visits.
    """
    wide = until.groupBy("key").agg(F.collect_list(F.struct("i", "gone")).alias("by"))
    each = trace.join(wide, trace["node"] == wide["key"], "left")
    path = F.array_sort(F.collect_list(F.struct("ttl", "node", "is_penultimate", "by")))
    whole = each.groupBy("cycle", "monitor", "dest").agg(path.alias("path")).withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(filters - 1))))

    def gone(h):
        own = F.filter(h["by"], lambda e: e["i"] == F.col("i"))
        return F.coalesce(F.try_element_at(own, F.lit(1))["gone"], F.lit(0)).cast("long")

    bare = whole.withColumn("path", F.transform("path", lambda h: F.struct(h["ttl"].alias("ttl"), h["node"].alias("node"), h["is_penultimate"].alias("is_penultimate"), gone(h).alias("gone"))))
    reach = lambda k: F.coalesce(F.array_max(F.transform(F.slice("path", F.lit(1), k), lambda h: h["gone"])), F.lit(0)).cast("long")
    hits = F.transform("path", lambda h, k: F.struct(h["ttl"].alias("ttl"), h["node"].alias("node"), h["is_penultimate"].alias("is_penultimate"), h["gone"].alias("gone"), reach(k).alias("reach")))
    return bare.select("i", "cycle", "monitor", "dest", hits.alias("hits"))


def shares(path: DataFrame, steps: DataFrame) -> DataFrame:
    """Outcome shares at ``steps(i, last, ...)``: after ``last`` visits of filter i, without a row for each step and trace.

    A hop ends its trace while ``reach <= last < gone``. Where that begins and ends is added up by place, the places
    are added up by step.
    """
    by = [c for c in steps.columns if c not in ("i", "last")]
    total = path.where("i = 0").groupBy("cycle").agg(F.count("*").alias("traces"))
    stop = path.select("i", "cycle", F.explode(F.filter("hits", lambda h: h["gone"] > h["reach"])).alias("h"))
    ends = F.array(F.struct(F.col("h.reach").alias("at"), F.lit(1).alias("d")), F.struct(F.col("h.gone").alias("at"), F.lit(-1).alias("d")))
    place = stop.select("i", "cycle", "h.is_penultimate", F.explode(ends).alias("x")).groupBy("i", "cycle", "x.at").agg(
        F.sum(F.when(F.col("is_penultimate"), F.col("x.d")).otherwise(0)).alias("good"), F.sum(F.when(~F.col("is_penultimate"), F.col("x.d")).otherwise(0)).alias("early")
    )
    met = place.join(F.broadcast(steps), (place["i"] == steps["i"]) & (place["at"] <= steps["last"])).groupBy(*[steps[c] for c in by], "cycle").agg(F.sum("good").alias("good"), F.sum("early").alias("early"))
    every = F.broadcast(steps.select(*by)).crossJoin(total)
    out = every.join(met, [*by, "cycle"], "left").select(*by, "cycle", "traces", F.coalesce("good", F.lit(0)).alias("good"), F.coalesce("early", F.lit(0)).alias("early"))
    share = lambda x: F.round(x / F.col("traces").cast("double"), 6)
    return out.select(*by, "cycle", "traces", share(F.col("good")).alias("success"), share(F.col("early")).alias("short"), share(F.col("traces") - F.col("good") - F.col("early")).alias("collision"))


def missed_shares(path: DataFrame, steps: DataFrame, links: bool) -> DataFrame:
    """Share of the nodes (or links) that the list's replay (filter 0) reveals and a step's does not.

    A node is revealed from the least ``reach`` of its hops on; one row for each node and filter answers for all steps.
    """
    by = [c for c in steps.columns if c not in ("i", "last")]
    hits = F.col("hits")
    if links:
        pair = F.transform(hits, lambda h, k: F.struct(F.try_element_at(hits, F.when(k > 0, k).otherwise(F.lit(None)).cast("int"))["node"].alias("a"), h["node"].alias("b"), h["reach"].alias("reach")))
        each = path.select("i", F.explode(pair).alias("h")).where("h.a is not null")
        what = ["h.a", "h.b"]
    else:
        each, what = path.select("i", F.explode("hits").alias("h")), ["h.node"]
    seen = each.groupBy("i", *what).agg(F.min("h.reach").alias("reach"))
    names = [w.split(".")[1] for w in what]
    ref = seen.where("i = 0 and reach <= 0").select(*names)
    at = seen.where("i > 0").join(ref, names).groupBy("i", "reach").agg(F.count("*").alias("n"))
    total = ref.agg(F.count("*").alias("total"))
    met = F.broadcast(steps).join(at, (steps["i"] == at["i"]) & (at["reach"] <= steps["last"]), "left").groupBy(*by).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
    return met.crossJoin(F.broadcast(total)).select(*by, F.round((F.col("total") - F.col("n")) / F.col("total").cast("double"), 6).alias("missed"))


def replay(trace: DataFrame, positive: DataFrame, skip_first_hop: bool = False, by: list[str] | None = None) -> DataFrame:
    """Outcome of every trace: stops at its first positive hop; ``by`` are further columns of ``positive``."""
    by = by or []
    walked = trace.where("ttl > 1") if skip_first_hop else trace
    first = walked.join(positive.select(F.col("key").alias("node"), *by), "node").groupBy(*by, "cycle", "monitor", "dest").agg(F.min(F.struct("ttl", "is_penultimate")).alias("x"))
    every = trace.groupBy("cycle", "monitor", "dest").agg(F.max("ttl").alias("hops"))
    if by:
        every = every.crossJoin(F.broadcast(positive.select(*by).distinct()))
    out = every.join(first, [*by, "cycle", "monitor", "dest"], "left")
    outcome = F.when(F.col("x").isNull(), "collision").when(F.col("x.is_penultimate"), "success").otherwise("short")
    return out.select(*by, "cycle", "monitor", "dest", F.col("x.ttl").alias("stop_ttl"), "hops", outcome.alias("outcome"))


def outcomes(replayed: DataFrame, by: list[str] | None = None) -> DataFrame:
    """traces, success, short and collision shares."""
    share = lambda k: F.round(F.avg((F.col("outcome") == k).cast("double")), 6).alias(k)
    return replayed.groupBy(*(by or ["cycle"])).agg(F.count("*").alias("traces"), share("success"), share("short"), share("collision"))


def probe_load(replayed: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Probes sent and saved: hops walked up to the stop, against the whole path and the destination."""
    sent = F.coalesce(F.col("stop_ttl"), F.col("hops") + 1)
    return replayed.groupBy(*(by or ["cycle"])).agg(F.sum(sent).cast("long").alias("sent"), F.sum(F.col("hops") + 1 - sent).cast("long").alias("saved"))


def seen_nodes(trace: DataFrame, replayed: DataFrame) -> DataFrame:
    """Nodes a replay still reveals: hops up to and including the stop."""
    walked = trace.join(replayed.select("cycle", "monitor", "dest", "stop_ttl"), ["cycle", "monitor", "dest"])
    return walked.where(F.col("stop_ttl").isNull() | (F.col("ttl") <= F.col("stop_ttl"))).select("node").distinct()


def seen_links(trace: DataFrame, replayed: DataFrame) -> DataFrame:
    """Links between successive hops a replay still reveals."""
    walked = trace.join(replayed.select("cycle", "monitor", "dest", "stop_ttl"), ["cycle", "monitor", "dest"])
    walked = walked.where(F.col("stop_ttl").isNull() | (F.col("ttl") <= F.col("stop_ttl")))
    w = Window.partitionBy("cycle", "monitor", "dest").orderBy("ttl")
    return walked.select(F.lag("node").over(w).alias("a"), F.col("node").alias("b")).where("a is not null").distinct()


def missed(reference: DataFrame, seen: DataFrame, name: str) -> DataFrame:
    """Share of the reference's rows that are not seen."""
    cols = reference.columns
    hit = reference.join(seen.withColumn("hit", F.lit(1)), cols, "left")
    return hit.agg(F.round(F.avg(F.col("hit").isNull().cast("double")), 6).alias(name))


def cooperative(trace: DataFrame, cycle: int = 1) -> DataFrame:
    """Cooperative early stop: a trace ends at the first node that a lower monitor's trace also passes."""
    own = trace.where(F.col("cycle") == cycle)
    low = own.groupBy("node").agg(F.min("monitor").alias("lowest"))
    first = own.join(low, "node").where("lowest < monitor").groupBy("cycle", "monitor", "dest").agg(F.min("ttl").alias("stop_ttl"))
    return own.groupBy("cycle", "monitor", "dest").agg(F.max("ttl").alias("hops")).join(first, ["cycle", "monitor", "dest"], "left")


def destination_hits(outcome_rows: DataFrame) -> DataFrame:
    """Destination hits after each cycle: every trace of the learning cycle, then collisions; running sum."""
    hits = outcome_rows.groupBy("cycle").agg(F.sum(F.when((F.col("cycle") == 0) | (F.col("outcome") == "collision"), 1).otherwise(0)).alias("hits"))
    return hits.withColumn("total", F.sum("hits").over(Window.orderBy("cycle")))
