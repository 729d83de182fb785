"""Clearing chosen 1-bits of a filter: four rules with frozen counters, three with live ones, three engines.

The rules visit the troublesome keys in order; a key that still tests positive resets one of its k positions. With
frozen counters the position a key *would* reset is known beforehand, so who acts is a first-in-order dominance problem
that a few rounds of joins decide exactly. With live counters a key may act as soon as no earlier undecided key shares
a position with it or with an element that holds one of its positions; such keys act in the same round. ``single_task``
runs the visit as one bounded group, ``blocked`` as one group for each block of a blocked filter.

Ties go to the hash of lowest index. Null keys are never members, false positives or troublesome.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import FilterSpec, hashed
from ..sources.tables import written
from .filters import build_positions

RULES = ("random", "min_fn", "max_fp", "ratio")
#: Rows (elements and keys times k) up to which the engine ``auto`` uses one task.
SINGLE_TASK_ROWS = 2_000_000
LOG = "key long, ord long, positions array<long>, pos long, j int, acted boolean"


@dataclass
class Cleared:
    """What a clearing run did: one log row for each troublesome key."""

    log: DataFrame
    rounds: int = 0

    @property
    def cleared(self) -> DataFrame:
        return self.log.where("acted").select("pos", "key", "ord", "j")


def numbered(df: DataFrame, order: list[Column], name: str = "ord") -> DataFrame:
    """Rows numbered from 1 in a total order without bringing them to one task: range partitions, then shifts."""
    ranged = written(df.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "ranged")
    counts = sorted((r[0], r[1]) for r in ranged.groupBy("part").count().collect())
    shifts, at = [], 0
    for part, n in counts:
        shifts.append((part, at))
        at += n
    shift = F.broadcast(df.sparkSession.createDataFrame(shifts, "part int, shift long"))
    rank = F.row_number().over(Window.partitionBy("part").orderBy(*order))
    return ranged.withColumn(name, rank).join(shift, "part").withColumn(name, (F.col(name) + F.col("shift")).cast("long")).drop("part", "shift")


def running(df: DataFrame, order: str, sums: dict[str, str]) -> DataFrame:
    """Running sums along ``order`` without one task for all rows: range partitions, then the sums of earlier ones."""
    ranged = written(df.repartitionByRange(order).withColumn("part", F.spark_partition_id()), "ranged")
    totals = sorted(tuple(r) for r in ranged.groupBy("part").agg(*[F.sum(c).cast("long") for c in sums]).collect())
    shifts, at = [], [0] * len(sums)
    for part, *own in totals:
        shifts.append((part, *at))
        at = [a + (b or 0) for a, b in zip(at, own)]
    names = [f"shift{i}" for i in range(len(sums))]
    shift = F.broadcast(df.sparkSession.createDataFrame(shifts, "part int, " + ", ".join(f"{n} long" for n in names)))
    w = Window.partitionBy("part").orderBy(order).rowsBetween(Window.unboundedPreceding, 0)
    out = ranged.join(shift, "part")
    for n, (c, name) in zip(names, sums.items()):
        out = out.withColumn(name, (F.sum(c).over(w) + F.col(n)).cast("long"))
    return out.drop("part", *names)


def md5_order(key: str = "key", run: int | None = None) -> list[Column]:
    text = F.col(key).cast("string")
    return [F.md5((text if run is None else F.concat(F.lit(f"{run}:"), text)).cast("binary")), F.col(key)]


def troublesome(fp: DataFrame, beta: float, order: list[Column] | None = None, count: int | None = None) -> DataFrame:
    """The first share ``beta`` of the false positives in ``order``, with ``ord``; at least one while beta > 0."""
    n = fp.count() if count is None else count
    take = min(n, max(1, round_half_up(beta * n))) if beta > 0 else 0
    return numbered(fp, order or md5_order()).where(F.col("ord") <= take)


def round_half_up(x: float) -> int:
    return int(np.floor(x + 0.5))


def counters(keys: DataFrame, among: DataFrame | None = None, name: str = "cnt", weight: str | None = None, multiplicity: str = "per_hash") -> DataFrame:
    """Elements per position of ``keys(positions, ...)``; ``among(pos)`` restricts the positions before the shuffle."""
    at = F.array_distinct("positions") if multiplicity == "distinct" else F.col("positions")
    each = keys.select(F.explode(at).alias("pos"), *([weight] if weight else []))
    if among is not None:
        each = each.join(among, "pos", "left_semi")
    return each.groupBy("pos").agg((F.sum(weight) if weight else F.count("*")).cast("long").alias(name))


def ratio_vector(v_a: DataFrame, v_b: DataFrame) -> DataFrame:
    """(pos, cnt_a, cnt_b, ratio); null where no false positive lies."""
    both = v_a.join(v_b, "pos", "full")
    both = both.select("pos", F.coalesce("cnt_a", F.lit(0)).alias("cnt_a"), F.coalesce("cnt_b", F.lit(0)).alias("cnt_b"))
    return both.withColumn("ratio", F.expr("try_divide(cast(cnt_a as double), cnt_b)"))


def element_lists(keys: DataFrame) -> DataFrame:
    """Long form (pos, key): the list of elements of every position."""
    return keys.select(F.explode("positions").alias("pos"), "key")


def drop_elements(lists: DataFrame, keys: DataFrame) -> DataFrame:
    return lists.join(keys.select("key"), "key", "left_anti").select("pos", "key")


def random_choice(seed: int, k: int) -> Column:
    """Index of the position the random rule resets."""
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.col("key").cast("string")).cast("binary"))
    return F.pmod(F.conv(F.substring(digest, 1, 15), 16, 10).cast("long"), F.lit(k)).cast("int")


def choose(b: DataFrame, rule: str, members: DataFrame, scope: DataFrame, seed: int = 0, k: int = 1, weight: str | None = None) -> DataFrame:
    """(key, ord, positions, pos, j): the position each troublesome key would reset, frozen counters."""
    if rule == "random":
        return b.withColumn("j", random_choice(seed, k)).withColumn("pos", F.element_at("positions", F.col("j") + 1)).select("key", "ord", "positions", "pos", "j")
    among = b.select(F.explode("positions").alias("pos")).distinct()
    each = b.select("key", "ord", "positions", F.posexplode("positions").alias("j", "pos"))
    v_a = counters(members, among, "cnt_a") if rule in ("min_fn", "ratio") else None
    v_b = counters(scope, among, "cnt_b", weight) if rule in ("max_fp", "ratio") else None
    for v in (v_a, v_b):
        if v is not None:
            each = each.join(v, "pos", "left")
    a, n = F.coalesce(F.col("cnt_a"), F.lit(0)).cast("double"), F.col("cnt_b").cast("double")
    score = {"min_fn": a, "max_fp": -n, "ratio": F.try_divide(a, n)}[rule]
    each = each.withColumn("score", score).where(F.col("score").isNotNull())
    best = each.groupBy("key").agg(F.min_by(F.struct("pos", "j"), F.struct("score", "j")).alias("x"))
    return b.join(best, "key").select("key", "ord", "positions", "x.pos", "x.j")


def resolve_rounds(chosen: DataFrame) -> Cleared:
    """Who acts, by rounds over (key, ord, positions, pos, j): exactly the visit in order.

    A key is out when an earlier acting key resets one of its positions; it acts when, besides, no earlier undecided
    key would. States are written tables; the driver learns one count for each round.
    """
    open_, done, rounds = written(chosen, "open"), [], 0
    fresh = None
    while not open_.isEmpty():
        rounds += 1
        first_open = open_.groupBy("pos").agg(F.min("ord").alias("open_ord"))
        each = open_.select("key", "ord", F.explode(F.array_distinct("positions")).alias("pos")).join(first_open, "pos", "left")
        # Resets of earlier rounds were held against all that is still open when they were new.
        if fresh is not None:
            each = each.join(fresh.groupBy("pos").agg(F.min("ord").alias("act_ord")), "pos", "left")
        else:
            each = each.withColumn("act_ord", F.lit(None).cast("long"))
        state = each.groupBy("key").agg(
            F.coalesce(F.bool_or(F.col("act_ord") < F.col("ord")), F.lit(False)).alias("out"), F.coalesce(F.bool_or(F.col("open_ord") < F.col("ord")), F.lit(False)).alias("waits")
        )
        now = written(open_.join(state, "key"), "round")
        decided = now.where("out or not waits").select("key", "ord", "positions", "pos", "j", (~F.col("out")).alias("acted"))
        done.append(decided)
        fresh = decided.where("acted").select("pos", "ord")
        open_ = now.where("not out and waits").select("key", "ord", "positions", "pos", "j")
    if not done:
        return Cleared(chosen.withColumn("acted", F.lit(False)), 0)
    log = done[0]
    for d in done[1:]:
        log = log.unionByName(d)
    return Cleared(log, rounds)


def _visit(rule: str, live: bool, seed_j: bool):
    """The visit in order over one group: ``b(key, ord, positions, j)`` and ``e(side, positions, weight)``."""

    def run(b: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        b = b.sort_values("ord")
        count = {"a": {}, "b": {}}
        at: dict[int, list[int]] = {}
        spots = [p.tolist() for p in e["positions"]] if len(e) else []
        sides, weights = e["side"].tolist(), e["weight"].tolist()
        for i, own in enumerate(spots):
            c = count[sides[i]]
            for p in own:
                c[p] = c.get(p, 0) + weights[i]
            if live:
                for p in set(own):
                    at.setdefault(p, []).append(i)
        dead = bytearray(len(spots))
        gone: set[int] = set()
        out = []
        for r in b.itertuples(index=False):
            own = r.positions.tolist()
            acts = not any(p in gone for p in own)
            j = r.j if seed_j else None
            if not seed_j and (acts or not live):
                best = None
                for i, p in enumerate(own):
                    a, n = count["a"].get(p, 0), count["b"].get(p, 0)
                    score = a if rule == "min_fn" else -n if rule == "max_fp" else a / n if n else None
                    if score is not None and (best is None or score < best[0]):
                        best = (score, i)
                j = best[1] if best else 0
            pos = own[j] if j is not None else None
            out.append((r.key, r.ord, own, pos, j, acts))
            if not acts:
                continue
            gone.add(pos)
            if live:
                for i in at.get(pos, ()):
                    if not dead[i]:
                        dead[i] = 1
                        c = count[sides[i]]
                        for p in spots[i]:
                            c[p] -= weights[i]
        log = pd.DataFrame(out, columns=["key", "ord", "positions", "pos", "j", "acted"])
        return log.astype({"pos": "Int64", "j": "Int32"})

    return run


def touching(elements: DataFrame, among: DataFrame) -> DataFrame:
    """Elements that hold one of the positions ``among(pos)``."""
    hit = elements.select("side", "key", F.explode(F.array_distinct("positions")).alias("pos")).join(among, "pos", "left_semi").select("side", "key").distinct()
    return elements.join(hit, ["side", "key"], "left_semi")


def elements_of(members: DataFrame, scope: DataFrame, rule: str, weight: str | None = None) -> DataFrame:
    """(side, key, positions, weight) of the elements the rule counts."""
    w = F.col(weight).cast("long") if weight else F.lit(1).cast("long")
    own = [F.col(c).alias(c) for c in ("key", "positions")]  # fresh columns: the scope may be the troublesome keys themselves
    a = members.select(F.lit("a").alias("side"), *own, F.lit(1).cast("long").alias("weight"))
    b = scope.select(F.lit("b").alias("side"), *own, w.alias("weight"))
    return {"random": a.limit(0), "min_fn": a, "max_fp": b, "ratio": a.unionByName(b)}[rule]


def resolve_groups(b: DataFrame, elements: DataFrame, rule: str, live: bool, seed: int, k: int, block: Column) -> Cleared:
    """One task for each value of ``block`` (a column of both sides); a constant makes it one task."""
    among = b.select(F.explode("positions").alias("pos")).distinct()
    near = touching(elements, among) if rule != "random" else elements
    j = random_choice(seed, k) if rule == "random" else F.lit(0)
    left = b.select("key", "ord", "positions", j.alias("j"), block.alias("block"))
    right = near.select("side", "positions", "weight", block.alias("block"))
    visit = _visit(rule, live, rule == "random")

    def run(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        return visit(x, y)

    return Cleared(left.groupBy("block").cogroup(right.groupBy("block")).applyInPandas(run, LOG), 1)


def _visit_flat(rule: str, k: int):
    """The live visit of one group over ``b(ord, key, j, pos)`` and ``e(side, key, pos, weight)``, one row a position.

    Of an element only the positions of troublesome keys are given; no other counter is ever read.
    """

    def run(b: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        b = b.sort_values(["ord", "j"])
        # A missing cogroup side may come without columns.
        spots, at = np.unique(b["pos"].to_numpy(np.int64), return_inverse=True)
        own = at.reshape(-1, k)
        side_a = e["side"].to_numpy() == "a" if len(e) else np.empty(0, bool)
        keys = e["key"].to_numpy(np.int64) if len(e) else np.empty(0, np.int64)
        weight = e["weight"].to_numpy(np.int64) if len(e) else np.empty(0, np.int64)
        pos = np.searchsorted(spots, e["pos"].to_numpy(np.int64)) if len(e) else np.empty(0, np.int64)
        order = np.lexsort((keys, side_a))
        side_a, keys, weight, pos = side_a[order], keys[order], weight[order], pos[order]
        new = np.ones(len(keys), bool)
        new[1:] = (keys[1:] != keys[:-1]) | (side_a[1:] != side_a[:-1])
        start = np.append(np.flatnonzero(new), len(keys))
        element = np.cumsum(new) - 1
        by_pos = np.argsort(pos, kind="stable")
        holders, first = element[by_pos], np.searchsorted(pos[by_pos], np.arange(len(spots) + 1))
        count = [np.zeros(len(spots), np.int64), np.zeros(len(spots), np.int64)]
        np.add.at(count[0], pos[side_a], weight[side_a])
        np.add.at(count[1], pos[~side_a], weight[~side_a])
        dead, gone = np.zeros(len(start) - 1, bool), np.zeros(len(spots), bool)
        acted, chosen = [], []
        for mine in own.tolist():
            if any(gone[p] for p in mine):
                acted.append(False)
                chosen.append(None)
                continue
            best = (None, 0)
            for i, p in enumerate(mine):
                a, n = int(count[0][p]), int(count[1][p])
                score = a if rule == "min_fn" else -n if rule == "max_fp" else a / n if n else None
                if score is not None and (best[0] is None or score < best[0]):
                    best = (score, i)
            acted.append(True)
            chosen.append(best[1])
            p = mine[best[1]]
            gone[p] = True
            for x in set(holders[first[p] : first[p + 1]].tolist()):
                if not dead[x]:
                    dead[x] = True
                    lo, hi = start[x], start[x + 1]
                    np.subtract.at(count[0 if side_a[lo] else 1], pos[lo:hi], weight[lo:hi])
        whole = spots[own]
        log = pd.DataFrame({"key": b["key"].to_numpy(np.int64)[::k], "ord": b["ord"].to_numpy(np.int64)[::k], "positions": list(whole)})
        log["pos"] = pd.array([None if j is None else int(w[j]) for w, j in zip(whole, chosen)], dtype="Int64")
        log["j"] = pd.array(chosen, dtype="Int32")
        return log.assign(acted=acted)

    return run


def resolve_live_groups(b: DataFrame, elements: DataFrame, rule: str, k: int, group) -> Cleared | None:
    """Live counters, one task for each group of keys and positions that share none with another group.

    ``group(name)`` gives the group of a key or position column. None if a task would hold more than
    ``SINGLE_TASK_ROWS`` rows (a row is an element's position that a troublesome key has too).
    """
    among = b.select(F.explode("positions").alias("pos")).distinct()
    flat = written(elements.select("side", "key", "weight", F.explode("positions").alias("pos")).join(among, "pos", "left_semi"), "touched")
    left = b.select("key", "ord", F.posexplode("positions").alias("j", "pos")).withColumn("group", group("key"))
    right = flat.withColumn("group", group("pos"))
    most = left.select("group").unionByName(right.select("group")).groupBy("group").count().agg(F.max("count")).first()[0] or 0
    if most > SINGLE_TASK_ROWS:
        return None
    visit = _visit_flat(rule, k)

    def run(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        return visit(x, y)

    return Cleared(left.groupBy("group").cogroup(right.groupBy("group")).applyInPandas(run, LOG), 1)


def resolve_live_rounds(b: DataFrame, elements: DataFrame, rule: str) -> Cleared:
    """Live counters by rounds; conflicts are shared positions, directly or through a living element."""
    open_, done, rounds, gone = written(b.select("key", "ord", "positions"), "open"), [], 0, None
    alive = elements
    while not open_.isEmpty():
        rounds += 1
        each = open_.select("key", "ord", F.explode(F.array_distinct("positions")).alias("pos"))
        mpos = each.groupBy("pos").agg(F.min("ord").alias("mp"))
        # Only living elements that an undecided key still touches can matter from here on.
        alive = touching(alive, mpos.select("pos"))
        if gone is not None:
            lost = alive.select("side", "key", F.explode("positions").alias("pos")).join(gone, "pos", "left_semi").select("side", "key").distinct()
            alive = alive.join(lost, ["side", "key"], "left_anti")
        alive = written(alive, "alive")
        held = alive.select("side", F.col("key").alias("x"), F.explode(F.array_distinct("positions")).alias("pos"))
        mx = held.join(mpos, "pos").groupBy("side", "x").agg(F.min("mp").alias("mx"))
        through = held.join(mx, ["side", "x"]).groupBy("pos").agg(F.min("mx").alias("mt"))
        mp2 = mpos.join(through, "pos", "left").select("pos", F.least("mp", "mt").alias("mp2"))
        first = each.join(mp2, "pos").groupBy("key", "ord").agg(F.min("mp2").alias("least"))
        acts = first.where("ord = least").select("key").join(open_, "key")
        spots = acts.select("key", "ord", "positions", F.posexplode("positions").alias("j", "pos"))
        near = alive.select("side", "weight", F.explode("positions").alias("pos")).join(spots.select("pos"), "pos", "left_semi")
        count = near.groupBy("pos").agg(
            F.sum(F.when(F.col("side") == "a", F.col("weight")).otherwise(0)).alias("cnt_a"), F.sum(F.when(F.col("side") == "b", F.col("weight")).otherwise(0)).alias("cnt_b")
        )
        spots = spots.join(count, "pos", "left")
        a, n = F.coalesce("cnt_a", F.lit(0)).cast("double"), F.coalesce("cnt_b", F.lit(0)).cast("double")
        score = {"min_fn": a, "max_fp": -n, "ratio": F.try_divide(a, n)}[rule]
        spots = spots.withColumn("score", score).where(F.col("score").isNotNull())
        now = spots.groupBy("key", "ord", "positions").agg(F.min_by(F.struct("pos", "j"), F.struct("score", "j")).alias("x"))
        now = written(now.select("key", "ord", "positions", "x.pos", "x.j", F.lit(True).alias("acted")), "acts")
        gone = now.select("pos").distinct()
        left = open_.join(now.select("key"), "key", "left_anti")
        out = left.select("key", F.explode("positions").alias("pos")).join(gone, "pos", "left_semi").select("key").distinct()
        state = written(left.join(out.withColumn("out", F.lit(True)), "key", "left"), "state")
        done += [now, state.where("out").select("key", "ord", "positions", F.lit(None).cast("long").alias("pos"), F.lit(None).cast("int").alias("j"), F.lit(False).alias("acted"))]
        open_ = state.where("out is null").select("key", "ord", "positions")
    if not done:
        return Cleared(b.sparkSession.createDataFrame([], LOG), 0)
    log = done[0]
    for d in done[1:]:
        log = log.unionByName(d)
    return Cleared(log, rounds)


def engine_for(b: DataFrame, elements: DataFrame, k: int) -> str:
    """``single_task`` if the rows that a live visit would hold (keys and elements that touch them, times k) are few."""
    rows = k * b.count()
    if rows <= SINGLE_TASK_ROWS:
        rows += k * touching(elements, b.select(F.explode("positions").alias("pos")).distinct()).count()
    return "single_task" if rows <= SINGLE_TASK_ROWS else "rounds"


def visit_frozen(chosen: DataFrame, engine: str = "auto") -> Cleared:
    """Who acts among keys whose choice is known: (key, ord, positions, pos, j)."""
    if engine == "auto":
        engine = "single_task" if chosen.count() <= SINGLE_TASK_ROWS else "rounds"
    return _dominate(chosen) if engine == "single_task" else resolve_rounds(chosen)


def clear(members: DataFrame, fp: DataFrame, b: DataFrame, spec: FilterSpec, rule: str = "ratio", live: bool = False, scope: str = "all", engine: str = "auto", seed: int = 0, weight: str | None = None, group=None) -> Cleared:
    """Clear bits for ``b(key, positions, ord)``; ``members`` and ``fp`` carry ``key, positions``.

    ``group``: for visits side by side that share no position, the group of a key or position column by name; live
    visits then take a task each, as long as each has few rows.

    ``scope``: the keys whose positions the false-positive counters hold, ``all`` false positives or the
    ``troublesome`` ones. ``live`` has no effect on the random rule.
    """
    if rule not in RULES:
        raise ValueError(f"unknown rule {rule!r}")
    scope_keys = fp if scope == "all" else b
    live = live and rule != "random"
    if not live and engine != "blocked":
        if engine not in ("auto", "rounds", "single_task"):
            raise ValueError(f"unknown engine {engine!r}")
        return visit_frozen(choose(b, rule, members, scope_keys, seed, spec.k, weight), engine)
    elements = elements_of(members, scope_keys, rule, weight)
    if engine == "auto" and group is not None:
        done = resolve_live_groups(b, elements, rule, spec.k, group)
        if done is not None:
            return done
        engine = "rounds"
    if engine == "auto":
        engine = engine_for(b, elements, spec.k)
    if engine == "rounds":
        return resolve_live_rounds(b, elements, rule)
    block = F.lit(0).cast("long")
    if engine == "blocked":
        block = ((F.element_at("positions", 1) - 1) / spec.block_bits).cast("long")
    elif engine != "single_task":
        raise ValueError(f"unknown engine {engine!r}")
    return resolve_groups(b, elements, rule, live, seed, spec.k, block)


def _dominate(chosen: DataFrame) -> Cleared:
    """Frozen choices visited in one bounded task."""

    def run(b: pd.DataFrame) -> pd.DataFrame:
        gone: set[int] = set()
        acted = []
        b = b.sort_values("ord")
        for own, pos in zip(b["positions"], b["pos"]):
            acts = gone.isdisjoint(own.tolist())
            if acts:
                gone.add(pos)
            acted.append(acts)
        return b.drop(columns="one").assign(acted=acted)

    return Cleared(chosen.select("key", "ord", "positions", "pos", "j", F.lit(0).alias("one")).groupBy("one").applyInPandas(run, LOG), 1)


def randomized(pos: DataFrame, s: int, seed: int = 0) -> DataFrame:
    """``s`` set positions in the order of a seeded digest: clearing without regard to keys."""
    order = [F.md5(F.concat(F.lit(f"{seed}:"), F.col("pos").cast("string")).cast("binary")), F.col("pos")]
    return numbered(pos, order).where(F.col("ord") <= s).select("pos")


def reset_bits(pos: DataFrame, gone: DataFrame) -> DataFrame:
    """Position table without the given bits."""
    return pos.join(gone.select("pos"), "pos", "left_anti")


def hit_by(keys: DataFrame, gone: DataFrame) -> DataFrame:
    """Keys (with ``positions``) that hold a cleared position: false positives removed, or members lost."""
    lost = keys.select("key", F.explode("positions").alias("pos")).join(gone.select("pos"), "pos", "left_semi").select("key").distinct()
    return keys.join(lost, "key", "left_semi")


def false_positives(universe: DataFrame, members: DataFrame, spec: FilterSpec) -> DataFrame:
    """Foreign keys that test positive: (key, positions), over the observed universe."""
    from .filters import positives

    pos = build_positions(members, spec)
    others = universe.select("key").join(members.select("key"), "key", "left_anti")
    return hashed(positives(others, pos, spec), spec)


def budget(log: DataFrame, members: DataFrame, max_resets: int | None = None, max_fn: int | None = None) -> DataFrame:
    """The longest prefix of the resets in order that stays within ``max_resets`` bits and ``max_fn`` lost members."""
    gone = log.where("acted").select("pos", "ord")
    first = members.select("key", F.explode("positions").alias("pos")).join(gone, "pos").groupBy("key").agg(F.min("ord").alias("ord"))
    per = gone.join(first.groupBy("ord").agg(F.count("*").alias("lost")), "ord", "left").select("pos", "ord", F.coalesce("lost", F.lit(0)).alias("lost"))
    per = running(per.withColumn("one", F.lit(1)), "ord", {"one": "resets", "lost": "fn"})
    ok = F.lit(True)
    if max_resets is not None:
        ok &= F.col("resets") <= max_resets
    if max_fn is not None:
        ok &= F.col("fn") <= max_fn
    return per.where(ok).select("pos", "ord", "resets", "fn")
