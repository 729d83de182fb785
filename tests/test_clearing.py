"""The worked miniature, engines against each other, invariants, edge cases and the statistical behaviour."""

import pytest
from pyspark.sql import functions as F

from bcfilter.functions.hashing import FilterSpec, hashed
from bcfilter.operators import clearing, filters, measures, tracing
from bcfilter.plans import workloads
from bcfilter.plans.base import Setting
from bcfilter.sources.tables import written

MEMBERS = {1: (1, 2), 2: (2, 3), 3: (3, 4), 4: (5, 6), 5: (6, 7)}
FALSE = {11: (1, 3), 12: (2, 4), 13: (3, 5), 14: (4, 6), 15: (3, 7), 16: (6, 6)}
SPEC = FilterSpec(12, 2)
CASES = [
    ("min_fn", False, "all", {1, 4, 5}, {1, 3, 4}, {15, 16}),
    ("min_fn", True, "all", {1, 2, 3, 4}, {1, 2, 3}, {16}),
    ("max_fp", False, "all", {3, 4}, {2, 3}, {16}),
    ("max_fp", False, "troublesome", {3, 4}, {2, 3}, {16}),
    ("max_fp", True, "all", {3, 4}, {2, 3}, {16}),
    ("max_fp", True, "troublesome", {3, 4}, {2, 3}, {16}),
    ("ratio", False, "all", {3, 4}, {2, 3}, {16}),
    ("ratio", False, "troublesome", {1, 3, 4}, {1, 2, 3}, {16}),
    ("ratio", True, "all", {3, 4}, {2, 3}, {16}),
    ("ratio", True, "troublesome", {1, 3, 4}, {1, 2, 3}, {16}),
]


def keyed(spark, d):
    return spark.createDataFrame([(k, list(p)) for k, p in d.items()], "key long, positions array<long>")


@pytest.mark.parametrize("engine", ["rounds", "single_task"])
@pytest.mark.parametrize("rule,live,scope,cleared,lost,left", CASES)
def test_miniature(spark, engine, rule, live, scope, cleared, lost, left):
    a, fp = keyed(spark, MEMBERS), keyed(spark, FALSE)
    b = spark.createDataFrame([(k, list(FALSE[k]), i + 1) for i, k in enumerate((11, 12, 13, 14))], "key long, positions array<long>, ord long")
    done = clearing.clear(a, fp, b, SPEC, rule, live, scope, engine)
    gone = written(done.cleared, "gone")
    assert {r.pos for r in gone.collect()} == cleared
    assert {r.key for r in clearing.hit_by(a, gone).collect()} == lost
    removed = {r.key for r in clearing.hit_by(fp, gone).collect()}
    assert set(FALSE) - removed == left
    log = {r.key: r.acted for r in done.log.collect()}
    assert len(log) == 4 and sum(log.values()) == len(cleared)


def test_members_counted_per_hash_and_distinct(spark):
    fp = keyed(spark, FALSE)
    assert {r.pos: r.cnt for r in clearing.counters(fp).collect()} == {1: 1, 2: 1, 3: 3, 4: 2, 5: 1, 6: 3, 7: 1}
    assert {r.pos: r.cnt for r in clearing.counters(fp, multiplicity="distinct").collect()}[6] == 2


def test_no_false_negative_gives_null_chi(spark):
    a, fp = keyed(spark, {1: (1, 2)}), keyed(spark, {11: (3, 4)})
    b = fp.withColumn("ord", F.lit(1).cast("long"))
    row = measures.table_row(a, fp, b, clearing.clear(a, fp, b, SPEC, "min_fn", engine="rounds"), 9, SPEC, 1.0, "min_fn").first()
    assert (row.fn, row.removed, row.chi) == (0, 1, None)


@pytest.mark.parametrize("engine", ["rounds", "single_task"])
@pytest.mark.parametrize("rule,live", [("ratio", False), ("ratio", True), ("random", False)])
def test_empty_troublesome_set(spark, engine, rule, live):
    a, fp = keyed(spark, MEMBERS), keyed(spark, FALSE)
    b = fp.limit(0).withColumn("ord", F.lit(1).cast("long"))
    assert clearing.clear(a, fp, b, SPEC, rule, live, engine=engine).cleared.count() == 0


def test_null_keys_are_dropped_and_probe_as_null(spark):
    spec = FilterSpec(64, 3)
    a = spark.createDataFrame([(1,), (None,), (7,)], "key long")
    pos = filters.build_positions(a, spec)
    assert pos.count() <= 6
    for f in (filters.probe_join, filters.probe_broadcast):
        got = {r.key: r.maybe for r in f(a, pos, spec).collect()}
        assert got == {1: True, 7: True, None: None}


def test_empty_member_set_rejects_everything(spark):
    spec = FilterSpec(64, 3)
    pos = filters.build_positions(spark.createDataFrame([], "key long"), spec)
    u = spark.range(20).withColumnRenamed("id", "key")
    assert filters.probe_join(u, pos, spec).where("maybe").count() == 0
    assert filters.probe_shuffle(u, filters.bitmap_of(pos), spec).where("maybe").count() == 0


def test_large_negative_and_string_keys(spark):
    for family in ("xxhash", "linear", "md5"):
        spec = FilterSpec(40_000, 4, family)
        keys = spark.createDataFrame([(-5,), (2**62,), (0,)], "key long")
        pos = filters.build_positions(keys, spec)
        assert filters.probe_join(keys, pos, spec).where("maybe").count() == 3
        assert pos.where("pos < 1 or pos > 40000").count() == 0
    words = spark.createDataFrame([("a",), ("ß",), ("",)], "key string")
    for family in ("xxhash", "md5"):
        spec = FilterSpec(999, 3, family)
        assert filters.probe_shuffle(words, filters.build_bitmap(words, spec), spec).where("maybe").count() == 3


def test_bad_specifications():
    for bad in (dict(m=0, k=1), dict(m=5, k=0), dict(m=5, k=6), dict(m=5, k=1, family="none")):
        with pytest.raises(ValueError):
            FilterSpec(**bad)


def test_numbering_is_gapless_and_ordered(spark):
    df = spark.range(5000).select(((F.col("id") * 7919) % 5000).alias("key"))
    got = clearing.numbered(df, [F.col("key")]).collect()
    assert all(r.ord == r.key + 1 for r in got) and len(got) == 5000


@pytest.fixture(scope="module")
def replica(spark):
    """The simulation's rates at a fifth of its size: n = 2,000 of 400,000, m = 20,000, k = 5."""
    u = spark.range(400_000).withColumnRenamed("id", "key")
    spec = FilterSpec(20_000, 5, "xxhash")
    a = written(u.orderBy(F.xxhash64("key")).limit(2000), "a")
    fp = written(clearing.false_positives(u, a, spec), "fp")
    return Setting(u, hashed(a, spec), fp, spec, 2000, 400_000, fp.count())


def test_rules_rank_and_trade_off(replica):
    """Ratio beats max-FP beats min-FN beats random in chi; chi falls as beta grows; no positive is left at beta 1."""
    assert abs(replica.n_fp / 398_000 - 0.0094) < 0.0015
    chi = {}
    for rule in clearing.RULES:
        got = {r.beta: r for r in workloads.sweep(replica, rule, (0.1, 0.5, 1.0)).collect()}
        chi[rule] = [got[b].chi for b in (0.1, 0.5, 1.0)]
        assert got[1.0].removed == replica.n_fp and got[1.0].b_extra == 0 and got[0.5].s <= got[0.5].b
    for i in range(3):
        assert chi["ratio"][i] > chi["max_fp"][i] > chi["min_fn"][i] > chi["random"][i] > 1
    assert chi["ratio"][0] > chi["ratio"][1] > chi["ratio"][2]
    for rule, published in (("random", (1.409, 1.377, 1.357)), ("min_fn", (1.756, 1.653, 1.561)), ("max_fp", (2.061, 1.760, 1.612)), ("ratio", (2.402, 2.005, 1.792))):
        assert all(abs(x / y - 1) < 0.12 for x, y in zip(chi[rule], published)), (rule, chi[rule])


def test_live_counters_do_better_at_high_beta(replica):
    for rule in ("min_fn", "ratio"):
        row = {}
        for live in (False, True):
            b = clearing.troublesome(replica.fp, 1.0, count=replica.n_fp)
            done = clearing.clear(replica.members, replica.fp, b, replica.spec, rule, live, engine="single_task")
            done.log = written(done.log, "log")
            row[live] = measures.table_row(replica.members, replica.fp, b, done, 400_000, replica.spec, 1.0, rule).first().chi
        assert row[True] > 1.2 * row[False]


def test_engine_is_chosen_by_the_rows_a_task_would_hold(spark, monkeypatch):
    """A large scope of false positives that touch the troublesome key makes a live visit run by rounds."""
    spec = FilterSpec(50, 2)
    a = hashed(spark.range(20).withColumnRenamed("id", "key"), spec)
    fp = hashed(spark.range(100, 2100).withColumnRenamed("id", "key"), spec)
    b = fp.where("key < 102").withColumn("ord", F.col("key") - 99)
    assert clearing.engine_for(b, clearing.elements_of(a, fp, "ratio"), 2) == "single_task"
    monkeypatch.setattr(clearing, "SINGLE_TASK_ROWS", 200)
    assert clearing.engine_for(b, clearing.elements_of(a, b, "ratio"), 2) == "single_task"
    assert clearing.engine_for(b, clearing.elements_of(a, fp, "ratio"), 2) == "rounds"
    rounds = clearing.clear(a, fp, b, spec, "ratio", live=True)
    monkeypatch.undo()
    one = clearing.clear(a, fp, b, spec, "ratio", live=True)
    assert rounds.rounds >= 1 and sorted(map(tuple, rounds.cleared.collect())) == sorted(map(tuple, one.cleared.collect()))


def test_sweep_equals_a_visit_for_each_beta(replica):
    """Prefixes of one visit against visits of their own, for frozen and live counters."""
    for live in (False, True):
        got = {r.beta: (r.b, r.b_extra, r.removed, r.fn, r.s) for r in workloads.sweep(replica, "ratio", (0.02, 0.3), live=live).collect()}
        for beta in (0.02, 0.3):
            b = written(clearing.troublesome(replica.fp, beta, count=replica.n_fp), "b")
            done = clearing.clear(replica.members, replica.fp, b, replica.spec, "ratio", live)
            done.log = written(done.log, "log")
            row = measures.table_row(replica.members, replica.fp, b, done, 400_000, replica.spec, beta, "ratio").first()
            assert got[beta] == (row.b, row.b_extra, row.removed, row.fn, row.s)


def test_dleft_and_sliced_builds(spark):
    from bcfilter.operators import baselines

    u = spark.range(3000).select(F.col("id").alias("key"), (F.col("id") % 5 == 0).alias("is_member"))
    row = baselines.dleft(u, u.where("is_member").select("key")).first()
    assert row.fn == 0 and row.fp < 60 and row.deepest <= 9


def test_live_visits_side_by_side_take_a_task_each(spark, monkeypatch):
    """Groups that are small each but not together stay out of the rounds, with the same resets."""
    keyed_by = lambda df, spec: workloads.composite(hashed(df.select(F.col("id").alias("key"), (F.col("id") % 4).cast("int").alias("i")), spec), "i")
    spec = FilterSpec(60, 3)
    a, fp = keyed_by(spark.range(120), spec), keyed_by(spark.range(1000, 1200), spec)
    b = written(clearing.numbered(fp, [workloads.group_of("key"), F.col("key")]).where("key % 3 > 0"), "b")
    whole = 3 * clearing.touching(clearing.elements_of(a, fp, "ratio"), b.select(F.explode("positions").alias("pos"))).count()
    monkeypatch.setattr(clearing, "SINGLE_TASK_ROWS", whole // 2)
    for rule in ("min_fn", "max_fp", "ratio"):
        assert clearing.engine_for(b, clearing.elements_of(a, fp, rule), 3) == "rounds" or rule != "ratio"
        got = clearing.clear(a, fp, b, spec, rule, live=True, group=workloads.group_of)
        assert got.rounds == 1
        one = clearing.clear(a, fp, b, spec, rule, live=True, engine="single_task")
        assert sorted(map(tuple, got.cleared.collect())) == sorted(map(tuple, one.cleared.collect()))
        assert got.log.count() == b.count()
    monkeypatch.setattr(clearing, "SINGLE_TASK_ROWS", 10)
    assert clearing.resolve_live_groups(b, clearing.elements_of(a, fp, "ratio"), "ratio", 3, workloads.group_of) is None


def test_legs_stand_for_all_traces(spark):
    """Nodes, ends and outcomes from the two legs against the traces themselves; a tail without hops included."""
    approach = spark.createDataFrame([(m, n, [m, 10 + n]) for m in (1, 2) for n in (0, 1)], "monitor int, nation int, path array<long>")
    tail = spark.createDataFrame([(0, d, d % 3, [100 + d % 4, 200 + d % 7] if d % 5 else []) for d in range(40)], "cycle int, dest long, nation int, path array<long>")
    t = tail.join(approach.withColumnRenamed("path", "before"), "nation").withColumn("path", F.concat("before", "path"))
    hops = t.select("cycle", "monitor", "dest", F.size("path").alias("n"), F.posexplode("path").alias("at", "node")).select("cycle", "monitor", "dest", (F.col("at") + 1).alias("ttl"), "node", (F.col("at") + 1 == F.col("n")).alias("is_penultimate"))
    same = lambda x, y: sorted(map(tuple, x.collect())) == sorted(map(tuple, y.collect()))
    assert same(tracing.ends(approach, tail), tracing.stop_set(hops)) and same(tracing.known_nodes(approach, tail), tracing.degrees(hops))
    sets = [{200, 203, 11}, {101, 205, 2}, {10}, set(), {1, 2, 10, 200}]
    masks = spark.createDataFrame([(k, sum(1 << b for b, s in enumerate(sets) if k in s)) for k in set().union(*sets)], "key long, mask long")
    steps = spark.createDataFrame([(b, f"s{b}") for b in range(len(sets))], "bit int, name string")
    got = {r.name: (r.traces, r.success, r.short, r.collision) for r in tracing.mask_shares(approach, tail, masks, steps).collect()}
    for b, s in enumerate(sets):
        positive = spark.createDataFrame([(k,) for k in s], "key long")
        row = tracing.outcomes(tracing.replay(hops, positive)).first()
        assert got[f"s{b}"] == (row.traces, row.success, row.short, row.collision)
