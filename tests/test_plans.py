"""Physical plans: pruned scans, pushed filters, built-in expressions on the hot paths, no task that takes all rows."""

import pytest
from pyspark.sql import functions as F

from bcfilter import registry
from bcfilter.functions.hashing import FilterSpec, hashed
from bcfilter.operators import clearing, filters


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_scan_reads_only_what_is_asked(spark, sf):
    p = plan(registry.QUERIES["scan_orders"](spark, sf))
    assert "ReadSchema: struct<o_orderkey:bigint,o_orderpriority:string>" in p


def test_range_predicates_reach_the_scan(spark, sf):
    p = plan(registry.QUERIES["pred_range"](spark, sf))
    assert "PushedFilters: [IsNotNull(o_" in p and "o_custkey" not in p and "o_orderpriority" not in p


@pytest.mark.parametrize("family", ["linear", "md5", "xxhash", "double", "blocked"])
def test_positions_stay_in_the_jvm(spark, family):
    df = hashed(spark.range(10).withColumnRenamed("id", "key"), FilterSpec(1000, 2, family, blocks=4))
    assert "Python" not in plan(df) and "Arrow" not in plan(df)


def test_build_and_staged_probe_are_native_and_combine_before_the_shuffle(spark):
    keys = spark.range(1000).withColumnRenamed("id", "key")
    spec = FilterSpec(5000, 3)
    pos = filters.build_positions(keys, spec)
    p = plan(pos)
    assert p.count("HashAggregate(keys=[pos") == 2 and p.count("Exchange") == 1 and "Python" not in p
    assert "Python" not in plan(filters.probe_negative(keys, pos, spec)) and "CartesianProduct" not in plan(filters.probe_negative(keys, pos, spec))


def test_choice_is_native_and_counts_only_touched_positions(spark):
    spec = FilterSpec(500, 2)
    a = hashed(spark.range(100).withColumnRenamed("id", "key"), spec)
    b = hashed(spark.range(200, 220).withColumnRenamed("id", "key"), spec).withColumn("ord", F.col("key") - 199)
    p = plan(clearing.choose(b, "ratio", a, b))
    assert "Python" not in p and "LeftSemi" in p and "SinglePartition" not in p


def test_numbering_has_no_task_for_all_rows(spark):
    df = clearing.numbered(spark.range(1000).withColumnRenamed("id", "key"), [F.col("key").desc()])
    assert "SinglePartition" not in plan(df)


@pytest.mark.parametrize("name", ["fig_fp_curves", "fn_interval", "size_best_k", "size_for_target", "size_fp_count", "size_fp_rate"])
def test_sizes_and_intervals_come_from_a_given_table(spark, sf, name):
    assert any(f.endswith("orders.parquet") for f in registry.QUERIES[name](spark, sf).inputFiles())


def test_cost_model_is_that_of_the_filter_over_the_given_keys(spark, sf, duck):
    got = sorted(map(tuple, registry.QUERIES["m_cost_model"](spark, sf).collect()))
    assert got == sorted(duck.execute(registry.ORACLE_SQL["m_cost_model"]).fetchall())
    n = spark.read.parquet(f"{sf}/orders.parquet").where("o_orderpriority = '1-URGENT'").count()
    b, m = next(r[2] for r in got if r[:2] == ("random", "frozen")) // 3, 5 * n
    assert ("min_fn", "frozen", 3 * (n + b), 4 * m + b) in got
