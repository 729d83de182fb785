"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line with seconds and rates."""

import json
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)
os.environ["PYTHONPATH"] = HERE + os.pathsep + os.environ.get("PYTHONPATH", "")

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
QUERIES = (
    "bf_positions bf_bitmap bf_blocked bf_probe_broadcast bf_probe_shuffle bf_probe_negative clear_random clear_min_fn clear_max_fp clear_ratio clear_ratio_live "
    "w_sim_table_ratio w_trace_success w_trace_beta_sweep w_contamination w_join_prefilter join_prefilter_exact"
).split()


def replica(spark):
    """The published simulation at its own size: 2,000,000 keys, 10,000 members, 100,000 bits, 5 hashes, all betas."""
    from pyspark.sql import functions as F

    from bcfilter.functions.hashing import FilterSpec, hashed
    from bcfilter.operators import clearing
    from bcfilter.plans.base import Setting
    from bcfilter.plans.workloads import BETAS, sweep
    from bcfilter.sources.tables import written

    u = spark.range(2_000_000).withColumnRenamed("id", "key")
    spec = FilterSpec(100_000, 5, "xxhash")
    at = time.time()
    a = written(u.orderBy(F.xxhash64("key")).limit(10_000), "a")
    fp = written(clearing.false_positives(u, a, spec), "fp")
    probe = time.time() - at
    s = Setting(u, hashed(a, spec), fp, spec, 10_000, 2_000_000, fp.count())
    chi, took = {}, {}
    for rule in clearing.RULES:
        at = time.time()
        chi[rule] = {str(r.beta): r.chi for r in sweep(s, rule, BETAS).collect()}
        took[rule] = round(time.time() - at, 3)
    return {"probe_s": round(probe, 3), "probes_per_s": round(1_990_000 / probe), "false_positives": s.n_fp, "sweep_s": took, "chi": chi}


def main() -> None:
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from bcfilter import registry

    spark.range(1000).selectExpr("sum(id)").collect()
    times = {}
    for name in QUERIES:
        at = time.time()
        registry.QUERIES[name](spark, SF_DIR).write.format("noop").mode("overwrite").save()
        times[name] = round(time.time() - at, 3)
    keys = spark.read.parquet(f"{SF_DIR}/orders.parquet").count()
    rates = {f"{n}_keys_per_s": round(keys / times[n]) for n in ("bf_probe_broadcast", "bf_probe_shuffle", "bf_probe_negative")}
    out = {"metric": "total_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "rates": rates, "replica": replica(spark), "sf": os.path.basename(SF_DIR.rstrip("/"))}
    print(json.dumps(out))


if __name__ == "__main__":
    main()
