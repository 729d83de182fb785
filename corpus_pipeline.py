"""Five-stage corpus pipeline; each stage reads what the one before kept.

Language identification drops what it rejects; of each group of near-duplicates one document stays; documents that
leak a benchmark item go; the mix repeats or drops documents so that sources meet their target weights; the last stage
deals what is left into shards. A stage's result is to be
written before the next stage is called, as ``run`` does: it writes each stage's rows as Parquet in the shared folder
and reads them back.
"""

from __future__ import annotations

import threading
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bcfilter.llm.common import drop_table, materialize, recorded, small_batches, table
from bcfilter.llm.decontaminate import leaks
from bcfilter.llm.language import identify_documents
from bcfilter.llm.minhash import near_duplicates
from bcfilter.llm.mixing import mix
from bcfilter.llm.sharding import shard_documents

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


class _Scratch(threading.local):
    """Tables in the shared folder that the last stage of this thread's run left; each thread runs its own pipeline."""

    def __init__(self):
        self.tables: list = []

    def clear(self) -> list:
        while self.tables:
            drop_table(self.tables.pop())
        return self.tables


_SCRATCH = _Scratch()


def _stage(f):
    """Drops what the stage before left in the shared folder, for its result is written by then, and notes its own.

    The stages' Python workers are reused, so one stage's largest batch stays in memory through the next: batches are small.
    """

    @wraps(f)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        with recorded(_SCRATCH.clear()), small_batches(spark):
            return f(spark, docs, sf_dir)

    return run_stage


#: Ids to be dropped that are broadcast at most; beyond, texts and ids meet by shuffle.
MOST_BROADCAST_IDS = 500_000


def _keyed(docs: DataFrame, ordered: bool = False) -> DataFrame:
    """Written rows with a key of their own as ``doc_id`` and the id they came with as ``own_id``.

    ``ordered`` makes keys rise with the id (null last), then with the text's hash, for operators that keep the least.
    """
    rows = docs.select(*COLUMNS).withColumnRenamed("doc_id", "own_id")
    if ordered:
        rows = rows.withColumn("tie", F.monotonically_increasing_id())
        rows = rows.orderBy(F.col("own_id").asc_nulls_last(), F.xxhash64("text"), "tie").drop("tie")
    return materialize(rows.withColumn("doc_id", F.monotonically_increasing_id()), "keyed")


def _plain(rows: DataFrame) -> DataFrame:
    """Rows with the id they came with."""
    return rows.select(F.col("own_id").alias("doc_id"), *COLUMNS[1:])


def _without(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """Keyed rows whose key is not among ``ids``, few of which a stage is expected to drop."""
    gone = materialize(ids.select(F.col("doc_id").alias("gone")).distinct(), "gone_ids")
    few = gone.count() <= MOST_BROADCAST_IDS
    return _plain(docs.join(F.broadcast(gone) if few else gone, docs["doc_id"] == F.col("gone"), "left_anti"))


@_stage
def keep_identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose language is known."""
    docs = _keyed(docs)
    return _without(docs, identify_documents(docs).where(~F.col("kept")))


@_stage
def keep_one_of_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The row of least doc_id (null last) of each group at 0.8 on five words; rows without words are in no group."""
    docs = _keyed(docs, ordered=True)
    found = near_duplicates(docs, size=5, percent=80)
    return _without(docs, found.where(~F.col("kept")))


@_stage
def keep_clean_of_benchmarks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows without a benchmark leak."""
    docs = _keyed(docs)
    return _without(docs, leaks(docs, table(spark, sf_dir, "benchmark")))


@_stage
def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as the mix takes it (never, once or twice)."""
    docs = _keyed(docs)
    copies = mix(docs).select(F.col("doc_id").alias("chosen"), "copies").where("copies > 0")
    taken = docs.join(copies, docs["doc_id"] == F.col("chosen"))
    return _plain(taken.withColumn("copy", F.explode(F.sequence(F.lit(1), "copies"))))


def deal_shards(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row with its shard and slot."""
    _SCRATCH.clear()
    return shard_documents(docs)


STAGES = [
    ("language", keep_identified),
    ("near duplicates", keep_one_of_near_duplicates),
    ("decontamination", keep_clean_of_benchmarks),
    ("mixing", mix_sources),
    ("sharding", deal_shards),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        before, docs = docs, stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = materialize(docs, f"stage_{k}")
            drop_table(before)
    return docs
