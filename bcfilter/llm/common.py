"""Shared folder, materialised tables and word rules used by the operators of this subpackage."""

from __future__ import annotations

import tempfile
import threading
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word: a run of characters that are not ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"

_LOCAL: list[str] = []
_RECORDS: list[list] = []
#: Rows that a Python worker gets at once inside ``small_batches``; it holds a batch of whole texts twice over.
BATCH_ROWS = 1000
_BATCHES: dict[int, tuple[int, str]] = {}
_BATCHES_LOCK = threading.Lock()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a local one of our own only where the session names none."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    if not _LOCAL:
        _LOCAL.append("file://" + tempfile.mkdtemp(prefix="bcf_shared_"))
    return _LOCAL[0]


def new_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/{tag}_{uuid.uuid4().hex}"


def materialize(df: DataFrame, tag: str = "table") -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends in files that outlive an executor."""
    spark = df.sparkSession
    path = new_path(spark, tag)
    df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back.bcf_path = path
    if _RECORDS:
        _RECORDS[-1].append(back)
    return back


@contextmanager
def recorded(tables: list):
    """Tables that are materialised inside are also put on the list, for their owner to drop."""
    _RECORDS.append(tables)
    try:
        yield
    finally:
        _RECORDS.pop()


@contextmanager
def small_batches(spark: SparkSession, rows: int = BATCH_ROWS):
    """What runs inside hands Python workers at most ``rows`` rows at once; then the session's own setting returns.

    Threads that share a session share the setting; the last of them to leave restores it.
    """
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    with _BATCHES_LOCK:
        inside, own = _BATCHES.get(id(spark), (0, spark.conf.get(key)))
        if not inside and not 0 < int(own) <= rows:
            spark.conf.set(key, rows)
        _BATCHES[id(spark)] = inside + 1, own
    try:
        yield
    finally:
        with _BATCHES_LOCK:
            inside, own = _BATCHES.pop(id(spark))
            if inside > 1:
                _BATCHES[id(spark)] = inside - 1, own
            else:
                spark.conf.set(key, own)


def drop_table(df: DataFrame) -> None:
    """Remove the files of a table written by ``materialize`` once nothing reads it any more."""
    path = getattr(df, "bcf_path", None)
    if path:
        spark = df.sparkSession
        jvm = spark._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(p, True)


def word_count(text) -> F.Column:
    """Words of a text; null counts none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def text_key(text) -> F.Column:
    """128-bit digest that is equal exactly for equal texts; null has a value of its own."""
    return F.coalesce(F.md5(text.cast("binary")), F.lit("null"))


def lookup(spark: SparkSession, rows: list, schema, most: int = 200_000) -> DataFrame:
    """A table of rows the driver holds, broadcast while it has at most ``most`` rows and joined by shuffle beyond."""
    df = spark.createDataFrame(rows, schema)
    return F.broadcast(df) if len(rows) <= most else df
