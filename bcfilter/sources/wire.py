"""Filter files and wire format: a header with the specification and 4 KiB rows, compressed or not; versioned."""

from __future__ import annotations

import json
import zlib

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import FilterSpec

VERSION = 1
MAGIC = b"BCF1"


def _header(spec: FilterSpec, compress: bool = False) -> str:
    return json.dumps({"version": VERSION, "m": spec.m, "k": spec.k, "family": spec.family, "seed": spec.seed, "blocks": spec.blocks, "compress": compress}, sort_keys=True)


def spec_of(header: str) -> FilterSpec:
    h = json.loads(header)
    if h["version"] != VERSION:
        raise ValueError(f"filter version {h['version']} is not {VERSION}")
    return FilterSpec(h["m"], h["k"], h["family"], h["seed"], h["blocks"])


def save(bitmap: DataFrame, spec: FilterSpec, path: str) -> None:
    """Bitmap rows and a one-row header side by side."""
    bitmap.write.mode("overwrite").parquet(f"{path}/bits")
    bitmap.sparkSession.createDataFrame([(_header(spec),)], "header string").coalesce(1).write.mode("overwrite").parquet(f"{path}/header")


def load(spark: SparkSession, path: str) -> tuple[DataFrame, FilterSpec]:
    spec = spec_of(spark.read.parquet(f"{path}/header").first()[0])
    return spark.read.schema("bucket long, bits binary").parquet(f"{path}/bits"), spec


def encode(bitmap: DataFrame, spec: FilterSpec, compress: bool = False) -> DataFrame:
    """One message for each bitmap row: magic, header length, header, bucket, payload."""
    header = _header(spec, compress).encode()

    @F.pandas_udf("binary")
    def pack(bucket: pd.Series, bits: pd.Series) -> pd.Series:
        lead = MAGIC + len(header).to_bytes(4, "big") + header
        return pd.Series([lead + int(b).to_bytes(8, "big") + (zlib.compress(bytes(x)) if compress else bytes(x)) for b, x in zip(bucket, bits)])

    return bitmap.select(pack("bucket", "bits").alias("message"))


def decode(messages: DataFrame) -> DataFrame:
    """(bucket, bits) of messages; a wrong magic or version fails."""

    def run(batches):
        for rows in batches:
            out = []
            for m in rows["message"]:
                m = bytes(m)
                if m[:4] != MAGIC:
                    raise ValueError("no filter message")
                n = int.from_bytes(m[4:8], "big")
                spec_of(m[8 : 8 + n].decode())
                body = m[16 + n :]
                out.append((int.from_bytes(m[8 + n : 16 + n], "big"), zlib.decompress(body) if json.loads(m[8 : 8 + n])["compress"] else body))
            yield pd.DataFrame(out, columns=["bucket", "bits"])

    return messages.mapInPandas(run, "bucket long, bits binary")
