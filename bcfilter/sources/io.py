"""Readers, writers, SQL registration, a Python data source and a table function for filters."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.hashing import LINEAR, FilterSpec, P


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """Files of a format; text formats want a schema, nothing is inferred."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    r = spark.read.format(fmt).options(**options)
    return (r.schema(schema) if schema else r).load(path)


def write(df: DataFrame, fmt: str, path: str, mode: str = "overwrite", partition_by: list[str] | None = None, **options) -> None:
    w = df.write.format(fmt).mode(mode).options(**options)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def register_sql(spark: SparkSession, prefix: str, pos: DataFrame, spec: FilterSpec) -> None:
    """SQL functions ``<prefix>_positions(key)`` (SQL, linear family) and ``<prefix>_contains(positions)`` (Arrow UDF)."""
    from ..operators.filters import contains_udf, packed_bits

    if spec.family != "linear":
        raise ValueError("the SQL form is that of the linear family")
    each = ", ".join(f"pmod(pmod({a}L * pmod(key + 1, {P}L) + {b}, {P}L), {spec.m}L) + 1" for a, b in LINEAR[: spec.k])
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {prefix}_positions(key BIGINT) RETURNS ARRAY<BIGINT> RETURN array({each})")
    spark.udf.register(f"{prefix}_contains", contains_udf(spark, packed_bits(pos, spec)))


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _KeyReader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.m, self.k = (int(options.get(x, d)) for x, d in (("n", 1000), ("m", 10000), ("k", 3)))

    def partitions(self):
        step = max(1, -(-self.n // 8))
        return [_Range(a, min(self.n, a + step)) for a in range(0, self.n, step)]

    def read(self, part):
        for key in range(part.lo, part.hi):
            yield key, [((a * ((key + 1) % P) + b) % P) % self.m + 1 for a, b in LINEAR[: self.k]]


class FilterKeys(DataSource):
    """Generator of integer keys with their positions: ``spark.read.format("filter_keys")``, options n, m, k."""

    @classmethod
    def name(cls):
        return "filter_keys"

    def schema(self):
        return "key bigint, positions array<bigint>"

    def reader(self, schema):
        return _KeyReader(self.options)


def positions_udtf():
    """Table function (key, m, k) -> (j, pos)."""

    @F.udtf(returnType="j int, pos bigint")
    class Positions:
        def eval(self, key: int, m: int, k: int):
            if key is not None:
                for j, (a, b) in enumerate(LINEAR[:k]):
                    yield j + 1, ((a * ((key + 1) % P) + b) % P) % m + 1

    return Positions
