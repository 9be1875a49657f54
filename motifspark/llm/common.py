"""Helpers shared by the training-data operators."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifspark.sources.shared import durable, new_folder, release  # noqa: F401


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(c: Column) -> Column:
    """Lower-case A-Z only; the built-in ``lower`` is used where the text is pure ASCII."""
    slow = F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.when(F.length(c) == F.octet_length(c), F.lower(c)).otherwise(slow)


def text_or_empty(c: Column) -> Column:
    return F.coalesce(c.cast("string"), F.lit(""))


def _bytes_of(c: Column, kind: T.DataType) -> Column:
    """Bytes that a value takes as a row in memory, at least."""
    if isinstance(kind, (T.StringType, T.BinaryType)):
        return F.coalesce(F.octet_length(c), F.lit(0)) + 24
    if isinstance(kind, T.ArrayType):
        each = F.transform(c, lambda x: _bytes_of(x, kind.elementType).cast("long"))
        return F.coalesce(F.aggregate(each, F.lit(0).cast("long"), lambda a, x: a + x), F.lit(0)) + 32
    if isinstance(kind, T.StructType):
        return sum((_bytes_of(c[f.name], f.dataType) for f in kind), F.lit(16))
    if isinstance(kind, T.MapType):
        return _bytes_of(F.map_keys(c), T.ArrayType(kind.keyType)) + _bytes_of(F.map_values(c), T.ArrayType(kind.valueType))
    return F.lit(8)


def measured_bytes(df: DataFrame) -> int:
    """Size of a table as rows in memory, summed over its values."""
    row = sum((_bytes_of(F.col(f"`{f.name}`"), f.dataType) for f in df.schema), F.lit(16))
    return df.agg(F.coalesce(F.sum(row.cast("long")), F.lit(0))).first()[0]


def sized_broadcast(df: DataFrame, limit_bytes: int) -> DataFrame:
    """Mark a materialised table for broadcast if its measured size stays within the limit."""
    return F.broadcast(df) if measured_bytes(df) <= limit_bytes else df


def sealed(df: DataFrame, keep: list, made: dict[str, Column]) -> DataFrame:
    """``keep`` and the columns ``made``, behind a generator of one row.

    Predicates on columns made by higher-order functions would otherwise be pushed below, with whole arrays written out
    inside their lambdas and evaluated again for every element.
    """
    return df.select(*keep, F.inline(F.array(F.struct(*[c.alias(n) for n, c in made.items()]))))
