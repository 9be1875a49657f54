"""Event logs in files: CSV, JSON and XES in, Parquet out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifspark.operators.log import build_log


def read_log_csv(spark: SparkSession, path: str, case: str, order: str, activity: str, order_type: str = "timestamp") -> DataFrame:
    """Log of a CSV file with a header; only the three named columns are read."""
    raw = spark.read.option("header", True).csv(path)
    return build_log(raw.select(case, F.col(order).cast(order_type).alias(order), activity), [case], [order], activity)


def read_log_json(spark: SparkSession, path: str, case: str, order: str, activity: str, order_type: str = "timestamp") -> DataFrame:
    schema = f"`{case}` string, `{order}` string, `{activity}` string"
    raw = spark.read.schema(schema).json(path)
    return build_log(raw.withColumn(order, F.col(order).cast(order_type)), [case], [order], activity)


_PAIR = "array<struct<_key:string,_value:string>>"
_XES = f"string {_PAIR}, event array<struct<string:{_PAIR},date:{_PAIR}>>"


def read_log_xes(spark: SparkSession, path: str) -> DataFrame:
    """Log of an XES file by the XML source: ``concept:name`` names cases and activities, events keep their order."""
    raw = spark.read.format("xml").option("rowTag", "trace").schema(_XES).load(path)
    name = lambda pairs: F.element_at(F.filter(pairs, lambda p: p["_key"] == "concept:name"), 1)["_value"]
    rows = raw.select(name(F.col("string")).alias("case"), F.posexplode("event").alias("pos", "e"))
    return build_log(rows.select("case", "pos", name(F.col("e.string")).alias("activity")), ["case"], ["pos"], "activity")


def save_patterns(patterns: DataFrame, path: str) -> None:
    patterns.write.mode("overwrite").partitionBy("n_leaves").parquet(path)


def save_traces(log: DataFrame, table: str, buckets: int = 64) -> None:
    """The log as a table bucketed by case, so that later joins by case need no shuffle."""
    log.write.mode("overwrite").bucketBy(buckets, "case_id").sortBy("case_id").saveAsTable(table)


def save_graph(document: DataFrame, path: str) -> None:
    document.select("json").write.mode("overwrite").text(path)
