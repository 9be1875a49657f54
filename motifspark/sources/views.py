"""Log views over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifspark.operators.log import build_log


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _events(spark: SparkSession, sf_dir: str, case: list[Column], activity: Column) -> DataFrame:
    return build_log(load_table(spark, sf_dir, "events"), [F.col("user_id"), *case], ["ts", "event_id"], activity)


def _week() -> Column:
    return F.date_format(F.date_trunc("week", "ts"), "yyyy-MM-dd")


def banded() -> Column:
    band = F.when(F.col("value") < 20, "lo").when(F.col("value") < 60, "mid").otherwise("hi")
    return F.concat_ws("-", "event_type", band)


def log_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _events(spark, sf_dir, [], F.col("event_type"))


def log_user_rich(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _events(spark, sf_dir, [], F.when(F.col("event_type").isNotNull(), banded()))


def log_user_week(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _events(spark, sf_dir, [_week()], F.col("event_type"))


def log_user_3day(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _events(spark, sf_dir, [F.floor(F.datediff(F.col("ts"), F.lit("2024-01-01")) / 3)], F.col("event_type"))


def log_user_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _events(spark, sf_dir, [F.date_format("ts", "yyyy-MM-dd")], F.col("event_type"))


def log_user_week_rich(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _events(spark, sf_dir, [_week()], banded())


def _orders(spark: SparkSession, sf_dir: str, activity: Column, where: str | None = None) -> DataFrame:
    orders = load_table(spark, sf_dir, "orders")
    return build_log(orders.where(where) if where else orders, ["o_custkey"], ["o_orderdate", "o_orderkey"], activity)


def log_cust_status(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _orders(spark, sf_dir, F.col("o_orderstatus"))


def log_cust_priority(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _orders(spark, sf_dir, F.col("o_orderpriority"))


def log_cust_status_prio(spark: SparkSession, sf_dir: str, keep: int = 10) -> DataFrame:
    """Orders of the customers whose key modulo 10 is below ``keep``: 3 and 4 give the two samples."""
    return _orders(spark, sf_dir, F.concat_ws("-", "o_orderstatus", F.substring("o_orderpriority", 1, 1)), f"o_custkey % 10 < {keep}" if keep < 10 else None)


def _lines(lines: DataFrame, activity: Column) -> DataFrame:
    return build_log(lines, ["l_orderkey"], ["l_shipdate", "l_linenumber", "l_partkey", "l_suppkey"], activity)


def log_order_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _lines(load_table(spark, sf_dir, "lineitem"), F.concat("l_returnflag", "l_linestatus"))


def log_order_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part types as activities; Spark broadcasts ``part`` as long as its size allows."""
    parts = load_table(spark, sf_dir, "part").select("p_partkey", "p_type")
    lines = load_table(spark, sf_dir, "lineitem")
    return _lines(lines.join(parts, lines.l_partkey == parts.p_partkey), F.col("p_type"))


def log_conv(spark: SparkSession, sf_dir: str) -> DataFrame:
    return build_log(load_table(spark, sf_dir, "conversations"), ["conv_id"], ["turn"], "role")


def log_conv_rich(spark: SparkSession, sf_dir: str) -> DataFrame:
    size = F.least(F.floor(F.length("text") / 150), F.lit(8))
    return build_log(load_table(spark, sf_dir, "conversations"), ["conv_id"], ["turn"], F.concat_ws("-", "role", size))


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        log_user, log_user_rich, log_user_week, log_user_3day, log_user_day, log_user_week_rich, log_cust_status, log_cust_priority,
        log_cust_status_prio, log_order_lines, log_order_parts, log_conv, log_conv_rich,
    )
}
