"""Event logs: one row per case with its ordered activities."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifspark.sources.shared import durable as store  # noqa: F401

LOG = "case_id string, acts array<string>, n int, weight bigint"


def build_log(events: DataFrame, case: list[Column | str], order: list[Column | str], activity: Column | str) -> DataFrame:
    """``case_id, acts, n, weight`` of an event table.

    One shuffle by case carries the order columns and the label alone. Events without an activity are left out; cases
    are named by their parts joined with ``|``; ties in the order fall to the label, so a log is always the same.
    """
    as_col = lambda c: F.col(c) if isinstance(c, str) else c
    parts = [as_col(c).alias(f"c{i}") for i, c in enumerate(case)]
    keys = [f"c{i}" for i in range(len(case))]
    one = F.struct(*[as_col(c).alias(f"o{i}") for i, c in enumerate(order)], as_col(activity).cast("string").alias("act"))
    rows = events.select(*parts, one.alias("e")).where("e.act is not null")
    held = rows.groupBy(*keys).agg(F.array_sort(F.collect_list("e")).alias("es"))
    acts = F.transform("es", lambda e: e["act"])
    return held.select(F.concat_ws("|", *[F.col(k).cast("string") for k in keys]).alias("case_id"), acts.alias("acts")).select(
        "case_id", "acts", F.size("acts").alias("n"), F.lit(1).cast("long").alias("weight")
    )


def dropped_events(events: DataFrame, activity: str) -> int:
    """Events that :func:`build_log` leaves out."""
    return events.where(F.col(activity).isNull()).count()


def variants(log: DataFrame) -> DataFrame:
    """One row per distinct sequence with the number of its cases as weight; supports stay the same."""
    held = log.groupBy("acts").agg(F.sum("weight").alias("weight"), F.min("case_id").alias("case_id"))
    return held.select("case_id", "acts", F.size("acts").alias("n"), "weight")


def activities(log: DataFrame) -> DataFrame:
    """``activity, n_cases`` over the cases that hold it."""
    each = log.select("weight", F.explode(F.array_distinct("acts")).alias("activity"))
    return each.groupBy("activity").agg(F.sum("weight").alias("n_cases"))


def project_log(log: DataFrame, keep: list[str]) -> DataFrame:
    """The log restricted to some activities; cases without any of them stay, with no events."""
    wanted = F.array(*[F.lit(a) for a in keep])
    acts = F.filter("acts", lambda a: F.array_contains(wanted, a))
    return log.withColumn("acts", acts).withColumn("n", F.size("acts"))


def sample_cases(log: DataFrame, mod: int, keep: int) -> DataFrame:
    """Cases whose hashed id falls into the first ``keep`` of ``mod`` classes."""
    return log.where(F.pmod(F.xxhash64("case_id"), F.lit(mod)) < keep)


def filter_log(log: DataFrame, min_length: int = 1, must_have: list[str] | None = None, case_like: str | None = None) -> DataFrame:
    out = log.where(F.col("n") >= min_length)
    for a in must_have or ():
        out = out.where(F.array_contains("acts", a))
    return out.where(F.col("case_id").like(case_like)) if case_like else out


def directly_follows(log: DataFrame) -> DataFrame:
    """``a, b, n``: how often b comes right after a; pairs are made within rows and summed before the shuffle."""
    pairs = F.expr("case when size(acts) > 1 then arrays_zip(slice(acts, 1, size(acts) - 1), slice(acts, 2, size(acts) - 1)) end")
    each = log.select("weight", F.explode(pairs).alias("p")).select("weight", F.col("p.0").alias("a"), F.col("p.1").alias("b"))
    return each.groupBy("a", "b").agg(F.sum("weight").alias("n"))


def check_unique_cases(log: DataFrame) -> int:
    """Number of case ids that occur more than once; zero in a valid log."""
    return log.groupBy("case_id").count().where("count > 1").count()


def index_positions(log: DataFrame) -> DataFrame:
    """Adds ``post``: a map of each activity to its places, in increasing order."""
    posts = F.map_from_arrays(
        F.array_distinct("acts"),
        F.transform(F.array_distinct("acts"), lambda a: F.filter(F.transform("acts", lambda x, i: F.when(x == a, i + 1)), lambda p: p.isNotNull())),
    )
    return log.withColumn("post", posts)


def empty_log(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], LOG)
