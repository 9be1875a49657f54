"""Relational helpers around event logs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from motifspark.functions.columns import contains_expr
from motifspark.plans.tree import Tree


def attach_labels(events: DataFrame, dim: DataFrame, key: str, dim_key: str, label: str, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Events with a dimension's label; the dimension is broadcast only if its counted rows stay within the bound."""
    own = dim.select(F.col(dim_key).alias(key), F.col(label).alias("activity"))
    return events.join(F.broadcast(own) if own.count() <= broadcast_rows else own, key)


def positions(events: DataFrame, case: list[str], order: list[str]) -> DataFrame:
    """Adds ``pos``, the 1-based place of an event in its case."""
    return events.withColumn("pos", F.row_number().over(Window.partitionBy(*case).orderBy(*order)))


def next_after(placed: DataFrame, a: str, b: str) -> DataFrame:
    """``case_id, pos_a, pos_b``: for each event ``a`` the first ``b`` after it (null if none), by one running minimum."""
    later = Window.partitionBy("case_id").orderBy("pos").rowsBetween(1, Window.unboundedFollowing)
    found = placed.withColumn("pos_b", F.min(F.when(F.col("activity") == b, F.col("pos"))).over(later))
    return found.where(F.col("activity") == a).select("case_id", F.col("pos").alias("pos_a"), "pos_b")


def sessionize(events: DataFrame, key: str, ts: str, order: list[str], gap_seconds: int) -> DataFrame:
    """Adds ``session_no``, counted up from 1 at each gap of more than ``gap_seconds``."""
    w = Window.partitionBy(key).orderBy(*order)
    micros = F.unix_micros(F.col(ts).cast("timestamp"))
    gap = micros - F.lag(micros).over(w)
    new = F.when(gap.isNull() | (gap > gap_seconds * 1_000_000), 1).otherwise(0)
    return events.withColumn("new", new).withColumn("session_no", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("new")


def hits(log: DataFrame, tree: Tree | str) -> DataFrame:
    """Ids of the cases that exhibit a tree."""
    return log.where(contains_expr(tree)).select("case_id")


def hits_union(log: DataFrame, a: Tree | str, b: Tree | str) -> DataFrame:
    return hits(log, a).union(hits(log, b)).distinct()


def hits_intersect(log: DataFrame, a: Tree | str, b: Tree | str) -> DataFrame:
    return hits(log, a).intersect(hits(log, b))


def hits_except(log: DataFrame, a: Tree | str, b: Tree | str) -> DataFrame:
    return hits(log, a).subtract(hits(log, b))


def support_by(log: DataFrame, trees: list[Tree | str], keys: list[str], mode: str = "group") -> DataFrame:
    """Counts of trees by grouping columns of the log: ``group``, ``rollup`` or ``cube``."""
    flags = [contains_expr(t) for t in trees]
    grouped = {"group": log.groupBy, "rollup": log.rollup, "cube": log.cube}[mode](*keys)
    sums = [F.sum(F.when(f, F.col("weight")).otherwise(0)).alias(f"n{i}") for i, f in enumerate(flags)]
    out = grouped.agg(F.sum("weight").alias("n_cases"), *sums)
    rows = F.array(*[F.struct(F.lit(str(t)).alias("tree"), F.col(f"n{i}").alias("n_hits")) for i, t in enumerate(trees)])
    return out.select(*keys, "n_cases", F.inline(rows))


def interval_pairs(occ: DataFrame, condition: Column) -> DataFrame:
    """Pairs of occurrences of different patterns within a case under a condition on ``a.lo, a.hi, b.lo, b.hi``."""
    a, b = occ.alias("a"), occ.alias("b")
    met = a.join(b, (F.col("a.case_id") == F.col("b.case_id")) & (F.col("a.pid") != F.col("b.pid")) & condition)
    return met.select(F.col("a.case_id").alias("case_id"), F.col("a.pid").alias("src"), F.col("b.pid").alias("dst"))


def relation_matrix(edges: DataFrame, kinds: tuple[str, ...]) -> DataFrame:
    """One row per pair of patterns, one column per kind of relation."""
    return edges.groupBy("src", "dst").pivot("kind", list(kinds)).agg(F.first("support"))


def top_patterns(patterns: DataFrame, n: int, within: str | None = None) -> DataFrame:
    """The ``n`` patterns of highest count, ties by tree, over all or within each value of a column."""
    if within is None:
        return patterns.orderBy(F.desc("n_hits"), "tree").limit(n)
    rank = F.row_number().over(Window.partitionBy(within).orderBy(F.desc("n_hits"), "tree"))
    return patterns.withColumn("rank", rank).where(F.col("rank") <= n)


def not_in(df: DataFrame, other: DataFrame, key: str) -> DataFrame:
    """Rows whose key is not in the other table; null equals null."""
    return df.join(other.select(F.col(key).alias("k")), F.col(key).eqNullSafe(F.col("k")), "left_anti")
