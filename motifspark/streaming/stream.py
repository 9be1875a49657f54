"""Pattern support over event streams: windows as cases, and running state of open cases."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from motifspark.functions.columns import contains_expr
from motifspark.plans.tree import Tree, parse_tree

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def stream_events(spark: SparkSession, folder: str, files_per_trigger: int = 1, schema: str = EVENTS) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def case_window(kind: str = "tumbling", size: str = "7 days", slide: str | None = None, gap: str = "1 day", ts: str = "ts") -> Column:
    return F.session_window(ts, gap) if kind == "session" else F.window(ts, size, slide if kind == "sliding" else None)


def stream_log(events: DataFrame, key: str, activity: str, order: list[str], watermark: str = "1 day", **window) -> DataFrame:
    """Cases out of windows per key: ``case_id, window_start, acts, n, weight``. Rows later than the watermark are dropped by
    Spark and counted in its progress metrics. Works on batch tables alike, where the watermark has no effect."""
    held = events.withWatermark("ts", watermark).where(F.col(activity).isNotNull())
    one = F.struct(*order, F.col(activity).alias("act"))
    cases = held.groupBy(case_window(**window).alias("w"), F.col(key)).agg(F.array_sort(F.collect_list(one)).alias("es"))
    acts = F.transform("es", lambda e: e["act"])
    start = F.col("w.start")
    return cases.select(F.concat_ws("|", F.col(key).cast("string"), start.cast("string")).alias("case_id"), start.alias("window_start"), acts.alias("acts"), F.size(acts).alias("n"), F.lit(1).cast("long").alias("weight"))


def stream_support(cases: DataFrame, trees: list[Tree | str]) -> DataFrame:
    """``case_id, window_start`` and one flag per tree; append mode passes it on to any sink."""
    return cases.select("case_id", "window_start", *[contains_expr(t).alias(f"hit{i}") for i, t in enumerate(trees)])


def merge_counts(store: dict[tuple[str, str], list[int]], trees: list[str]):
    """A ``foreachBatch`` sink that adds up hits and cases by window in a dictionary of the driver (one entry per window)."""

    def sink(batch: DataFrame, _: int) -> None:
        sums = [F.sum(F.col(f"hit{i}").cast("long")).alias(f"h{i}") for i in range(len(trees))]
        for r in batch.groupBy("window_start").agg(F.count("*").alias("n"), *sums).collect():
            for i, t in enumerate(trees):
                held = store.setdefault((str(r["window_start"]), t), [0, 0])
                held[0] += r[f"h{i}"]
                held[1] += r["n"]

    return sink


def distinct_events(events: DataFrame, watermark: str = "1 day") -> DataFrame:
    """Events without those that repeat an id within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


class Progress:
    """Earliest match of one tree, advanced event by event; ``ends`` holds the end of each node, 0 while it has none."""

    def __init__(self, tree: Tree):
        self.program: list[tuple] = []
        self._add(tree)

    def _add(self, t: Tree) -> int:
        if t.is_leaf:
            self.program.append(("leaf", t.label))
        else:
            parts = (t.left, t.right) if t.op != "loop" else (t.left, t.right, t.left)
            self.program.append((t.op, tuple(self._add(p) for p in parts)))
        return len(self.program) - 1

    def advance(self, ends: list[int], activity: str, pos: int) -> None:
        def step(i: int, start: int) -> int:
            op, arg = self.program[i]
            if ends[i]:
                return ends[i]
            if op == "leaf":
                ends[i] = pos if arg == activity and pos > start else 0
            elif op in ("seq", "loop"):
                at = start
                for j in arg:
                    at = step(j, at)
                    if not at:
                        break
                ends[i] = at
            else:
                got = [step(j, start) for j in arg]
                ends[i] = max(got) * all(got) if op == "and" else min((g for g in got if g), default=0)
            return ends[i]

        step(len(self.program) - 1, 0)


def open_cases(events: DataFrame, key: str, activity: str, order: list[str], trees: list[Tree | str], idle_ms: int | None = None) -> DataFrame:
    """Running state per key: ``key, tree, pos`` whenever a tree is completed, at the place of the completing event.

    State is one number per node of the trees, whatever the length of the case; events of a trigger are taken in order
    and must not be older than those of earlier triggers. With ``idle_ms`` a key without events for so long is forgotten.
    """
    own = [parse_tree(t) if isinstance(t, str) else t for t in trees]
    machines = [Progress(t) for t in own]

    def run(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        n, flat = state.get if state.exists else (0, [0] * sum(len(m.program) for m in machines))
        ends, at = [], 0
        for m in machines:
            ends.append(list(flat[at : at + len(m.program)]))
            at += len(m.program)
        done = []
        for row in pd.concat(frames).sort_values(order)[activity]:
            n += 1
            for t, m, e in zip(own, machines, ends, strict=True):
                if not e[-1]:
                    m.advance(e, row, n)
                    if e[-1]:
                        done.append((str(k[0]), str(t), n))
        state.update((n, [x for e in ends for x in e]))
        if idle_ms:
            state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame(done, columns=["key", "tree", "pos"])

    grouped = events.select(key, activity, *[o for o in order if o not in (key, activity)]).groupBy(key)
    return grouped.applyInPandasWithState(run, "key string, tree string, pos bigint", "n bigint, ends array<bigint>", "append", GroupStateTimeout.ProcessingTimeTimeout if idle_ms else GroupStateTimeout.NoTimeout)
