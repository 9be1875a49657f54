"""Level-wise mining of frequent, compact and maximal patterns.

The log is read once per level by an Arrow kernel that holds a bounded block of traces at a time; what crosses the
network is one row of counters per candidate and task. ``scan`` aligns every candidate in full, ``growth`` extends the
places stored for its two seeds, ``search`` is the classical best-first alignment; all three give the same patterns.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifspark.plans.lattice import Candidate, atomic_patterns, construction_tree, next_level
from motifspark.plans.language import LanguageTooLarge, words
from motifspark.plans.seeds import seed_kinds
from motifspark.plans.tree import Tree, canonical, parse_tree

from . import kernel
from .log import activities, store, variants
from .search import align_trace

COUNTS = "i int, hits bigint, realigned bigint, reused bigint, states bigint"
PATTERNS = "pid string, tree string, depth int, n_leaves int, root string, n_hits bigint, support double, precision double, compact boolean, maximal boolean, seed1 string, seed2 string"
CELLS = 2 << 20  # places of the padded block of traces that a kernel holds at a time
ROWS = 1 << 16  # traces of such a block at most


class TooManyCandidates(RuntimeError):
    pass


@dataclass
class MiningResult:
    """``patterns``: reported ones as rows. ``frequent``: counts of all frequent trees by canonical word. ``dag``: seeds.
    ``counters``: work per level. ``log``: the coded log the miner ran on, with ``codes`` for its activities."""

    spark: SparkSession
    rows: list[tuple]
    frequent: dict[str, int]
    dag: list[tuple[str, str, str]]
    counters: list[dict]
    log: DataFrame
    codes: dict[str, int]
    n_cases: int
    wall_s: float = 0.0
    trees: list[Tree] = field(default_factory=list)

    @property
    def patterns(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, PATTERNS)

    @property
    def pattern_dag(self) -> DataFrame:
        return self.spark.createDataFrame(self.dag, "child string, parent string, op string")

    @property
    def work(self) -> DataFrame:
        schema = "level int, n_candidates bigint, n_frequent bigint, reused bigint, realigned bigint, states bigint, wall_s double"
        return self.spark.createDataFrame([tuple(c.values()) for c in self.counters], schema)

    def occurrences(self) -> DataFrame:
        return occurrences(self.log, self.trees, self.codes)


def min_count(tau: float, n: int) -> int:
    return max(1, math.ceil(tau * n - 1e-9))


def encode(log: DataFrame, compress: bool = True, max_activities: int = 10_000) -> tuple[DataFrame, dict[str, int]]:
    """The log with activities as numbers, stored once, and the dictionary (bounded: an error beyond the limit)."""
    labels = sorted(r["activity"] for r in activities(log).limit(max_activities + 1).collect())
    if len(labels) > max_activities:
        raise ValueError(f"more than {max_activities} activities")
    codes = {a: i for i, a in enumerate(labels)}
    own = variants(log) if compress else log
    values = pa.array(labels, pa.string())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            acts = b.column(1)
            coded = pa.ListArray.from_arrays(acts.offsets, pc.index_in(acts.values, value_set=values))
            yield pa.RecordBatch.from_arrays([b.column(0), coded, b.column(2)], ["case_id", "acts", "weight"])

    return store(own.select("case_id", "acts", "weight").mapInArrow(run, "case_id string, acts array<int>, weight bigint")), codes


def gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Arrow batches put together up to the size of a block, so that a kernel works on long columns."""
    held: list[pa.RecordBatch] = []
    rows = cells = 0
    for b in batches:
        held.append(b)
        rows += b.num_rows
        cells += len(b.column(b.schema.get_field_index("acts")).values)
        if rows >= ROWS or cells >= CELLS:
            yield pa.concat_batches(held)
            held, rows, cells = [], 0, 0
    if held:
        yield pa.concat_batches(held)


def blocks(batch: pa.RecordBatch, columns: list[str]) -> Iterator[tuple[np.ndarray, list[pa.Array]]]:
    """The coded traces of a batch as padded matrices of bounded size, traces of like length together.

    A block ends where its number of traces times the length of its longest would pass ``CELLS``; only a single trace
    may be longer than that.
    """
    lists = batch.column(batch.schema.get_field_index("acts"))
    lengths = np.diff(lists.offsets.to_numpy())
    order = np.argsort(lengths, kind="stable")
    at = 0
    while at < len(order):
        cells = np.arange(1, min(ROWS, len(order) - at) + 1) * lengths[order[at : at + ROWS]]  # grows, as lengths do
        take = max(1, int(np.searchsorted(cells, CELLS, side="right")))
        ids = pa.array(order[at : at + take])
        own = lists.take(ids)
        yield kernel.pad(own.values.to_numpy(zero_copy_only=False), own.offsets.to_numpy()), [batch.column(batch.schema.get_field_index(c)).take(ids) for c in columns]
        at += take


def _all(tr: kernel.Traces) -> tuple[np.ndarray, np.ndarray]:
    return np.arange(tr.rows), np.zeros(tr.rows, np.int32)


def _plain_counts(trees: list[Tree], codes: dict[str, int], mode: str) -> Callable:
    """Kernel that counts the hits of trees by full alignment of complete traces."""
    labels = list(codes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(trees), 4), np.int64)
        for b in gathered(batches):
            for acts, (weight,) in blocks(b, ["weight"]):
                w = weight.to_numpy()
                if mode == "search":
                    traces = [[labels[c] for c in row if c >= 0] for row in acts.tolist()]
                    for i, t in enumerate(trees):
                        found = [align_trace(t, x) for x in traces]
                        total[i, 0] += sum(int(n) for n, f in zip(w, found, strict=True) if f.hit)
                        total[i, 3] += sum(f.states for f in found)
                    continue
                tr = kernel.Traces(acts, codes)
                for i, t in enumerate(trees):
                    m = kernel.scan(tr, t, *_all(tr))
                    total[i, 0] += w[m.end < tr.far].sum()
                    total[i, 1] += tr.rows * len(m.at)
        yield _counter_batch(total)

    return run


def _counter_batch(total: np.ndarray) -> pa.RecordBatch:
    cols = [pa.array(np.arange(len(total), dtype=np.int32))] + [pa.array(total[:, j]) for j in range(4)]
    return pa.RecordBatch.from_arrays(cols, ["i", "hits", "realigned", "reused", "states"])


def _summed(log: DataFrame, run: Callable) -> dict[int, tuple[int, int, int, int]]:
    rows = log.mapInArrow(run, COUNTS).groupBy("i").agg(*[F.sum(c).alias(c) for c in ("hits", "realigned", "reused", "states")]).collect()
    return {r["i"]: (r["hits"], r["realigned"], r["reused"], r["states"]) for r in rows}


def count_trees(log: DataFrame, trees: list[Tree], codes: dict[str, int], mode: str = "scan", chunk: int = 2000) -> list[tuple[int, int, int, int]]:
    """``(hits, realigned, reused, states)`` of each tree over a coded log, one pass for every ``chunk`` trees."""
    return _in_chunks(log, trees, lambda part: _plain_counts(part, codes, mode), chunk)


def _in_chunks(log: DataFrame, items: list, kernel_of: Callable[[list], Callable], chunk: int) -> list[tuple[int, int, int, int]]:
    """Counters of all items. A log with fewer splits than the cluster has cores is read by several jobs at once, each
    with a part of the items; a large log keeps the cluster busy with one job after another."""
    cores = log.sparkSession.sparkContext.defaultParallelism
    jobs = max(1, cores // max(1, len(log.inputFiles()))) if len(items) > 200 else 1
    size = min(chunk, max(100, -(-len(items) // jobs)))
    parts = [items[at : at + size] for at in range(0, len(items), size)]
    with ThreadPoolExecutor(jobs) as pool:
        got = list(pool.map(lambda part: _summed(log, kernel_of(part)), parts))
    return [g.get(i, (0, 0, 0, 0)) for g, part in zip(got, parts, strict=True) for i in range(len(part))]


def _widths(trees: dict[str, Tree]) -> dict[str, list[kernel.Slot]]:
    return {w: kernel.slots(t) for w, t in trees.items()}


@dataclass
class Held:
    """Places of a tree by slot, over all rows of a block, and the rows in which it is matched."""

    at: dict[kernel.Slot, np.ndarray]
    hit: np.ndarray


def _unpack(maps: pa.Array, layout: dict[str, list[kernel.Slot]], rows: int) -> dict[str, Held]:
    """Stored places as columns; rows without a match hold zeros."""
    width = sum(len(s) for s in layout.values())
    flat = maps.flatten().to_numpy(zero_copy_only=False).reshape(rows, width) if width else np.zeros((rows, 0), np.int32)
    flat = np.ascontiguousarray(flat.T)
    out, at = {}, 0
    for w, own in layout.items():
        out[w] = Held({s: flat[at + k] for k, s in enumerate(own)}, flat[at] > 0)
        at += len(own)
    return out


def _grown(tr: kernel.Traces, c: Candidate, stored: dict[str, Held] | Places, work: kernel.Work, loops: str = "grown") -> Held:
    """The candidate's places out of those of its seeds."""
    one, two = stored[c.seed1], stored[c.seed2]
    m = kernel.grow(tr, c.tree, c.path, one.at, two.at, one.hit & two.hit, work, loops)
    return Held(m.at, m.end < tr.far)


def _growth_counts(cands: list[Candidate], codes: dict[str, int], layout: dict, loops: str) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(cands), 4), np.int64)
        for b in gathered(batches):
            for acts, (weight, maps) in blocks(b, ["weight", "maps"]):
                tr = kernel.Traces(acts, codes)
                _count_grown(total, cands, tr, weight.to_numpy(), _unpack(maps, layout, tr.rows), loops)
        yield _counter_batch(total)

    return run


def _count_grown(total: np.ndarray, cands: list[Candidate], tr: kernel.Traces, w: np.ndarray, stored: dict[str, Held] | Places, loops: str = "grown") -> None:
    even = w.size and (w == w[0]).all()
    for i, c in enumerate(cands):
        work = kernel.Work()
        hit = _grown(tr, c, stored, work, loops).hit
        total[i, :3] += w[0] * np.count_nonzero(hit) if even else w[hit].sum(), work.realigned, work.reused


class Places:
    """Places of frequent trees on one block of traces, grown out of those of their own seeds when first asked for.

    Within ``room`` bytes trees are held for the candidates that follow; beyond it the oldest go and are grown again if
    needed. Columns that a tree shares with its seeds are counted once for each.
    """

    def __init__(self, tr: kernel.Traces, known: dict[str, Candidate], room: int = 192 << 20):
        self.tr, self.known, self.room = tr, known, room
        self._held: dict[str, Held] = {}

    def __getitem__(self, pid: str) -> Held:
        if (own := self._held.get(pid)) is None:
            own = self._held[pid] = self._grow(pid)
            self.room -= sum(p.nbytes for p in own.at.values())
            while self.room < 0 and len(self._held) > 2:
                gone = self._held.pop(next(iter(self._held)))
                self.room += sum(p.nbytes for p in gone.at.values())
        return own

    def _grow(self, pid: str) -> Held:
        if (c := self.known.get(pid)) is None:  # an activity
            p = self.tr.table(pid)[:, 0].copy()
            return Held({(pid, ()): p}, p < self.tr.far)
        return _grown(self.tr, c, self, kernel.Work())


def _regrown_counts(cands: list[Candidate], codes: dict[str, int], known: dict[str, Candidate], loops: str) -> Callable:
    """Kernel that grows candidates out of seeds whose places are made in the task itself, so that nothing is stored
    between levels. The counters hold the work on the candidates."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(cands), 4), np.int64)
        for b in gathered(batches):
            for acts, (weight,) in blocks(b, ["weight"]):
                tr = kernel.Traces(acts, codes)
                _count_grown(total, cands, tr, weight.to_numpy(), Places(tr, known), loops)
        yield _counter_batch(total)

    return run


def ancestors(cands: list[Candidate], seeds: dict[str, Candidate]) -> dict[str, Candidate]:
    """The seeds of some candidates, their seeds, and so on; activities are left out."""
    out: dict[str, Candidate] = {}
    todo = [s for c in cands for s in (c.seed1, c.seed2)]
    while todo:
        pid = todo.pop()
        if pid in seeds and pid not in out:
            out[pid] = seeds[pid]
            todo += [seeds[pid].seed1, seeds[pid].seed2]
    return out


def _advance(kept: list[Candidate], codes: dict[str, int], before: dict, after: dict) -> Callable:
    """Kernel that replaces the stored places of one level by those of the next; rows without a match hold zeros."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for acts, (case, raw, weight, maps) in blocks(b, ["case_id", "acts", "weight", "maps"]):
                tr = kernel.Traces(acts, codes)
                stored = _unpack(maps, before, tr.rows)
                cols = []
                for c in kept:
                    own = _grown(tr, c, stored, kernel.Work())
                    cols += [np.where(own.hit, own.at[s], 0) for s in after[c.pid]]
                yield _with_maps(case, raw, weight, cols, tr.rows)

    return run


def _with_maps(case: pa.Array, acts: pa.Array, weight: pa.Array, cols: list[np.ndarray], rows: int) -> pa.RecordBatch:
    flat = np.stack(cols, axis=1).ravel() if cols else np.zeros(0, np.int32)
    offsets = np.arange(rows + 1, dtype=np.int32) * len(cols)
    maps = pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat.astype(np.int32)))
    return pa.RecordBatch.from_arrays([case, acts, weight, maps], ["case_id", "acts", "weight", "maps"])


MAPPED = "case_id string, acts array<int>, weight bigint, maps array<int>"


def _first_maps(labels: list[str], codes: dict[str, int]) -> Callable:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for acts, (case, own, weight) in blocks(b, ["case_id", "acts", "weight"]):
                tr = kernel.Traces(acts, codes)
                firsts = [tr.next(a, *_all(tr)) for a in labels]
                yield _with_maps(case, own, weight, [np.where(p < tr.far, p, 0) for p in firsts], tr.rows)

    return run


def pair_stats(log: DataFrame) -> DataFrame:
    """``a, b, n_seq, n_and, n_loop`` of all ordered pairs in one pass: pairs are made within rows from the first and
    last places of each activity and summed before the shuffle, so no case is expanded beyond its distinct activities."""
    ends = F.expr("transform(array_distinct(acts), a -> struct(a as a, array_position(acts, a) as f, size(acts) + 1 - array_position(reverse(acts), a) as l))")
    each = log.select("acts", "weight", ends.alias("e"))
    pairs = F.expr(
        """flatten(transform(e, x -> transform(filter(e, y -> y.a <> x.a), y -> struct(x.a as a, y.a as b,
             int(x.f < y.l) as s,
             int(transform(array(array_position(slice(acts, cast(x.f + 1 as int), size(acts)), y.a)), p -> p > 0 and x.l > x.f + p)[0]) as r))))"""
    )
    flat = each.select("weight", F.inline(pairs))
    return flat.groupBy("a", "b").agg(
        F.sum(F.col("weight") * F.col("s")).alias("n_seq"), F.sum("weight").alias("n_and"), F.sum(F.col("weight") * F.col("r")).alias("n_loop")
    )


def support(log: DataFrame, trees: list[Tree | str], mode: str = "scan") -> DataFrame:
    """``tree, n_hits, n_cases, support`` of given trees over a log."""
    own = [parse_tree(t) if isinstance(t, str) else t for t in trees]
    if mode != "search":
        for t in own:
            kernel.check_distinct(t)
    coded, codes = encode(log)
    n = coded.agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]
    got = count_trees(coded, own, codes, mode)
    rows = [(str(t), int(h), int(n), round(h / n, 6) if n else 0.0) for t, (h, *_) in zip(own, got, strict=True)]
    return log.sparkSession.createDataFrame(rows, "tree string, n_hits bigint, n_cases bigint, support double")


def observed_words(coded: DataFrame, trees: list[Tree], codes: dict[str, int]) -> dict[int, int]:
    """Number of distinct words with which each tree is matched, over the whole log."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, str]] = set()
        for b in gathered(batches):
            for acts, _ in blocks(b, []):
                tr = kernel.Traces(acts, codes)
                for i, t in enumerate(trees):
                    m = kernel.scan(tr, t, *_all(tr))
                    hit = m.end < tr.far
                    if hit.any():
                        seen |= {(i, " ".join(w)) for w in kernel.seen_words(t, {s: p[hit] for s, p in m.at.items()})}
        rows = sorted(seen)
        yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.string())], ["i", "word"])

    rows = coded.mapInArrow(run, "i int, word string").distinct().groupBy("i").count().collect()
    return {r["i"]: r["count"] for r in rows}


def precision_table(coded: DataFrame, trees: list[Tree], codes: dict[str, int]) -> list[tuple[int, int, float]]:
    """``(words seen, words of two rounds, precision)`` of each tree."""
    got = observed_words(coded, trees, codes)
    out = []
    for i, t in enumerate(trees):
        try:
            n = len(words(t, 2))
        except LanguageTooLarge:
            n = 0
        out.append((got.get(i, 0), n, got.get(i, 0) / n if n else 0.0))
    return out


def and_orders(t: Tree) -> list[tuple[tuple[int, ...], Tree, Tree]]:
    """For each ``and`` node the tree with a sequence in its place, in both orders."""
    out = []
    for path, x in t.nodes():
        if x.op == "and":
            out.append((path, t.replace(path, Tree("seq", None, x.left, x.right)), t.replace(path, Tree("seq", None, x.right, x.left))))
    return out


def choice_branches(t: Tree) -> list[tuple[tuple[int, ...], Tree, Tree]]:
    """For each ``xor`` node the tree with either branch alone in its place."""
    return [(path, t.replace(path, x.left), t.replace(path, x.right)) for path, x in t.nodes() if x.op == "xor"]


def match_order_counts(coded: DataFrame, trees: list[Tree], codes: dict[str, int]) -> list[list[tuple[int, int]]]:
    """For each ``and`` node of each tree, in how many cases its left or its right child starts first in the match."""
    spots = [[(p, x) for p, x in t.nodes() if x.op == "and"] for t in trees]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((sum(map(len, spots)), 4), np.int64)
        for b in gathered(batches):
            for acts, (weight,) in blocks(b, ["weight"]):
                tr, w, k = kernel.Traces(acts, codes), weight.to_numpy(), 0
                for t, own in zip(trees, spots, strict=True):
                    m = kernel.scan(tr, t, *_all(tr))
                    for _, x in own:
                        lo = [np.stack([p for s, p in m.at.items() if s[0] in side.alphabet and not any(s[1])]).min(0) for side in (x.left, x.right)]
                        total[k, 0] += w[(m.end < tr.far) & (lo[0] < lo[1])].sum()
                        total[k, 1] += w[(m.end < tr.far) & (lo[1] < lo[0])].sum()
                        k += 1
        yield _counter_batch(total)

    got, k, out = _summed(coded, run), 0, []
    for own in spots:
        out.append([got.get(k + j, (0, 0))[:2] for j in range(len(own))])
        k += len(own)
    return out


def compactness(coded: DataFrame, trees: list[Tree], codes: dict[str, int], count: int, min_order_count: int = 1, and_order: str = "containment") -> list[dict[str, bool]]:
    """The four conditions of each tree: no choice at the root (C1), no choice with just one frequent branch (C2), loops
    that repeat (C3, always so as loops run twice), both orders under each ``and`` (C4)."""
    probes: list[Tree] = []
    spans = []
    for t in trees:
        ands = and_orders(t) if and_order == "containment" else []
        xors = choice_branches(t)
        spans.append((len(ands), len(xors)))
        probes += [v for _, x, y in ands + xors for v in (x, y)]
    got = [h for h, *_ in count_trees(coded, probes, codes)] if probes else []
    matched = match_order_counts(coded, trees, codes) if and_order == "match" else [[]] * len(trees)
    out, k = [], 0
    for t, (n_and, n_xor), own in zip(trees, spans, matched, strict=True):
        pairs = [(got[k + 2 * j], got[k + 2 * j + 1]) for j in range(n_and + n_xor)]
        k += 2 * (n_and + n_xor)
        both = pairs[:n_and] + list(own)
        out.append({
            "no_root_choice": t.op != "xor",
            "choice_ok": all((x >= count) == (y >= count) for x, y in pairs[n_and:]),
            "loop_repeats": True,
            "both_orders": all(min(p) >= min_order_count for p in both),
        })
    return out


def mine_patterns(
    log: DataFrame,
    min_support: float = 0.7,
    min_precision: float = 0.0,
    max_depth: int = 2,
    mode: str = "growth",
    maximality: str = "regular",
    choices: bool = True,
    choice_rule: str = "exact",
    choice_check: str = "every",
    min_order_count: int = 1,
    and_order: str = "containment",
    max_leaves: int | None = None,
    max_candidates: int = 200_000,
    compress: bool = True,
    chunk: int = 2000,
    places: str = "regrown",
    loops: str = "grown",
    measure_precision: bool = False,
) -> MiningResult:
    """Frequent patterns of a log up to a depth.

    ``mode``: ``growth``, ``scan`` or ``search``. ``maximality``: ``none``, ``regular`` (trees of the construction of a
    frequent tree go) or ``generalized`` (generalised seeds of a frequent tree go too). ``choice_rule``: ``exact``, or
    ``paper`` for the union of the seeds' hits also within loop bodies. ``choice_check``: ``every`` choice of a reported
    tree has no or two frequent branches, or only the one that was ``made`` last, of two infrequent seeds; trees with
    another choice of just one frequent branch are then reported too, with ``compact`` false. ``and_order``:
    ``containment`` or ``match``.
    ``places`` (growth): ``regrown`` makes the places of seeds again within each task and reads only the log, ``stored``
    writes those of a level in the shared folder, which pays where seeds cost more than reading their places. ``loops``
    (growth): ``grown``, or ``realigned`` for the published rule that a changed loop is aligned again as a whole.
    Precision is measured if ``min_precision`` or ``measure_precision`` asks for it, else it is null; ``maximal`` tells
    whether a tree survives the rule named, or the regular one under ``none``.
    A level with more than ``max_candidates`` candidates raises; nothing is cut silently. An empty log has no patterns.
    """
    for name, value, known in (
        ("mode", mode, ("growth", "scan", "search")), ("maximality", maximality, ("none", "regular", "generalized")), ("choice_rule", choice_rule, ("exact", "paper")),
        ("choice_check", choice_check, ("every", "made")), ("and_order", and_order, ("containment", "match")), ("places", places, ("regrown", "stored")), ("loops", loops, ("grown", "realigned")),
    ):
        if value not in known:
            raise ValueError(f"{name} is {value!r}, not one of {', '.join(known)}")
    if not (0 <= min_support <= 1 and 0 <= min_precision <= 1 and max_depth >= 1):
        raise ValueError("thresholds lie between 0 and 1, and the depth is 1 at least")
    began = time.time()
    spark = log.sparkSession
    coded, codes = encode(log, compress)
    n = coded.agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]
    need = min_count(min_support, n)
    level = 2
    layout = {a: [(a, ())] for a in codes}
    stored = mode == "growth" and places == "stored"
    mapped = store(coded.mapInArrow(_first_maps(list(codes), codes), MAPPED)) if stored and codes else coded
    cands = {c.pid: c for c in (Candidate(t, (), t.left.label, t.right.label) for t in atomic_patterns(codes))}
    frequent: dict[str, int] = {}
    seeds: dict[str, Candidate] = {}
    counters, dag = [], []
    while cands:
        if len(cands) > max_candidates:
            raise TooManyCandidates(f"{len(cands)} candidates of {level} leaves")
        started = time.time()
        got = _evaluate(mapped, list(cands.values()), codes, mode, layout if stored else seeds, stored, choice_rule, chunk, loops)
        good = {pid: c for pid, c in cands.items() if got[pid][0] >= need}
        frequent |= {pid: got[pid][0] for pid in good}
        seeds |= good
        dag += [(pid, s, c.op) for pid, c in good.items() for s in (c.seed1, c.seed2)]
        work = {k: sum(g[j] for g in got.values()) for j, k in ((2, "reused"), (1, "realigned"), (3, "states"))}
        if max_leaves and level >= max_leaves:
            following = {}
        else:
            low = {canonical(c.tree): got[p][0] for p, c in cands.items() if 0 < got[p][0] < need} if choices else {}
            following = next_level([canonical(c.tree) for c in good.values()], low, max_depth, need)
        if following and stored:
            used = {s for c in following.values() if c.op != "xor" and not c.tree.has("xor") for s in (c.seed1, c.seed2)}
            kept = [c for p, c in good.items() if p in used]
            after = _widths({c.pid: c.tree for c in kept})
            mapped = store(mapped.mapInArrow(_advance(kept, codes, layout, after), MAPPED))
            layout = after
        counters.append({"level": level, "n_candidates": len(cands), "n_frequent": len(good), **work, "wall_s": time.time() - started})
        cands, level = following, level + 1

    trees = [parse_tree(p) for p in sorted(frequent)]
    ok = compactness(coded, trees, codes, need, min_order_count, and_order) if trees else []
    prec = [p for *_, p in precision_table(coded, trees, codes)] if trees and (min_precision > 0 or measure_precision) else [None] * len(trees)
    dropped = not_maximal(trees, maximality)
    rows, kept = [], []
    for t, c, p in zip(trees, ok, prec, strict=True):
        pid = str(t)
        asked = [v for k, v in c.items() if choice_check == "every" or k != "choice_ok"]
        if all(asked) and (p is None or p >= min_precision) and (maximality == "none" or pid not in dropped):
            s = seeds[pid]
            rows.append((pid, str(s.tree), t.depth, t.n_leaves, t.op, int(frequent[pid]), round(frequent[pid] / n, 6), p, all(c.values()), pid not in dropped, s.seed1, s.seed2))
            kept.append(t)
    return MiningResult(spark, rows, frequent, dag, counters, coded, codes, int(n), time.time() - began, kept)


def not_maximal(trees: list[Tree], maximality: str = "regular") -> set[str]:
    """Canonical words of trees that another one of the list makes redundant."""
    out = set().union(*[construction_tree(t) for t in trees])
    if maximality == "generalized":
        out |= set().union(*[set(seed_kinds(t)) for t in trees])
    return out


def _evaluate(log: DataFrame, cands: list[Candidate], codes: dict, mode: str, base: dict, stored: bool, choice_rule: str, chunk: int, loops: str) -> dict[str, tuple[int, int, int, int]]:
    """Counters by candidate. Candidates with a choice always take the full way, as their union may not be grown.

    ``base``: the layout of stored places, or the frequent trees from which they are grown again."""
    out: dict[str, tuple[int, int, int, int]] = {}
    grown = [c for c in cands if mode == "growth" and not c.tree.has("xor")]
    plain = [c for c in cands if not (mode == "growth" and not c.tree.has("xor"))]
    union = [c for c in plain if choice_rule == "paper" and c.op == "xor"]
    grown.sort(key=lambda c: (c.seed1, c.seed2))  # candidates with a seed in common follow each other
    way = (lambda part: _growth_counts(part, codes, base, loops)) if stored else (lambda part: _regrown_counts(part, codes, ancestors(part, base), loops))
    got = _in_chunks(log, grown, way, chunk)
    out |= dict(zip([c.pid for c in grown], got, strict=True))
    full = [c for c in plain if c not in union] if union else plain
    counted = count_trees(log, [c.tree for c in full], codes, "search" if mode == "search" else "scan", chunk)
    out |= dict(zip([c.pid for c in full], counted, strict=True))
    if union:
        got = _summed(log, _union_counts([(parse_tree(c.seed1), parse_tree(c.seed2)) for c in union], codes))
        out |= {c.pid: got.get(i, (0, 0, 0, 0)) for i, c in enumerate(union)}
    return out


def _union_counts(pairs: list[tuple[Tree, Tree]], codes: dict) -> Callable:
    """Kernel that counts the cases in which either seed is found: the support of a choice without aligning it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(pairs), 4), np.int64)
        for b in gathered(batches):
            for acts, (weight,) in blocks(b, ["weight"]):
                tr, w = kernel.Traces(acts, codes), weight.to_numpy()
                hits: dict[str, np.ndarray] = {}
                for t in {str(x): x for p in pairs for x in p}.values():
                    hits[str(t)] = kernel.scan(tr, t, *_all(tr)).end < tr.far
                for i, (x, y) in enumerate(pairs):
                    total[i, 0] += w[hits[str(x)] | hits[str(y)]].sum()
        yield _counter_batch(total)

    return run


OCCURRENCES = "case_id string, pid string, word array<string>, shadow array<int>, lo int, hi int, weight bigint"


def occurrences(coded: DataFrame, trees: list[Tree], codes: dict[str, int]) -> DataFrame:
    """One row per case and pattern that it exhibits: the word, its places in order, first and last place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for acts, (case, weight) in blocks(b, ["case_id", "weight"]):
                tr = kernel.Traces(acts, codes)
                for t in trees:
                    m = kernel.scan(tr, t, *_all(tr))
                    hit = np.nonzero(m.end < tr.far)[0]
                    own = kernel.slots(t)
                    at = np.stack([m.at[s][hit] for s in own], axis=1)
                    rank = np.argsort(at, axis=1, kind="stable")
                    places = [[p for p in row if p] for row in np.take_along_axis(at, rank, 1).tolist()]
                    names = [[own[k][0] for k, p in zip(r, ps, strict=True) if p] for r, ps in zip(rank.tolist(), np.take_along_axis(at, rank, 1).tolist(), strict=True)]
                    ids = pa.array(hit)
                    cols = [case.take(ids), pa.array([str(t)] * len(hit), pa.string()), pa.array(names, pa.list_(pa.string())), pa.array(places, pa.list_(pa.int32())),
                            pa.array([p[0] for p in places], pa.int32()), pa.array([p[-1] for p in places], pa.int32()), weight.take(ids)]
                    yield pa.RecordBatch.from_arrays(cols, [x.split()[0] for x in OCCURRENCES.split(", ")])

    return coded.mapInArrow(run, OCCURRENCES)


def growth_branches(log: DataFrame, tree: Tree, path: tuple[int, ...]) -> DataFrame:
    """``realigned, reused, n_rows, n_hits`` of one candidate grown out of its seeds over a log."""
    from motifspark.plans.lattice import regular_seeds

    coded, codes = encode(log, compress=False)
    s1, s2, _, _ = regular_seeds(tree)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((1, 4), np.int64)
        for b in gathered(batches):
            for acts, (weight,) in blocks(b, ["weight"]):
                tr = kernel.Traces(acts, codes)
                one, two = (kernel.scan(tr, s, *_all(tr)) for s in (s1, s2))
                valid = (one.end < tr.far) & (two.end < tr.far)
                work = kernel.Work()
                m = kernel.grow(tr, tree, path, one.at, two.at, valid, work)
                total[0] += weight.to_numpy()[m.end < tr.far].sum(), work.realigned, work.reused, np.count_nonzero(valid)
        yield _counter_batch(total)

    got = _summed(coded, run).get(0, (0, 0, 0, 0))
    return log.sparkSession.createDataFrame([(str(tree), got[1], got[2], got[3], got[0])], "tree string, realigned bigint, reused bigint, n_rows bigint, n_hits bigint")

