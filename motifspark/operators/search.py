"""Search alignment: the classical best-first alignment of a whole trace with a whole tree.

Only trace moves may be skipped for free; a state is a place in the trace together with what is left of the tree. It is
exact for every tree, repeated activities included, and exponential at worst; it serves as the baseline.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

from motifspark.plans.tree import Tree


class SearchTooLarge(RuntimeError):
    pass


@dataclass
class Alignment:
    """``places``: of the word's letters, 1-based. ``states``: expanded states."""

    hit: bool
    word: tuple[str, ...]
    places: tuple[int, ...]
    states: int


def _steps(t: Tree | None) -> Iterator[tuple[str, Tree | None]]:
    """Letters with which the rest ``t`` can go on, each with what is left afterwards (None: done)."""
    if t is None:
        return
    if t.is_leaf:
        yield t.label, None
    elif t.op == "xor":
        yield from _steps(t.left)
        yield from _steps(t.right)
    elif t.op == "seq":
        for a, rest in _steps(t.left):
            yield a, t.right if rest is None else Tree("seq", None, rest, t.right)
    elif t.op == "and":
        for a, rest in _steps(t.left):
            yield a, t.right if rest is None else Tree("and", None, rest, t.right)
        for a, rest in _steps(t.right):
            yield a, t.left if rest is None else Tree("and", None, t.left, rest)
    else:  # a loop runs its body, redo and body
        yield from _steps(Tree("seq", None, t.left, Tree("seq", None, t.right, t.left)))


def align_trace(t: Tree, trace: list[str], max_states: int = 2_000_000) -> Alignment:
    """A match with the least last place, found by best-first search over ``(place, rest of the tree)``."""
    heap: list[tuple[int, int, Tree | None, tuple, tuple]] = [(0, 0, t, (), ())]
    seen: set[tuple[int, Tree | None]] = set()
    states = ties = 0
    while heap:
        at, _, rest, word, places = heapq.heappop(heap)
        if rest is None:
            return Alignment(True, word, places, states)
        if (at, rest) in seen:
            continue
        seen.add((at, rest))
        states += 1
        if states > max_states:
            raise SearchTooLarge(f"more than {max_states} states for {t}")
        for a, after in _steps(rest):
            try:
                p = trace.index(a, at) + 1
            except ValueError:
                continue
            ties += 1
            heapq.heappush(heap, (p, ties, after, (*word, a), (*places, p)))
    return Alignment(False, (), (), states)


MOVES = "case_id string, moves array<struct<log:string,model:string>>, word array<string>, shadow array<int>, lo int, hi int, states bigint"


def align_search(log: DataFrame, tree: Tree, max_states: int = 2_000_000) -> DataFrame:
    """Alignments of a log (with activity labels) and a tree; cases without a match have null columns."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.struct([("log", pa.string()), ("model", pa.string())])
        for b in batches:
            cols: list[list] = [[] for _ in range(7)]
            for case, acts in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                f = align_trace(tree, acts, max_states)
                used = set(f.places)
                moves = [{"log": x, "model": x if i in used else None} for i, x in enumerate(acts, 1)] if f.hit else None
                found = (moves, list(f.word), list(f.places), f.places[0], f.places[-1]) if f.hit else (None,) * 5
                for c, v in zip(cols, (case, *found, f.states), strict=True):
                    c.append(v)
            types = [pa.string(), pa.list_(kind), pa.list_(pa.string()), pa.list_(pa.int32()), pa.int32(), pa.int32(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], [x.split()[0] for x in ("case_id", "moves", "word", "shadow", "lo", "hi", "states")])

    return log.select("case_id", "acts").mapInArrow(run, MOVES)
