"""Vectorised alignment of process trees with batches of traces.

For every activity a table gives its next place strictly after each place of each trace. A tree is then a straight
program: a leaf is one gather, a sequence starts its right child at the end of its left one, concurrency takes the
later end, a choice the earlier one, a loop runs body, redo and body again. Earliest ends are monotone in the
start, so the greedy program is exact for trees of distinct activities. All steps work on whole columns of traces.

Growth fills a candidate's places from the places of its two seeds, kept as whole columns. Whatever the change leaves
alone is taken over as it is; the new node, and what must move behind it, is decided by comparing columns, and only
rows in which the seeds' places do not fit are looked up again.
"""

from __future__ import annotations

import functools
from dataclasses import dataclass, field

import numpy as np

from motifspark.plans.tree import Path, Tree, loop_block

Slot = tuple[str, tuple[int, ...]]  # activity, and which run of each loop around it


def slots(t: Tree, runs: tuple[int, ...] = ()) -> list[Slot]:
    """Places that a match of the tree stores, in program order; a loop body has two runs."""
    if t.is_leaf:
        return [(t.label, runs)]
    if t.op == "loop":
        return slots(t.left, (*runs, 0)) + slots(t.right, (*runs, 0)) + slots(t.left, (*runs, 1))
    return slots(t.left, runs) + slots(t.right, runs)


def check_distinct(t: Tree) -> None:
    if t.n_leaves != len(t.alphabet):
        raise ValueError(f"{t} repeats an activity; use the search aligner")


class Traces:
    """A batch of traces as next-place tables. ``acts``: codes padded with -1; places count from 1, ``far`` is none.

    Tables and held matches stay within ``room`` bytes; beyond it the oldest table goes and is made again if asked for.
    """

    def __init__(self, acts: np.ndarray, codes: dict[str, int], room: int = 256 << 20):
        self.acts, self.codes = acts, codes
        self.rows, self.width = acts.shape
        self.far = self.width + 1
        self.every = np.arange(self.rows)
        self.base = self.every * (self.width + 2)
        self._next: dict[str, np.ndarray] = {}
        self._held: dict[str, Match] = {}
        self._room, self._table_room = 48 << 20, room

    def from_start(self, t: Tree) -> Match:
        """Match of a tree from the start of all rows; two-leaf trees are held for others that contain them, within bounds."""
        if (found := self._held.get(str(t))) is None:
            found = scan(self, t, np.arange(self.rows), np.zeros(self.rows, np.int32), shared=False)
            size = 4 * self.rows * (len(found.at) + 1)
            if t.n_leaves <= 2 and size <= self._room:
                self._held[str(t)] = found
                self._room -= size
        return found

    def table(self, a: str) -> np.ndarray:
        if (held := self._next.get(a)) is None:
            place = np.where(self.acts == self.codes.get(a, -2), np.arange(1, self.width + 1, dtype=np.int32), np.int32(self.far))
            held = np.full((self.rows, self.width + 2), self.far, np.int32)
            if self.width:
                held[:, : self.width] = np.minimum.accumulate(place[:, ::-1], axis=1)[:, ::-1]
            self._next[a] = held
            self._table_room -= held.nbytes
            while self._table_room < 0 and len(self._next) > 1:
                self._table_room += self._next.pop(next(iter(self._next))).nbytes
        return held

    def next(self, a: str, rows: np.ndarray, start: np.ndarray) -> np.ndarray:
        return self.table(a).ravel().take((self.base if len(rows) == self.rows else self.base[rows]) + start)


def pad(flat: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Ragged lists of codes as a matrix padded with -1."""
    lengths = np.diff(offsets)
    out = np.full((len(lengths), int(lengths.max(initial=0))), -1, np.int32)
    out[np.arange(out.shape[1]) < lengths[:, None]] = flat[offsets[0] : offsets[-1]]
    return out


@dataclass
class Work:
    """What an alignment did: places looked up again and places copied, summed over rows."""

    realigned: int = 0
    reused: int = 0


@dataclass
class Match:
    """Ends of the matches of some rows and the places of their slots (``far``: no match, 0: branch not taken)."""

    end: np.ndarray
    at: dict[Slot, np.ndarray] = field(default_factory=dict)


def scan(tr: Traces, t: Tree, rows: np.ndarray, start: np.ndarray, work: Work | None = None, runs: tuple[int, ...] = (), shared: bool = True) -> Match:
    """Earliest match strictly after ``start`` of each row, by the full program.

    ``shared``: subtrees that start with the trace are taken from the block's store if no work is counted."""
    if shared and work is None and not runs and 1 < t.n_leaves <= 2 and len(rows) == tr.rows and not start.any():
        return tr.from_start(t)
    if t.is_leaf:
        p = tr.next(t.label, rows, start)
        if work:
            work.realigned += len(rows)
        return Match(p, {(t.label, runs): p})
    if t.op == "loop":
        first = scan(tr, t.left, rows, start, work, (*runs, 0))
        redo = scan(tr, t.right, rows, first.end, work, (*runs, 0))
        again = scan(tr, t.left, rows, redo.end, work, (*runs, 1))
        return Match(again.end, first.at | redo.at | again.at)
    left = scan(tr, t.left, rows, start, work, runs)
    if t.op == "seq":
        right = scan(tr, t.right, rows, left.end, work, runs)
        return Match(right.end, left.at | right.at)
    right = scan(tr, t.right, rows, start, work, runs)
    if t.op == "and":
        return Match(np.maximum(left.end, right.end), left.at | right.at)
    first_wins = left.end <= right.end
    at = {s: np.where(first_wins, p, 0) for s, p in left.at.items()} | {s: np.where(first_wins, 0, p) for s, p in right.at.items()}
    return Match(np.minimum(left.end, right.end), at)


def _ends(at: dict[Slot, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    own = list(at.values())
    return functools.reduce(np.minimum, own), functools.reduce(np.maximum, own)


def grow(tr: Traces, t: Tree, path: Path, seed1: dict[Slot, np.ndarray], seed2: dict[Slot, np.ndarray], valid: np.ndarray, work: Work | None = None, loops: str = "grown") -> Match:
    """Match of a candidate out of the places of its seeds; all columns run over all rows of the batch.

    ``path`` leads to the new node, whose left leaf is in ``seed1`` and right leaf in ``seed2``; ``valid`` marks the rows that
    both seeds match. Ends of other rows are ``far``; places mean something only where the end is not. ``loops``:
    ``realigned`` runs the full program on the outermost loop around the change, ``grown`` only on the second run of a
    body that the change lies in.
    """
    work = work or Work()
    n = int(np.count_nonzero(valid))
    full = n == tr.rows
    every = tr.every if full else np.flatnonzero(valid)
    block = loop_block(t, path) if loops == "realigned" else None
    whole_block = block is not None and t.at(block).op == "loop"

    def again(node: Tree, rows: np.ndarray, start: np.ndarray | None, runs: tuple[int, ...] = ()) -> Match:
        """Full program on some rows, spread over all."""
        found = scan(tr, node, rows, np.zeros(len(rows), np.int32) if start is None else start[rows], work, runs)
        if len(rows) == tr.rows:
            return found
        spread = []
        for p in (found.end, *found.at.values()):
            spread.append(np.full(tr.rows, tr.far, np.int32))
            spread[-1][rows] = p
        return Match(spread[0], dict(zip(found.at, spread[1:], strict=True)))

    def behind(node: Tree, runs: tuple[int, ...], start: np.ndarray) -> Match:
        """An unchanged node that must lie behind ``start``: of both seeds' places the earlier ones that do."""
        one, two = ({s: seed[s] for s in slots(node, runs)} for seed in (seed1, seed2))
        (lo1, hi1), (lo2, hi2) = _ends(one), _ends(two)
        fits1, fits2 = lo1 > start, lo2 > start
        from_two = fits2 & ((lo2 < lo1) | ~fits1)
        rows = (~(fits1 | fits2) if full else ~(fits1 | fits2) & valid).nonzero()[0]
        at = {s: np.where(from_two, two[s], one[s]) for s in one}
        end = np.where(from_two, hi2, hi1)
        if len(rows):
            found = scan(tr, node, rows, start[rows], work, runs)
            for s in at:
                at[s][rows] = found.at[s]
            end[rows] = found.end
        work.reused += len(at) * (n - len(rows))
        return Match(end, at)

    def unchanged(node: Tree, runs: tuple[int, ...]) -> Match:
        kept = {s: seed1[s] for s in slots(node, runs)}
        work.reused += len(kept) * n
        return Match(_ends(kept)[1], kept)

    def fresh(node: Tree, runs: tuple[int, ...]) -> Match:
        a, b = node.left.label, node.right.label
        pa, pb = seed1[a, runs], seed2[b, runs]
        work.reused += n
        if node.op == "and":
            work.reused += n
            return Match(np.maximum(pa, pb), {(a, runs): pa, (b, runs): pb})
        late = (pb <= pa if full else (pb <= pa) & valid).nonzero()[0]  # the stored place is not behind the other leaf
        if len(late):
            pb = pb.copy()
            pb[late] = tr.next(b, late, pa[late])
        work.realigned += len(late)
        work.reused += n - len(late)
        if node.op == "seq":
            return Match(pb, {(a, runs): pa, (b, runs): pb})
        third = again(node.left, every, pb, (*runs, 1))
        return Match(third.end, {(a, (*runs, 0)): pa, (b, (*runs, 0)): pb} | third.at)

    def step(node: Tree, here: Path, start: np.ndarray | None, runs: tuple[int, ...]) -> Match:
        """The changed node; what is left of it has not changed, so it starts where it did in the seeds."""
        if whole_block and here == block:
            return again(node, every, start, runs)
        if here == path:
            return fresh(node, runs)
        right = path[len(here)] == 1
        if node.op == "and":
            same = unchanged(node.left if right else node.right, runs)
            other = step(node.right if right else node.left, (*here, int(right)), start, runs)
            return Match(np.maximum(same.end, other.end), same.at | other.at)
        inner = (*runs, 0) if node.op == "loop" else runs
        if right:
            left = unchanged(node.left, inner)
            redo = step(node.right, (*here, 1), left.end, inner)
        else:
            left = step(node.left, (*here, 0), start, inner)
            redo = behind(node.right, inner, left.end)
        if node.op == "seq":
            return Match(redo.end, left.at | redo.at)
        last = behind(node.left, (*runs, 1), redo.end) if right else again(node.left, every, redo.end, (*runs, 1))
        return Match(last.end, left.at | redo.at | last.at)

    m = again(t, every, None) if t.has("xor") else step(t, (), None, ())
    return m if full else Match(np.where(valid, m.end, np.int32(tr.far)), m.at)


def boundaries(t: Tree, at: dict[Slot, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """First and last place of matches; slots of branches not taken are 0 and do not count."""
    m = np.stack([at[s] for s in slots(t)])
    lo = np.where(m == 0, np.iinfo(np.int32).max, m).min(0)
    return lo, m.max(0)


def seen_words(t: Tree, at: dict[Slot, np.ndarray]) -> set[tuple[str, ...]]:
    """Distinct words, in order of place, of some matches."""
    own = slots(t)
    m = np.stack([at[s] for s in own], axis=1)
    rank = np.argsort(m, axis=1, kind="stable")
    taken = np.take_along_axis(m, rank, 1) > 0
    distinct = np.unique(np.where(taken, rank, -1), axis=0)
    return {tuple(own[i][0] for i in row if i >= 0) for row in distinct.tolist()}
