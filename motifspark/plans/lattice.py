"""The candidate lattice: combinations of trees that differ in one leaf, and its inverse, regular seeds."""

from __future__ import annotations

import itertools
from collections import defaultdict
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

from .tree import CONSTRAINING, SYMMETRIC, Path, Tree, canonical, canonical_word, leaf, node, orders

HOLE = Tree(None, "_")


def atomic_patterns(activities: Iterable[str]) -> list[Tree]:
    """Two-leaf trees of different activities. A choice at the root is never compact, so none is made."""
    out = []
    for a, b in itertools.permutations(sorted(activities), 2):
        out += [node(op, leaf(a), leaf(b)) for op in CONSTRAINING if op not in SYMMETRIC or a < b]
    return out


def combination_leaves(t: Tree) -> list[Path]:
    """Leaves at the greatest depth or one above it, with no deeper leaf to their right."""
    found = []
    deepest_right = -1
    for path, _ in reversed(t.leaves()):
        if len(path) >= t.depth - 1 and deepest_right <= len(path):
            found.append(path)
        deepest_right = max(deepest_right, len(path))
    return found


def hole_keys(t: Tree) -> Iterator[tuple[str, Path, Tree]]:
    """``(tree with a hole, path, variant)`` for every combination leaf of every order of the tree."""
    for v in orders(t):
        for path in combination_leaves(v):
            yield str(v.replace(path, HOLE)), path, v


def combinable(t: Tree, u: Tree) -> bool:
    """Whether some orders of both differ in exactly one potential combination leaf."""
    mine = {(k, v.at(p).label) for k, p, v in hole_keys(t)}
    return any(k == k2 and a != v.at(p).label for k2, p, v in hole_keys(u) for k, a in mine)


@dataclass(frozen=True)
class Candidate:
    """``tree`` in the order in which it was made; the new node is at ``path``; seeds by canonical word."""

    tree: Tree
    path: Path
    seed1: str
    seed2: str

    @property
    def pid(self) -> str:
        return canonical_word(self.tree)

    @property
    def op(self) -> str:
        return self.tree.at(self.path).op


def combine(t: Tree, u: Tree, op: str) -> list[Candidate]:
    """Candidates of two trees under an operator, both directions where the operator has one."""
    return list(_joined([t, u], [(op, op in SYMMETRIC)]))


def _joined(trees: Iterable[Tree], ops: list[tuple[str, bool]]) -> Iterator[Candidate]:
    by_hole: dict[str, dict[str, tuple[Path, Tree]]] = defaultdict(dict)
    for t in trees:
        for key, path, v in hole_keys(t):
            by_hole[key].setdefault(v.at(path).label, (path, v))
    for group in by_hole.values():
        for (a, (path, v)), (b, (_, w)) in itertools.permutations(sorted(group.items()), 2):
            for op, symmetric in ops:
                if not (symmetric and a > b):
                    yield Candidate(v.replace(path, node(op, leaf(a), leaf(b))), path, canonical_word(v), canonical_word(w))


def next_level(frequent: Iterable[Tree], infrequent: dict[Tree, int], max_depth: int, min_count: int) -> dict[str, Candidate]:
    """Candidates with one leaf more, by canonical word.

    Constraining operators join frequent trees; a choice joins two infrequent ones whose counts can reach the
    threshold together. Every pair of a canonical tree with another orientation is tried, so each class is reached.
    """
    out: dict[str, Candidate] = {}

    def keep(c: Candidate) -> None:
        if c.tree.depth <= max_depth and c.tree.op != "xor" and c.tree.n_leaves == len(c.tree.alphabet):
            out.setdefault(c.pid, c)

    for c in _joined(frequent, [(op, op in SYMMETRIC) for op in CONSTRAINING]):
        keep(c)
    counts = {canonical_word(t): n for t, n in infrequent.items()}
    for c in _joined(infrequent, [("xor", True)]):
        if counts[c.seed1] + counts[c.seed2] >= min_count:
            keep(c)
    return out


def collapse_point(t: Tree) -> Path | None:
    """The right-most node at the greatest depth but one whose children are leaves at the greatest depth."""
    if t.is_leaf:
        return None
    deepest = [p for p, x in t.leaves() if len(p) == t.depth]
    return deepest[-1][:-1]


def regular_seeds(t: Tree) -> tuple[Tree, Tree, str, str] | None:
    """Both seeds of a tree in its own order, and the two leaves that they keep."""
    if (path := collapse_point(t)) is None:
        return None
    a, b = t.at(path).left, t.at(path).right
    return t.replace(path, a), t.replace(path, b), a.label, b.label


def seed_words(t: Tree) -> set[str]:
    """Canonical words of the regular seeds of all orders of a tree: the trees that it drops when it is added."""
    return {canonical_word(s) for v in orders(t) if (r := regular_seeds(v)) for s in r[:2]}


def construction_tree(t: Tree) -> set[str]:
    """All trees, as canonical words, out of which combinations make ``t``, itself left out."""
    seen: set[str] = set()
    todo = [canonical(t)]
    while todo:
        x = todo.pop()
        for v in orders(x):
            if r := regular_seeds(v):
                for s in r[:2]:
                    if (w := canonical_word(s)) not in seen:
                        seen.add(w)
                        todo.append(canonical(s))
    return seen


def candidate_levels(trees: Iterable[Tree]) -> dict[int, set[str]]:
    """The construction graph of some trees, by number of leaves."""
    out: dict[int, set[str]] = defaultdict(set)
    from .tree import parse_tree

    for t in trees:
        for w in construction_tree(t) | {canonical_word(t)}:
            out[parse_tree(w).n_leaves].add(w)
    return dict(sorted(out.items()))


def all_trees(activities: list[str], max_depth: int, ops: tuple[str, ...] = CONSTRAINING, max_leaves: int | None = None) -> set[str]:
    """Every tree of distinct activities up to a depth, as canonical words; the brute-force list of tests and oracles."""

    def of(acts: frozenset[str], d: int) -> Iterator[Tree]:
        if len(acts) == 1:
            yield leaf(next(iter(acts)))
            return
        if d == 0 or len(acts) > 1 << d:
            return
        items = sorted(acts)
        for k in range(1, len(items)):
            for part in itertools.combinations(items, k):
                rest = acts - set(part)
                for x in of(frozenset(part), d - 1):
                    for y in of(rest, d - 1):
                        for op in ops:
                            yield node(op, x, y)

    most = min(len(activities), 1 << max_depth, max_leaves or len(activities))
    found: set[str] = set()
    for k in range(2, most + 1):
        for acts in itertools.combinations(sorted(activities), k):
            found |= {canonical_word(t) for t in of(frozenset(acts), max_depth) if t.op != "xor"}
    return found
