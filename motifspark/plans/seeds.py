"""Generalised seeds, loop seeds and the test whether one tree is a seed of another."""

from __future__ import annotations

import functools

from .lattice import regular_seeds
from .tree import SYMMETRIC, Tree, canonical, canonical_word, orders


@functools.lru_cache(maxsize=1 << 14)
def seed_closure(t: Tree) -> frozenset[Tree]:
    """All generalised seeds of a tree, itself included, in canonical order.

    A leaf has itself. Under a constraining operator the seeds are those of both children and all their recombinations;
    under a choice only the recombinations, since a branch alone is no consequence of the choice.
    """
    if t.is_leaf:
        return frozenset({t})
    left, right = seed_closure(t.left), seed_closure(t.right)
    both = {canonical(Tree(t.op, None, x, y)) for x in left for y in right}
    return frozenset(both if t.op == "xor" else both | left | right)


def seed_kinds(t: Tree) -> dict[str, str]:
    """Proper seeds as canonical words, each ``regular`` or ``alternative``."""
    regular = {canonical_word(s) for s in (regular_seeds(t) or ())[:2]}
    own = canonical_word(t)
    return {w: "regular" if w in regular else "alternative" for s in seed_closure(canonical(t)) if (w := str(s)) != own}


def is_seed(small: Tree, big: Tree) -> bool:
    """Whether ``small`` is a proper seed of ``big``, decided by recursion over both trees without the closure."""

    @functools.cache
    def within(s: Tree, b: Tree) -> bool:
        if s.depth > b.depth or s.n_leaves > b.n_leaves:
            return False
        if b.is_leaf:
            return s == b
        if s.op == b.op:
            pairs = [(s.left, s.right)] + [(s.right, s.left)] * (s.op in SYMMETRIC)
            if any(within(x, b.left) and within(y, b.right) for x, y in pairs):
                return True
        return b.op != "xor" and (within(s, b.left) or within(s, b.right))

    return canonical_word(small) != canonical_word(big) and within(canonical(small), canonical(big))


def loop_seeds(t: Tree, transitive: bool = False) -> set[str]:
    """Trees with a sequence in place of one loop (``transitive``: of one or more), as canonical words."""
    out: set[str] = set()
    for path, x in t.nodes():
        if x.op == "loop":
            relaxed = t.replace(path, Tree("seq", None, x.left, x.right))
            out.add(canonical_word(relaxed))
            if transitive:
                out |= loop_seeds(relaxed, True)
    return out


def is_loop_seed(small: Tree, big: Tree) -> bool:
    return canonical_word(small) in loop_seeds(big)


def swaps(t: Tree) -> set[str]:
    return {str(x) for x in orders(t)}
