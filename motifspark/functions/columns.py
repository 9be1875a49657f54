"""Column builders: process trees compiled into built-in expressions over an array of activities.

All of it is transparent to Catalyst; no Python runs. Positions are bound once per step by a one-element ``transform``.
"""

from __future__ import annotations

import itertools

from pyspark.sql import Column
from pyspark.sql import functions as F

from motifspark.plans.language import Word
from motifspark.plans.tree import Tree, parse_tree


def _tree(t: Tree | str) -> Tree:
    return parse_tree(t) if isinstance(t, str) else t


def _quoted(a: str) -> str:
    return "'" + a.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _end(t: Tree, acts: str, start: str, names: itertools.count) -> str:
    """SQL of the earliest end strictly after ``start`` (an int), null if there is none."""
    let = lambda value, body: (lambda v: f"transform(array({value}), {v} -> {body(v)})[0]")(f"v{next(names)}")
    if t.is_leaf:
        found = f"cast(array_position(slice({acts}, {start} + 1, size({acts})), {_quoted(t.label)}) as int)"
        return let(found, lambda p: f"case when {p} > 0 then {start} + {p} end")
    then = lambda s, child: let(s, lambda v: f"case when {v} is not null then {_end(child, acts, v, names)} end")
    if t.op == "seq":
        return then(_end(t.left, acts, start, names), t.right)
    if t.op == "loop":
        return then(then(_end(t.left, acts, start, names), t.right), t.left)
    left, right = _end(t.left, acts, start, names), _end(t.right, acts, start, names)
    if t.op == "xor":
        return f"least({left}, {right})"  # nulls do not count
    return let(left, lambda x: let(right, lambda y: f"case when {x} is not null and {y} is not null then greatest({x}, {y}) end"))


def tree_sql(t: Tree | str, acts: str = "acts") -> str:
    """Boolean SQL expression: does the trace exhibit the tree."""
    return f"({_end(_tree(t), acts, '0', itertools.count())} is not null)"


def contains_expr(t: Tree | str, acts: str = "acts") -> Column:
    return F.coalesce(F.expr(tree_sql(t, acts)), F.lit(False))


def end_expr(t: Tree | str, acts: str = "acts") -> Column:
    return F.expr(_end(_tree(t), acts, "0", itertools.count()))


def _slots(t: Tree, acts: str, start: str, names: itertools.count) -> str:
    """SQL of the places of a match in program order (0 for a branch not taken), null if there is none."""
    let = lambda value, body: (lambda v: f"transform(array({value}), {v} -> {body(v)})[0]")(f"s{next(names)}")
    if t.is_leaf:
        found = f"cast(array_position(slice({acts}, {start} + 1, size({acts})), {_quoted(t.label)}) as int)"
        return let(found, lambda p: f"case when {p} > 0 then array({start} + {p}) end")
    after = lambda x, child: let(x, lambda v: f"case when {v} is not null then concat({v}, {_slots(child, acts, f'array_max({v})', names)}) end")
    if t.op == "seq":
        return after(_slots(t.left, acts, start, names), t.right)
    if t.op == "loop":
        return after(after(_slots(t.left, acts, start, names), t.right), t.left)
    left, right = _slots(t.left, acts, start, names), _slots(t.right, acts, start, names)
    if t.op == "and":
        return f"concat({left}, {right})"
    n, m = _width(t.left), _width(t.right)
    return let(left, lambda x: let(right, lambda y: (
        f"case when {x} is null and {y} is null then cast(null as array<int>) when {y} is null or array_max({x}) <= array_max({y}) "
        f"then concat({x}, array_repeat(0, {m})) else concat(array_repeat(0, {n}), {y}) end")))  # fmt: skip


def _width(t: Tree) -> int:
    if t.is_leaf:
        return 1
    return _width(t.left) * (2 if t.op == "loop" else 1) + _width(t.right)


def shadow_expr(t: Tree | str, acts: str = "acts") -> Column:
    """Places of the earliest match in program order, null without a match."""
    return F.expr(_slots(_tree(t), acts, "0", itertools.count()))


def boundary_expr(shadow: str = "shadow") -> Column:
    """``struct(lo, hi)`` of a column of places."""
    taken = F.filter(shadow, lambda p: p > 0)
    return F.struct(F.array_min(taken).alias("lo"), F.array_max(taken).alias("hi"))


def is_subsequence(word: str, acts: str = "acts") -> Column:
    """Whether array column ``word`` is a subsequence of array column ``acts``, by a fold with a cursor."""
    return F.expr(f"aggregate({acts}, 0, (at, a) -> case when at < size({word}) and {word}[least(at, size({word}) - 1)] = a then at + 1 else at end) >= size({word})")


def shadow_of_word(word: Word, acts: str = "acts") -> Column:
    """Leftmost places of a literal word in a trace, null if it is not contained."""
    t = Tree(None, word[-1])
    for a in reversed(word[:-1]):
        t = Tree("seq", None, Tree(None, a), t)
    return shadow_expr(t, acts)


def is_leftmost(word: str, shadow: str, acts: str = "acts") -> Column:
    """Whether each letter of array ``word`` sits at its first place after its predecessor's."""
    return F.expr(
        f"""size({word}) = size({shadow}) and forall(sequence(1, size({word})), i -> {acts}[{shadow}[i - 1] - 1] = {word}[i - 1]
            and not array_contains(slice({acts}, case when i = 1 then 1 else {shadow}[greatest(i - 2, 0)] + 1 end,
              greatest({shadow}[i - 1] - case when i = 1 then 0 else {shadow}[greatest(i - 2, 0)] end - 1, 0)), {word}[i - 1]))"""
    )
