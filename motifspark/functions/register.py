"""SQL surface: scalar and table functions on trees given as text."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifspark.plans.language import words
from motifspark.plans.lattice import hole_keys
from motifspark.plans.seeds import is_seed, loop_seeds, seed_kinds
from motifspark.plans.tree import Tree, canonical_word, parse_tree


def _row(*names: str) -> T.StructType:
    return T.StructType([T.StructField(n, T.StringType()) for n in names])


def _earliest(t: Tree, trace: list, at: int) -> int | None:
    if t.is_leaf:
        try:
            return trace.index(t.label, at) + 1
        except ValueError:
            return None
    if t.op in ("seq", "loop"):
        end: int | None = at
        for child in (t.left, t.right) if t.op == "seq" else (t.left, t.right, t.left):
            end = None if end is None else _earliest(child, trace, end)
        return end
    x, y = _earliest(t.left, trace, at), _earliest(t.right, trace, at)
    if t.op == "and":
        return None if x is None or y is None else max(x, y)
    return min((e for e in (x, y) if e is not None), default=None)


@F.pandas_udf(T.BooleanType())
def tree_contains(acts: pd.Series, tree: pd.Series) -> pd.Series:
    parsed = {t: parse_tree(t) for t in tree.unique()}
    return pd.Series([a is not None and _earliest(parsed[t], list(a), 0) is not None for a, t in zip(acts, tree, strict=True)])


@F.pandas_udf(T.StringType())
def canonical_text(tree: pd.Series) -> pd.Series:
    return tree.map(lambda t: canonical_word(parse_tree(t)))


@F.pandas_udf(T.IntegerType())
def tree_depth(tree: pd.Series) -> pd.Series:
    return tree.map(lambda t: parse_tree(t).depth)


@F.pandas_udf(T.BooleanType())
def seed_of(small: pd.Series, big: pd.Series) -> pd.Series:
    return pd.Series([is_seed(parse_tree(a), parse_tree(b)) for a, b in zip(small, big, strict=True)])


@F.udtf(returnType=_row("word"))
class TreeWords:
    def eval(self, tree: str, rounds: int) -> Iterator[tuple[str]]:
        for w in sorted(words(parse_tree(tree), rounds)):
            yield (" ".join(w),)


@F.udtf(returnType=_row("seed", "kind"))
class SeedClosure:
    def eval(self, tree: str) -> Iterator[tuple[str, str]]:
        yield from sorted(seed_kinds(parse_tree(tree)).items())


@F.udtf(returnType=_row("seed"))
class LoopSeeds:
    def eval(self, tree: str) -> Iterator[tuple[str]]:
        yield from ((s,) for s in sorted(loop_seeds(parse_tree(tree))))


@F.udtf(returnType=_row("hole", "leaf"))
class HoleKeys:
    def eval(self, tree: str) -> Iterator[tuple[str, str]]:
        yield from sorted({(k, v.at(p).label) for k, p, v in hole_keys(parse_tree(tree))})


def register(spark: SparkSession) -> None:
    """Names: ``tree_contains(acts, tree)``, ``canonical_word``, ``tree_depth``, ``is_seed`` and the table functions
    ``tree_words(tree, rounds)``, ``seed_closure``, ``loop_seeds``, ``hole_keys``. ``columns.tree_sql`` gives the native
    expression of a fixed tree."""
    for name, f in (("tree_contains", tree_contains), ("canonical_word", canonical_text), ("tree_depth", tree_depth), ("is_seed", seed_of)):
        spark.udf.register(name, f)
    for name, f in (("tree_words", TreeWords), ("seed_closure", SeedClosure), ("loop_seeds", LoopSeeds), ("hole_keys", HoleKeys)):
        spark.udtf.register(name, f)
