"""Baselines: a local-model miner that grows trees out of single activities, and sequential patterns."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.fpm import PrefixSpan
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifspark.plans.language import words
from motifspark.plans.tree import OPS, SYMMETRIC, Tree, canonical_word, leaf, node, parse_tree

from . import kernel
from .mine import blocks, encode, gathered


def fragments(coded: DataFrame, trees: list[Tree], codes: dict[str, int]) -> list[int]:
    """Matches of each tree that do not overlap, summed over all cases: the program runs again from each end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(trees), np.int64)
        for b in gathered(batches):
            for acts, (weight,) in blocks(b, ["weight"]):
                tr, w = kernel.Traces(acts, codes), weight.to_numpy()
                for i, t in enumerate(trees):
                    rows, start = np.arange(tr.rows), np.zeros(tr.rows, np.int32)
                    while len(rows):
                        end = kernel.scan(tr, t, rows, start).end
                        rows, start = rows[end < tr.far], end[end < tr.far]
                        total[i] += w[rows].sum()
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(trees), dtype=np.int32)), pa.array(total)], ["i", "n"])

    got = {r["i"]: r["n"] for r in coded.mapInArrow(run, "i int, n bigint").groupBy("i").agg(F.sum("n").alias("n")).collect()}
    return [got.get(i, 0) for i in range(len(trees))]


def determinism(t: Tree) -> float:
    """Inverse of the mean number of letters that may follow a proper prefix of a word of the tree."""
    follow: dict[tuple, set[str]] = {}
    for w in words(t, 2, compact=False):
        for i, a in enumerate(w):
            follow.setdefault(w[:i], set()).add(a)
    return len(follow) / sum(map(len, follow.values()))


def local_models(log: DataFrame, size: int = 4, limit: int = 500, min_support: float = 0.7, min_determinism: float = 0.5) -> DataFrame:
    """``tree, n_fragments, support, determinism, quality``: the ``limit`` best trees of up to ``size`` leaves.

    Support is c/(c+1) for c fragments that do not overlap, quality the mean of support and determinism. Each round
    replaces a leaf of every kept tree by an operator over the leaf and another activity, in both orders.
    """
    coded, codes = encode(log)
    kept: dict[str, tuple] = {}
    frontier = [leaf(a) for a in codes]
    for n in range(1, size + 1):
        counts = fragments(coded, frontier, codes) if frontier else []
        rows = []
        for t, c in zip(frontier, counts, strict=True):
            d, s = determinism(t), c / (c + 1)
            if s >= min_support and d >= min_determinism:
                rows.append((canonical_word(t), int(c), round(s, 6), round(d, 6), round((s + d) / 2, 6)))
        rows.sort(key=lambda r: (-r[4], -r[1], r[0]))
        rows = rows[:limit]
        kept |= {r[0]: r for r in rows}
        grown: dict[str, Tree] = {}
        if n < size:
            for r in rows:
                t = parse_tree(r[0])
                for path, x in t.leaves():
                    for y in codes:
                        if y not in t.alphabet:
                            for op in OPS:
                                for a, b in ((x, leaf(y)), (leaf(y), x))[: 1 if op in SYMMETRIC else 2]:
                                    new = t.replace(path, node(op, a, b))
                                    grown.setdefault(canonical_word(new), new)
        frontier = list(grown.values())
    best = sorted(kept.values(), key=lambda r: (-r[4], -r[1], r[0]))[:limit]
    return log.sparkSession.createDataFrame(best, "tree string, n_fragments bigint, support double, determinism double, quality double")


def sequential_patterns(log: DataFrame, min_support: float, max_length: int = 3) -> DataFrame:
    """``sequence, n`` of Spark's PrefixSpan; counts of pure sequences must coincide with the miner's."""
    each = log.select(F.transform("acts", lambda a: F.array(a)).alias("sequence"))
    found = PrefixSpan(minSupport=min_support, maxPatternLength=max_length).findFrequentSequentialPatterns(each)
    flat = F.array_join(F.transform("sequence", lambda s: s[0]), " ")
    return found.where(F.forall("sequence", lambda s: F.size(s) == 1)).select(flat.alias("sequence"), F.col("freq").alias("n"))
