"""Post-processing: drop what follows from other patterns and all but one of patterns with equal languages.

Closures, loop seeds and language keys are made per pattern on the executors; which pattern dominates which is then an
equi-join on canonical words, not a comparison of all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifspark.plans.language import LanguageTooLarge, language_key, words
from motifspark.plans.lattice import seed_words
from motifspark.plans.seeds import loop_seeds, seed_kinds
from motifspark.plans.tree import Tree, canonical_word, parse_tree


def closure_table(patterns: DataFrame, transitive: bool = False) -> DataFrame:
    """``pid, seed, kind`` for the generalised seeds (regular, alternative) and loop seeds of each pattern."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for pid in b.column(0).to_pylist():
                t = parse_tree(pid)
                rows += [(pid, s, kind) for s, kind in seed_kinds(t).items()]
                rows += [(pid, s, "loop") for s in loop_seeds(t, transitive)]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.string()) for i in range(3)], ["pid", "seed", "kind"])

    return patterns.select("pid").mapInArrow(run, "pid string, seed string, kind string")


def with_language_key(patterns: DataFrame) -> DataFrame:
    """``pid, lang``: the key of each pattern's language."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            pids = b.column(0)
            yield pa.RecordBatch.from_arrays([pids, pa.array([language_key(parse_tree(p)) for p in pids.to_pylist()], pa.string())], ["pid", "lang"])

    return patterns.select("pid").mapInArrow(run, "pid string, lang string")


def equivalence_classes(patterns: DataFrame) -> DataFrame:
    """``pid, lang, representative``: the least canonical word of each language."""
    keyed = with_language_key(patterns)
    return keyed.join(keyed.groupBy("lang").agg(F.min("pid").alias("representative")), "lang").select("pid", "lang", "representative")


def regular_maximal(patterns: DataFrame) -> DataFrame:
    """Patterns that are no regular seed of another one in the table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            seeds = sorted({s for pid in b.column(0).to_pylist() for s in seed_words(parse_tree(pid))})
            yield pa.RecordBatch.from_arrays([pa.array(seeds, pa.string())], ["pid"])

    return patterns.join(patterns.select("pid").mapInArrow(run, "pid string").distinct(), "pid", "left_anti")


def postprocess(patterns: DataFrame, generalized: bool = True, loop: bool = True, equivalence: bool = True, transitive: bool = False) -> DataFrame:
    """``pid, lang`` of the patterns that stay.

    Removal is decided on the whole input: a pattern goes if another one of a different language has it among its
    generalised seeds or loop seeds, and takes its equivalents along; of every language left one pattern stays.
    """
    keyed = with_language_key(patterns)
    kinds = [k for k, on in (("regular", generalized), ("alternative", generalized), ("loop", loop)) if on]
    kept = keyed
    if kinds:
        seeds = closure_table(patterns, transitive).where(F.col("kind").isin(kinds))
        big = keyed.select(F.col("pid").alias("big"), F.col("lang").alias("big_lang"))
        hit = seeds.join(big, seeds.pid == big.big).select(F.col("seed").alias("pid"), "big_lang")
        gone = keyed.join(hit, "pid").where("lang <> big_lang").select("lang").distinct()
        kept = keyed.join(gone, "lang", "left_anti")
    if equivalence:
        kept = kept.groupBy("lang").agg(F.min("pid").alias("pid"))
    return kept.select("pid", "lang")


def removals(patterns: DataFrame, transitive: bool = False) -> DataFrame:
    """``pid, by, kind``: every pattern that post-processing finds to follow from another one, and in which way."""
    keyed = with_language_key(patterns)
    own, big = keyed.select(F.col("pid").alias("seed"), "lang"), keyed.select("pid", F.col("lang").alias("big_lang"))
    met = closure_table(patterns, transitive).distinct().join(own, "seed").join(big, "pid").where("lang <> big_lang")
    return met.select(F.col("seed").alias("pid"), F.col("pid").alias("by"), "kind")


def cost_drivers(patterns: DataFrame) -> DataFrame:
    """``pid, depth, n_leaves, n_words, n_seeds, n_loop_seeds``: what makes post-processing of a pattern costly."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [(p, *drivers_of(parse_tree(p))) for p in b.column(0).to_pylist()]
            cols = list(zip(*rows, strict=True)) or [()] * 6
            types = [pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], ["pid", "depth", "n_leaves", "n_words", "n_seeds", "n_loop_seeds"])

    return patterns.select("pid").mapInArrow(run, "pid string, depth int, n_leaves int, n_words bigint, n_seeds bigint, n_loop_seeds bigint")


def drivers_of(t: Tree) -> tuple[int, int, int | None, int, int]:
    """Depth, leaves, words of two rounds (none beyond the limit of languages), generalised and loop seeds."""
    try:
        n_words = len(words(t, 2))
    except LanguageTooLarge:
        n_words = None
    return t.depth, t.n_leaves, n_words, len(seed_kinds(t)), len(loop_seeds(t))


def post_report(patterns: DataFrame) -> list[tuple[str, int, int, float]]:
    """``(step, before, after, ratio)`` for each pruning alone and for all of them."""
    n = patterns.count()
    steps = {
        "generalized": {"loop": False, "equivalence": False},
        "loop": {"generalized": False, "equivalence": False},
        "equivalence": {"generalized": False, "loop": False},
        "all": {},
    }
    out = []
    for name, flags in steps.items():
        after = postprocess(patterns, **flags).count()
        out.append((name, n, after, round(after / n, 6) if n else 1.0))
    return out


def monotonicity_violations(frequent: dict[str, int]) -> tuple[int, int]:
    """``(pairs, violations)``: seeds of constraining trees must be at least as frequent as the trees."""
    pairs = bad = 0
    for pid, n in frequent.items():
        t = parse_tree(pid)
        if not t.has("xor"):
            for s in seed_words(t):
                if s in frequent:
                    pairs += 1
                    bad += frequent[s] < n
    return pairs, bad


def canonical_pids(texts: list[str]) -> list[str]:
    return [canonical_word(parse_tree(t)) for t in texts]
