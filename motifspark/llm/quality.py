"""Quality rules: a threshold table compiled into one projection of built-in expressions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import sealed, text_or_empty

#: Frequent function words of the four languages of the corpus.
STOP_WORDS = (
    "the of and to in is it that for on with as was at by be this are from or an not "
    "der die und den von zu das mit sich des auf für ist im dem nicht ein eine als auch "
    "de la le et les des en un du une que est pour qui dans par plus pas au sur "
    "el los del las se por con una su para es al lo como más o pero sus"
).split()


@dataclass(frozen=True)
class Rule:
    """A document fails if ``metric op bound`` holds, given at least ``min_words`` words."""

    metric: str
    op: str
    bound: float
    min_words: int = 0


#: Production thresholds. Ratios are per word or per line; a rule with ``min_words`` is silent on shorter texts.
DEFAULT_RULES = (
    Rule("n_words", "<", 20),
    Rule("repeat_ratio", ">", 0.30),
    Rule("mean_word_chars", "<", 1.5),
    Rule("mean_word_chars", ">", 18.0),
    Rule("symbol_ratio", ">", 0.30),
    Rule("dup_line_ratio", ">", 0.60, 50),
    Rule("stutter_ratio", ">", 0.30),
    Rule("capital_ratio", ">", 0.50),
    Rule("letter_ratio", "<", 0.40),
    Rule("stop_words", "<", 1, 80),
)

_WORD = r"[^\x20\x09-\x0D]+"


def text_metrics(text: Column) -> dict[str, Column]:
    """Base counts of a text that is not null; ``w`` and ``g`` are columns made by :func:`measure`."""
    lines = F.expr(r"filter(split(t, '\n'), x -> x rlike '[^\\x20\\x09-\\x0D]')")
    return {
        "n_words": F.size("w").cast("long"),
        "word_chars": F.length(F.regexp_replace(text, r"[\x20\x09-\x0D]+", "")).cast("long"),
        "n_symbols": (F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))).cast("long"),
        "n_lines": F.size(lines).cast("long"),
        "n_dup_lines": (F.size(lines) - F.size(F.array_distinct(lines))).cast("long"),
    }


def repeated_words(width: int = 8) -> Column:
    """Words inside windows of ``width`` words that occur twice or more in the row's word array ``w``.

    Window hashes (column ``g``) are sorted with their places only if some hash repeats; equal neighbours are then
    confirmed on the words themselves, so a clash of hashes cannot count.
    """
    return F.expr(
        f"""case when size(g) = size(array_distinct(g)) then 0L else
        aggregate(
          array_sort(transform(
            transform(array(array_sort(transform(g, (h, i) -> struct(h, i)))),
              s -> filter(transform(s, (x, j) -> struct(x.i as i,
                (j > 0 and s[greatest(j - 1, 0)].h = x.h
                  and slice(w, s[greatest(j - 1, 0)].i + 1, {width}) = slice(w, x.i + 1, {width}))
                or (s[least(j + 1, size(s) - 1)].h = x.h and j < size(s) - 1
                  and slice(w, s[least(j + 1, size(s) - 1)].i + 1, {width}) = slice(w, x.i + 1, {width})) as dup)),
                y -> y.dup))[0],
            z -> z.i)),
          struct(0L as n, -{width} as last),
          (a, i) -> struct(a.n + least({width}, i - a.last) as n, i as last),
          a -> a.n) end"""
    )


def measure(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Adds the base counts and the ratios which rules refer to; one narrow pass, no shuffle, no user function."""
    own = docs.withColumn("t", text_or_empty(F.col(text_col)))
    own = own.withColumn("w", F.expr(rf"filter(split(t, '[\\x20\\x09-\\x0D]+'), x -> x <> '')"))
    grams = "transform(sequence(1, size(w) - 7), i -> xxhash64(w[i-1], w[i], w[i+1], w[i+2], w[i+3], w[i+4], w[i+5], w[i+6]))"
    own = own.withColumn("g", F.expr(f"case when size(w) > 8 then {grams} else cast(array() as array<bigint>) end"))
    counts = text_metrics(F.col("t"))
    counts["n_repeat_words"] = repeated_words()
    stop = F.array(*[F.lit(x) for x in STOP_WORDS])
    counts["n_letters"] = F.length(F.regexp_replace("t", r"\P{L}+", "")).cast("long")
    counts["n_capitals"] = F.length(F.regexp_replace("t", r"\P{Lu}+", "")).cast("long")
    counts["n_stutter"] = F.expr("size(filter(w, (x, i) -> i > 0 and x = w[greatest(i - 1, 0)]))").cast("long")
    counts["stop_words"] = F.size(F.array_intersect(F.split(F.lower("t"), " ", -1), stop)).cast("long")
    own = sealed(own, [F.col(f"`{c}`") for c in docs.columns], counts)
    n = F.greatest(F.col("n_words"), F.lit(1))
    return own.withColumns(
        {
            "repeat_ratio": F.col("n_repeat_words") / n,
            "mean_word_chars": F.col("word_chars") / n,
            "symbol_ratio": F.col("n_symbols") / n,
            "dup_line_ratio": F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1)),
            "stutter_ratio": F.col("n_stutter") / n,
            "letter_ratio": F.col("n_letters") / F.greatest(F.col("word_chars"), F.lit(1)),
            "capital_ratio": F.col("n_capitals") / F.greatest(F.col("n_letters"), F.lit(1)),
        }
    )


def compile_rules(rules: tuple[Rule, ...]) -> Column:
    """Array of the names of failed rules, as one expression."""

    def failed(r: Rule) -> Column:
        c = F.col(r.metric)
        hit = {"<": c < r.bound, "<=": c <= r.bound, ">": c > r.bound, ">=": c >= r.bound}[r.op]
        return F.when(hit & (F.col("n_words") >= r.min_words), F.lit(f"{r.metric} {r.op} {r.bound:g}"))

    return F.filter(F.array(*[failed(r) for r in rules]), lambda x: x.isNotNull())


def quality_rules(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: tuple[Rule, ...] = DEFAULT_RULES) -> DataFrame:
    """``doc_id``, base counts, ``base_failed``, ``failed_rules`` and ``kept`` for every row.

    A null text counts as empty: all counts are zero and it fails the length rule. Repeated rows stay repeated; an
    empty table gives an empty result; other columns are ignored, whatever their names.
    """
    own = measure(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")))
    bad = (F.col("n_words") < 20) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 30)
    own = own.withColumn("base_failed", bad).withColumn("failed_rules", compile_rules(rules))
    kept = ~F.col("base_failed") & (F.size("failed_rules") == 0)
    base = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    return own.select("doc_id", *base, "base_failed", "failed_rules", kept.alias("kept"))
