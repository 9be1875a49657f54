"""Benchmark decontamination as a prefix-filtered set join with exact verification.

Every window of an item (``window`` consecutive words; a shorter item is one window) is a set of word shingles that
must all occur for the window to occur. Shingles are ordered by their frequency in the corpus, and only the rarest of a
window, its prefix, is joined with the places of the documents. Where it meets one, the place of the window in the
document follows from the shingle's place in the window; windows that would start before the text or end behind it
are dropped, and the rest are compared word for word.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, durable, sized_broadcast, text_or_empty

_GAPS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words(text: Column) -> Column:
    """Lower-cased words: runs of a-z, 0-9 and characters beyond ASCII."""
    return F.array_remove(F.split(ascii_lower(text_or_empty(text)), _GAPS, -1), "")


def text_key(text: Column) -> Column:
    return F.xxhash64(text, F.length(text))


def _key(at: str, n: int) -> Column:
    return F.expr(f"xxhash64({', '.join(f'w[{at} + {i}]' for i in range(n))})")


def item_windows(bench: DataFrame, item_col: str, text_col: str, window: int) -> DataFrame:
    """``item_id, win, len``: the distinct windows of every item with an id and a word."""
    w = bench.select(F.col(item_col).cast("string").alias("item_id"), words(F.col(text_col)).alias("w")).where("item_id is not null and size(w) > 0")
    at = F.expr(f"explode(sequence(1, size(w) - least(size(w), {window}) + 1))")
    cut = w.select("item_id", "w", at.alias("at")).select("item_id", F.expr(f"slice(w, at, {window})").alias("win"))
    return cut.distinct().withColumn("len", F.size("win"))


def shingled(windows: DataFrame, shingle: int) -> DataFrame:
    """``wid, win, len, s, off, key``: the shingles of each window, of ``shingle`` words or its whole length."""
    own = windows.withColumn("w", F.col("win")).withColumn("s", F.least("len", F.lit(shingle)))
    at = own.select("*", F.expr("explode(sequence(0, len - s))").alias("off"))
    key = F.coalesce(*[F.when(F.col("s") == n, _key("off", n)) for n in range(1, shingle + 1)])
    return at.withColumn("key", key).drop("w")


def _places(docs: DataFrame, lengths: list[int]) -> DataFrame:
    """``dk, w, at, s, key`` for every place of every document and every shingle length in use.

    The word array is only referred to while places are made, joined and verified in one generated stage.
    """
    at = docs.where("size(w) > 0").select("doc_id", "tk", "w", F.expr("explode(sequence(0, size(w) - 1))").alias("at"))
    if len(lengths) == 1:
        n = lengths[0]
        return at.where(f"at + {n} <= size(w)").withColumn("s", F.lit(n)).withColumn("key", _key("at", n))
    made = [F.expr(f"case when at + {n} <= size(w) then struct({n} as s, xxhash64({', '.join(f'w[at + {i}]' for i in range(n))}) as key) end") for n in lengths]
    return at.select("doc_id", "tk", "w", "at", F.inline(F.filter(F.array(*made), lambda x: x.isNotNull())))


def decontaminate(
    docs: DataFrame,
    bench: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    window: int = 13,
    shingle: int = 5,
    share: int = 20,
    broadcast_bytes: int = 48 << 20,
    keep_key: bool = False,
) -> DataFrame:
    """``doc_id, n_words, n_hit, n_items, items_sha256, items, contaminated`` for every row of ``docs``.

    A word is hit inside any occurrence of a window; a document is contaminated if at least one word in ``share`` is
    hit. Null and wordless texts have no words and are clean; items without id or word are left out; repeated rows give
    equal results; rows that share an id but not the text are judged each on its own text (``keep_key`` adds its key ``tk``). Without items all rows are
    clean. The table of shingles is broadcast only below ``broadcast_bytes``, and shuffled by its keys beyond.
    """
    own = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("t"))
    own = own.select("doc_id", text_key(F.col("t")).alias("tk"), words(F.col("t")).alias("w"))

    parts = durable(shingled(item_windows(bench, item_col, item_text_col, window), shingle))
    lengths = sorted(r["s"] for r in parts.select("s").distinct().collect())  # at most `shingle` values
    none = F.array().cast("array<string>")
    key = ["tk"] if keep_key else []
    if not lengths:
        return own.select(
            *key, "doc_id", F.size("w").cast("long").alias("n_words"), F.lit(0).cast("long").alias("n_hit"), F.lit(0).cast("long").alias("n_items"),
            F.sha2(F.lit(""), 256).alias("items_sha256"), none.alias("items"), F.lit(False).alias("contaminated"),
        )

    keys = sized_broadcast(durable(parts.select("s", "key").distinct()), broadcast_bytes)
    freq = durable(_places(own, lengths).drop("w").join(keys, ["s", "key"]).groupBy("s", "key").agg(F.count("*").alias("freq")))
    rated = parts.join(freq, ["s", "key"], "left").withColumn("freq", F.coalesce("freq", F.lit(0)))
    rare = rated.groupBy("item_id", "win", "len", "s").agg(F.min(F.struct("freq", "key", "off")).alias("r"))
    prefix = durable(rare.where("r.freq > 0").select("item_id", "win", "len", "s", "r.key", "r.off"))
    prefix = sized_broadcast(prefix, broadcast_bytes)

    inside = F.expr("at >= off and at - off + len <= size(w)")
    same = F.expr("slice(w, at - off + 1, len) = win")
    met = _places(own, lengths).alias("d").join(prefix.alias("p"), ["s", "key"]).where(inside & same)
    met = met.select("doc_id", "tk", "item_id", F.expr("at - off").alias("a"), F.expr("at - off + len").alias("z"))
    per_doc = met.groupBy("doc_id", "tk").agg(F.sort_array(F.collect_set(F.struct("a", "z"))).alias("spans"), F.sort_array(F.collect_set("item_id")).alias("items"))
    hit = F.expr("aggregate(spans, struct(0L as n, 0 as z), (x, s) -> struct(x.n + greatest(0, s.z - greatest(x.z, s.a)) as n, greatest(x.z, s.z) as z), x -> x.n)")
    per_doc = per_doc.select(F.col("doc_id").alias("i"), F.col("tk").alias("k"), hit.alias("n_hit"), "items")

    base = own.select("doc_id", "tk", F.size("w").cast("long").alias("n_words"))
    out = base.join(per_doc, F.col("doc_id").eqNullSafe(F.col("i")) & (F.col("tk") == F.col("k")), "left")
    out = out.withColumn("n_hit", F.coalesce("n_hit", F.lit(0).cast("long"))).withColumn("items", F.coalesce("items", none))
    return out.select(
        *key,
        "doc_id",
        "n_words",
        "n_hit",
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        "items",
        ((F.col("n_hit") > 0) & (F.col("n_hit") * share >= F.col("n_words"))).alias("contaminated"),
    )
