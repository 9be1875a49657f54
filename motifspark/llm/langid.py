"""Language identification by compression with per-language zstandard raw-content dictionaries."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

UNKNOWN = "und"
_NOT_WORDS = re.compile(r"[\W\d_]+")


@dataclass(frozen=True)
class LanguageModel:
    """``dictionaries``: raw content by language. ``slice_bytes``: texts are encoded slice by slice, so that each
    part of a long text is judged by the dictionaries and not by its own earlier parts. ``min_margin``: share of
    the best size by which it must undercut the runner-up, or the text is rejected as too narrow a case."""

    dictionaries: dict[str, bytes]
    slice_bytes: int = 1024
    level: int = 6
    min_margin: float = 0.002


def letters_only(text: str) -> str:
    """Lower-cased text with every run of other characters made one space; letters are the characters of category L."""
    found = _NOT_WORDS.sub(" ", text)
    if not found.replace(" ", "a").isalpha():  # fractions and the like are words for the pattern, but no letters
        found = " ".join("".join(c if c.isalpha() else " " for c in found).split())
    return found.strip().lower()


def held_out(id_col: Column) -> Column:
    return F.crc32(id_col.cast("string")) % 3 == 1


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", docs_per_lang: int = 160, chars_per_doc: int = 2048, **options) -> LanguageModel:
    """Dictionaries from a bounded sample of labelled rows whose crc32(id) modulo 3 is not 1.

    At most ``docs_per_lang`` rows of ``chars_per_doc`` characters each are taken for a language, chosen by the hash of
    their id, so the sample, the model and what the driver holds do not grow with the input. Rows with a null text,
    label or id are not learned from; a table without labelled rows gives an empty model that rejects everything.
    """
    labelled = docs.select(F.col(id_col).alias("i"), F.col(text_col).cast("string").alias("t"), F.col(lang_col).cast("string").alias("l"))
    labelled = labelled.where("i is not null and l is not null and t is not null").where(~F.coalesce(held_out(F.col("i")), F.lit(True)))
    counts = {r["l"]: r["n"] for r in labelled.groupBy("l").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return LanguageModel({}, **options)
    draw = F.pmod(F.xxhash64(F.col("i").cast("string")), F.lit(1 << 20))
    shares = F.create_map(*[F.lit(x) for l, n in counts.items() for x in (l, int((1 << 20) * min(1.0, 4 * docs_per_lang / n)))])
    some = labelled.withColumn("h", draw).where(F.col("h") < shares[F.col("l")])
    some = some.select("l", "i", "h", F.substring("t", 1, chars_per_doc).alias("t"))
    rank = F.row_number().over(Window.partitionBy("l").orderBy("h", F.col("i").cast("string"), "t"))
    rows = some.withColumn("k", rank).where(F.col("k") <= docs_per_lang).collect()
    parts: dict[str, list[str]] = {l: [] for l in counts}
    for r in sorted(rows, key=lambda r: (r["l"], -r["k"])):
        parts[r["l"]].append(letters_only(r["t"]))
    return LanguageModel({l: " ".join(p).encode() for l, p in parts.items() if any(p)}, **options)


def _encoders(model: LanguageModel) -> list[tuple[str, zstandard.ZstdCompressor]]:
    out = []
    for lang in sorted(model.dictionaries):
        d = zstandard.ZstdCompressionDict(model.dictionaries[lang], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        d.precompute_compress(level=model.level)
        out.append((lang, zstandard.ZstdCompressor(dict_data=d, write_content_size=False, write_dict_id=False)))
    return out


def classify(text: str | None, encoders: list, model: LanguageModel) -> tuple[str, float, bool]:
    """``(language, score, rejected)``. The score is the share by which the best size undercuts the runner-up."""
    data = letters_only(text or "").encode()
    if not data or not encoders:
        return UNKNOWN, 0.0, True
    step = model.slice_bytes
    slices = [data[i : i + step] for i in range(0, len(data), step)]
    sizes = sorted((sum(len(z.compress(s)) for s in slices), lang) for lang, z in encoders)
    best = sizes[0][0]
    second = sizes[1][0] if len(sizes) > 1 else best * 2
    return sizes[0][1], min(1.0, (second - best) / second), second - best < model.min_margin * best


def identify(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, held_out, lang_pred, score, rejected`` for every row, from the whole text and nothing else.

    Null, empty and letterless texts are ``und`` with score 0 and are rejected; a tie goes to the language that sorts
    first and is rejected as too narrow. Repeated rows stay repeated; an empty table gives an empty result.
    """
    return annotate(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text")), model).select(
        "doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "lang_pred", "score", "rejected"
    )


def annotate(docs: DataFrame, model: LanguageModel, text_col: str = "text") -> DataFrame:
    """All columns of ``docs`` with ``lang_pred, score, rejected``, row by row as :func:`identify` says.

    Columns of these names in ``docs`` are replaced; an empty table gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoders = _encoders(model)
        for b in batches:
            texts = b.column(b.schema.get_field_index(text_col))
            found = [classify(t.as_py(), encoders, model) for t in texts]
            pred, score, rejected = zip(*found, strict=True) if found else ((), (), ())
            extra = [pa.array(pred, pa.string()), pa.array(score, pa.float64()), pa.array(rejected, pa.bool_())]
            yield pa.RecordBatch.from_arrays([*b.columns, *extra], [*b.schema.names, "lang_pred", "score", "rejected"])

    kept = docs.drop("lang_pred", "score", "rejected")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema)
    return kept.mapInArrow(run, f"{schema}, lang_pred string, score double, rejected boolean")


def accuracy(found: DataFrame, docs: DataFrame) -> DataFrame:
    """Held-out accuracy of :func:`identify` by language, against the labels of ``docs``."""
    truth = docs.where("lang is not null").select("doc_id", "lang")
    joined = found.where("held_out").join(truth, "doc_id")
    return joined.groupBy("lang").agg(F.count("*").alias("n"), F.avg((F.col("lang") == F.col("lang_pred")).cast("double")).alias("accuracy"))
