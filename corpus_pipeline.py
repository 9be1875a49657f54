"""Corpus preparation: five stages from raw documents to packed training sequences."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifspark.llm import decontam, langid, neardup, packing, secrets, simhash
from motifspark.llm.common import durable, new_folder, read_table, sized_broadcast
from motifspark.sources.shared import remove, scratch

#: Bound on a table of ids that a stage broadcasts.
BROADCAST_BYTES = 32 << 20


def keep_identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised; those with no letter (null and empty texts too) or too narrow a margin go.

    A tie of two languages is too narrow; repeated rows share one verdict; an empty table stays empty.
    """
    model = langid.fit(docs)
    return langid.annotate(docs, model).where("not rejected").select(*[F.col(f"`{c}`") for c in docs.columns])


def keep_one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str, grouped: Callable[[DataFrame], DataFrame] = simhash.near_duplicates) -> DataFrame:
    """One row of each group of near duplicates: the least doc_id, and one row of those that repeat it.

    Rows without a doc_id cannot be told apart and stay. The ids that go are broadcast below a bound, so that texts are
    shuffled only where repeats are many.
    """
    groups = durable(grouped(docs).where("doc_id is not null"))
    gone = _sized(groups.where("doc_id <> component_id").select("doc_id").distinct())
    kept = docs.join(gone, "doc_id", "left_anti")
    twice = durable(groups.groupBy("doc_id").count().where("count > 1").select("doc_id"))
    if not twice.isEmpty():
        again = _sized(twice)
        kept = kept.join(again, "doc_id", "left_anti").unionByName(kept.join(again, "doc_id", "left_semi").dropDuplicates(["doc_id"]))
    return kept.select(*[F.col(f"`{c}`") for c in docs.columns])


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group linked by sets of five-word shingles whose Jaccard similarity is 0.8 or more.

    Links within the covering radius of SimHash are found first, the others by prefixes. The least doc_id of a group
    stays; texts without a word are copies of each other; rows without a doc_id stay; an empty table stays empty.
    """
    return keep_one_of_each_group(spark, docs, sf_dir, neardup.similar_groups)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which less than a twentieth of the words are benchmark passages, each judged by its own text.

    Null and wordless texts are clean; repeated rows share one verdict; an empty table stays empty.
    """
    found = decontam.decontaminate(docs, read_table(spark, sf_dir, "benchmark"), keep_key=True).where("contaminated")
    found = _sized(found.select(F.col("doc_id").alias("i"), F.col("tk").alias("k")).distinct())
    same = docs.doc_id.eqNullSafe(found.i) & (decontam.text_key(docs.text.cast("string")) == found.k)
    return docs.join(found, same, "left_anti")


def _sized(ids: DataFrame) -> DataFrame:
    return sized_broadcast(durable(ids), BROADCAST_BYTES)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with secrets in their texts masked and the character count brought up to date."""
    return secrets.redact(docs).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of packed sequences; null and empty texts are the end id alone, repeated rows are packed each, an empty
    table gives no piece."""
    return packing.pack_documents(docs)


STAGES = [
    ("language_id", keep_identified),
    ("near_dedup", drop_near_copies),
    ("decontamination", drop_contaminated),
    ("secret_scan", redact_secrets),
    ("packing", pack),
]

#: Compression sizes, fingerprints and token ids are beyond SQL; tests/llm holds the run against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on ``documents``; each result is written as Parquet in the shared folder and read back."""
    docs = read_table(spark, sf_dir, "documents")
    folder = new_folder(spark, "pipeline-")
    for i, (name, stage) in enumerate(STAGES):
        with scratch(spark):  # what a stage keeps on the way goes once its result is written
            stage(spark, docs, sf_dir).write.parquet(f"{folder}/{i}-{name}")
        if i:
            remove(spark, f"{folder}/{i - 1}-{STAGES[i - 1][0]}")
        docs = spark.read.parquet(f"{folder}/{i}-{name}")
    return docs
