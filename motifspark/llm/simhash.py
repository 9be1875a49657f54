"""SimHash near-duplicate detection with covering locality-sensitive hashing.

Fingerprints are majority votes over hashed word shingles. Candidate pairs come from ``2**(r+1) - 1`` structured
bit masks: every bit position carries a non-zero vector of r+1 bits, and table v keeps the positions whose vector has
odd overlap with v. The at most r positions in which two fingerprints differ span at most r dimensions, so some
table keeps none of them and the pair collides there: no pair within the radius is lost.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, sized_broadcast
from .components import connected_components

SEED = 42
BITS = 64
CHUNK = 1 << 15
#: Bound on the table of fingerprints with a component other than their row's own that is broadcast.
BROADCAST_BYTES = 32 << 20


def fingerprint_bytes(text: bytes, shingle: int = 3) -> int:
    """SimHash of one UTF-8 text; zero if it has no word."""
    words = text.lower().split()  # on bytes: A-Z only, and the six ASCII white spaces
    if not words:
        return 0
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), SEED)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    starts, ends = starts[: len(words) - shingle + 1].tolist(), ends[shingle - 1 :].tolist()
    votes = np.zeros(BITS, np.int64)
    digest = xxhash.xxh64_intdigest
    for at in range(0, len(starts), CHUNK):
        pairs = zip(starts[at : at + CHUNK], ends[at : at + CHUNK], strict=True)
        h = np.array([digest(joined[a:b], SEED) for a, b in pairs], dtype="<u8")
        votes += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    over = 2 * votes > len(starts)
    return int(np.packbits(over, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """``(doc_id, fp)`` with the 64-bit fingerprint as a signed long. Null, empty and wordless texts get zero."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = [fingerprint_bytes(t.as_buffer().to_pybytes() if t.is_valid else b"", shingle) for t in b.column(1)]
            fp = pa.array(np.array(fps, dtype=np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays([b.column(0), fp], ["doc_id", "fp"])

    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").cast("binary").alias("t"))
    return src.mapInArrow(run, "doc_id long, fp long")


def covering_masks(radius: int) -> list[int]:
    """Masks of the covering family, as unsigned 64-bit integers."""
    width = (1 << (radius + 1)) - 1
    vector = [1 + i % width for i in range(BITS)]
    return [sum(1 << i for i in range(BITS) if bin(vector[i] & v).count("1") % 2) for v in range(1, width + 1)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def near_edges(distinct: DataFrame, radius: int = 2, small: int = 8) -> DataFrame:
    """Links ``(u, v)`` that join all fingerprints (column ``fp``, distinct) within ``radius`` differing bits.

    Buckets of a covering table with up to ``small`` members have their pairs checked one by one. In larger buckets no
    pairs are made: members are grouped by the points of the ball of radius/2 (2: one flipped bit) over the bits
    which the table's mask leaves free, where two members meet exactly if they differ in at most ``radius`` bits,
    and each is linked with the least member at the point. Both ways are exact and reach the same components.
    """
    if radius != 2:
        raise ValueError("the exact path for large buckets is written for radius 2")
    masks = covering_masks(radius)
    keys = F.array(*[F.struct(F.lit(i).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("k")) for i, m in enumerate(masks)])
    placed = distinct.select("fp", F.inline(keys))
    sizes = placed.groupBy("t", "k").agg(F.count("*").alias("n")).where("n > 1")
    members = durable(placed.join(sizes, ["t", "k"]))

    few = members.where(F.col("n") <= small).groupBy("t", "k").agg(F.sort_array(F.collect_list("fp")).alias("f"))
    pairs = F.expr(
        f"""flatten(transform(f, (x, i) -> transform(filter(slice(f, i + 2, size(f)),
            y -> bit_count(x ^ y) <= {radius}), y -> struct(y as u, x as v))))"""
    )
    direct = few.select(F.inline(pairs))

    flips = [[0] + [_signed(1 << b) for b in range(BITS) if not m >> b & 1] for m in masks]
    ball = F.element_at(F.array(*[F.array(*[F.lit(x).cast("long") for x in f]) for f in flips]), F.col("t") + 1)
    near = members.where(F.col("n") > small).select("t", "fp", F.explode(ball).alias("x"))
    near = near.select("t", "fp", F.col("fp").bitwiseXOR(F.col("x")).alias("z"))
    least = near.groupBy("t", "z").agg(F.min("fp").alias("v"), F.count("*").alias("n")).where("n > 1")
    stars = near.join(least.select("t", "z", "v"), ["t", "z"]).where("fp <> v").select(F.col("fp").alias("u"), "v")
    return direct.union(stars).distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, radius: int = 2) -> DataFrame:
    """One row per document: ``doc_id, fingerprint, component_id``.

    ``component_id`` is the smallest doc_id reachable over links of at most ``radius`` differing bits, itself included.
    Null, empty and wordless texts have fingerprint zero and are linked like any other; repeated rows stay repeated;
    rows with a null doc_id keep a null id and take part in links through their fingerprint only; an empty table gives
    an empty result. Exact copies meet in one group before anything is paired, so hot groups cost one aggregate.
    """
    prints = durable(fingerprints(docs, id_col, text_col, shingle))
    classes = durable(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id"), F.count("*").alias("m")))
    comp = connected_components(near_edges(classes.select("fp"), radius))
    linked = classes.join(comp.withColumnRenamed("node", "fp"), "fp")
    least = linked.groupBy("root").agg(F.min("first_id").alias("least_id"))
    moved = linked.join(least, "root").select("fp", "least_id")
    # rows that stand for themselves need no lookup, so only copies and linked fingerprints travel, by broadcast in bounds
    ids = classes.join(moved, "fp", "left").where("m > 1 or least_id < first_id").select("fp", F.coalesce("least_id", "first_id").alias("group_id"))
    looked = prints.join(sized_broadcast(durable(ids), BROADCAST_BYTES), "fp", "left")
    return looked.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.coalesce("group_id", "doc_id").alias("component_id"))
