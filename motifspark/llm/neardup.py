"""Near copies: SimHash links with covering masks, checked and completed by the exact similarity of shingle sets.

Fingerprints within the covering radius give the first candidates. Texts of similarity 0.8 differ in some ten of 64
bits, beyond any radius whose ``2**(r+1) - 1`` masks could be afforded, so the links that covering cannot see come from
shingles: in any one order of the shingles, two sets of similarity t or more share one among the first
``n - ceil(t * n) + 1`` of each, n being its own size. Frequent shingles come last in the order, which keeps the
meeting places small. Candidates of either origin are sifted by 128-bit fingerprints, far beyond the distance that pairs
of the similarity can have, and what passes is checked on the whole sets.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, measured_bytes, release, sized_broadcast
from .components import connected_components
from .simhash import SEED, near_edges

#: Similarity as a fraction, so that all comparisons are of whole numbers.
SIMILARITY = (4, 5)
#: Bound on the frequent shingles that a task knows by count; others count as rare. It changes the order, not the result.
FREQUENT = 200_000
BROADCAST_BYTES = 32 << 20
#: Bytes of text that are turned into sets at a time.
WINDOW = 4 << 20

#: Differing bits of 128 beyond which sets are not compared. A pair at the similarity differs in 19.4 on average with a
#: deviation of 4.1, so one in some 10 billion of them is lost; unrelated texts differ in 64, deviation 5.7.
SIFT = 46

#: Sets with which all others at a meeting place are compared, before those still apart are compared with one another.
CENTRES = 16

PRINTS = "doc_id long, tk long, key long, n int, fp long, fq long, h long, c long"


def shingle_set(text: bytes, shingle: int = 5) -> np.ndarray:
    """Sorted distinct hashes of the shingles of one UTF-8 text; a shorter text is one shingle, one without a word none."""
    words = text.lower().split()  # on bytes: A-Z only, and the six ASCII white spaces
    if not words:
        return np.zeros(0, np.int64)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    last = min(shingle, len(words)) - 1
    pairs = zip(starts[: len(words) - last].tolist(), ends[last:].tolist(), strict=True)
    return np.unique(np.fromiter((xxhash.xxh64_intdigest(joined[a:b], SEED) for a, b in pairs), np.uint64, len(words) - last).view(np.int64))


def set_key(s: np.ndarray) -> int:
    return int(np.uint64(xxhash.xxh3_64_intdigest(s.tobytes(), SEED)).view(np.int64))


def mixed(s: np.ndarray) -> np.ndarray:
    """A second hash out of a first one, by two rounds of multiply and shift."""
    x = s.view(np.uint64)
    for _ in range(2):
        x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return (x ^ (x >> np.uint64(32))).view(np.int64)


def set_fingerprint(s: np.ndarray, chunk: int = 1 << 15) -> int:
    """SimHash of a set of shingle hashes as a signed number; zero for the empty set."""
    votes = np.zeros(64, np.int64)
    for at in range(0, len(s), chunk):
        votes += np.unpackbits(s[at : at + chunk].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * votes > len(s), bitorder="little").view("<i8")[0])


def far(x: str, y: str) -> str:
    """SQL: the 128 bits of two sets differ too much for the similarity."""
    return f"bit_count({x}fp ^ {y}fp) + bit_count({x}fq ^ {y}fq) > {SIFT}"


def _windows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Slices of the batches with their texts (last column), of bounded size each."""
    for b in batches:
        at, held, texts = 0, 0, []
        for i, t in enumerate(b.column(b.num_columns - 1)):
            texts.append(t.as_buffer().to_pybytes() if t.is_valid else b"")
            held += len(texts[-1])
            if held > WINDOW:
                yield b.slice(at, i + 1 - at), texts
                at, held, texts = i + 1, 0, []
        if texts:
            yield b.slice(at), texts


def _batch(cols: list, names: str) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c) if not isinstance(c, pa.Array) else c for c in cols], [x.split()[0] for x in names.split(", ")])


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    t = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(t).alias("tk"), t.cast("binary").alias("t"))


def set_prints(docs: DataFrame, shingle: int) -> DataFrame:
    """One row of ``doc_id, tk, key, n, fp, fq`` for each text: hash of the text, hash, size and fingerprints of its set. Rows
    with ``h, c`` instead tell shingles that repeat within a window and how often, which is enough for an order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, texts in _windows(batches):
            sets = [shingle_set(t, shingle) for t in texts]
            h, c = np.unique(np.concatenate(sets), return_counts=True)
            h, c = h[c > 1], c[c > 1].astype(np.int64)
            k, none = len(sets), np.zeros(len(h), np.int64)
            empty = pa.nulls(k, pa.int64())
            own = [np.array([f(s) for s in sets], t) for f, t in ((set_key, np.int64), (len, np.int32), (set_fingerprint, np.int64), (lambda s: set_fingerprint(mixed(s)), np.int64))]
            yield _batch([b.column(0), b.column(1), *own, empty, empty], PRINTS)
            if len(h):
                gone = pa.nulls(len(h), pa.int64())
                yield _batch([gone, gone, gone, none.astype(np.int32), gone, gone, h, c], PRINTS)

    return docs.mapInArrow(run, PRINTS)


PLACED = "h long, key long, n int, r int, fp long, fq long"


def prefixes(docs: DataFrame, shingle: int, counts: DataFrame, frequent: int = FREQUENT) -> DataFrame:
    """``(h, key, n, r, fp, fq)``: the shingles of each set at which sets of the similarity must meet, rarest first.

    ``r`` counts the shingles from there to the end of the set: two sets that first meet there share no more than the
    lesser of the two counts.
    """
    top = counts.orderBy(F.desc("c"), "h").limit(frequent).toPandas().sort_values("h")
    known = docs.sparkSession.sparkContext.broadcast((top.h.to_numpy(np.int64), top.c.to_numpy(np.int64)))
    num, den = SIMILARITY

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hs, cs = known.value
        for _, texts in _windows(batches):
            out: tuple[list, ...] = [], [], [], [], [], []
            for text in texts:
                h = shingle_set(text, shingle)
                if not len(h):
                    continue
                c = np.zeros(len(h), np.int64)
                if len(hs):
                    at = np.minimum(np.searchsorted(hs, h), len(hs) - 1)
                    c = np.where(hs[at] == h, cs[at], 0)
                first = len(h) - -(-num * len(h) // den) + 1
                out[0].append(h[np.lexsort((h, c))[:first]])
                out[1].append(np.full(first, set_key(h), np.int64))
                out[2].append(np.full(first, len(h), np.int32))
                out[3].append((len(h) - np.arange(first)).astype(np.int32))
                out[4].append(np.full(first, set_fingerprint(h), np.int64))
                out[5].append(np.full(first, set_fingerprint(mixed(h)), np.int64))
            if out[0]:
                yield _batch([np.concatenate(x) for x in out], PLACED)

    return docs.mapInArrow(run, PLACED)


def _similar(pairs: DataFrame, docs: DataFrame, classes: DataFrame, shingle: int) -> DataFrame:
    """The pairs ``(u, v)`` of set keys whose sets are of the similarity. Sets are made again for texts of some pair only."""
    num, den = SIMILARITY
    pairs = durable(pairs.distinct())
    release(docs.sparkSession)
    keys = pairs.select(F.col("u").alias("key")).union(pairs.select("v")).distinct()
    wanted = durable(classes.join(keys, "key").select(F.col("first_id").alias("i"), F.col("first_tk").alias("k")))
    named = docs.join(sized_broadcast(wanted, BROADCAST_BYTES), docs.doc_id.eqNullSafe(F.col("i")) & (docs.tk == F.col("k")), "left_semi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, texts in _windows(batches):
            sets = [shingle_set(t, shingle) for t in texts]
            n = np.array([len(s) for s in sets], np.int64)
            sh = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(n))), pa.int32()), pa.array(np.concatenate(sets)))
            yield _batch([np.array([set_key(s) for s in sets], np.int64), n.astype(np.int32), sh], "key, n, sh")

    sets = durable(named.mapInArrow(run, "key long, n int, sh array<long>"))
    if sets.count() > wanted.count():  # rows that repeat an id and its text
        sets = durable(sets.dropDuplicates(["key"]))
    a, b = (sets.select(F.col("key").alias(x), F.col("n").alias(f"n{x}"), F.col("sh").alias(f"s{x}")) for x in "uv")
    both = pairs.join(a, "u").join(b, "v").withColumn("i", F.size(F.array_intersect("su", "sv")))
    return durable(both.where(f"{num + den} * i >= {num} * (nu + nv)").select("u", "v"))


def similar_edges(docs: DataFrame, prints: DataFrame, classes: DataFrame, counts: DataFrame, shingle: int, frequent: int = FREQUENT, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Links ``(u, v)`` that join set keys exactly as all pairs of the similarity would.

    First every set is compared with one other at each of its meeting places, and at its fingerprint and the
    fingerprints linked with it, then with a fixed number of others where sets of several components still meet; what
    these links join need not be compared again. Only pairs that meet somewhere and are still apart follow.
    """
    num, den = SIMILARITY
    copies = classes.where("m > 1").select("key", "first_id", "first_tk")
    again = prints.join(copies, "key").where("not (doc_id <=> first_id and tk = first_tk)")
    again = durable(again.select(F.col("doc_id").alias("i"), F.col("tk").alias("k")).distinct())
    own = docs
    if measured_bytes(again) <= broadcast_bytes:  # else copies meet at equal keys, which no later step pairs
        own = docs.join(F.broadcast(again), docs.doc_id.eqNullSafe(F.col("i")) & (docs.tk == F.col("k")), "left_anti")
    placed = durable(prefixes(own, shingle, counts, frequent))
    met = durable(placed.groupBy("h").agg(F.count("*").alias("m")).where("m > 1").select("h"))
    members = durable(placed.join(sized_broadcast(met, broadcast_bytes), "h"))
    release(docs.sparkSession)
    near = lambda x, y: f"{num + den} * least({x}r, {y}r) >= {num} * ({x}n + {y}n) and not {far(x, y)}"
    # keys are hashes, so the least one is as good a centre as any, and the same at most meeting places of similar sets
    first = members.groupBy("h").agg(F.min(F.struct("key", "n", "r", "fp", "fq")).alias("p"))
    stars = members.join(first, "h").where("key <> p.key").where(near("", "p.")).select(F.greatest("key", "p.key").alias("u"), F.least("key", "p.key").alias("v"))

    by_print = classes.where("n > 0").groupBy("fp").agg(F.min(F.struct("key", "fq")).alias("rep"))
    same = classes.where("n > 0").join(by_print, "fp").where("key <> rep.key").where(f"bit_count(fq ^ rep.fq) <= {SIFT}")
    same = same.select(F.greatest("key", "rep.key").alias("u"), F.least("key", "rep.key").alias("v"))
    a, b = (by_print.select(F.col("fp").alias(x), F.col("rep").alias(f"k{x}")) for x in "uv")
    covered = near_edges(by_print.select("fp")).join(a, "u").join(b, "v").where(f"bit_count(ku.fq ^ kv.fq) <= {SIFT}")
    covered = covered.select(F.greatest("ku.key", "kv.key").alias("u"), F.least("ku.key", "kv.key").alias("v"))

    edges = _similar(stars.union(same).union(covered), docs, classes, shingle)
    for last in (False, True):
        release(docs.sparkSession)
        comp = connected_components(edges).withColumnRenamed("node", "key")
        rooted = members.join(sized_broadcast(comp, broadcast_bytes), "key", "left").withColumn("root", F.coalesce("root", "key"))
        several = rooted.groupBy("h").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count("*").alias("m")).where("lo < hi and m > 2").select("h")
        members = durable(rooted.join(sized_broadcast(durable(several), broadcast_bytes), "h", "left_semi"))
        if members.isEmpty():
            break
        y = members
        if not last:
            # the set with most links, as the original of many copies, is near to those that are not near to each other
            ends = edges.select(F.col("u").alias("key")).union(edges.select("v")).groupBy("key").agg(F.count("*").alias("links"))
            linked = members.join(sized_broadcast(durable(ends), broadcast_bytes), "key", "left").withColumn("links", F.coalesce("links", F.lit(0)))
            picks = [F.struct("links", "key"), *[F.xxhash64(F.lit(i), "key") for i in range(CENTRES)]]
            y = linked.groupBy("h").agg(F.array_distinct(F.array(*[F.max_by(F.struct(*members.columns), o) for o in picks])).alias("p")).select(F.inline("p"))
        x, y = members.alias("x"), y.alias("y")
        once = F.col("x.key") > F.col("y.key") if last else F.lit(True)
        met = x.join(y, (F.col("x.h") == F.col("y.h")) & (F.col("x.root") != F.col("y.root")) & once & F.expr(near("x.", "y.")))
        rest = durable(met.select(F.greatest("x.key", "y.key").alias("u"), F.least("x.key", "y.key").alias("v")).distinct())
        members = members.drop("root")
        if not rest.isEmpty():
            edges = durable(edges.union(_similar(rest, docs, classes, shingle)))
    return edges


def similar_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, frequent: int = FREQUENT, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """``(doc_id, component_id)`` for every row: the least doc_id reachable over pairs of the similarity or more.

    Null, empty and wordless texts have the empty set and are copies of each other; rows with a null doc_id keep it
    and join others through their text only; repeated rows stay repeated; an empty table gives an empty result. Sets
    are told apart by 64 bits of their hash.
    """
    texts = _texts(docs, id_col, text_col)
    made = durable(set_prints(texts, shingle))
    prints = made.where("key is not null")
    counts = made.where("h is not null").groupBy("h").agg(F.sum("c").alias("c")).where("c > 4")
    one = F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "tk"))
    classes = prints.groupBy("key").agg(one.alias("o"), F.min("n").alias("n"), F.min("fp").alias("fp"), F.min("fq").alias("fq"), F.count("*").alias("m"))
    classes = durable(classes.select("key", F.col("o.doc_id").alias("first_id"), F.col("o.tk").alias("first_tk"), "n", "fp", "fq", "m"))
    comp = connected_components(similar_edges(texts, prints, classes, counts, shingle, frequent, broadcast_bytes))
    linked = classes.join(comp, classes.key == comp.node)
    least = linked.groupBy("root").agg(F.min("first_id").alias("least_id"))
    moved = linked.join(least, "root").where("least_id is not null and not least_id <=> first_id").select("key", "least_id")
    # rows that stand for themselves need no join: only copies and linked sets are looked up
    other = classes.join(moved, "key", "left").where("m > 1 or least_id is not null").select("key", F.coalesce("least_id", "first_id").alias("group_id"))
    looked = prints.join(sized_broadcast(durable(other), broadcast_bytes), "key", "left")
    return looked.select("doc_id", F.coalesce("group_id", "doc_id").alias("component_id"))
