"""Cost-balanced packing of tokenised documents into training sequences.

Attention cost of a piece of n tokens is estimated as ``linear * n + quadratic * n * n``. Descending pieces go to the
sequence of lowest cost that has room; a piece is cut only where none of the cheapest sequences can take it whole.
"""

from __future__ import annotations

import base64
import functools
import heapq
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, cost double"

#: White-space characters in a row that ``tiktoken`` is given at most; 700,000 are known to work.
LONGEST_BLANK = 100_000


@dataclass(frozen=True)
class PackingSpec:
    """``block``: remainders that are balanced together, the bound on a task's memory. ``tries``: sequences looked at
    before a piece is cut. ``ranks``/``pattern``: byte-pair ranks and split pattern; None takes the public 50k set."""

    capacity: int = 1024
    end_id: int = 0
    linear: float = 1.0
    quadratic: float = 1.0 / 1024
    block: int = 4096
    tries: int = 4
    ranks: str | None = None
    pattern: str | None = None


@functools.cache
def encoder(ranks: str | None, pattern: str | None):
    """Byte-level BPE with the ids of the public vocabulary, for texts that ``special_reader`` does not take."""
    import tiktoken

    if ranks is None or pattern is None:
        import public_tokenizers

        ranks = ranks or public_tokenizers.path("byte_bpe_50k.tiktoken")
        pattern = pattern or public_tokenizers.PATTERN
    with open(ranks, "rb") as f:
        table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("bpe", pat_str=pattern, mergeable_ranks=table, special_tokens={})


@functools.cache
def special_reader():
    """The public tokenizer itself, and the pattern of its added tokens."""
    import public_tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    added = [t.content for t in tok.get_added_tokens_decoder().values()]
    return tok, re.compile("|".join(map(re.escape, added)) or r"(?!)")


def encode(text: str, spec: PackingSpec) -> list[int]:
    """Token ids of a text as the public tokenizer gives them.

    ``tiktoken`` is the faster, but it knows no added token and panics on white-space runs of about a million
    characters; texts with either go to the public tokenizer. With ranks or a pattern of the caller's own there is none.
    """
    if spec.ranks is None and spec.pattern is None:
        tok, added = special_reader()
        blank = len(text) > LONGEST_BLANK and any(m.end() - m.start() > LONGEST_BLANK for m in re.finditer(r"\s+", text))
        if blank or added.search(text):
            return tok.encode(text, add_special_tokens=False).ids
    return encoder(spec.ranks, spec.pattern).encode_ordinary(text)


def assign(lengths: list[int], capacities: list[int], spec: PackingSpec) -> tuple[list[list[tuple[int, int, int]]], list[tuple[int, int]]]:
    """Place pieces into sequences of given capacities; pieces and parts are ``(piece, from, tokens)``.

    Returns the parts of each sequence in order, and what did not fit as ``(piece, from)``.
    """
    cost = lambda n: spec.linear * n + spec.quadratic * n * n
    room = list(capacities)
    placed: list[list[tuple[int, int, int]]] = [[] for _ in room]
    open_ = [(0.0, s) for s in range(len(room))]
    heapq.heapify(open_)
    left = []
    for p in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        at, n = 0, lengths[p]
        while n:
            seen = []
            while open_ and len(seen) < spec.tries:
                seen.append(heapq.heappop(open_))
                if room[seen[-1][1]] >= n:
                    break
            if not seen:
                left.append((p, at))
                break
            pick = seen.pop() if room[seen[-1][1]] >= n else seen.pop(0)
            for x in seen:
                heapq.heappush(open_, x)
            c, s = pick
            take = min(n, room[s])
            placed[s].append((p, at, take))
            room[s] -= take
            at, n = at + take, n - take
            if room[s]:
                heapq.heappush(open_, (c + cost(take), s))
    return placed, left


def _powers(n: int) -> list[int]:
    return [1 << b for b in range(n.bit_length() - 1, -1, -1) if n >> b & 1]


class _Packer:
    def __init__(self, spec: PackingSpec, first_id: int):
        self.spec, self.next_id, self.rows = spec, first_id, []
        self.pending: list[tuple[int | None, int, np.ndarray, int]] = []  # doc, start, ids, tokens of the document

    def emit(self, doc, start, ids, total, offset):
        spec, n = self.spec, len(ids)
        self.rows.append((doc, start, n, zlib.crc32(ids.tobytes()), total, self.next_id, offset, spec.linear * n + spec.quadratic * n * n))

    def add(self, doc, ids):
        cap, n = self.spec.capacity, len(ids)
        for at in range(0, n - n % cap, cap):
            self.emit(doc, at, ids[at : at + cap], n, 0)
            self.next_id += 1
        if n % cap:
            self.pending.append((doc, n - n % cap, ids[n - n % cap :], n))
        if len(self.pending) >= self.spec.block:
            self.pack(last=False)

    def pack(self, last: bool):
        """Fill whole sequences; what is over waits for the next block, and at the end goes into sequences whose
        sizes are powers of two, which need no padding."""
        cap = self.spec.capacity
        lengths = [len(x[2]) for x in self.pending]
        total = sum(lengths)
        caps = [cap] * (total // cap) + (_powers(total % cap) if last else [])
        placed, left = assign(lengths, caps, self.spec)
        for parts in placed:
            offset = 0
            for p, at, n in parts:
                doc, start, ids, whole = self.pending[p]
                self.emit(doc, start + at, ids[at : at + n], whole, offset)
                offset += n
            self.next_id += bool(parts)
        self.pending = [(d, s + at, ids[at:].copy(), w) for p, at in left for d, s, ids, w in [self.pending[p]]]

    def flush(self) -> pa.RecordBatch:
        cols = zip(*self.rows, strict=True) if self.rows else [[]] * 8
        types = [pa.int64()] * 7 + [pa.float64()]
        names = [x.split()[0] for x in PIECES.split(", ")]
        self.rows = []
        return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, types, strict=False)], names)


def pack_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", spec: PackingSpec | None = None) -> DataFrame:
    """One row per piece: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, cost``.

    Each partition packs its own documents block by block, without a shuffle; sequence ids carry the partition number,
    so a task that runs again gives the same rows. Null and empty texts are the end id alone; a null doc_id stays null;
    repeated rows are packed each; an empty table gives an empty result. Whole texts are encoded, whatever their length.
    """
    spec = spec or PackingSpec()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = _Packer(spec, TaskContext.get().partitionId() << 32)
        for b in batches:
            for doc, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = [*encode(text.as_py() or "", spec), spec.end_id]
                packer.add(doc, np.array(ids, dtype="<u4"))
                if len(packer.rows) > 20_000:
                    yield packer.flush()
        packer.pack(last=True)
        yield packer.flush()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, PIECES)


def packing_report(pieces: DataFrame, capacity: int = 1024) -> DataFrame:
    """Sequences, tokens, padded tokens and the spread of attention cost. A power of two is not padded."""
    seqs = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"), F.sum("cost").alias("cost"))
    padded = F.when(F.bit_count(F.col("n")) == 1, F.col("n")).otherwise(F.lit(capacity))
    return seqs.agg(
        F.count("*").alias("n_sequences"),
        F.sum("n").alias("n_tokens"),
        F.sum(padded - F.col("n")).alias("n_padding"),
        F.avg("cost").alias("mean_cost"),
        F.max("cost").alias("max_cost"),
    )
