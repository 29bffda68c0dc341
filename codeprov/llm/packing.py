"""Packing of token sequences by best-fit-decreasing, with splitting of overlong documents.

Documents are encoded where they lie, cut into pieces of at most ``length`` tokens without loss, and the
pieces are dealt to shards by a hash. Each shard packs by best-fit-decreasing: a segment tree over
capacities finds the fullest open sequence that still takes a piece. The result are id matrices of equal
rows, cumulative segment lengths and positions that start again with each piece.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.llm import bpe
from codeprov.llm.common import parts_for, slices

LENGTH = 2048
#: Bytes of text for which there is one shard.
SHARD_BYTES = 8 << 20
#: Rows of one id in a task that go to the same shard; further ones, if alike, to another.
ALIKE = 64


class Capacities:
    """Open sequences by free space: a segment tree over the capacities 1 to ``most`` counts those that occur."""

    def __init__(self, most: int) -> None:
        self.size = 1 << max(1, most).bit_length()
        self.count = [0] * (2 * self.size)
        self.open: list[list[int]] = [[] for _ in range(most + 1)]

    def add(self, free: int, bin_: int) -> None:
        self.open[free].append(bin_)
        i = free + self.size
        while i:
            self.count[i] += 1
            i >>= 1

    def take(self, need: int) -> tuple[int, int] | None:
        """The sequence with the least free space of at least ``need``, removed from the tree."""
        i, count = need + self.size, self.count
        while not count[i]:
            # Up while this is a right child, then over to the next larger capacities.
            while i & 1:
                i >>= 1
            if i == 0:
                return None
            i += 1
            if i & (i - 1) == 0:
                return None
        while i < self.size:
            i = 2 * i if count[2 * i] else 2 * i + 1
        free = i - self.size
        bin_ = self.open[free].pop()
        while i:
            count[i] -= 1
            i >>= 1
        return free, bin_


def best_fit_decreasing(sizes: list[int], length: int) -> list[list[int]]:
    """Piece numbers of each sequence; pieces of one size in the order given. Every size is 1 to ``length``."""
    bins: list[list[int]] = []
    tree = Capacities(length)
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        found = tree.take(sizes[i])
        if found is None:
            free, at = length, len(bins)
            bins.append([])
        else:
            free, at = found
        bins[at].append(i)
        if free > sizes[i]:
            tree.add(free - sizes[i], at)
    return bins


def pieces(docs: DataFrame, length: int = LENGTH, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """doc_id, piece (from 0), start (in tokens), tokens (16-bit little-endian where ids fit, else 32-bit) and salt.

    ``salt`` counts the rows of one id in a task by ``ALIKE``, so that very many equal rows do not meet in one shard.
    """
    shared = bpe.share(docs.sparkSession, path, pattern)
    width = "<u2" if max((r for _, r in shared.value[0]), default=0) < 1 << 16 else "<u4"
    size = np.dtype(width).itemsize

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c, seen = bpe.codec(shared), Counter()
        for b in slices(batches):
            owner, number, start, tokens, salt = [], [], [], [], []
            for i, (doc, t) in enumerate(zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist(), strict=True)):
                seen[doc] += 1
                ids = np.frombuffer(c.encode(t or ""), "<u4").astype(width).tobytes()
                for k, at in enumerate(range(0, len(ids), length * size)):
                    owner.append(i)
                    number.append(k)
                    start.append(k * length)
                    tokens.append(ids[at : at + length * size])
                    salt.append((seen[doc] - 1) // ALIKE)
            yield pa.RecordBatch.from_arrays([b.column("doc_id").take(pa.array(owner, pa.int64())), pa.array(number, pa.int32()), pa.array(start, pa.int64()), pa.array(tokens, pa.binary()), pa.array(salt, pa.int32())], names=["doc_id", "piece", "start", "tokens", "salt"])

    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(work, "doc_id long, piece int, start long, tokens binary, salt int")
    return out.withColumn("width", F.lit(size))


_SEQUENCE = "shard int, sequence int, n_tokens int, input_ids binary, cu_seqlens array<int>, position_ids binary, doc_ids array<long>, starts array<long>"


def _lists(rows: list[np.ndarray], kind) -> pa.ListArray:
    offsets = np.cumsum([0, *(len(r) for r in rows)], dtype=np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(rows) if rows else np.zeros(0, kind)).cast(pa.from_numpy_dtype(kind)))


def row_of(binary: bytes) -> np.ndarray:
    """A row of ids or positions as integers."""
    return np.frombuffer(binary, "<i4")


def pack(docs: DataFrame, length: int = LENGTH, pad_id: int = 0, shard_bytes: int = SHARD_BYTES, path: str | None = None, pattern: str | None = None) -> DataFrame:
    """One row for each packed sequence: ``length`` input_ids (padded with ``pad_id``), cu_seqlens (0 to
    n_tokens), position_ids (from 0 in each piece; in the padding too), and the pieces' doc_ids and starts.
    Ids and positions are matrix rows: little-endian 32-bit integers in a binary (``row_of`` reads one).

    Null and empty texts have no token and so no piece. Very long texts are cut without loss. Repeated rows are
    packed each; up to ``ALIKE`` rows of an id in a task, the result depends on the rows alone and not on how they
    are spread. Extra columns are ignored, also where they bear the name of a result. An empty table gives an
    empty result.
    """
    shards = parts_for(docs, "text", shard_bytes)
    src = pieces(docs, length, path, pattern).withColumn("shard", F.pmod(F.xxhash64("doc_id", "piece", "tokens", "salt"), F.lit(shards)).cast("int"))

    def work(key, group):
        order = group.sort_by([("doc_id", "ascending"), ("start", "ascending"), ("tokens", "ascending")])
        kind = "<u2" if order.num_rows and order.column("width")[0].as_py() == 2 else "<u4"
        tokens = [np.frombuffer(x, kind) for x in order.column("tokens").to_pylist()]
        doc, start = order.column("doc_id"), np.array(order.column("start").to_pylist(), dtype=np.int64)
        bins = best_fit_decreasing([len(t) for t in tokens], length)
        ids, cu, places, count = [], [], [], np.arange(length, dtype="<i4")
        for b in bins:
            row = np.full(length, pad_id, dtype="<i4")
            place = np.empty(length, dtype="<i4")
            at, ends = 0, [0]
            for i in b:
                n = len(tokens[i])
                row[at : at + n] = tokens[i]
                place[at : at + n] = count[:n]
                at += n
                ends.append(at)
            place[at:] = count[: length - at]
            ids.append(row.tobytes())
            places.append(place.tobytes())
            cu.append(np.array(ends, dtype=np.int32))
        flat = pa.array([i for b in bins for i in b], pa.int64())
        offsets = pa.array(np.cumsum([0, *(len(b) for b in bins)], dtype=np.int32))
        n = len(bins)
        docs_of = pa.ListArray.from_arrays(offsets, doc.combine_chunks().take(flat))
        starts_of = pa.ListArray.from_arrays(offsets, pa.array(start).take(flat))
        return pa.Table.from_arrays(
            [pa.array([key[0].as_py()] * n, pa.int32()), pa.array(range(n), pa.int32()), pa.array([int(c[-1]) for c in cu], pa.int32()), pa.array(ids, pa.binary()), _lists(cu, np.int32), pa.array(places, pa.binary()), docs_of, starts_of],
            names=["shard", "sequence", "n_tokens", "input_ids", "cu_seqlens", "position_ids", "doc_ids", "starts"],
        )

    return src.groupBy("shard").applyInArrow(work, _SEQUENCE)


def matrices(packed: DataFrame) -> DataFrame:
    """One row for each shard: n_sequences, length, and little-endian 32-bit binaries in row order.

    ``ids`` and ``positions`` are matrices of n_sequences rows; ``cu_seqlens`` holds all rows' bounds one
    after another, ``cu_offsets`` where each row's begin. Write it with ``write.parquet``.
    """

    def work(key, group):
        order = group.sort_by("sequence")
        flat = lambda c: np.asarray(order.column(c).combine_chunks().flatten(), dtype="<i4").tobytes()
        joined = lambda c: b"".join(order.column(c).to_pylist())
        sizes = [len(x) for x in order.column("cu_seqlens").to_pylist()]
        length = len(order.column("input_ids")[0].as_py()) // 4
        offsets = np.cumsum([0, *sizes], dtype="<i4").tobytes()
        return pa.table({"shard": pa.array([key[0].as_py()], pa.int32()), "n_sequences": pa.array([order.num_rows], pa.int32()), "length": pa.array([length], pa.int32()), "ids": [joined("input_ids")], "positions": [joined("position_ids")], "cu_seqlens": [flat("cu_seqlens")], "cu_offsets": [offsets]})

    return packed.groupBy("shard").applyInArrow(work, "shard int, n_sequences int, length int, ids binary, positions binary, cu_seqlens binary, cu_offsets binary")


def unpack(packed: DataFrame) -> DataFrame:
    """doc_id and all its token ids again, from packed sequences (for ids that stand in one row of the input)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            doc, start, ids = [], [], []
            for binary, cu, docs, starts in zip(*(b.column(c).to_pylist() for c in ("input_ids", "cu_seqlens", "doc_ids", "starts")), strict=True):
                row = row_of(binary)
                for d, s, x, y in zip(docs, starts, cu, cu[1:], strict=False):
                    doc.append(d)
                    start.append(s)
                    ids.append(row[x:y])
            yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(start, pa.int64()), _lists(ids, np.int32)], names=["doc_id", "start", "ids"])

    rows = packed.mapInArrow(work, "doc_id long, start long, ids array<int>")
    return rows.groupBy("doc_id").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("start", "ids"))), lambda x: x["ids"])).alias("ids"))
