"""Every query against every target: the exact reference of candidate search, quadratic by nature.

Queries of few letters go to every task. A task takes the edit distance of each different part of the queries with each
different part of its targets, many parts of both side by side, and nothing is left out; the answers are those of ``order_free``.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.clone.levels import distances
from codeprov.clone.links import Parts, numbered
from codeprov.clone.score import order_free
from codeprov.operators.joins import broadcast_blocks

#: Letters of targets in one go, letters of queries that may go to every task, query parts side by side, bytes of a table of cells.
LETTERS, MOST_ASKED, LANES, CELLS = 1 << 18, 1 << 20, 1024, 1 << 16
#: Tasks for each partition of a shuffle: texts differ in length.
TASKS = 4


def _columns(words: list[bytes], parts: Parts, order: np.ndarray, kind: type) -> np.ndarray:
    """Edit distances (parts of ``order``, the longest first, by ``words``): a word's last letter is the highest bit of a number.

    The bits below a word's first letter never change, and hand on the step that a column begins with.
    """
    width = np.iinfo(kind).bits
    table, every = np.zeros((256, len(words)), kind), np.zeros(len(words), kind)
    for w, word in enumerate(words):
        for i, x in enumerate(word, width - len(word)):
            table[x, w] |= kind(1 << i)
            every[w] |= kind(1 << i)
    raw, one = np.frombuffer(parts.data, np.uint8), kind(1)
    out = np.empty((len(order), len(words)), np.int32)
    rows = max(1, CELLS // (every.nbytes or 1))
    for at in range(0, len(order), rows):
        u = order[at : at + rows]
        length, start = parts.length[u].astype(np.int64), parts.starts[u]
        more, less = np.tile(every, (len(u), 1)), np.zeros((len(u), len(words)), kind)
        equal, down, across, up = (np.empty_like(more) for _ in range(4))
        left = np.searchsorted(-length, -np.arange(int(length[0])), "left")
        for j, k in enumerate(left):
            p, m, e, d, a, b = (x[:k] for x in (more, less, equal, down, across, up))
            np.take(table, raw[start[:k] + j], axis=0, out=e, mode="clip")
            np.bitwise_or(e, m, out=d)
            np.bitwise_and(e, p, out=a)
            a += p
            a ^= p
            a |= e
            np.bitwise_or(a, p, out=b)
            np.invert(b, out=b)
            b |= m
            a &= p
            b <<= one
            b |= one
            a <<= one
            np.bitwise_and(b, d, out=m)
            np.bitwise_or(d, b, out=p)
            np.invert(p, out=p)
            p |= a
        out[at : at + rows] = length[:, None] + np.bitwise_count(more).astype(np.int32) - np.bitwise_count(less)
    return out


def _bests(words: list[bytes], parts: Parts) -> np.ndarray:
    """The highest delta of each of ``words`` (rows) in each fingerprint of ``parts``."""
    numbered(parts, parts)
    # Kinds from the longest to the shortest, and of each fingerprint its kinds.
    order = np.argsort(-parts.length[parts.first].astype(np.int64), kind="stable")
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    kinds, first = rank[parts.kind], parts.first[order]
    length = parts.length[first].astype(np.int64)
    out = np.empty((len(words), len(parts.ptr) - 1))
    sizes = np.array([len(w) for w in words])
    low = 0
    for kind in (np.uint8, np.uint16, np.uint32, np.uint64):
        mine = np.flatnonzero((sizes > low) & (sizes <= np.iinfo(kind).bits))
        low = np.iinfo(kind).bits
        for at in range(0, len(mine), LANES):
            some = mine[at : at + LANES]
            found = np.ascontiguousarray(_columns([words[w] for w in some], parts, first, kind).T)
            for c, w in enumerate(some):
                out[w] = np.maximum.reduceat((100.0 * (1 - found[c] / np.maximum(length, sizes[w])))[kinds], parts.ptr[:-1])
    for w in np.flatnonzero(sizes > low):
        out[w] = np.maximum.reduceat((100.0 * (1 - distances(words[w], parts, first) / np.maximum(length, sizes[w])))[kinds], parts.ptr[:-1])
    return out


def _groups(queries: list[tuple[int, list[bytes]]]) -> Iterator[list[tuple[int, list[bytes]]]]:
    """Queries in groups of about ``LANES`` parts."""
    group, n = [], 0
    for q in queries:
        if group and n + len(q[1]) > LANES:
            yield group
            group, n = [], 0
        group.append(q)
        n += len(q[1])
    if group:
        yield group


def _scores(queries: list[tuple[int, list[bytes]]], fps: list[str]) -> Iterator[tuple[int, np.ndarray | None]]:
    """Each query with its score against each of the fingerprints ``fps``; no score without a part of the query."""
    held = np.flatnonzero([x != "" for x in fps])
    parts = Parts("".join(f"{fps[k]}\n" for k in held).encode()) if len(held) else None
    for group in _groups(queries):
        words = sorted({s for _, q in group for s in q})
        at = {s: k for k, s in enumerate(words)}
        best = _bests(words, parts) if words and parts is not None else np.zeros((len(words), 0))
        for id, q in group:
            score = np.zeros(len(fps))
            if q:
                score[held] = reduce(lambda x, y: x + y, (best[at[s]] for s in q)) / len(q)
            yield id, score if q else None


def _forward(queries: DataFrame, targets: DataFrame) -> DataFrame:
    asked = [(int(r.id), r.fp.encode().split(b".") if r.fp else []) for r in queries.select("id", F.array_join("subs", ".").alias("fp")).collect()]
    letters, schema = LETTERS, pa.schema([("query_id", pa.int64()), ("target_id", pa.int64()), ("score", pa.float64())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own, texts = batch.column("id").to_numpy(), batch.column("fp").to_pylist()
            sizes, at = np.cumsum([len(x) + 1 for x in texts]), 0
            while at < len(texts):
                to = max(at + 1, int(np.searchsorted(sizes, (sizes[at - 1] if at else 0) + letters, "right")))
                for q, score in _scores(asked, texts[at:to]):
                    n = to - at
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(n, q)), pa.array(own[at:to]), pa.nulls(n, pa.float64()) if score is None else pa.array(score)], schema=schema)
                at = to

    tasks = TASKS * int(targets.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    t = targets.select(F.col("id").cast("long").alias("id"), F.array_join("subs", ".").alias("fp"))
    return t.repartition(tasks, "id").mapInArrow(work, "query_id long, target_id long, score double")


def all_pairs(queries: DataFrame, targets: DataFrame, direction: str = "forward") -> DataFrame:
    if direction == "forward" and (queries.agg(F.sum(F.length(F.array_join("subs", ".")) + 1)).first()[0] or 0) <= MOST_ASKED:
        return _forward(queries, targets)
    q = queries.select(F.col("id").alias("query_id"), F.col("subs").alias("q"))
    t = targets.select(F.col("id").alias("target_id"), F.col("subs").alias("t"))
    pairs = reduce(DataFrame.unionByName, [t.crossJoin(block) for block in broadcast_blocks(q, "16 + length(array_join(q, '.'))")])
    return pairs.select("query_id", "target_id", order_free("q", "t", direction).alias("score"))
