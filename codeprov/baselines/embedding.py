"""The embedding baseline: pairs of vectors by cosine, in blocks."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.operators.joins import broadcast_blocks
from codeprov.session import cut_lineage

#: Vectors in a block; a task holds two blocks at a time.
BLOCK = 1024


def _blocks(df: DataFrame, id: str, vector: str, label: str | None, n: int) -> DataFrame:
    """``block, ids, labels, known, m``: ``n`` blocks of vectors as bytes (8 for an id or label, 4 for a number)."""
    rows = df.where(F.col(id).isNotNull() & F.col(vector).isNotNull())
    l = F.col(label).cast("long") if label else F.lit(None).cast("long")
    rows = rows.select(F.pmod(F.xxhash64(id), F.lit(n)).cast("int").alias("block"), F.col(id).cast("long").alias("i"), F.coalesce(l, F.lit(0)).alias("l"), l.isNotNull().cast("tinyint").alias("k"), F.col(vector).cast("array<float>").alias("v"))

    def pack(t: pa.Table) -> pa.Table:
        column = lambda c: [t[c].combine_chunks().to_numpy().tobytes()]
        m = t["v"].combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float32)
        return pa.table({"block": pa.array([t["block"][0].as_py()], pa.int32()), "ids": column("i"), "labels": column("l"), "known": column("k"), "m": [m.tobytes()]})

    return cut_lineage(rows.repartition(n, "block").groupBy("block").applyInArrow(pack, "block int, ids binary, labels binary, known binary, m binary"))


def _meetings(df: DataFrame, id: str, vector: str, label: str | None, block: int) -> DataFrame:
    """Every two blocks in one row, and every block with itself.

    A block meets the half of the others that follows it in a circle, so that all have as many meetings. One side
    stays where it is, the other is broadcast, so many bytes at a time as ``broadcast_blocks`` allows.
    """
    n = max(1, -(-df.count() // block))
    packed = _blocks(df, id, vector, label, n)
    a, b = (packed.select(*(F.col(c).alias(f"{side}{c}") for c in packed.columns)) for side in ("x_", "y_"))
    step = F.pmod(F.col("y_block") - F.col("x_block"), F.lit(n))
    meet = (step * 2 < n) | ((step * 2 == n) & (F.col("x_block") < F.col("y_block")))
    return reduce(DataFrame.unionByName, [a.join(part, meet) for part in broadcast_blocks(b, "64 + length(y_ids) + length(y_labels) + length(y_known) + length(y_m)")])


def _cosines(batches: Iterator[pa.RecordBatch], least: float) -> Iterator[tuple[np.ndarray, ...]]:
    """Ids of both sides, cosine, and whether the labels are equal, of the pairs of each meeting at or over ``least``."""

    def side(row, s):
        ids, labels = (np.frombuffer(row[f"{s}_{c}"], np.int64) for c in ("ids", "labels"))
        m = np.frombuffer(row[f"{s}_m"], np.float32).astype(np.float64).reshape(len(ids), -1)
        norm = np.linalg.norm(m, axis=1, keepdims=True)
        return ids, labels, np.frombuffer(row[f"{s}_known"], np.int8) > 0, np.divide(m, norm, out=np.zeros_like(m), where=norm > 0), norm[:, 0] > 0

    for batch in batches:
        for k in range(batch.num_rows):
            row = {c: batch.column(c)[k].as_py() for c in batch.schema.names}
            (i, p, u, m, ok), (j, q, v, w, fine) = side(row, "x"), side(row, "y")
            c = m @ w.T
            at = np.flatnonzero(c >= least)
            r, s = np.divmod(at, len(j))
            keep = ok[r] & fine[s]
            if row["x_block"] == row["y_block"]:
                keep &= i[r] < j[s]
            r, s, at = r[keep], s[keep], at[keep]
            yield i[r], j[s], c.ravel()[at], (p[r] == q[s]) & u[r] & v[s]


def cosine_pairs(df: DataFrame, threshold: float = 0.9, id: str = "vec_id", vector: str = "embedding", block: int = BLOCK) -> DataFrame:
    """``a, b, cosine`` for a < b at or over the threshold; vectors without length match nothing.

    The work is quadratic by nature (it is the baseline); blocks of vectors meet each other once, and each
    meeting is one matrix product in one task.
    """

    def multiply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for i, j, c, _ in _cosines(batches, threshold):
            yield pa.RecordBatch.from_pydict({"a": np.minimum(i, j), "b": np.maximum(i, j), "cosine": c})

    return _meetings(df, id, vector, None, block).mapInArrow(multiply, "a long, b long, cosine double")


def cosine_counts(df: DataFrame, thresholds: list[float], label: str = "label", id: str = "vec_id", vector: str = "embedding", block: int = BLOCK) -> DataFrame:
    """``threshold, pairs, same_label``: how many pairs ``cosine_pairs`` has for each threshold, counted where they are formed."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros((2, len(thresholds)), np.int64)
        for _, _, c, same in _cosines(batches, min(thresholds)):
            for k, t in enumerate(thresholds):
                hit = c >= t
                n[:, k] += hit.sum(), (hit & same).sum()
        yield pa.RecordBatch.from_pydict({"threshold": np.array(thresholds, np.float64), "pairs": n[0], "same_label": n[1]})

    rows = _meetings(df, id, vector, label, block).mapInArrow(count, "threshold double, pairs long, same_label long")
    levels = df.sparkSession.createDataFrame([(float(t),) for t in thresholds], "threshold double")
    found = rows.groupBy("threshold").agg(F.sum("pairs").alias("pairs"), F.sum("same_label").alias("same_label"))
    return levels.join(F.broadcast(found), "threshold", "left").na.fill(0)


def token_vectors(df: DataFrame, id: str, text: str = "text", dims: int = 64) -> DataFrame:
    """Hashed counts of words: ``vec_id, embedding`` for texts without vectors of their own."""
    words = F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    places = F.transform(words, lambda w: F.pmod(F.xxhash64(w), F.lit(dims)))
    counts = F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.size(F.filter(places, lambda p: p == i)).cast("float"))
    return df.select(F.col(id).alias("vec_id"), counts.alias("embedding"))
