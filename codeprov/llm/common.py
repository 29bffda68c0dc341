"""Shared pieces of the corpus operators: reading, batching, sizing and lineage."""

from __future__ import annotations

import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codeprov.session import shared_folder

#: Bytes of text that an Arrow worker handles at once.
SLICE_BYTES = 4 << 20
#: Rows of one gathered table.
MOST_ROWS = 200_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut_lineage(df: DataFrame) -> DataFrame:
    """``df`` written once to the shared checkpoint folder (``shared_folder``) and read back."""
    context = df.sparkSession.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The batches again, cut so that ``column`` holds about ``most`` bytes in each (one row at least)."""
    for batch in batches:
        if batch.num_rows == 0:
            continue
        start, held = 0, 0
        lengths = pc.binary_length(batch.column(column)).fill_null(0).to_pylist()
        for i, n in enumerate(lengths):
            if held and held + n > most:
                yield batch.slice(start, i - start)
                start, held = i, 0
            held += n
        yield batch.slice(start)


def gathered(batches: Iterator[pa.RecordBatch], most: int, column: str = "text") -> Iterator[tuple[int, pa.Table]]:
    """The rows of a task in tables of about ``most`` bytes of ``column`` each, with numbers that no other table of the job has."""
    number = TaskContext.get().partitionId() << 32
    held, size = [], 0
    for b in slices(batches, column, most):
        held.append(b)
        size += pc.sum(pc.binary_length(b.column(column))).as_py() or 0
        if size >= most or sum(x.num_rows for x in held) >= MOST_ROWS:
            yield number, pa.Table.from_batches(held)
            held, size, number = [], 0, number + 1
    if held:
        yield number, pa.Table.from_batches(held)


def runs(sorted_: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of each run of equal values."""
    if not len(sorted_):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.flatnonzero(np.concatenate([[True], sorted_[1:] != sorted_[:-1]]))
    return at, np.append(at[1:], len(sorted_))


def shard_of(keys: np.ndarray, shards: int) -> np.ndarray:
    """The range of a 64-bit hash by its top 32 bits; monotone in the hash."""
    return ((keys >> np.uint64(32)) * np.uint64(shards) >> np.uint64(32)).astype(np.int64)


_resident: dict = {}


def resident(name, build):
    """The one model that a reused worker keeps: ``build()`` under ``name``; a model of another name is let go first."""
    if name not in _resident:
        _resident.clear()
        _resident[name] = build()
    return _resident[name]


def parts_for(df: DataFrame, column: str, each: int, least: int = 1) -> int:
    """How many parts of about ``each`` bytes the strings of ``column`` make; from the rows, not from settings."""
    total = df.agg(F.sum(F.octet_length(column)).alias("n")).first()["n"] or 0
    return max(least, -(-int(total) // each))


def held_out(mod: int, rest: int, column: str = "doc_id"):
    """Whether a row is kept from learning: crc32 of its id as text leaves ``rest`` by ``mod``."""
    return F.coalesce(F.crc32(F.col(column).cast("string").cast("binary")) % mod == rest, F.lit(False))


def text_or_empty(column: str = "text"):
    return F.coalesce(F.col(column), F.lit("")).alias("text")


os.environ.setdefault("OMP_NUM_THREADS", "1")
