"""Document fingerprints by locally consistent parsing.

Characters, then phrases, are named; runs of one name collapse; deterministic coin tossing turns each name
into one of a few labels that depends on a handful of neighbours only; local maxima of the labels begin
phrases, which are named from the names inside. So equal substrings get equal names in their interior,
wherever they stand. The names of some levels, reduced to the least in each of a few bins, are the
fingerprint; the share of agreeing bins is the likeness of two fingerprints.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Levels of the hierarchy whose names are kept, and the bins of each (a phrase of level k spans about 3^k characters).
LEVELS = {2: 16, 3: 32, 4: 16}
BINS = sum(LEVELS.values())
#: Bytes of text in a bucket of neighbouring documents, and the most buckets.
BUCKET_BYTES, MOST_BUCKETS = 8 << 20, 100_000
SLICE_CHARS = 1 << 20

_U = np.uint64
_rng = np.random.Generator(np.random.PCG64(20240613))
_WEIGHTS = _rng.integers(1, 1 << 63, 64, dtype=np.uint64) * _U(2) + _U(1)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    x = (x ^ (x >> _U(29))) * _U(0x9E3779B97F4A7C15)
    return x ^ (x >> _U(32))


def _toss_table(size: int) -> np.ndarray:
    """Label of a value (row) beside its left neighbour (column), both below ``size``."""
    a = np.arange(size)[:, None]
    x = a ^ np.arange(size)[None, :]
    k = np.bitwise_count((x & -x) - 1)
    k[x == 0] = 0
    return (2 * k + (a >> k & 1)).astype(np.uint8)


_TOSS = [_toss_table(128), _toss_table(16), _toss_table(8)]


def parse(names: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One level: names (uint64) and whether each opens a text, to the phrases' names and the same."""
    n = len(names)
    if n == 0:
        return names, first
    same = np.zeros(n, dtype=bool)
    np.equal(names[1:], names[:-1], out=same[1:])
    same &= ~first
    if same.any():
        at = np.flatnonzero(~same)
        run = np.diff(np.append(at, n)).astype(np.uint64)
        names, first = names[at], first[at]
        long = run > 1
        names = np.where(long, _mix(names + run * _WEIGHTS[63]), names)
        n = len(names)
    x = np.empty_like(names)
    x[0] = 1
    np.bitwise_xor(names[1:], names[:-1], out=x[1:])
    x[first] = 1
    low = x & (~x + _U(1))
    k = np.bitwise_count(low - _U(1))
    label = (2 * k + ((names & low) != 0)).astype(np.uint8)
    for table in _TOSS:
        left = np.empty_like(label)
        left[0] = 0
        left[1:] = label[:-1]
        left[first] = label[first] ^ 1
        label = table[label & (len(table) - 1), left & (len(table) - 1)]
    rising = np.empty(n, dtype=bool)
    rising[0] = False
    np.greater(label[1:], label[:-1], out=rising[1:])
    falling = np.empty(n, dtype=bool)
    falling[-1] = False
    np.greater_equal(label[:-1], label[1:], out=falling[:-1])
    falling[:-1] &= ~first[1:]
    opens = rising & falling
    opens[1:] &= ~first[:-1]
    opens |= first
    starts = np.flatnonzero(opens)
    place = np.arange(n) - np.repeat(starts, np.diff(np.append(starts, n)))
    summed = np.add.reduceat(_mix(names) * _WEIGHTS[place & 63], starts)
    return _mix(summed), first[starts]


def fingerprints(texts: list[str]) -> np.ndarray:
    """A row of 31-bit values for each text: in each bin 1 + the least value of the names there, 0 if there is none."""
    out = np.zeros((len(texts), BINS), dtype=np.uint32)
    full = [i for i, t in enumerate(texts) if t]
    if not full:
        return out
    sizes = np.array([len(texts[i]) for i in full])
    names = np.frombuffer("".join(texts[i] for i in full).encode("utf-32-le", "surrogatepass"), dtype="<u4").astype(np.uint64)
    first = np.zeros(len(names), dtype=bool)
    first[np.concatenate([[0], np.cumsum(sizes)[:-1]])] = True
    names = _mix(names + _U(1))
    owner = np.array(full)
    at = 0
    for level in range(1, max(LEVELS) + 1):
        names, first = parse(names, first)
        bins = LEVELS.get(level)
        if bins:
            own = owner[np.cumsum(first) - 1]
            h = _mix(names ^ _WEIGHTS[level])
            cell = own * BINS + at + (h % _U(bins)).astype(np.int64)
            value = (h >> _U(33)).astype(np.uint32) + np.uint32(1)
            order = np.lexsort((value, cell))
            cells, where = np.unique(cell[order], return_index=True)
            out.reshape(-1)[cells] = value[order][where]
            at += bins
    return out


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row: agreeing bins by bins that either uses; 1 for two empty fingerprints."""
    used = (a > 0) | (b > 0)
    same = (a == b) & used
    n = used.sum(axis=1)
    return np.where(n == 0, 1.0, same.sum(axis=1) / np.maximum(n, 1))


def shown(prints: np.ndarray) -> list[str]:
    """Hexadecimal, eight digits for each bin."""
    return ["".join(f"{v:08x}" for v in row) for row in prints.tolist()]


def likeness_of(a: str, b: str) -> float:
    read = lambda s: np.array([[int(s[i : i + 8], 16) for i in range(0, len(s), 8)]])
    return float(likeness(read(a), read(b))[0])


def edited(text: str, following: str) -> str:
    """The last half (rounded down) replaced by as many first characters of the following text, or all it has."""
    half = len(text) // 2
    return text[: len(text) - half] + following[:half]


def _neighbours(docs: DataFrame, bucket_bytes: int) -> DataFrame:
    """Rows in buckets of ascending id; each bucket ends with copies (``own`` false) of the next one's first row.

    Bucket bounds are ids that occur, so the first row of a bucket is known without looking at it, and one
    shuffle of compressed texts brings neighbours together.
    """
    src = docs.select(F.coalesce(F.col("doc_id"), F.lit(-(1 << 63))).alias("key"), "doc_id", F.coalesce("text", F.lit("")).alias("text"))
    total = src.agg(F.sum(F.octet_length("text")).alias("b"), F.min("key").alias("least")).first()
    if total["least"] is None:
        return src.select(F.lit(0).alias("bucket"), F.lit(True).alias("own"), "key", "doc_id", F.lit(b"").alias("packed"))
    n = min(MOST_BUCKETS, 1 + int(total["b"] or 0) // bucket_bytes)
    cuts = src.agg(F.percentile_approx("key", [i / n for i in range(1, n)] or [0.5], max(10_000, 10 * n)).alias("c")).first()["c"] if n > 1 else []
    bounds = np.array(sorted({total["least"], *cuts}), dtype=np.int64)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=3).compress
        for b in batches:
            key = b.column("key").to_numpy()
            bucket = np.searchsorted(bounds, key, side="right") - 1
            edge = np.flatnonzero(bounds[bucket] == key)
            rows = np.concatenate([np.arange(len(key)), edge])
            to = np.concatenate([bucket, (bucket[edge] - 1) % len(bounds)])
            own = np.arange(len(rows)) < len(key)
            packed = [pack(t.as_buffer()) for t in b.column("text").cast(pa.binary())]
            yield pa.RecordBatch.from_arrays(
                [pa.array(to.astype(np.int32)), pa.array(own), pa.array(key[rows]), b.column("doc_id").take(pa.array(rows)), pa.array([packed[i] for i in rows], pa.binary())],
                names=["bucket", "own", "key", "doc_id", "packed"],
            )

    moved = src.mapInArrow(work, "bucket int, own boolean, key long, doc_id long, packed binary")
    return moved.repartition(len(bounds), "bucket").sortWithinPartitions("bucket", F.desc("own"), "key", "packed")


def compare_with_edits(docs: DataFrame, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """For every row: doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    A null text counts as empty. Rows stand in the order of their ids, a missing id first, rows of one id
    in the order of their text's compressed bytes; the last is followed by the first, an only row by itself.
    An empty table gives an empty result; extra columns are ignored.
    """
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"

    def finish(rows: list, prints: np.ndarray, n: int) -> pa.RecordBatch | None:
        """The first n rows, each with the one after it."""
        own = [i for i in range(n) if rows[i][1]]
        if not own:
            return None
        texts = [edited(rows[i][3], rows[i + 1][3]) for i in own]
        after = fingerprints(texts)
        mine, following = prints[own], prints[[i + 1 for i in own]]
        return pa.RecordBatch.from_arrays(
            [
                pa.array([rows[i][2] for i in own], pa.int64()),
                pa.array([len(rows[i][3]) for i in own], pa.int64()),
                pa.array([hashlib.sha256(t.encode("utf-8", "surrogatepass")).hexdigest() for t in texts]),
                pa.array(shown(mine)),
                pa.array(shown(after)),
                pa.array(likeness(mine, after)),
                pa.array(likeness(mine, following)),
            ],
            names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
        )

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor().decompress
        held: list = []
        prints = np.zeros((0, BINS), dtype=np.uint32)

        def flush(fresh: list) -> pa.RecordBatch | None:
            nonlocal held, prints
            rows = held + fresh
            prints = np.concatenate([prints, fingerprints([r[3] for r in fresh])])
            out = finish(rows, prints, len(rows) - 1)
            held, prints = rows[-1:], prints[-1:]
            return out

        fresh, chars = [], 0
        for b in batches:
            for bucket, own, _, doc, packed in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                text = unpack(packed).decode("utf-8", "surrogatepass") if packed else ""
                fresh.append((bucket, own, doc, text))
                chars += len(text)
                if chars >= SLICE_CHARS:
                    if (out := flush(fresh)) is not None:
                        yield out
                    fresh, chars = [], 0
        if fresh and (out := flush(fresh)) is not None:
            yield out

    return _neighbours(docs, bucket_bytes).mapInArrow(work, schema)
