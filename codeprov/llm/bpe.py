"""Byte-level BPE encoding and decoding with ranks of a public vocabulary.

Two tiers: a minimal perfect hash over the vocabulary resolves a pre-token that is a token itself with
one probe and one comparison; other pre-tokens are merged with a heap of adjacent pairs over a doubly
linked list of bytes, lowest rank first, leftmost on ties. Pre-tokens that recur are kept in a bounded
table, so a frequent word is resolved once for each worker.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
import sys
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.llm.common import resident, slices

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
#: Pre-tokens that a worker keeps, twice: about 200 bytes each, so at most some 260 MB.
KEPT = 650_000
#: Longer pre-tokens are never kept.
KEPT_LENGTH = 64


class PerfectHash:
    """Minimal perfect hash over byte strings: keys that meet no other in a level's bit vector have their place there.

    The rest go on to the next, smaller level. A key's number is the rank of its bit, read from one flat array.
    """

    def __init__(self, keys: list[bytes], load: float = 2.0) -> None:
        self.n = len(keys)
        h = np.array([xxhash.xxh3_64_intdigest(k) for k in keys], dtype=np.uint64)
        rest, taken, self.levels, at = np.arange(self.n), [], [], 0
        while len(rest):
            size = max(8, int(load * len(rest)))
            place = self._places(h[rest], len(self.levels), size)
            alone = np.bincount(place, minlength=size) == 1
            stays = alone[place]
            taken.append((at + place[stays], rest[stays]))
            self.levels.append((at, size))
            at += size
            rest = rest[~stays]
        place, owner = (np.concatenate(x) for x in zip(*taken, strict=True)) if taken else (np.zeros(0, np.int64),) * 2
        number = np.full(at, -1, dtype=np.int32)
        order = np.argsort(place)
        number[place[order]] = np.arange(self.n)
        self.number = array("i", number.tobytes())
        self.slots = array("i", owner[order].astype(np.int32).tobytes())
        self.keys = [keys[i] for i in self.slots]

    @staticmethod
    def _places(h: np.ndarray, level: int, size: int) -> np.ndarray:
        x = h ^ np.uint64((level + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        x = (x ^ x >> np.uint64(32)) * np.uint64(0xD6E8FEB86659FD93)
        return ((x ^ x >> np.uint64(32)) % np.uint64(size)).astype(np.int64)

    def find(self, key: bytes) -> int:
        """The number of ``key`` in the order given, or -1 if it is not one of the keys."""
        h = xxhash.xxh3_64_intdigest(key)
        for level, (at, size) in enumerate(self.levels):
            x = h ^ (level + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF
            x = (x ^ x >> 32) * 0xD6E8FEB86659FD93 & 0xFFFFFFFFFFFFFFFF
            i = self.number[at + (x ^ x >> 32) % size]
            if i >= 0:
                return self.slots[i] if self.keys[i] == key else -1
        return -1


class _Kept(dict):
    """Results by string, worked out once while they are among the last ``most`` to twice as many that were new.

    A full table becomes the former one, from which what is asked for again moves back.
    """

    def __init__(self, work, most: int) -> None:
        self.work, self.most, self.former = work, most, {}

    def __missing__(self, key: str) -> bytes:
        out = self.former.get(key)
        if out is None:
            out = self.work(key)
            if len(key) > KEPT_LENGTH:
                return out
        if len(self) >= self.most:
            self.former = dict(self)
            self.clear()
        self[key] = out
        return out


def narrow(pattern: str):
    """``findall`` of the pattern for texts of characters below 256, in ``re``; None where it says more than ``re`` can.

    The classes of letters, numbers and white space are written out from what ``regex`` holds them to be.
    """
    named = {x: "".join(re.escape(c) for c in map(chr, range(256)) if regex.fullmatch(x, c)) for x in (r"\p{L}", r"\p{N}", r"\s")}
    out, at, inside = [], 0, False
    while at < len(pattern):
        x = next((x for x in (*named, r"\S") if pattern.startswith(x, at)), pattern[at])
        if x in named:
            out.append(named[x] if inside else f"[{named[x]}]")
        elif x == r"\S":
            out.append(f"[^{named[r'\s']}]")
        else:
            if x == "\\" or inside and x == "[" or x == "(" and pattern[at : at + 3] not in ("(?:", "(?!", "(?="):
                return None
            inside = x == "[" or inside and x != "]"
            out.append(x)
        at += len(x)
    return re.compile("".join(out)).findall


def read_ranks(spark, path: str) -> list[tuple[bytes, int]]:
    """Rows of a rank file; read by Spark, so that it may lie in any store."""
    lines = spark.read.text(path if "://" in path else f"file://{path}").collect()
    return [(base64.b64decode(a), int(b)) for a, b in (r[0].split() for r in lines if r[0].strip())]


class Codec:
    """Encoder and decoder over ``(bytes, rank)`` rows; ``pattern`` cuts a text into pre-tokens."""

    def __init__(self, ranks: list[tuple[bytes, int]], pattern: str, kept: int | None = None) -> None:
        self.wide, self.narrow = regex.compile(pattern).findall, narrow(pattern)
        self.bytes_of = {r: b for b, r in ranks}
        self.hash = PerfectHash([b for b, _ in ranks])
        self.numbers = array("I", [r for _, r in ranks])
        rank_of = dict(ranks)
        self.byte_ids = [rank_of[bytes([i])] for i in range(256)]
        #: Rank of the token that two adjacent tokens make, by both ids in one integer.
        self.pairs = {rank_of[b[:i]] << 32 | rank_of[b[i:]]: r for b, r in ranks for i in range(1, len(b)) if b[:i] in rank_of and b[i:] in rank_of}
        pair = lambda a, b: self.pairs.get(self.byte_ids[a] << 32 | self.byte_ids[b])
        #: The same of two bytes, by both in one integer.
        self.of_bytes = [pair(a, b) for a in range(256) for b in range(256)]
        self.known = _Kept(self._piece, kept or KEPT)

    def cut(self, text: str) -> list[str]:
        """The pre-tokens of a text, in order."""
        if self.narrow is not None:
            try:
                text.encode("latin-1")
            except UnicodeEncodeError:
                return self.wide(text)
            return self.narrow(text)
        return self.wide(text)

    def _piece(self, piece: str) -> bytes:
        raw = piece.encode("utf-8", "surrogatepass")
        i = self.hash.find(raw)
        out = array("I", (self.numbers[i],) if i >= 0 else self.merge(raw))
        if sys.byteorder != "little":
            out.byteswap()
        return out.tobytes()

    def merge(self, raw: bytes) -> list[int]:
        """Ids of a pre-token: pairs leave a heap by (rank, place); one that is no longer there is passed over."""
        ids, n, first = [self.byte_ids[b] for b in raw], len(raw), self.of_bytes
        #: Rank of what each token and the one after it make; None at the last and where they make none.
        best = [first[a << 8 | b] for a, b in zip(raw, raw[1:], strict=False)]
        best.append(None)
        # Small numbers, while they fit: they are compared and taken apart faster.
        shift = 12 if n < 4096 else 40
        heap = [r << shift | i for i, r in enumerate(best) if r is not None]
        if not heap:
            return ids
        get, push, pop, mask = self.pairs.get, heapq.heappush, heapq.heappop, (1 << shift) - 1
        heapq.heapify(heap)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        while heap:
            x = pop(heap)
            i, r = x & mask, x >> shift
            if best[i] != r:
                continue
            j, ids[i] = after[i], r
            ids[j], best[j] = -1, None
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                s = best[i] = get(r << 32 | ids[k])
                if s is not None:
                    push(heap, s << shift | i)
            else:
                best[i] = None
            h = before[i]
            if h >= 0:
                s = best[h] = get(ids[h] << 32 | r)
                if s is not None:
                    push(heap, s << shift | h)
        return [t for t in ids if t >= 0]

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        return b"".join(map(self.known.__getitem__, self.cut(text)))

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(ids, dtype="<u4").tolist()))


def codec(shared) -> Codec:
    """The worker's codec of a broadcast ``(ranks, pattern, kept, name)``."""
    ranks, pattern, kept, name = shared.value
    return resident(("bpe", name, kept), lambda: Codec(ranks, pattern, kept))


def share(spark, path: str | None = None, pattern: str | None = None, kept: int = KEPT):
    """A broadcast of the vocabulary file (a fixed public file of about a megabyte)."""
    if path is None or pattern is None:
        import public_tokenizers

        path, pattern = path or public_tokenizers.path(VOCABULARY), pattern or public_tokenizers.PATTERN
    ranks = read_ranks(spark, path)
    name = hashlib.sha256(repr((ranks, pattern)).encode()).hexdigest()
    return spark.sparkContext.broadcast((ranks, pattern, kept, name))


def encode(docs: DataFrame, path: str | None = None, pattern: str | None = None, keep: tuple[str, ...] = ("doc_id",), as_binary: bool = False, kept: int = KEPT) -> DataFrame:
    """``keep`` columns, ``ids`` (array<int>, or little-endian 32-bit binary), n_tokens and both digests.

    A null text counts as empty: no tokens. Every row is encoded whole, however long, decoded again from its
    ids, and the hash of the decoded bytes is returned. Repeated rows give repeated rows, in no set order. Extra
    columns are ignored, also where they bear the name of a result; ``keep`` columns must not. An empty table
    gives an empty result. ``kept`` pre-tokens, or twice as many, stay in a worker's memory.
    """
    shared = share(docs.sparkSession, path, pattern, kept)
    named = {c: f"_k{i}" for i, c in enumerate(keep)}
    src = docs.select(*(F.col(c).alias(n) for c, n in named.items()), "text")
    schema = src.drop("text").schema
    for c, t in (("ids", "binary" if as_binary else "array<int>"), ("n_tokens", "long"), ("ids_sha256", "string"), ("decoded_sha256", "string")):
        schema = schema.add(c, t if t != "array<int>" else src.sparkSession.createDataFrame([], "x array<int>").schema[0].dataType)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(shared)
        for b in slices(batches):
            ids = [c.encode(t or "") for t in b.column("text").to_pylist()]
            if as_binary:
                shown = pa.array(ids, pa.binary())
            else:
                offsets = np.cumsum([0, *(len(i) // 4 for i in ids)], dtype=np.int32)
                shown = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.frombuffer(b"".join(ids), dtype="<i4")))
            yield pa.RecordBatch.from_arrays(
                [
                    *(b.column(n) for n in named.values()),
                    shown,
                    pa.array([len(i) // 4 for i in ids], pa.int64()),
                    pa.array([hashlib.sha256(i).hexdigest() for i in ids]),
                    pa.array([hashlib.sha256(c.decode(i)).hexdigest() for i in ids]),
                ],
                names=schema.names,
            )

    return src.mapInArrow(work, schema).withColumnsRenamed({n: c for c, n in named.items()})


def decode(ids: DataFrame, column: str = "ids", path: str | None = None, pattern: str | None = None) -> DataFrame:
    """``ids`` with a column ``text`` decoded from the array<int> ``column``; a null array gives null."""
    shared = share(ids.sparkSession, path, pattern)
    from pyspark.sql.types import StringType

    @F.udf(StringType(), useArrow=True)
    def text(values):
        return None if values is None else codec(shared).decode(np.asarray(values, dtype="<u4").tobytes()).decode("utf-8", "replace")

    return ids.withColumn("text", text(F.col(column)))
