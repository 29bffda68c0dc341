"""Language-model scoring with Elias-Fano n-gram tries, split over the cluster.

Tokens are words and one end of text. The model discounts counts by a constant and backs off: after a context
u, p(w | u) = max(c(u w) - D, 0) / c(u), rounded down to a step of the quantiser, plus what all these leave of
1 times p(w | shorter u); p(w) is the add-one estimate. So the probabilities after any context sum to 1,
rounding included. Orders from 2 on; contexts begin with as many starts of text as they need.

Counts grow with the corpus and are never gathered in one place. Documents stay where they lie, in batches of
token numbers; each batch sends its distinct contexts and their successors, with counts of its training
documents, to the key ranges that it hits. A range adds up, builds its trie, looks up what each batch asked and
answers; the batch then scores its documents. Contexts before a large share of all tokens are split by their
successors; these contexts and their counts are found over all documents.

A trie's levels (context hashes, child pointers, successors, quantised probabilities) are Elias-Fano coded or
byte arrays in files that are mapped into memory. A successor is stored relative to its context (context
number and hash form one monotone sequence) and found by successor search in the context's range. ``fit``
returns the tries as a table that can be written, and ``score`` takes such a table.
"""

from __future__ import annotations

import io
import os
import tempfile
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain, count

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.llm.common import cut_lineage, gathered, held_out, parts_for, runs, shard_of

#: Words of an n-gram, and what is taken off the count of one that was seen.
ORDER, DISCOUNT = 2, 0.75
#: Bytes of text in a batch, and for which there is one key range.
BATCH_BYTES, SHARD_BYTES = 5 << 20, 8 << 20
#: A context before a greater share of all tokens than a quarter of a range's, but at least this one, may be split.
LEAST_SHARE = 1e-5
#: Steps of the quantised log10 probabilities; 255 of them reach down to 10 ** -12.7.
STEP = 1 / 20

_U = np.uint64
START = np.uint64(xxhash.xxh3_64_intdigest(b"start of text", 1))
END = np.uint64(xxhash.xxh3_64_intdigest(b"end of text", 2))


def tokens(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").lower().split()


def pack_bits(values: np.ndarray, width: int) -> np.ndarray:
    """``width`` low bits of each value, one after another, as bytes."""
    if width == 0 or not len(values):
        return np.zeros(0, np.uint8)
    bits = (values[:, None] >> np.arange(width, dtype=np.uint64)[None, :]) & _U(1)
    return np.packbits(bits.astype(np.uint8).ravel(), bitorder="little")


class EliasFano:
    """A monotone sequence: high parts as unary gaps in a bit vector with a rank directory, low parts packed."""

    def __init__(self, low: np.ndarray, high: np.ndarray, n: int, width: int) -> None:
        self.low, self.n, self.width = low, n, width
        self.high = high
        ones = np.bitwise_count(high).astype(np.int64)
        self.rank1 = np.concatenate([[0], np.cumsum(ones)])
        self.rank0 = np.arange(len(high) + 1, dtype=np.int64) * 64 - self.rank1

    @classmethod
    def build(cls, values: np.ndarray, most: int) -> EliasFano:
        n = len(values)
        width = max(0, int(np.floor(np.log2(max(1.0, float(most) / max(1, n))))))
        high = (values >> _U(width)).astype(np.int64)
        size = (int(high[-1]) if n else 0) + n + 1
        words = np.zeros(-(-size // 64) + 1, dtype=np.uint64)
        at = high + np.arange(n)
        np.bitwise_or.at(words, at >> 6, _U(1) << (at & 63).astype(np.uint64))
        low = np.concatenate([np.concatenate([pack_bits(values[i : i + 65536], width) for i in range(0, n, 65536)] or [np.zeros(0, np.uint8)]), np.zeros(16, np.uint8)])
        return cls(low, words, n, width)

    def _select(self, k: np.ndarray, ones: bool) -> np.ndarray:
        """Place of the k-th (from 0) one or zero bit."""
        rank = self.rank1 if ones else self.rank0
        word = np.searchsorted(rank, k, side="right") - 1
        bits = np.asarray(self.high)[word]
        if not ones:
            bits = ~bits
        rest = k - rank[word]
        at = np.zeros(len(k), dtype=np.uint64)
        for span in (32, 16, 8, 4, 2, 1):
            below = np.bitwise_count((bits >> at) & _U((1 << span) - 1)).astype(np.int64)
            step = below <= rest
            rest = np.where(step, rest - below, rest)
            at += step.astype(np.uint64) * _U(span)
        return word * 64 + at.astype(np.int64)

    def lows(self, i: np.ndarray) -> np.ndarray:
        if self.width == 0:
            return np.zeros(len(i), dtype=np.uint64)
        bit = i * self.width
        byte, off = bit >> 3, (bit & 7).astype(np.uint64)
        out = np.zeros(len(i), dtype=np.uint64)
        low = np.asarray(self.low)
        for b in range(8):
            out |= low[byte + b].astype(np.uint64) << _U(8 * b)
        out >>= off
        if self.width > 56:
            over = low[byte + 8].astype(np.uint64)
            out |= np.where(off > 0, over << (_U(64) - np.maximum(off, _U(1))), _U(0))
        return out & _U((1 << self.width) - 1)

    def access(self, i: np.ndarray) -> np.ndarray:
        high = self._select(i, True) - i
        return high.astype(np.uint64) << _U(self.width) | self.lows(i)

    def find(self, x: np.ndarray, lo: np.ndarray | None = None, hi: np.ndarray | None = None) -> np.ndarray:
        """Index of each value within [lo, hi), or -1: the run with its high part, then a search in the low parts."""
        high = (x >> _U(self.width)).astype(np.int64)
        size = int(self.rank0[-1])
        inside = high < size
        h = np.where(inside, high, 0)
        a = np.where(h > 0, self._select(np.maximum(h - 1, 0), False) - np.maximum(h - 1, 0), 0)
        b = self._select(h, False) - h
        a, b = np.minimum(a, self.n), np.minimum(b, self.n)
        if lo is not None:
            a, b = np.maximum(a, lo), np.minimum(b, hi)
        a, end = np.where(inside, a, 0), np.where(inside, b, 0)
        b = end.copy()
        want = x & _U((1 << self.width) - 1)
        while True:
            open_ = np.flatnonzero(a < b)
            if not len(open_):
                break
            mid = (a[open_] + b[open_]) >> 1
            less = self.lows(mid) < want[open_]
            a[open_] = np.where(less, mid + 1, a[open_])
            b[open_] = np.where(less, b[open_], mid)
        out = np.full(len(x), -1, dtype=np.int64)
        ok = np.flatnonzero(a < end)
        hit = self.lows(a[ok]) == want[ok]
        out[ok[hit]] = a[ok[hit]]
        return out

    def save(self, place: str, name: str) -> None:
        np.save(f"{place}/{name}-low.npy", self.low)
        np.save(f"{place}/{name}-high.npy", self.high)
        np.save(f"{place}/{name}-size.npy", np.array([self.n, self.width]))

    @classmethod
    def open(cls, place: str, name: str) -> EliasFano:
        n, width = np.load(f"{place}/{name}-size.npy").tolist()
        return cls(np.load(f"{place}/{name}-low.npy", mmap_mode="r"), np.load(f"{place}/{name}-high.npy", mmap_mode="r"), n, width)


#: Probability of each code; 0 stands for what was not seen (or is less than the least step).
VALUES = np.concatenate([[0.0], 10.0 ** (-(254 - np.arange(255)) * STEP)])


def quantise(p: np.ndarray) -> np.ndarray:
    """The greatest code whose probability is not above each of ``p``."""
    return (np.searchsorted(VALUES, p * (1 + 1e-12), side="right") - 1).astype(np.uint8)


_LEVELS = ("contexts", "pointers", "children")


class Trie:
    """Contexts of one key range and their successors."""

    @staticmethod
    def write(place: str, contexts: np.ndarray, counts: np.ndarray, pointers: np.ndarray, children: np.ndarray, codes: np.ndarray) -> None:
        """Sorted contexts with counts; ``pointers`` (one more) into children (uint32, sorted in each context) and codes."""
        EliasFano.build(contexts, (1 << 64) - 1).save(place, "contexts")
        EliasFano.build(pointers.astype(np.uint64), max(1, len(children))).save(place, "pointers")
        number = np.repeat(np.arange(len(contexts), dtype=np.uint64), np.diff(pointers))
        EliasFano.build(number << _U(32) | children.astype(np.uint64), max(1, len(contexts)) << 32).save(place, "children")
        np.save(f"{place}/counts.npy", counts)
        np.save(f"{place}/masses.npy", np.add.reduceat(np.append(VALUES[codes], 0.0), pointers[:-1]) * (np.diff(pointers) > 0) if len(contexts) else np.zeros(0))
        np.save(f"{place}/codes.npy", codes)

    def __init__(self, place: str) -> None:
        self.contexts, self.pointers, self.children = (EliasFano.open(place, n) for n in _LEVELS)
        self.counts, self.masses, self.codes = (np.load(f"{place}/{n}.npy", mmap_mode="r") for n in ("counts", "masses", "codes"))

    def look_up(self, contexts: np.ndarray, sizes: np.ndarray, children: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Counts of contexts and the probability that their successors hold, and codes of ``sizes`` successors of each."""
        at = self.contexts.find(contexts) if self.contexts.n else np.full(len(contexts), -1)
        known = at >= 0
        counts, masses = np.zeros(len(contexts), dtype=np.int64), np.zeros(len(contexts))
        counts[known], masses[known] = np.asarray(self.counts)[at[known]], np.asarray(self.masses)[at[known]]
        codes = np.zeros(len(children), dtype=np.uint8)
        owner = np.repeat(at, sizes)
        ask = np.flatnonzero(owner >= 0)
        if len(ask) and self.children.n:
            own = owner[ask]
            lo, hi = self.pointers.access(own).astype(np.int64), self.pointers.access(own + 1).astype(np.int64)
            found = self.children.find(own.astype(np.uint64) << _U(32) | children[ask].astype(np.uint64), lo, hi)
            codes[ask[found >= 0]] = np.asarray(self.codes)[found[found >= 0]]
        return counts, masses, codes


def folded(place: str) -> bytes:
    """The files of a folder in one binary."""
    out = io.BytesIO()
    np.savez(out, **{n: np.frombuffer(open(f"{place}/{n}", "rb").read(), np.uint8) for n in sorted(os.listdir(place))})
    return out.getvalue()


def unfolded(binary: bytes, place: str) -> None:
    with np.load(io.BytesIO(binary)) as files:
        for n in files.files:
            files[n].tofile(f"{place}/{n}")


def _hash_words(words: list[bytes]) -> np.ndarray:
    digest = xxhash.xxh3_64_intdigest
    return np.array([digest(w) for w in words], dtype=np.uint64)


def _child(h: np.ndarray) -> np.ndarray:
    return (h >> _U(16)).astype(np.uint32)


def _mixed(x: np.ndarray, by: np.ndarray) -> np.ndarray:
    x = (x ^ by * _U(0x9E3779B97F4A7C15)) * _U(0xD6E8FEB86659FD93)
    return (x ^ (x >> _U(32))) * _U(0xC2B2AE3D27D4EB4F)


@dataclass
class Hot:
    """Split contexts (sorted): parts, training tokens after each, and what probability their successors hold."""

    keys: np.ndarray
    parts: np.ndarray
    totals: np.ndarray
    masses: np.ndarray


NONE_HOT = Hot(np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))


class Batch:
    """Tokens of some texts: ``keys`` (sorted distinct hashes), ``token`` (a number in them for each), tokens a text."""

    def __init__(self, keys: np.ndarray, token: np.ndarray, lengths: np.ndarray, train: np.ndarray, order: int) -> None:
        self.keys, self.token, self.lengths, self.order = keys, token, lengths, order
        self.learns = np.repeat(train, lengths)
        self.key_counts = np.bincount(token[self.learns], minlength=len(keys)).astype(np.int64)
        h = keys[token]
        place = (np.arange(len(token)) - np.repeat(np.cumsum(lengths) - lengths, lengths)).astype(np.int32)
        #: The context of each token, for each order from 2 on: hashes of its words, nearest first.
        self.contexts_of = []
        held = None
        for back in range(1, order):
            word = np.full(len(h), START)
            word[back:] = h[: len(h) - back]
            word[place < back] = START
            held = word if held is None else _mixed(held, word + _U(back))
            self.contexts_of.append(held)

    @classmethod
    def of(cls, texts: list[str], train: np.ndarray, order: int) -> Batch:
        ids: defaultdict = defaultdict(count().__next__)
        rows = [list(map(ids.__getitem__, tokens(t))) for t in texts]
        lengths = np.array([len(r) + 1 for r in rows], dtype=np.int64)
        end = len(ids)
        word = np.fromiter(chain.from_iterable(chain(r, (end,)) for r in rows), np.int32, int(lengths.sum()))
        del rows
        keys, place = np.unique(np.concatenate([_hash_words(list(ids)), np.array([END], dtype=np.uint64)]), return_inverse=True)
        return cls(keys, place.astype(np.int32)[word], lengths, train, order)

    def frequent(self, share: float) -> tuple[np.ndarray, np.ndarray]:
        """Contexts before more than ``share`` of the tokens here, and of how many."""
        out = [np.unique(c, return_counts=True) for c in self.contexts_of]
        keys, counts = (np.concatenate(x) for x in zip(*out, strict=True))
        often = counts > share * len(self.token)
        return keys[often], counts[often]

    def trained(self, keys: np.ndarray) -> np.ndarray:
        """Training tokens after each of the sorted contexts ``keys``."""
        out = np.zeros(len(keys) + 1, dtype=np.int64)
        for c in self.contexts_of:
            c = c[self.learns]
            at = np.searchsorted(keys, c)
            at[at == len(keys)] = 0
            out[: len(keys)] += np.bincount(at[keys[at] == c], minlength=len(keys))[: len(keys)] if len(keys) else 0
        return out[: len(keys)]

    def paired(self, hot: Hot) -> None:
        """Distinct contexts with their distinct successors; a split context stands under one key for each part."""
        child = _child(self.keys)
        own = []
        for c in self.contexts_of:
            if len(hot.keys):
                at = np.minimum(np.searchsorted(hot.keys, c), len(hot.keys) - 1)
                part = (child[self.token].astype(np.uint64) * hot.parts[at].astype(np.uint64) >> _U(32)) + _U(1)
                c = np.where(hot.keys[at] == c, _mixed(c, part << _U(20)), c)
            own.append(c)
        own.append(self.keys)
        self.contexts, number = np.unique(np.concatenate(own), return_inverse=True)
        number = number[: -len(self.keys)].astype(np.int32)
        orders = len(own) - 1
        del own
        pair = number.astype(np.int64) * len(self.keys) + np.tile(self.token, orders)
        order = np.argsort(pair, kind="stable").astype(np.int32)
        pair = pair[order]
        a, b = runs(pair)
        self.pair = np.empty(len(order), dtype=np.int32)
        self.pair[order] = np.repeat(np.arange(len(a), dtype=np.int32), b - a)
        context, last = np.divmod(pair[a], len(self.keys))
        del pair
        self.pair_child = child[last]
        self.pair_counts = np.add.reduceat(np.tile(self.learns, orders)[order], a, dtype=np.int64) if len(a) else np.zeros(0, np.int64)
        self.sizes = np.bincount(context, minlength=len(self.contexts))
        self.context_counts = np.zeros(len(self.contexts), dtype=np.int64)
        self.word_at = np.searchsorted(self.contexts, self.keys)
        self.context_counts[self.word_at] = self.key_counts
        #: For each order and token: its context, split or not, and the number of the split one or -1.
        self.context_at = number.reshape(orders, -1)
        self.hot_at = np.full(self.context_at.shape, -1, dtype=np.int32)
        for i, c in enumerate(self.contexts_of):
            if len(hot.keys):
                at = np.minimum(np.searchsorted(hot.keys, c), len(hot.keys) - 1)
                self.hot_at[i] = np.where(hot.keys[at] == c, at, -1)
        self.split_of = np.full(len(self.contexts), -1)
        held = self.hot_at >= 0
        self.split_of[self.context_at[held]] = self.hot_at[held]


def _squeeze(a: np.ndarray) -> bytes:
    """Small counts as bytes, larger ones after an escape, so that messages stay small."""
    small = np.minimum(a, 255).astype(np.uint8)
    large = a[a >= 255].astype("<u8")
    return zstandard.compress(len(a).to_bytes(8, "little") + small.tobytes() + large.tobytes(), 1)


def _expand(b: bytes) -> np.ndarray:
    raw = zstandard.decompress(b)
    n = int.from_bytes(raw[:8], "little")
    out = np.frombuffer(raw, np.uint8, n, 8).astype(np.int64)
    out[out == 255] = np.frombuffer(raw, "<u8", -1, 8 + n).astype(np.int64)
    return out


def _planes(a: np.ndarray) -> bytes:
    """Numbers below 2^32, least bytes first, then the next, compressed."""
    return zstandard.compress(np.ascontiguousarray(a.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes(), 3)


def _unplanes(b: bytes) -> np.ndarray:
    raw = np.frombuffer(zstandard.decompress(b), np.uint8).reshape(4, -1)
    return np.ascontiguousarray(raw.T).view("<u4").ravel()


_BATCH = "batch long, doc_ids array<long>, held binary, lengths binary, keys binary, tokens binary, often binary, times binary"
_ASKED = pa.schema([("shard", pa.int32()), ("batch", pa.int64()), *((c, pa.binary()) for c in ("contexts", "counts", "sizes", "children", "times", "split", "parents", "totals"))])
_SERVED = pa.schema([("shard", pa.int32()), ("batch", pa.int64()), *((c, pa.binary()) for c in ("counts", "masses", "codes", "parents", "held")), ("n", pa.int64()), ("v", pa.int64()), ("trie", pa.binary())])


def _ddl(schema: pa.Schema) -> str:
    kinds = {pa.int32(): "int", pa.int64(): "long", pa.binary(): "binary"}
    return ", ".join(f"{f.name} {kinds[f.type]}" for f in schema)


def _rows(docs: DataFrame, order: int, batch_bytes: int, share: float) -> DataFrame:
    """One row for each batch of documents, written once: token numbers and the hashes that they stand for."""

    def work(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for number, t in gathered(it, batch_bytes):
            held = np.array(t.column("held_out").to_pylist(), dtype=bool)
            b = Batch.of(t.column("text").to_pylist(), ~held, order)
            often, times = b.frequent(share)
            # Frequent words get small numbers: their bytes are more alike.
            rank = np.argsort(-np.bincount(b.token, minlength=len(b.keys)), kind="stable")
            small = np.empty(len(rank), dtype=np.int64)
            small[rank] = np.arange(len(rank))
            columns = [[number], [t.column("doc_id").to_pylist()], [held.tobytes()], [b.lengths.astype("<i8").tobytes()], [b.keys[rank].astype("<u8").tobytes()], [_planes(small[b.token])], [often.astype("<u8").tobytes()], [times.astype("<i8").tobytes()]]
            kinds = [pa.int64(), pa.list_(pa.int64()), *[pa.binary()] * 6]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["batch", "doc_ids", "held", "lengths", "keys", "tokens", "often", "times"])

    return cut_lineage(docs.mapInArrow(work, _BATCH))


def _read(row: dict, order: int) -> Batch:
    keys = np.frombuffer(row["keys"], "<u8")
    by = np.argsort(keys)
    place = np.empty(len(keys), dtype=np.int32)
    place[by] = np.arange(len(keys))
    return Batch(keys[by], place[_unplanes(row["tokens"])], np.frombuffer(row["lengths"], "<i8"), ~np.frombuffer(row["held"], bool), order)


_USED = ("batch", "held", "lengths", "keys", "tokens")


def _hot(rows: DataFrame, order: int, shards: int, share: float) -> Hot:
    """Contexts before more than ``share`` of all tokens, or somewhat less; at most 1 / ``share`` for each order."""

    def often(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for keys, times in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(keys, "<i8")), pa.array(np.frombuffer(times, "<i8"))], names=["key", "times"])

    def size(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            yield pa.RecordBatch.from_arrays([pa.array([int(np.frombuffer(x, "<i8").sum()) for x in b.column(0).to_pylist()], pa.int64())], names=["n"])

    total = rows.select("lengths").mapInArrow(size, "n long").agg(F.sum("n")).first()[0] or 0
    found = rows.select("often", "times").mapInArrow(often, "key long, times long").groupBy("key").agg(F.sum("times").alias("n")).where(F.col("n") > share * total).collect()
    if not found:
        return NONE_HOT
    n = {r["key"] & 0xFFFFFFFFFFFFFFFF: r["n"] for r in found}
    keys = np.array(sorted(n), dtype=np.uint64)
    parts = np.array([max(1, -(-4 * n[k] * shards // total)) for k in sorted(n)], dtype=np.int64)

    def trained(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for row in b.to_pylist():
                times = _read(row, order).trained(keys)
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(keys))), pa.array(times)], names=["i", "times"])

    totals = np.zeros(len(keys), dtype=np.int64)
    for r in rows.select(*_USED).mapInArrow(trained, "i long, times long").groupBy("i").agg(F.sum("times").alias("n")).collect():
        totals[r["i"]] = r["n"]
    return Hot(keys, parts, totals, np.zeros(len(keys)))


def _questions(row: dict, order: int, hot: Hot, shards: int) -> pa.Table:
    """A batch's distinct contexts and successors with its training counts, one message for each key range hit."""
    b = _read(row, order)
    b.paired(hot)
    ends = np.concatenate([[0], np.cumsum(b.sizes)])
    rows = []
    for x, y in zip(*runs(shard_of(b.contexts, shards)), strict=True):
        w, split = slice(ends[x], ends[y]), np.flatnonzero(b.split_of[x:y] >= 0)
        parents = b.split_of[x:y][split]
        rows.append(
            {
                "shard": int(shard_of(b.contexts[x : x + 1], shards)[0]),
                "batch": row["batch"],
                "contexts": b.contexts[x:y].astype("<u8").tobytes(),
                "counts": _squeeze(b.context_counts[x:y]),
                "sizes": _squeeze(b.sizes[x:y]),
                "children": b.pair_child[w].astype("<u4").tobytes(),
                "times": _squeeze(b.pair_counts[w]),
                "split": b.contexts[x:y][split].astype("<u8").tobytes(),
                "parents": parents.astype("<i8").tobytes(),
                "totals": hot.totals[parents].astype("<i8").tobytes(),
            }
        )
    return pa.Table.from_pylist(rows, schema=_ASKED)


def build(questions: list[dict], place: str, discount: float) -> tuple[int, int, np.ndarray, np.ndarray]:
    """Writes the trie of a range's counts; its training tokens, distinct ones, parents of split contexts and their masses."""
    contexts = np.concatenate([np.frombuffer(q["contexts"], "<u8") for q in questions])
    sizes = np.concatenate([_expand(q["sizes"]) for q in questions])
    times = np.concatenate([_expand(q["times"]) for q in questions])
    keys, inverse = np.unique(contexts, return_inverse=True)
    words = np.bincount(inverse, weights=np.concatenate([_expand(q["counts"]) for q in questions]), minlength=len(keys)).astype(np.int64)
    seen = times > 0
    pairs = (np.repeat(inverse, sizes).astype(np.uint64) << _U(32) | np.concatenate([np.frombuffer(q["children"], "<u4") for q in questions]).astype(np.uint64))[seen]
    order = np.argsort(pairs)
    a, _ = runs(pairs[order])
    pair_keys = pairs[order[a]]
    counts = np.add.reduceat(times[seen][order], a) if len(a) else np.zeros(0, np.int64)
    pointers = np.searchsorted(pair_keys, np.arange(len(keys) + 1, dtype=np.uint64) << _U(32))
    owner = (pair_keys >> _U(32)).astype(np.int64)
    totals = np.bincount(owner, weights=counts, minlength=len(keys))
    split, at = np.unique(np.concatenate([np.frombuffer(q["split"], "<u8") for q in questions]), return_index=True)
    parents, of_all = (np.concatenate([np.frombuffer(q[c], "<i8") for q in questions])[at] for c in ("parents", "totals"))
    totals[np.searchsorted(keys, split)] = of_all
    codes = quantise(np.maximum(counts - discount, 0) / totals[owner]) if len(counts) else np.zeros(0, np.uint8)
    Trie.write(place, keys, words, pointers, (pair_keys & _U(0xFFFFFFFF)).astype(np.uint32), codes)
    held = Trie(place).masses[np.searchsorted(keys, split)]
    return int(words.sum()), int((words > 0).sum()), parents, held


def _answer(trie: Trie, q: dict) -> dict:
    counts, masses, codes = trie.look_up(np.frombuffer(q["contexts"], "<u8"), _expand(q["sizes"]), np.frombuffer(q["children"], "<u4"))
    return {"shard": q["shard"], "batch": q["batch"], "counts": _squeeze(counts), "masses": zstandard.compress(masses.astype("<f4").tobytes(), 1), "codes": zstandard.compress(codes.tobytes(), 1)}


def _scores(row: dict, answers: list[dict], order: int, hot: Hot, big_n: int, big_v: int) -> pa.Table:
    b = _read(row, order)
    b.paired(hot)
    own = sorted(answers, key=lambda r: r["shard"])
    counts = np.concatenate([_expand(r["counts"]) for r in own])
    masses = np.concatenate([np.frombuffer(zstandard.decompress(r["masses"]), "<f4") for r in own]).astype(float)
    codes = np.concatenate([np.frombuffer(zstandard.decompress(r["codes"]), np.uint8) for r in own])
    known = counts[b.word_at]
    base = ((known + 1) / (big_n + big_v + 1))[b.token]
    p, seen = base, VALUES[codes][b.pair].reshape(order - 1, -1)
    for i in range(order - 1):
        mass = masses[b.context_at[i]]
        if len(hot.keys):
            mass = np.where(b.hot_at[i] >= 0, hot.masses[np.maximum(b.hot_at[i], 0)], mass)
        p = seen[i] + (1 - mass) * p
    n, begins = len(b.lengths), np.cumsum(b.lengths) - b.lengths
    sums = lambda x: np.add.reduceat(x, begins)
    return pa.table(
        {
            "doc_id": pa.array(row["doc_ids"], pa.int64()),
            "held_out": pa.array(np.frombuffer(row["held"], bool)),
            "n_tokens": pa.array(b.lengths),
            "n_known": pa.array(sums((known > 0).astype(np.int64)[b.token])),
            "train_tokens": pa.array(np.full(n, big_n, dtype=np.int64)),
            "base_score": pa.array(sums(np.log10(base))),
            "score": pa.array(sums(np.log10(p))),
        }
    )


_MODEL = "shard int, n long, v long, trie binary"


def _source(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(7, 2).alias("held_out"), F.coalesce("text", F.lit("")).alias("text"))


def _served(docs: DataFrame, order: int, discount: float, batch_bytes: int, shard_bytes: int, keep: bool) -> tuple[DataFrame, DataFrame, Hot, int]:
    """Batches, the ranges' answers to them (with tries, if they are to be kept), split contexts, number of ranges."""
    shards = parts_for(docs, "text", shard_bytes)
    share = max(1 / (4 * shards), LEAST_SHARE)
    rows = _rows(docs, order, batch_bytes, share)
    hot = _hot(rows, order, shards, share)

    def ask(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for row in b.to_pylist():
                yield from _questions(row, order, hot, shards).to_batches()

    def serve(key, group):
        questions = group.to_pylist()
        with tempfile.TemporaryDirectory() as place:
            n, v, parents, held = build(questions, place, discount)
            trie = Trie(place)
            out = [] if keep else [_answer(trie, q) for q in questions]
            out.append({"shard": key[0].as_py(), "batch": None, "parents": parents.astype("<i8").tobytes(), "held": held.astype("<f8").tobytes(), "n": n, "v": v, "trie": folded(place) if keep else None})
        return pa.Table.from_pylist(out, schema=_SERVED)

    served = cut_lineage(rows.select(*_USED).mapInArrow(ask, _ddl(_ASKED)).groupBy("shard").applyInArrow(serve, _ddl(_SERVED)))

    def masses(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for parents, held in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(parents, "<i8")), pa.array(np.frombuffer(held, "<f8"))], names=["i", "mass"])

    if len(hot.keys):
        for r in served.where("batch is null").select("parents", "held").mapInArrow(masses, "i long, mass double").groupBy("i").agg(F.sum("mass").alias("m")).collect():
            hot.masses[r["i"]] = r["m"]
    return rows, served, hot, shards


def fit(docs: DataFrame, order: int = ORDER, discount: float = DISCOUNT, batch_bytes: int = BATCH_BYTES, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """The model as a table: a trie for each key range, and one row (shard -1) for order, ranges and split contexts.

    Learns from the rows that are not held out. An empty table gives the model that has seen nothing.
    """
    _, served, hot, shards = _served(_source(docs), order, discount, batch_bytes, shard_bytes, True)
    out = io.BytesIO()
    np.savez(out, order=order, shards=shards, keys=hot.keys, parts=hot.parts, totals=hot.totals, masses=hot.masses)
    first = docs.sparkSession.createDataFrame([(-1, 0, 0, bytearray(out.getvalue()))], _MODEL)
    return served.select("shard", "n", "v", "trie").unionByName(first)


def score(docs: DataFrame, order: int = ORDER, discount: float = DISCOUNT, batch_bytes: int = BATCH_BYTES, shard_bytes: int = SHARD_BYTES, model: DataFrame | None = None) -> DataFrame:
    """For every row: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score.

    Without a ``model`` it learns from the rows that are not held out, and the tries answer while they are at
    hand. A null text counts as empty: its end is its only token. If nothing is held in, all counts are 0 and V
    is 0. Repeated rows count and are scored each; very long texts are scored whole. An empty table gives an empty
    result; extra columns are ignored. Words are known by 64-bit hashes, successors by 32 bits of theirs in a
    context.
    """
    src = _source(docs)
    if model is None:
        rows, served, hot, _ = _served(src, order, discount, batch_bytes, shard_bytes, False)
        about = served.where("batch is null")
        served = served.where("batch is not null")
    else:
        about = model.where("shard >= 0")
        with np.load(io.BytesIO(model.where("shard = -1").first()["trie"])) as x:
            order, shards, hot = int(x["order"]), int(x["shards"]), Hot(x["keys"], x["parts"], x["totals"], x["masses"])
        rows = _rows(src, order, batch_bytes, 1.0)

        def ask(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in it:
                for row in b.to_pylist():
                    yield from _questions(row, order, hot, shards).to_batches()

        def look(questions, tries):
            asked, found = questions.to_pylist(), tries.column("trie").to_pylist()
            with tempfile.TemporaryDirectory() as place:
                if found:
                    unfolded(found[0], place)
                else:
                    none = np.zeros(0, np.int64)
                    Trie.write(place, none.astype(np.uint64), none, np.zeros(1, np.int64), none.astype(np.uint32), none.astype(np.uint8))
                trie = Trie(place)
                return pa.Table.from_pylist([_answer(trie, q) for q in asked], schema=_SERVED)

        served = cut_lineage(rows.select(*_USED).mapInArrow(ask, _ddl(_ASKED)).groupBy("shard").cogroup(about.groupBy("shard")).applyInArrow(look, _ddl(_SERVED)))
    totals = about.agg(F.sum("n").alias("n"), F.sum("v").alias("v")).first()
    big_n, big_v = totals["n"] or 0, totals["v"] or 0
    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"

    def finish(group, answers):
        found = answers.to_pylist()
        return pa.concat_tables([_scores(r, found, order, hot, big_n, big_v) for r in group.to_pylist()])

    return rows.select("doc_ids", *_USED).groupBy("batch").cogroup(served.select("shard", "batch", "counts", "masses", "codes").groupBy("batch")).applyInArrow(finish, schema)


os.environ.setdefault("OMP_NUM_THREADS", "1")
