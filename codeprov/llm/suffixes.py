"""Repeated passages by sparse suffix arrays.

Only suffixes that start at content-selected positions are kept: the word k-gram with the least hash in
each window of w consecutive k-grams (a minimiser), so that any passage of k + w - 1 words has a kept
suffix inside, at the same place wherever the passage occurs. Documents stay where they lie, in batches.

First the batches ask, by key range, which first k-grams of kept suffixes occur again; only such suffixes
travel, once for each batch and context, as the words themselves. A range sorts its suffixes by their
words, compares neighbours for the length that they have in common, does the same with the words to the
left, read backwards, and from both lengths extends each match to every passage around the kept position.
Around a gram that very many documents have, each passage is asked for by its own hash before, so that what
differs from document to document beside a common passage goes nowhere.
Words decide there, so a meeting of hashes costs time and changes nothing: a word is marked if and only
if it lies in a passage of ``words`` words that two rows (or, if asked, two places) have in common.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator
from itertools import chain, count

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.llm.common import cut_lineage, gathered, parts_for, runs, shard_of

WORDS = 50
#: Words by whose hash suffixes are selected and first asked for.
GRAM = 16
BATCH_BYTES, SHARD_BYTES = 8 << 20, 16 << 20
#: A gram in more documents than this has its passages dealt one by one; of so many grams in all at most.
HOT, MOST_HOT = 20_000, 1_000_000

_U = np.uint64
_BASE = _U(0x9E3779B97F4A7C15)
_word = re.compile(r"[^\x20\x09-\x0D]+")


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    x = (x ^ (x >> _U(29))) * _U(0xC2B2AE3D27D4EB4F)
    return x ^ (x >> _U(32))


def _powers(n: int) -> np.ndarray:
    return np.concatenate([[_U(1)], np.cumprod(np.full(n, _BASE))])


def grams(h: np.ndarray, k: int) -> np.ndarray:
    """64-bit hash of each k consecutive word hashes: a polynomial by doubling, then mixed."""
    total = np.zeros(len(h), dtype=np.uint64)
    block, size, done = h.copy(), 1, 0
    power = lambda n: _powers(n)[n]
    rest = k
    while rest:
        if rest & 1:
            shifted = np.zeros_like(total)
            shifted[: len(h) - done] = block[done:]
            total = total * power(size) + shifted
            done += size
        rest >>= 1
        if rest:
            ahead = np.zeros_like(block)
            ahead[: len(h) - size] = block[size:]
            block = block * power(size) + ahead
            size *= 2
    return _mix(total[: len(h) - k + 1]) if len(h) >= k else np.zeros(0, np.uint64)


def least_of(values: np.ndarray, w: int) -> np.ndarray:
    """Place of the leftmost least value in each window of ``w``."""
    n = len(values) - w + 1
    at = np.arange(len(values))
    span = 1
    best = at
    while span < w:
        step = min(span, w - span)
        a, b = best[: len(best) - step], best[step:]
        best = np.where(values[b] < values[a], b, a)
        span += step
    return best[:n]


def _split(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").split()


def word_hashes(words: list[bytes]) -> np.ndarray:
    """A 64-bit hash of each word."""
    digest = xxhash.xxh3_64_intdigest
    return np.array([digest(w) for w in words] or [0], dtype=np.uint64)


#: A kept suffix: row and place (in words of the batch), the least and greatest number of words by which a passage begins before it.
_KEPT = np.dtype([("key", "<u8"), ("at", "<i8"), ("row", "<i4"), ("least", "u1"), ("most", "u1")])


def kept_suffixes(texts: list[str], words: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """Number of words of each text, and the kept suffixes of all texts in order."""
    ids: defaultdict = defaultdict(count().__next__)
    rows = [list(map(ids.__getitem__, _split(t))) for t in texts]
    counts = np.array([len(r) for r in rows], dtype=np.int64)
    n = int(counts.sum())
    if n < words:
        return counts, np.zeros(0, _KEPT)
    h = word_hashes(list(ids))[np.fromiter(chain.from_iterable(rows), np.int64, n)]
    key = grams(h, gram)
    place = least_of(key, words - gram + 1)
    ends = np.cumsum(counts)
    owner = np.repeat(np.arange(len(counts)), counts)[: len(place)]
    starts = np.flatnonzero(np.arange(len(place)) + words <= ends[owner])
    if not len(starts):
        return counts, np.zeros(0, _KEPT)
    at, row = place[starts], owner[starts]
    first, after = runs(at)
    out = np.zeros(len(first), _KEPT)
    # Least hashes are small ones; mixed again, the keys are even over all ranges.
    out["at"], out["row"], out["key"] = at[first], row[first], _mix(key[at[first]] + _BASE)
    out["most"], out["least"] = at[first] - starts[first], at[first] - starts[after - 1]
    return counts, out


def _cut(batch: int, keys: np.ndarray, shards: int, parts) -> list[dict]:
    """One message for each range that sorted keys fall in; ``parts(a, b)`` gives the columns of keys a to b."""
    return [{"shard": int(shard_of(keys[a : a + 1], shards)[0]), "batch": batch, **parts(a, b)} for a, b in zip(*runs(shard_of(keys, shards)), strict=True)]


_BATCH = "batch long, doc_ids array<long>, n_kept long, counts binary, kept binary, sizes binary, texts binary"
_ASKED = pa.schema([("shard", pa.int32()), ("batch", pa.int64()), ("keys", pa.binary()), ("counts", pa.binary())])
_FLAGS = pa.schema([("shard", pa.int32()), ("batch", pa.int64()), ("keys", pa.binary()), ("flags", pa.binary()), ("n_hot", pa.int64())])
_SENT = pa.schema([("shard", pa.int32()), ("batch", pa.int64()), ("keys", pa.binary()), ("left", pa.binary()), ("rows", pa.binary()), ("many", pa.binary()), ("uses", pa.binary()), ("places", pa.binary()), ("texts", pa.binary())])
_FOUND = pa.schema([("batch", pa.int64()), ("places", pa.binary()), ("masks", pa.binary())])


def _pack(raw: bytes) -> bytes:
    return zstandard.compress(raw, 3)


def _unpack(packed: bytes) -> bytes:
    return zstandard.decompress(packed)


def _ddl(schema: pa.Schema) -> str:
    kinds = {pa.int32(): "int", pa.int64(): "long", pa.binary(): "binary"}
    return ", ".join(f"{f.name} {kinds[f.type]}" for f in schema)


def batch_rows(docs: DataFrame, words: int, gram: int, batch_bytes: int) -> DataFrame:
    """One row for each batch of documents: ids, numbers of words, kept suffixes and compressed texts."""

    def work(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for number, t in gathered(it, batch_bytes):
            texts = t.column("text").to_pylist()
            counts, kept = kept_suffixes(texts, words, gram)
            raw = [x.encode("utf-8", "surrogatepass") for x in texts]
            columns = [[number], [t.column("doc_id").to_pylist()], [len(kept)], [counts.astype("<i8").tobytes()], [_pack(kept.tobytes())], [np.array([len(r) for r in raw], "<i8").tobytes()], [_pack(b"".join(raw))]]
            kinds = [pa.int64(), pa.list_(pa.int64()), pa.int64(), *[pa.binary()] * 4]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["batch", "doc_ids", "n_kept", "counts", "kept", "sizes", "texts"])

    return cut_lineage(docs.mapInArrow(work, _BATCH))


class _Texts:
    """Texts of a batch row, decoded when asked for."""

    def __init__(self, sizes: bytes, texts: bytes) -> None:
        self.ends = np.cumsum(np.frombuffer(sizes, "<i8"))
        self.raw = _unpack(texts)

    def __getitem__(self, i: int) -> bytes:
        return self.raw[self.ends[i - 1] if i else 0 : self.ends[i]]


def _numbers(batch: int, keys: np.ndarray, rows: np.ndarray, across: bool, shards: int) -> list[dict]:
    """The distinct keys, and in how many rows (or places) they are."""
    order = np.lexsort((rows, keys))
    k, r = keys[order], rows[order]
    a, b = runs(k)
    if across:
        new = np.concatenate([[True], (k[1:] != k[:-1]) | (r[1:] != r[:-1])]) if len(k) else np.zeros(0, bool)
        numbers = np.add.reduceat(new.astype(np.int64), a) if len(a) else a
    else:
        numbers = b - a
    keys = k[a]
    return _cut(batch, keys, shards, lambda x, y: {"keys": keys[x:y].astype("<u8").tobytes(), "counts": numbers[x:y].astype("<u4").tobytes()})


def _tell(key, group, hot: int):
    """Merges the sorted keys of all batches: 0 once, 1 again, 2 in more than ``hot`` rows."""
    rows = group.to_pylist()
    keys = [np.frombuffer(r["keys"], "<u8") for r in rows]
    every, inverse = np.unique(np.concatenate(keys), return_inverse=True)
    total = np.bincount(inverse, weights=np.concatenate([np.frombuffer(r["counts"], "<u4") for r in rows]), minlength=len(every))
    flags = (total >= 2).astype(np.uint8) + (total > hot)
    out = []
    for r, k in zip(rows, keys, strict=True):
        f = flags[np.searchsorted(every, k)]
        again = f > 0
        if again.any():
            out.append({"shard": r["shard"], "batch": r["batch"], "keys": k[again].astype("<u8").tobytes(), "flags": f[again].tobytes(), "n_hot": int((f == 2).sum())})
    return pa.Table.from_pylist(out, schema=_FLAGS)


def _windows(split: list[bytes], at: int, least: int, most: int, words: int) -> Iterator[tuple[int, bytes, int]]:
    """Each passage around a kept suffix: how many words before it it begins, its words and their hash."""
    for o in range(least, most + 1):
        text = b" ".join(split[at - o : at - o + words])
        yield o, text, xxhash.xxh3_64_intdigest(text, o)


def _splits(kept: np.ndarray, chosen: np.ndarray, counts: np.ndarray, texts: _Texts) -> Iterator[tuple[int, int, list[bytes], int, int, int, int]]:
    """Number, row, words of the row, place in it, key, least and most of each chosen suffix; rows are split once."""
    begins = np.cumsum(counts) - counts
    row, split = -1, []
    for i in chosen.tolist():
        key, at, r, least, most = kept[i].item()
        if r != row:
            row, split = r, texts[r].split()
        yield i, r, split, at - int(begins[r]), key, least, most


def _ask_windows(batch: int, kept: np.ndarray, counts: np.ndarray, texts: _Texts, hot: np.ndarray, words: int, shards: int, across: bool) -> list[dict]:
    """The passages around grams that very many rows have, by their hashes."""
    keys, rows = [], []
    for _, r, split, at, _, least, most in _splits(kept, np.flatnonzero(np.isin(kept["key"], hot)), counts, texts):
        own = [h for _, _, h in _windows(split, at, least, most, words)]
        keys += own
        rows += [r] * len(own)
    return _numbers(batch, np.array(keys, dtype=np.uint64), np.array(rows, dtype=np.int64), across, shards)


def _merged(answers: list[dict], kind: int) -> tuple[np.ndarray, np.ndarray]:
    own = [r for r in answers if r["kind"] == kind]
    if not own:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint8)
    keys = np.concatenate([np.frombuffer(r["keys"], "<u8") for r in own])
    order = np.argsort(keys)
    return keys[order], np.concatenate([np.frombuffer(r["flags"], np.uint8) for r in own])[order]


def _send(batch: int, kept: np.ndarray, counts: np.ndarray, texts: _Texts, answers: list[dict], words: int, shards: int, across: bool) -> list[dict]:
    """Suffixes whose first gram occurs again, with the words to the left that their passages need; equal ones once."""
    keys, flags = _merged(answers, 1)
    if not len(keys) or not len(kept):
        return []
    again = set(_merged(answers, 2)[0].tolist())
    place = np.minimum(np.searchsorted(keys, kept["key"]), len(keys) - 1)
    flag = np.where(keys[place] == kept["key"], flags[place], 0)
    found: dict[tuple, list] = {}
    for i, r, split, at, key, least, most in _splits(kept, np.flatnonzero(flag), counts, texts):
        if flag[i] == 2:
            pieces = [(h, o, text) for o, text, h in _windows(split, at, least, most, words) if h in again]
        else:
            pieces = [(key, most, b" ".join(split[at - most : at - least + words]))]
        for piece in pieces:
            held = found.setdefault(piece, [r, False, []])
            held[1] = held[1] or held[0] != r or not across and len(held[2]) > 0
            held[2].append(i)
    rows = sorted(found.items())
    keys = np.array([k for (k, _, _), _ in rows], dtype=np.uint64)

    def parts(a: int, b: int) -> dict:
        own = rows[a:b]
        return {
            "keys": keys[a:b].astype("<u8").tobytes(),
            "left": bytes(k[1] for k, _ in own),
            "rows": np.array([v[0] for _, v in own], "<u4").tobytes(),
            "many": bytes(v[1] for _, v in own),
            "uses": np.array([len(v[2]) for _, v in own], "<u4").tobytes(),
            "places": np.array([i for _, v in own for i in v[2]], "<u4").tobytes(),
            "texts": _pack(b"\n".join(k[2] for k, _ in own)),
        }

    return _cut(batch, keys, shards, parts)


def common_lengths(keys: np.ndarray, rows: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes in the order of key and words, and how many words each has in common with the one before (-1: other key).

    ``rows`` holds word numbers from 0, -1 beyond each row's length.
    """
    n, width = rows.shape
    raw = np.zeros((n, 8 + 4 * width), dtype=np.uint8)
    raw[:, :8] = keys.astype(">u8").view(np.uint8).reshape(n, 8)
    raw[:, 8:] = np.ascontiguousarray((rows + 1).astype(">u4")).view(np.uint8).reshape(n, 4 * width)
    order = np.argsort(raw.view(f"S{raw.shape[1]}").ravel(), kind="stable")
    k, r, size = keys[order], rows[order], lengths[order]
    out = np.full(n, -1, dtype=np.int64)
    if n > 1:
        differ = np.concatenate([r[1:] != r[:-1], np.ones((n - 1, 1), dtype=bool)], axis=1)
        out[1:] = np.where(k[1:] == k[:-1], np.minimum(differ.argmax(axis=1), np.minimum(size[1:], size[:-1])), -1)
    return order, out


def passages(keys: np.ndarray, left: np.ndarray, owner: np.ndarray, many: np.ndarray, split: list[list[bytes]] | tuple[np.ndarray, np.ndarray], words: int, across: bool) -> np.ndarray:
    """For each suffix the passages around it that occur again: bit o, if the one that begins o words before does.

    ``left`` words of each context stand before the kept position; ``owner`` is its row, ``many`` says that
    other rows (or places) have the same context. The context's length tells which passages it holds.
    """
    if isinstance(split, list):
        ids: defaultdict = defaultdict(count().__next__)
        sizes = np.array([len(x) for x in split], dtype=np.int64)
        flat = np.fromiter(map(ids.__getitem__, chain.from_iterable(split)), np.int64, int(sizes.sum()))
    else:
        flat, sizes = split
    n, begins = len(keys), np.cumsum(sizes) - sizes
    right = sizes - left

    def matrix(lengths: np.ndarray, start: np.ndarray, step: int) -> np.ndarray:
        j = np.arange(max(1, int(lengths.max())))
        inside = j[None, :] < lengths[:, None]
        return np.where(inside, flat[np.where(inside, start[:, None] + step * j[None, :], 0)], -1).astype(np.int32)

    order_r, common_r = common_lengths(keys, matrix(right, begins + left, 1), right)
    order_l, common_l = common_lengths(keys, matrix(left, begins + left - 1, -1), left)
    masks = np.zeros(n, dtype=np.uint64)
    for o in range(int((words - right).min()), int(left.max()) + 1):
        fits = (left >= o) & (right >= words - o)
        if not fits.any():
            continue
        right_group, left_group = np.empty(n, np.int64), np.empty(n, np.int64)
        right_group[order_r] = np.cumsum(common_r < words - o)
        left_group[order_l] = np.cumsum(common_l < o)
        at = np.flatnonzero(fits)
        group = right_group[at] * (n + 1) + left_group[at]
        order = np.argsort(group, kind="stable")
        a, b = runs(group[order])
        rows, twice = owner[at][order], many[at][order].astype(bool)
        hit = np.logical_or.reduceat(twice, a) | (np.minimum.reduceat(rows, a) != np.maximum.reduceat(rows, a) if across else b - a > 1)
        masks[at[order[np.repeat(hit, b - a)]]] |= _U(1 << o)
    return masks


def _extend(key, group, words: int, across: bool):
    """Sorts the suffixes of a key range, compares neighbours, extends; answers each batch by its kept suffixes."""
    messages = group.to_pylist()
    ids: defaultdict = defaultdict(count().__next__)
    flat, sizes, owners = [], [], []
    for m, r in enumerate(messages):
        split = [x.split() for x in _unpack(r["texts"]).split(b"\n")]
        sizes.append(np.array([len(x) for x in split], dtype=np.int64))
        flat.append(np.fromiter(map(ids.__getitem__, chain.from_iterable(split)), np.int64, int(sizes[-1].sum())))
        owners.append(np.frombuffer(r["rows"], "<u4").astype(np.int64) | m << 32)
    joined = lambda c, t: np.concatenate([np.frombuffer(r[c], t) for r in messages])
    masks = passages(joined("keys", "<u8"), joined("left", np.uint8).astype(np.int64), np.concatenate(owners), joined("many", np.uint8), (np.concatenate(flat), np.concatenate(sizes)), words, across)
    out, at = [], 0
    for r, size in zip(messages, sizes, strict=True):
        every = np.repeat(masks[at : at + len(size)], np.frombuffer(r["uses"], "<u4"))
        at += len(size)
        hit = every > 0
        if hit.any():
            out.append({"batch": r["batch"], "places": np.frombuffer(r["places"], "<u4")[hit].tobytes(), "masks": every[hit].astype("<u8").tobytes()})
    return pa.Table.from_pylist(out, schema=_FOUND)


def _marked(n: int, starts: np.ndarray, words: int) -> list[tuple[int, int]]:
    """Union of [start, start + words) over sorted starts."""
    if not len(starts):
        return []
    cut = np.flatnonzero(np.diff(starts) > words)
    a = starts[np.concatenate([[0], cut + 1])]
    b = starts[np.concatenate([cut, [len(starts) - 1]])] + words
    return list(zip(a.tolist(), b.tolist(), strict=True))


def repeated_passages(docs: DataFrame, words: int = WORDS, gram: int = GRAM, across: bool = True, batch_bytes: int = BATCH_BYTES, shard_bytes: int = SHARD_BYTES, hot: int = HOT) -> DataFrame:
    """For every row: doc_id, n_words, n_repeated, n_spans, and spans (array of word and code point bounds, end exclusive).

    ``across``: a passage counts if two rows have it; otherwise also if one row has it twice. Repeated rows
    are two rows. A null, empty or short text has no passage, very long texts are read whole. Words are compared
    as they are. A gram in more than ``hot`` rows (or a millionth of all kept suffixes) has each passage around it
    asked for and sent under the passage's own hash, so that no range gets all its contexts. An empty table gives an empty result; extra columns are ignored.
    """
    if not 1 <= gram <= words or words - gram >= 64:
        raise ValueError("a kept suffix must fit the passage, and begin at most 63 words after it")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    shards = parts_for(docs, "text", shard_bytes)
    held = batch_rows(docs, words, gram, batch_bytes)
    suffixes = lambda blob: np.frombuffer(_unpack(blob), _KEPT)

    def ask(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for number, kept in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                kept = suffixes(kept)
                yield from pa.Table.from_pylist(_numbers(number, kept["key"], kept["row"], across, shards), schema=_ASKED).to_batches()

    def ask_windows(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for r in b.to_pylist():
                found = _ask_windows(r["batch"], suffixes(r["kept"]), np.frombuffer(r["counts"], "<i8"), _Texts(r["sizes"], r["texts"]), hot_keys, words, shards, across)
                yield from pa.Table.from_pylist(found, schema=_ASKED).to_batches()

    def hot_of(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            for keys, flags in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(keys, "<i8")[np.frombuffer(flags, np.uint8) == 2])], names=["key"])

    def send(group, answers):
        out = []
        for r in group.to_pylist():
            out += _send(r["batch"], suffixes(r["kept"]), np.frombuffer(r["counts"], "<i8"), _Texts(r["sizes"], r["texts"]), answers.to_pylist(), words, shards, across)
        return pa.Table.from_pylist(out, schema=_SENT)

    schema = "doc_id long, n_words long, n_repeated long, n_spans long, spans array<struct<first_word: int, last_word: int, start: int, end: int>>"
    shown = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_repeated", pa.int64()), ("n_spans", pa.int64()), ("spans", pa.list_(pa.struct([("first_word", pa.int32()), ("last_word", pa.int32()), ("start", pa.int32()), ("end", pa.int32())])))])

    def finish(group, answers):
        out = []
        for r in group.to_pylist():
            kept, counts, texts = suffixes(r["kept"]), np.frombuffer(r["counts"], "<i8"), _Texts(r["sizes"], r["texts"])
            masks = np.zeros(len(kept), dtype=np.uint64)
            for x in answers.to_pylist():
                np.bitwise_or.at(masks, np.frombuffer(x["places"], "<u4"), np.frombuffer(x["masks"], "<u8"))
            hit = np.flatnonzero(masks)
            bits = (masks[hit][:, None] >> np.arange(words - gram + 1, dtype=np.uint64)[None, :]) & _U(1) > 0
            i, o = np.nonzero(bits)
            starts = np.sort(kept["at"][hit[i]] - o)
            begins = np.cumsum(counts) - counts
            at = np.searchsorted(starts, np.append(begins, counts.sum()))
            for d, doc in enumerate(r["doc_ids"]):
                mine = _marked(int(counts[d]), starts[at[d] : at[d + 1]] - begins[d], words)
                bounds = [m.span() for m in _word.finditer(texts[d].decode("utf-8", "surrogatepass"))] if mine else []
                out.append({"doc_id": doc, "n_words": int(counts[d]), "n_repeated": sum(e - s for s, e in mine), "n_spans": len(mine), "spans": [{"first_word": s, "last_word": e, "start": bounds[s][0], "end": bounds[e - 1][1]} for s, e in mine]})
        return pa.Table.from_pylist(out, schema=shown)

    hot = max(hot, (held.agg(F.sum("n_kept")).first()[0] or 0) // MOST_HOT)
    flags = cut_lineage(held.select("batch", "kept").mapInArrow(ask, _ddl(_ASKED)).groupBy("shard").applyInArrow(lambda key, group: _tell(key, group, hot), _ddl(_FLAGS)))
    # More than `hot` rows have each of these: there are fewer than MOST_HOT.
    hot_keys = np.array(sorted(r[0] & 0xFFFFFFFFFFFFFFFF for r in flags.where("n_hot > 0").select("keys", "flags").mapInArrow(hot_of, "key long").distinct().collect()), dtype=np.uint64)
    flags = flags.withColumn("kind", F.lit(1))
    if len(hot_keys):
        windows = held.select("batch", "counts", "kept", "sizes", "texts").mapInArrow(ask_windows, _ddl(_ASKED)).groupBy("shard").applyInArrow(lambda key, group: _tell(key, group, 1 << 62), _ddl(_FLAGS))
        flags = flags.unionByName(windows.withColumn("kind", F.lit(2)))
    sent = held.select("batch", "counts", "kept", "sizes", "texts").groupBy("batch").cogroup(flags.groupBy("batch")).applyInArrow(send, _ddl(_SENT))
    found = sent.groupBy("shard").applyInArrow(lambda key, group: _extend(key, group, words, across), _ddl(_FOUND))
    return held.groupBy("batch").cogroup(found.groupBy("batch")).applyInArrow(finish, schema)


def brute_force(rows: list[tuple], words: int = WORDS, across: bool = True) -> list[list[tuple[int, int]]]:
    """Marked word ranges of each row, from all passages; for tests."""
    seen: dict[tuple, set] = {}
    split = [_word.findall(t or "") for _, t in rows]
    for i, w in enumerate(split):
        for s in range(len(w) - words + 1):
            seen.setdefault(tuple(w[s : s + words]), set()).add(i if across else (i, s))
    out = []
    for w in split:
        hit = np.array([s for s in range(len(w) - words + 1) if len(seen[tuple(w[s : s + words])]) >= 2], dtype=np.int64)
        out.append(_marked(len(w), hit, words))
    return out
