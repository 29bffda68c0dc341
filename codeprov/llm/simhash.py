"""SimHash near-duplicates found by Golay-code fuzzy hashing.

A 64-bit fingerprint is cut into segments of 23, 23 and 18 bits. Words of 23 bits decode to exactly one
word of the binary Golay code at distance 3 or less. If two fingerprints differ in at most three bits,
then two of the three segments differ in at most one bit each (pigeonhole), and for such segments the
code word of the one is within distance 4 of the other. So each fingerprint is filed once per pair of
segments under its two decoded code words, and looks up the (one or six) code words near each segment.
Keys that meet are joined, and the full distance is checked inside the join, which emits a link once.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.llm.common import cut_lineage, slices
from codeprov.llm.components import components

SEED = 42
SHINGLE = 3
MOST_BITS = 3
#: Low bit and width of each segment.
SEGMENTS = ((0, 23), (23, 23), (46, 18))
PAIRS = ((0, 1), (0, 2), (1, 2))
#: Generator polynomial of the binary Golay code of length 23 (a fixed value).
GENERATOR = 0xC75


def _masks() -> list[int]:
    return [((1 << n) - 1) << at for at, n in SEGMENTS]


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """Unsigned 64-bit majority hash of the word shingles of ``text``; 0 where it has no word."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    if len(words) < shingle:
        grams = [b" ".join(words)]
    else:
        grams = map(b" ".join, zip(*(words[i:] for i in range(shingle)), strict=False))
    digest = xxhash.xxh64_intdigest
    h = np.array([digest(g, SEED) for g in grams], dtype=">u8")
    set_bits = np.zeros(64, dtype=np.int64)
    for start in range(0, len(h), 1 << 15):
        block = h[start : start + (1 << 15)]
        set_bits += np.unpackbits(block.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int32)
    return int.from_bytes(np.packbits(set_bits * 2 > len(h)).tobytes(), "big")


def fingerprints(docs: DataFrame, text: str = "text", shingle: int = SHINGLE, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns and ``fp`` (BIGINT, the fingerprint's bits) for every row; a narrow step."""
    src = docs.select(*keep, F.col(text).alias("_text"))
    schema = src.drop("_text").schema.add("fp", "long")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, "_text"):
            out = np.array([fingerprint(t, shingle) for t in b.column("_text").to_pylist()], dtype=np.uint64).view(np.int64)
            columns = [b.column(c) for c in keep]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(out)], names=[*keep, "fp"])

    return src.mapInArrow(work, schema)


class Golay:
    """Syndrome tables of the (23, 12) code: for each syndrome the error patterns of weight 4 or less."""

    def __init__(self) -> None:
        def rest(v: int) -> int:
            for bit in range(22, 10, -1):
                if v >> bit & 1:
                    v ^= GENERATOR << (bit - 11)
            return v

        unit = [rest(1 << i) for i in range(23)]
        self.tables = []
        for at in (0, 8, 16):
            t = np.zeros(256, dtype=np.int64)
            for v in range(256):
                s = 0
                for i in range(8):
                    if v >> i & 1 and at + i < 23:
                        s ^= unit[at + i]
                t[v] = s
            self.tables.append(t)
        self.leader = np.full(2048, -1, dtype=np.int64)
        far: dict[int, list[int]] = {}
        for weight in range(5):
            for bits in itertools.combinations(range(23), weight):
                s = e = 0
                for i in bits:
                    s, e = s ^ unit[i], e | 1 << i
                if weight < 4:
                    self.leader[s] = e
                else:
                    far.setdefault(s, []).append(e)
        #: -1 fills the rows of syndromes whose leader has weight below 3: no other code word is within 4.
        self.near = np.full((2048, 6), -1, dtype=np.int64)
        self.near[:, 0] = self.leader
        for s, patterns in far.items():
            self.near[s, 1 : 1 + len(patterns)] = patterns

    def syndrome(self, v: np.ndarray) -> np.ndarray:
        t = self.tables
        return t[0][v & 255] ^ t[1][v >> 8 & 255] ^ t[2][v >> 16 & 255]

    def filed(self, v: np.ndarray) -> np.ndarray:
        """Index (12 bits) of the code word that each word decodes to."""
        return (v ^ self.leader[self.syndrome(v)]) >> 11

    def looked_up(self, v: np.ndarray) -> np.ndarray:
        """Indices of all code words within distance 4, up to six in a row; -1 where there are fewer."""
        e = self.near[self.syndrome(v)]
        return np.where(e < 0, -1, (v[:, None] ^ e) >> 11)


_golay: list[Golay] = []


def golay() -> Golay:
    if not _golay:
        _golay.append(Golay())
    return _golay[0]


def keys(fps: np.ndarray, lookup: bool) -> tuple[np.ndarray, np.ndarray]:
    """Row numbers and keys of fingerprints (uint64): one key per pair of segments, or all to look up."""
    g = golay()
    parts = [((fps >> np.uint64(at)) & np.uint64((1 << n) - 1)).astype(np.int64) for at, n in SEGMENTS]
    index = [g.looked_up(p) if lookup else g.filed(p)[:, None] for p in parts]
    rows, out = [], []
    for number, (a, b) in enumerate(PAIRS):
        key = (index[a][:, :, None] << 12 | index[b][:, None, :]) | number << 24
        fits = (index[a][:, :, None] >= 0) & (index[b][:, None, :] >= 0)
        at, i, j = np.nonzero(fits)
        rows.append(at)
        out.append(key[at, i, j])
    return np.concatenate(rows), np.concatenate(out)


def _keyed(distinct: DataFrame, lookup: bool) -> DataFrame:
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for start in range(0, b.num_rows, 2000):
                fps = b.column("fp").slice(start, 2000).to_numpy(zero_copy_only=False).astype(np.int64)
                rows, found = keys(fps.view(np.uint64), lookup)
                yield pa.RecordBatch.from_arrays([pa.array(found), pa.array(fps[rows])], names=["key", "fp"])

    return distinct.select("fp").mapInArrow(work, "key long, fp long")


def links(distinct: DataFrame, most_bits: int = MOST_BITS) -> DataFrame:
    """``u, v`` for each two distinct fingerprints (column ``fp``) that differ in 1 to ``most_bits`` <= 3 bits, once."""
    if not 0 <= most_bits <= 3:
        raise ValueError("two segments with one error each are only sure up to three bits")
    filed, asked = _keyed(distinct, False).alias("a"), _keyed(distinct, True).alias("b")
    near = [f"(bit_count((a.fp ^ b.fp) & {m if m < 1 << 63 else m - (1 << 64)}L) <= 1)" for m in _masks()]
    first = f"CASE WHEN {near[0]} AND {near[1]} THEN 0 WHEN {near[0]} AND {near[2]} THEN 1 ELSE 2 END"
    on = f"a.key = b.key AND a.fp < b.fp AND bit_count(a.fp ^ b.fp) <= {most_bits} AND shiftright(a.key, 24) = {first}"
    return filed.hint("merge").join(asked, F.expr(on)).select(F.col("a.fp").alias("u"), F.col("b.fp").alias("v"))


def near_duplicates(docs: DataFrame, text: str = "text", id: str = "doc_id", shingle: int = SHINGLE, most_bits: int = MOST_BITS) -> DataFrame:
    """``doc_id, fingerprint, component_id`` for every row of ``docs``.

    Null or wordless texts have fingerprint 0 and are linked like any other. Repeated ids give repeated
    rows. A row without id gets the component of its fingerprint, which is null if no member has an id.
    An empty table gives an empty result; other columns are ignored.
    """
    rows = cut_lineage(fingerprints(docs.select(F.col(id).alias("doc_id"), F.col(text).alias("text")), shingle=shingle))
    groups = cut_lineage(rows.groupBy("fp").agg(F.min("doc_id").alias("least")))
    parts = components(links(groups, most_bits))
    rooted = groups.join(parts, groups.fp == parts.node, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    rooted = cut_lineage(rooted)
    firsts = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    named = cut_lineage(rooted.join(cut_lineage(firsts).hint("merge"), "root").select("fp", "component_id"))
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return rows.join(named.hint("merge"), "fp").select("doc_id", hexed.alias("fingerprint"), "component_id")


def brute_force(texts: dict[int, str | None], shingle: int = SHINGLE, most_bits: int = MOST_BITS) -> dict[int, tuple[str, int]]:
    """The same by comparing all pairs; for tests."""
    fps = {i: fingerprint(t, shingle) for i, t in texts.items()}
    root = {i: i for i in fps}

    def find(x: int) -> int:
        while root[x] != x:
            x = root[x]
        return x

    for a, b in itertools.combinations(sorted(fps), 2):
        if (fps[a] ^ fps[b]).bit_count() <= most_bits:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    return {i: (f"{fp:016x}", find(i)) for i, fp in fps.items()}
