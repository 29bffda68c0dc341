"""Benchmark decontamination by Wu-Manber search over words.

Every 13-word window of a benchmark item is a pattern (an item of fewer words is one whole pattern). The
patterns of one length form one search table: a shift table over blocks of two words tells how far the
window may jump; where the shift is zero, the bucket of the last block, then the first block, selects
the few patterns that are compared word by word. In clean text most words are never looked at.

Items travel as text, in blocks of bounded size; a worker numbers the words of a block, so that its patterns are
places in one flat array, and holds the tables of one block at a time. Further blocks are further rounds over the
texts at hand within the same narrow step: a benchmark of any size neither outgrows memory nor moves documents.
"""

from __future__ import annotations

import hashlib
from array import array
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.llm.common import gathered, resident

WINDOW = 13
BLOCK = 2
#: Bytes of benchmark text whose tables a worker holds at once (some 50 MB), and of documents that wait for further blocks.
ITEM_BYTES, WAIT_BYTES = 1 << 20, 24 << 20

#: A-Z to a-z; every other ASCII character that is neither letter nor digit to a blank.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_FOLD).split()


class Tables:
    """Search tables of ``(id, text)`` rows: patterns of each length are places in ``flat``, the items' word numbers.

    Wordless items give no pattern. A pattern that stands at several places is listed at each.
    """

    def __init__(self, items: list[tuple], window: int = WINDOW) -> None:
        self.number: dict[bytes, int] = {}
        self.items = [i for i, _ in items]
        self.flat = array("i")
        #: For each length: shifts of word blocks, and the places of patterns by their last block.
        self.by: dict[int, tuple[dict, dict]] = {}
        #: Where each item begins in ``flat``.
        self.begins = array("q")
        for _, text in items:
            w = [self.number.setdefault(x, len(self.number)) for x in words(text)]
            self.begins.append(len(self.flat))
            self.flat.extend(w)
            if not w:
                continue
            m = min(window, len(w))
            shift, buckets = self.by.setdefault(m, ({}, {}))
            block, at = min(BLOCK, m), len(self.flat) - len(w)
            for i in range(len(w) - block + 1):
                key = self.key(w[i : i + block])
                # The last of a pattern's words is as far from the block's end as it can be, but within the item.
                jump = max(0, m - block - i)
                if shift.get(key, m) > jump:
                    shift[key] = jump
                if i + block >= m:
                    held = buckets.get(key)
                    place = at + i + block - m
                    buckets[key] = place if held is None else (*held, place) if type(held) is tuple else (held, place)

    @staticmethod
    def key(block: list[int]) -> int:
        return block[0] << 32 | block[1] if len(block) == 2 else block[0]

    def owner(self, place: int) -> int:
        """The item whose words hold a place."""
        return bisect_right(self.begins, place) - 1

    def search(self, text: list[int]) -> Iterator[tuple[int, int, int]]:
        """Start, length and place in ``flat`` of each occurrence; ``text`` in word numbers, -1 for words of no item."""
        flat, n = self.flat, len(text)
        for m, (shift, buckets) in self.by.items():
            b = min(BLOCK, m)
            furthest, end, get = m - b + 1, m, shift.get
            while end <= n:
                last = text[end - 1]
                if last < 0:
                    end += m
                    continue
                if b == 2:
                    before = text[end - 2]
                    if before < 0:
                        end += m - 1
                        continue
                    key = before << 32 | last
                else:
                    key = last
                jump = get(key, furthest)
                if jump:
                    end += jump
                    continue
                start, found = end - m, buckets[key]
                first, here = text[start], None
                for place in found if type(found) is tuple else (found,):
                    if flat[place] == first:
                        here = here or array("i", text[start:end])
                        if flat[place : place + m] == here:
                            yield start, m, place
                end += 1


def tables(items: list[tuple], window: int = WINDOW) -> Tables:
    return Tables(items, window)


def _blocks(benchmark: DataFrame, item_bytes: int) -> Iterator[list[tuple]]:
    """The items in blocks of about ``item_bytes`` of text, each collected by itself."""
    src = benchmark.select(F.col("item_id").cast("string").alias("item_id"), "text").where("item_id is not null and text is not null").distinct()
    total = src.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = -(-int(total) // item_bytes)
    for i in range(n):
        part = src if n == 1 else src.where(F.pmod(F.xxhash64("item_id"), F.lit(n)) == i)
        yield sorted(tuple(r) for r in part.collect())


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, item_bytes: int = ITEM_BYTES, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns, n_words, n_hit, n_items, items (sorted array), contaminated for every row of ``docs``.

    Null or wordless texts have no words and no hit. Items with null id or text are left out; repeated
    items count once. An empty benchmark hits nothing; an empty table gives no rows. A document is
    contaminated if a twentieth of its words lies inside occurrences. Very long texts are searched whole, repeated
    rows give repeated rows; extra columns are ignored, also where they bear the name of a result.
    """
    named = {c: f"_k{i}" for i, c in enumerate(keep)}
    src = docs.select(*(F.col(c).alias(n) for c, n in named.items()), "text")
    schema = src.drop("text").schema.add("n_words", "long").add("n_hit", "long").add("items", src.sparkSession.createDataFrame([], "x array<string>").schema[0].dataType)
    context = docs.sparkSession.sparkContext
    shared = [(context.broadcast(block), hashlib.sha256(repr((window, block)).encode()).hexdigest()) for block in _blocks(benchmark, item_bytes)]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, t in gathered(batches, WAIT_BYTES if len(shared) > 1 else WAIT_BYTES // 6):
            texts = t.column("text").to_pylist()
            counts, marks, found = [0] * len(texts), [None] * len(texts), [set() for _ in texts]
            for block, name in shared:
                own = resident(("items", name), lambda block=block: Tables(block.value, window))
                get = own.number.get
                for i, text in enumerate(texts):
                    numbers = [get(x, -1) for x in words(text)]
                    counts[i] = len(numbers)
                    for start, m, place in own.search(numbers):
                        if marks[i] is None:
                            marks[i] = bytearray(len(numbers))
                        marks[i][start : start + m] = b"\1" * m
                        found[i].add(own.items[own.owner(place)])
            if not shared:
                counts = [len(words(x)) for x in texts]
            arrays = [pa.array(counts, pa.int64()), pa.array([0 if x is None else sum(x) for x in marks], pa.int64()), pa.array([sorted(x) for x in found], pa.list_(pa.string()))]
            whole = pa.Table.from_arrays([*(t.column(n) for n in named.values()), *arrays], names=schema.names)
            yield from whole.combine_chunks().to_batches()

    out = src.mapInArrow(work, schema)
    out = out.select(*(F.col(k).alias(c) for c, k in named.items()), "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), "items")
    return out.withColumn("contaminated", F.expr("n_hit > 0 AND 20 * n_hit >= n_words"))


def digest(found: DataFrame) -> DataFrame:
    """The columns of the query, with the hash of the sorted item ids."""
    return found.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), "contaminated")


def brute_force(docs: list[tuple], items: list[tuple], window: int = WINDOW) -> dict:
    """The same by trying every window at every position; for tests."""
    out = {}
    for doc, text in docs:
        w, hit, ids = words(text), set(), set()
        for item, other in items:
            v = words(other)
            m = min(window, len(v))
            for p in {tuple(v[i : i + m]) for i in range(len(v) - m + 1)} if v else ():
                for s in range(len(w) - m + 1):
                    if tuple(w[s : s + m]) == p:
                        hit |= set(range(s, s + m))
                        ids.add(str(item))
        out[doc] = (len(w), len(hit), len(ids), hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w))
    return out
