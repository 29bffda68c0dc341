"""Cells of a grid of gram lengths, shares and scores that each pair reaches, decided where the targets lie.

The queries are few and short and go to every task; a task counts their grams in its targets, bounds the scores from the
letters that two parts share, and takes the edit distances of one part with many at a time. Only pairs that reach a cell
are written. The answers are those of ``match.scored``.
"""

from __future__ import annotations

from collections.abc import Iterator
from fractions import Fraction
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.clone.links import _BIT, _CODE, Parts, gathered, placed
from codeprov.functions.text import levenshtein_bits

#: Letters of targets that are looked at in one go, and of queries that may go to every task.
LETTERS, MOST_ASKED = 1 << 20, 1 << 20


def distances(s: bytes, parts: Parts, u: np.ndarray) -> np.ndarray:
    """Edit distances of ``s`` with the parts ``u``: one bit of a number for each letter of ``s``, all parts side by side."""
    if len(s) > 64:
        return np.array([levenshtein_bits(s, parts[k]) for k in u], np.int64)
    order = np.argsort(-parts.length[u].astype(np.int64), kind="stable")
    u = u[order]
    length, start = parts.length[u].astype(np.int64), parts.starts[u]
    raw = np.frombuffer(parts.data, np.uint8)
    places = np.zeros(256, np.uint64)
    for i, x in enumerate(s):
        places[x] |= np.uint64(1 << i)
    one, last = np.uint64(1), np.uint64(len(s) - 1)
    more, less = np.full(len(u), np.uint64(0xFFFFFFFFFFFFFFFF)), np.zeros(len(u), np.uint64)
    out = np.full(len(u), len(s), np.int64)
    n = np.searchsorted(-length, -np.arange(int(length[0]) if len(u) else 0), "left")
    for j, k in enumerate(n):
        p, m = more[:k], less[:k]
        equal = places[raw[start[:k] + j]]
        across = ((equal & p) + p ^ p) | equal
        down = equal | m
        up, fall = m | ~(across | p), p & across
        out[:k] += (up >> last & one).astype(np.int64) - (fall >> last & one).astype(np.int64)
        up, fall = up << one | one, fall << one
        more[:k], less[:k] = fall | ~(down | up), up & down
    back = np.empty(len(u), np.int64)
    back[order] = out
    return back


def shares(s: bytes, number: int, parts: Parts) -> tuple[np.ndarray, np.ndarray]:
    """Length, and the most that a delta of ``s`` can be, as a share, with each different part; 1 only if equal."""
    codes = _BIT[_CODE[np.frombuffer(s, np.uint8)]]
    letters = np.bitwise_or.reduce(codes)
    first = parts.first
    common = np.minimum(len(s) - int(np.bitwise_count(letters)), parts.repeats[first].astype(np.int64)) + np.bitwise_count(letters & parts.letters[first])
    most = np.maximum(len(s), parts.length[first].astype(np.int64))
    common = np.minimum(common, most - 1)
    if number >= 0:
        common[number] = most[number]
    return most, common / most


def bests(s: bytes, number: int, parts: Parts, rows: np.ndarray) -> np.ndarray:
    """The highest delta of ``s`` in each of the fingerprints ``rows``, exact."""
    places, begins = gathered(parts.ptr, rows)
    kinds = parts.kind[places]
    most, bound = shares(s, number, parts)
    known = np.full(len(bound), -1.0)
    if number >= 0:
        known[number] = 100.0
    counts = np.diff(np.append(begins, len(kinds)))
    # First the parts of the highest bound of each fingerprint, then those that could still beat what was found.
    while True:
        low = np.maximum.reduceat(known[kinds], begins).clip(0.0)
        high = np.maximum.reduceat(np.where(known[kinds] < 0, bound[kinds], -1.0), begins)
        left = high > low / 100 + 1e-12
        if not left.any():
            return low
        least = np.repeat(np.where(left, np.maximum(low / 100 + 1e-12, high - 0.1), 9.0), counts)
        ask = np.unique(kinds[(bound[kinds] >= least) & (known[kinds] < 0)])
        known[ask] = 100.0 * (1 - distances(s, parts, parts.first[ask]) / most[ask])


def _grams(parts: Parts, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Fingerprint and gram, both ascending and each pair once; one whose parts are all shorter than ``n`` has none."""
    raw = np.frombuffer(parts.data, np.uint8)
    code = _CODE[raw].astype(np.int64)
    m = max(0, len(code) - n + 1)
    gram, ok = np.zeros(m, np.int64), np.ones(m, bool)
    for k in range(n):
        gram = gram << 6 | code[k : k + m] & 63
        ok &= code[k : k + m] < 64
    ends = parts.starts[parts.ptr[1:] - 1] + parts.length[parts.ptr[1:] - 1]
    row = np.searchsorted(ends, np.arange(m))
    keys = np.sort((row << 6 * n | gram)[ok])
    keys = keys[np.append(True, keys[1:] != keys[:-1])] if len(keys) else keys
    return keys >> 6 * n, keys & 64**n - 1


def shared(a: Parts, b: Parts, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of shared grams (queries by targets), and of the queries' grams; whole strings stand for those without a gram."""
    q, t = len(a.ptr) - 1, len(b.ptr) - 1
    row, gram = _grams(a, n)
    order = np.argsort(gram, kind="stable")
    row, gram = row[order], gram[order]
    of, other = _grams(b, n)
    sizes, held = np.bincount(row, minlength=q), np.bincount(of, minlength=t)
    at = np.searchsorted(gram, other)
    times = np.searchsorted(gram, other, "right") - at
    places = np.repeat(at - np.cumsum(times) + times, times) + np.arange(int(times.sum()))
    out = np.bincount(row[places] * t + np.repeat(of, times), minlength=q * t).reshape(q, t)
    whole = {}
    for k in np.flatnonzero(held == 0):
        whole.setdefault(b.whole(k), []).append(k)
    for k in np.flatnonzero(sizes == 0):
        out[k, whole.get(a.whole(k), [])] = 1
    return out, np.maximum(sizes, 1)


def cells(a: Parts, b: Parts, ns: list[int], etas: list[float], epss: list[float]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """For each query its targets that reach a cell, and the cells (targets by n, eta and eps)."""
    placed(a, b)
    counts = [shared(a, b, n) for n in ns]
    least = Fraction(str(min(etas)))
    floor, every = 100 * min(epss) - 1e-9, np.arange(len(b.ptr) - 1)
    for q in range(len(a.ptr) - 1):
        found = [(c[q] > 0) & (c[q] * least.denominator >= least.numerator * int(g[q])) for c, g in counts]
        rows = every[reduce(np.logical_or, found)]
        mine = range(a.ptr[q], a.ptr[q + 1])
        high = []
        for s in mine if len(rows) else []:
            places, begins = gathered(b.ptr, rows)
            high.append(100 * np.maximum.reduceat(shares(a[s], int(a.word[s]), b)[1][b.kind[places]], begins))
        # A part's bound gives way to its best delta, and who cannot reach the least score any more is left out.
        for k in range(len(high)):
            kept = sum(high) / len(high) >= floor - 1e-6
            rows, high = rows[kept], [h[kept] for h in high]
            if not len(rows):
                break
            high[k] = bests(a[mine[k]], int(a.word[mine[k]]), b, rows)
        if not len(rows):
            continue
        score = reduce(lambda x, y: x + y, high, np.zeros(len(rows))) / len(high)
        ok = np.array([f[rows] & (c[q, rows] >= eta * g[q]) & (score >= 100 * eps - 1e-9) for f, (c, g) in zip(found, counts, strict=True) for eta in etas for eps in epss]).T
        hit = ok.any(axis=1)
        yield q, rows[hit], ok[hit]


class _Whole(Parts):
    def whole(self, k: int) -> bytes:
        end = self.ptr[k + 1] - 1
        return self.data[self.starts[self.ptr[k]] : self.starts[end] + self.length[end]]


def _parts(fps: list[str]) -> _Whole:
    return _Whole("".join(f"{x}\n" for x in fps).encode())


def reached(queries: DataFrame, targets: DataFrame, ns: list[int], etas: list[float], epss: list[float]) -> DataFrame:
    """``query_id, target_id, cells`` of the pairs that reach a cell: places in the grid, the scores counting fastest, then the shares."""
    q = queries.where("size(subs) > 0").select("id", F.array_join("subs", ".").alias("fp"))
    t = targets.where("size(subs) > 0").select(F.col("id").cast("long").alias("id"), F.array_join("subs", ".").alias("fp"))
    packed = q.agg(F.collect_list("id").alias("q_ids"), F.collect_list("fp").alias("q_fps")).first()
    ids, fps, letters = [int(x) for x in packed.q_ids], list(packed.q_fps), LETTERS

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = _parts(fps) if fps else None
        for batch in batches if fps else []:
            own, texts = batch.column("id").to_numpy(), batch.column("fp").to_pylist()
            sizes, at = np.cumsum([len(x) + 1 for x in texts]), 0
            while at < len(texts):
                to = max(at + 1, int(np.searchsorted(sizes, (sizes[at - 1] if at else 0) + letters, "right")))
                for k, rows, ok in cells(a, _parts(texts[at:to]), ns, etas, epss):
                    yield pa.RecordBatch.from_pydict({"query_id": pa.array(np.full(len(rows), ids[k])), "target_id": pa.array(own[at:to][rows]), "cells": pa.array([np.flatnonzero(x).tolist() for x in ok], pa.list_(pa.int32()))})
                at = to

    return t.mapInArrow(work, "query_id long, target_id long, cells array<int>")
