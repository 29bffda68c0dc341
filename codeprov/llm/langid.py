"""Language identification by cross-parsing entropy over suffix automata.

For each language a suffix automaton is built over a bounded sample of its labelled text. A text is cut
greedily into phrases, each the longest next piece that occurs in the sample; the language that needs
fewest phrases, normalised to bits per character, wins. Cross-parsing only ever follows forward edges or
restarts at the root, so an automaton becomes one dense table (state, letter) -> (next state, new phrase?)
and a worker parses thousands of blocks of text against all languages in lockstep. Where a block goes on from
another one, a second parse from that one's last state runs beside the first until both are in the same state;
from there on they are one, so the difference up to there corrects the count and whole texts are parsed exactly.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.llm.common import held_out, resident, slices

#: The bound of the labelled sample: documents of each language, or pieces of long ones, up to so many letters.
SAMPLE_CHARS = 24_000
#: And at most so many candidate documents of a language are looked at on the driver.
SAMPLE_DOCS = 60
#: Documents from which a language that is short of text gets pieces, about.
PIECE_DOCS = 48
#: So many languages get the whole bound; more of them share the letters of so many.
FULL_LANGUAGES = 64
#: Letters of the dense table: 0 pads, 1..39 frequent letters, the others share 24 classes by code block.
LETTERS, FREQUENT = 64, 40
#: A longer text is parsed in blocks of so many letters side by side; what the restarts add is taken off again.
BLOCK = 2048


def letters_only(column) -> F.Column:
    """Lower-cased text with every run of characters that are not letters as one blank."""
    return F.regexp_replace(F.lower(column), r"[^\p{L}]+", " ")


class SuffixAutomaton:
    """All substrings of a text, as forward edges from state 0."""

    def __init__(self, text: str) -> None:
        self.next: list[dict] = [{}]
        link, length, last = [-1], [0], 0
        for ch in text:
            cur = len(self.next)
            self.next.append({})
            length.append(length[last] + 1)
            link.append(0)
            p = last
            while p >= 0 and ch not in self.next[p]:
                self.next[p][ch] = cur
                p = link[p]
            if p >= 0:
                q = self.next[p][ch]
                if length[p] + 1 == length[q]:
                    link[cur] = q
                else:
                    clone = len(self.next)
                    self.next.append(dict(self.next[q]))
                    length.append(length[p] + 1)
                    link.append(link[q])
                    while p >= 0 and self.next[p].get(ch) == q:
                        self.next[p][ch] = clone
                        p = link[p]
                    link[q] = link[cur] = clone
            last = cur


class Alphabet:
    def __init__(self, texts: list[str]) -> None:
        counts = Counter()
        for t in texts:
            counts.update(t)
        frequent = [c for c, _ in sorted(counts.items(), key=lambda x: (-x[1], x[0]))][: FREQUENT - 1]
        self.low = np.empty(0x3000, dtype=np.uint8)
        self.low[:] = FREQUENT + (np.arange(0x3000) >> 7) % (LETTERS - FREQUENT)
        self.high: dict[int, int] = {}
        for i, c in enumerate(frequent, 1):
            if ord(c) < 0x3000:
                self.low[ord(c)] = i
            else:
                self.high[ord(c)] = i

    def classes(self, text: str) -> np.ndarray:
        cp = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype="<u4")
        out = self.low[np.minimum(cp, 0x2FFF)]
        far = cp >= 0x3000
        if far.any():
            out[far] = FREQUENT + (cp[far] >> 7) % (LETTERS - FREQUENT)
            for c, i in self.high.items():
                out[cp == c] = i
        return out


class Model:
    """Dense cross-parsing tables of all languages, one after another."""

    def __init__(self, samples: dict[str, str]) -> None:
        self.languages = sorted(samples)
        self.alphabet = Alphabet([samples[k] for k in self.languages])
        tables, self.starts, at = [], [], 0
        for k in self.languages:
            sa = SuffixAutomaton(self.alphabet.classes(samples[k]).tolist())
            n = len(sa.next)
            edge = np.full((n + 1, LETTERS), -1, dtype=np.int64)
            for x, out in enumerate(sa.next):
                for c, to in out.items():
                    edge[x, c] = to
            # State n stands before the first letter and after a letter that the sample lacks: whatever follows opens a phrase.
            fresh = np.where(edge[0] < 0, n, edge[0])
            moved = np.where(edge < 0, (fresh[None, :] + at) << 7 | 1, (edge + at) << 7)
            moved[:, 0] = (np.arange(n + 1) + at) << 7
            if at + n >= (1 << 24) - 1:
                raise ValueError("the samples are too long for the packed table")
            tables.append(moved.astype(np.int32))
            self.starts.append((at + n) << 6)
            at += n + 1
        self.table = np.concatenate(tables).ravel() if tables else np.zeros(0, np.int32)
        self.bits = [np.log2(max(2, len(samples[k]))) for k in self.languages]

    def phrases(self, texts: list[str]) -> np.ndarray:
        """Phrases of each text (rows) for each language (columns)."""
        out = np.zeros((len(texts), len(self.languages)), dtype=np.int64)
        owner, blocks = [], []
        for i, t in enumerate(texts):
            c = self.alphabet.classes(t)
            for s in range(0, len(c), BLOCK):
                owner.append(i)
                blocks.append(c[s : s + BLOCK])
        if not blocks or not self.languages:
            return out
        order = sorted(range(len(blocks)), key=lambda j: -len(blocks[j]))
        sizes = np.array([len(blocks[j]) for j in order])
        grid = np.zeros((len(order), sizes[0]), dtype=np.uint8)
        for row, j in enumerate(order):
            grid[row, : len(blocks[j])] = blocks[j]
        grid = np.ascontiguousarray(grid.T)
        fresh = np.array(self.starts, dtype=np.int32)[:, None]
        state = np.repeat(fresh, len(order), axis=1)
        count = np.zeros(state.shape, dtype=np.int32)
        alive = np.searchsorted(-sizes, -np.arange(sizes[0]), side="left")
        for step in range(sizes[0]):
            k = alive[step]
            moved = self.table.take(state[:, :k] + grid[step, :k])
            count[:, :k] += moved & 1
            np.bitwise_and(moved >> 1, ~63, out=state[:, :k])
        owner = np.array(owner)
        np.add.at(out, owner[order], count.T)
        row_of = np.empty(len(order), dtype=np.int64)
        row_of[order] = np.arange(len(order))
        later = np.flatnonzero(owner[1:] == owner[:-1]) + 1
        if len(later):
            rows, before = row_of[later], row_of[later - 1]
            went, wrong = state[:, before], np.repeat(fresh, len(rows), axis=1)
            extra = np.zeros(went.shape, dtype=np.int64)
            for step in range(sizes[0]):
                apart = np.flatnonzero((went != wrong).any(axis=0))
                if not len(apart):
                    break
                c = grid[step, rows[apart]]
                a, f = self.table.take(went[:, apart] + c), self.table.take(wrong[:, apart] + c)
                extra[:, apart] += (a & 1) - (f & 1)
                went[:, apart], wrong[:, apart] = a >> 1 & ~63, f >> 1 & ~63
            np.add.at(out, owner[later], extra.T)
            for i in np.unique(owner[later[(went != wrong).any(axis=0)]]).tolist():
                # Some block never came together: its last state was another, so the text is parsed from its start.
                out[i] = self._in_order(self.alphabet.classes(texts[i]))
        return out

    def _in_order(self, letters: np.ndarray) -> list[int]:
        found, table = [], memoryview(self.table)
        for state in self.starts:
            n = 0
            for c in letters.tolist():
                moved = table[state + c]
                n += moved & 1
                state = moved >> 1 & ~63
            found.append(n)
        return found

    def predict(self, texts: list[str | None]) -> list[tuple[str, float]]:
        """Language and score of texts that hold letters and blanks only."""
        clean = [(t or "").strip() for t in texts]
        bits = self.phrases(clean) * np.array(self.bits) / np.maximum(1, [len(t) for t in clean])[:, None] if self.languages else None
        out = []
        for i, t in enumerate(clean):
            if not t or bits is None:
                out.append(("und", 0.0))
                continue
            p = np.exp2(-4 * (bits[i] - bits[i].min()))
            best = int(bits[i].argmin())
            out.append((self.languages[best], float(p[best] / p.sum())))
        return out


def sample(labelled: DataFrame, chars: int = SAMPLE_CHARS, docs: int = SAMPLE_DOCS) -> dict[str, str]:
    """Training text of every language with a letter: distinct documents in the order of a hash, up to ``chars`` letters.

    ``labelled`` has text and lang. Beyond ``FULL_LANGUAGES`` languages all share the letters of so many. Whole
    documents of at most a quarter of the bound come first: thinned by the hash of their text, copies fall
    together, and about four times ``docs`` rows of a language reach the driver. A language that stays short
    of text is looked for again, thinned by its distinct documents (most rows may be copies), then filled with
    pieces of its longer documents.
    """
    labelled = labelled.where("text is not null and lang is not null")
    counts = {r["lang"]: r["n"] for r in labelled.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    chars = max(64, chars * FULL_LANGUAGES // max(FULL_LANGUAGES, len(counts)))
    rows = labelled.select("lang", letters_only(F.col("text")).alias("t"), F.xxhash64("text").alias("h")).where(F.length(F.trim("t")) > 0)
    short, long = rows.where(F.length("t") <= chars // 4), rows.where(F.length("t") > chars // 4)
    out: dict[str, str] = {}

    def by_lang(kept: DataFrame, numbers: dict[str, int], most: int) -> dict[str, list]:
        """Distinct rows of each language in ``numbers``, about ``most`` or all of them, in the order of their hash."""
        found: dict[str, list] = {lang: [] for lang in numbers}
        if numbers:
            share = F.create_map(*(F.lit(x) for lang, n in numbers.items() for x in (lang, min(1.0, most / n))))[F.col("lang")]
            once = kept.where(F.pmod("h", F.lit(1 << 30)) / (1 << 30) < share).groupBy("lang", "h").agg(F.min("t").alias("t"))
            for r in sorted(once.collect(), key=lambda x: (x["h"], x["t"])):
                found[r["lang"]].append(r["t"].strip())
        return found

    def distinct(kept: DataFrame, langs: list[str]) -> dict[str, int]:
        return {r["lang"]: r["n"] for r in kept.where(F.col("lang").isin(langs)).groupBy("lang").agg(F.approx_count_distinct("h").alias("n")).collect()} if langs else {}

    def take(found: dict[str, list]) -> None:
        for lang, most in found.items():
            rest, texts = chars, []
            for t in most[:docs]:
                if len(t) < rest:
                    texts.append(t)
                    rest -= len(t) + 1
            if texts:
                out[lang] = " ".join(texts)

    poor = lambda: [lang for lang in counts if len(out.get(lang, "")) < chars // 2]
    take(by_lang(short, counts, 4 * docs))
    take(by_lang(short, distinct(short, [lang for lang in poor() if 4 * docs < counts[lang]]), 4 * docs))
    numbers = distinct(long, poor())
    few = [lang for lang, n in numbers.items() if n <= PIECE_DOCS // 6]
    size = F.when(F.col("lang").isin(few), chars).otherwise(chars // 4)
    place = F.expr("1 + pmod(h, greatest(1, length(t) - size + 1))").cast("int")
    pieces = long.withColumn("size", size).select("lang", "h", F.substr("t", place, F.col("size")).alias("t"))
    for lang, found in by_lang(pieces, numbers, PIECE_DOCS).items():
        # A quarter of the bound from each document, then the rest of what was read of them.
        for t in [t[: chars // 4] for t in found] + [t[chars // 4 :] for t in found]:
            rest = chars - len(out.get(lang, ""))
            if t and rest > 1:
                out[lang] = f"{out[lang]} {t[: rest - 1]}" if lang in out else t[:rest]
    return out


def fit(labelled: DataFrame, chars: int = SAMPLE_CHARS, docs: int = SAMPLE_DOCS) -> dict[str, str]:
    """The model's state: training text by language, a few hundred kilobytes at most."""
    return sample(labelled, chars, docs)


def _model(samples: dict[str, str]) -> Model:
    name = hashlib.sha256(repr(sorted(samples.items())).encode()).hexdigest()
    return resident(("langid", name), lambda: Model(samples))


def predict(docs: DataFrame, samples: dict[str, str], keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns, ``lang_pred`` and ``score`` (0 to 1) for every row; a narrow step over ``text`` alone.

    A null text, or one without a letter, is ``und`` with score 0, as is every text if nothing was learned.
    Ties go to the language that sorts first. Very long texts are parsed whole, repeated rows give repeated rows,
    and columns beside ``keep`` are ignored, also where they bear the name of a result. An empty table gives an
    empty result.
    """
    shared = docs.sparkSession.sparkContext.broadcast(samples)
    named = {c: f"_k{i}" for i, c in enumerate(keep)}
    src = docs.select(*(F.col(c).alias(n) for c, n in named.items()), letters_only(F.col("text")).alias("text"))
    schema = src.drop("text").schema.add("lang_pred", "string").add("score", "double")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = _model(shared.value)
        for b in slices(batches):
            found = model.predict(b.column("text").to_pylist())
            yield pa.RecordBatch.from_arrays([*(b.column(n) for n in named.values()), pa.array([x for x, _ in found], pa.string()), pa.array([s for _, s in found], pa.float64())], names=schema.names)

    return src.mapInArrow(work, schema).withColumnsRenamed({n: c for c, n in named.items()})


def identify(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Learn from the rows of ``docs`` that are not held out (crc32 of the id by 3 leaves 1), predict all."""
    samples = fit(docs.where(~held_out(3, 1)).select("text", "lang"))
    return predict(docs.withColumn("_held", held_out(3, 1)), samples, ("_held", *keep)).withColumnRenamed("_held", "held_out").select(*keep, "held_out", "lang_pred", "score")
