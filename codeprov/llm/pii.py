"""Personal data found by fixed patterns and a semi-Markov conditional random field.

The patterns give the base spans. Around digits and at signs (zones), every plausible segment is a
candidate for each kind; features of the whole span (digit groups, checksum, separators, neighbours)
score it, and bounded-entity dynamic programming chooses boundaries and kinds together. Weights come
from the conditional likelihood (forward-backward over segments) of labels that the patterns do not
decide: base spans with what decides them taken away (the plus, the check digit, the dots of the domain),
and segments after a word that names their kind. The sample of zones is bounded and drawn for each kind.
What looks like such a label but has none is left out, not a counterexample. Decoding is joint with the base
spans held fixed: the model scores whole segments and has no transitions, so the best segmentation of a zone
that contains them is they and the best segmentation of what they leave, which is what is searched.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.llm.common import cut_lineage, slices

KINDS = ("email", "ip", "card", "phone")
#: Bounds of the training sample and of an entity.
SAMPLE_ZONES, ZONE_CHARS, MOST_TOKENS, MOST_DIGITS = 600, 300, 24, 20
#: Views of each label that are learned.
VIEWS = 3
#: Characters before a segment in which its last three words are looked at, and words that name a kind.
LEAD = 32
CUES = {w: k for k, words in ((0, "email mail correo courriel"), (2, "card karte kreditkarte carte tarjeta visa mastercard amex"), (3, "phone telephone tel telefon téléphone teléfono call mobile mobil handy cell fax whatsapp")) for w in words.split()}
#: A word with a digit or at sign, and such words after single blanks; linear in the text, in Java too.
ZONE = r"(?<!\S)[^\s0-9@]*+[0-9@]\S*+(?:\x20[^\s0-9@]*+[0-9@]\S*+)*+"

_zone = re.compile(ZONE, re.ASCII)
_token = re.compile(r"[0-9]+|[A-Za-z]+|.", re.DOTALL)
_domain = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_ip = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_card = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_phone = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_any = re.compile(r"[0-9@]")
_word = re.compile(r"[^\W\d_]+")
_local = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def _octet(s: str) -> bool:
    s = s.lstrip("0")
    return len(s) < 3 or len(s) == 3 and s <= "255"


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """``(start, kind number, end)`` by start and kind, in code points."""
    out = []
    at = text.find("@")
    end = 0
    while at >= 0:
        start = at
        while start > end and text[start - 1] in _local:
            start -= 1
        m = _domain.match(text, at + 1) if start < at else None
        if m:
            out.append((start, 0, m.end()))
            end = m.end()
        at = text.find("@", max(at + 1, end))
    for m in _ip.finditer(text):
        if all(map(_octet, m.group().split("."))):
            out.append((m.start(), 1, m.end()))
    for m in _card.finditer(text):
        if m.end() - m.start() >= 12:
            d = _digits(m.group())
            if 12 <= len(d) <= 19 and luhn(d):
                out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in _phone.finditer(text):
            if 9 <= len(_digits(m.group())) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


def _around(text: str, at: int) -> str:
    """The kind of character at a place; an end of the text and a mark that ends a word count as blank."""
    if not 0 <= at < len(text):
        return "blank"
    c = text[at]
    if c == ":" and text[at - 1 : at].isalpha():
        return "blank"
    if c in ".,;:!?" and not text[at + 1 : at + 2].isalnum():
        return "blank"
    return "digit" if c.isdigit() else "letter" if c.isalpha() else "blank" if c.isspace() else c


def _cued(text: str, at: int) -> set[int]:
    """Kinds named by the last three words before a place."""
    return {CUES[w] for w in _word.findall(text[max(0, at - LEAD) : at].lower())[-3:] if w in CUES}


def candidates(text: str, start: int, end: int) -> tuple[list[int], list[tuple[int, int, int, list[str]]]]:
    """Token bounds of a zone, and segments ``(first token, token after, kind, features)``."""
    marks = [m.start() for m in _token.finditer(text, start, end)] + [end]
    n = len(marks) - 1
    segments = []
    cued: dict[int, set[int]] = {}

    def add(i: int, j: int, kind: int, own: list[str]) -> None:
        k = KINDS[kind]
        if i not in cued:
            cued[i] = _cued(text, marks[i])
        near = [f"before {_around(text, marks[i] - 1)}", f"after {_around(text, marks[j])}", f"cued {kind in cued[i]}"]
        segments.append((i, j, kind, [f"{k} {f}" for f in ("is", *near, *own)]))

    for i in range(n):
        first = text[marks[i]]
        numeric = "0" <= first <= "9"
        if numeric or first in "+(":
            digits, groups, seps = "", [], set()
            for j in range(i, min(n, i + MOST_TOKENS)):
                c = text[marks[j]]
                piece = text[marks[j] : marks[j + 1]]
                if "0" <= c <= "9":
                    digits += piece
                    groups.append(len(piece))
                    if len(digits) > MOST_DIGITS:
                        break
                    shape = ".".join(map(str, groups))
                    if numeric and len(groups) == 4 and seps == {"."} and j == i + 6:
                        add(i, j + 1, 1, [f"octets {all(map(_octet, text[marks[i] : marks[j + 1]].split('.')))}"])
                    if numeric and len(digits) >= 10 and seps <= {" ", "-", "."}:
                        add(i, j + 1, 2, [f"digits {len(digits)}", f"luhn {luhn(digits)} {12 <= len(digits) <= 19} {len(groups) == 1}", f"opens {digits[0]}", f"shape {shape}" if len(groups) < 7 else "shape long"])
                    if len(digits) >= 7:
                        opening = first if not numeric else "digit"
                        add(i, j + 1, 3, [f"opens {opening}", f"digits {len(digits)}", f"opens {opening} fits {9 <= len(digits) <= 15}", f"shape {shape}" if len(groups) < 7 else "shape long", f"ends {groups[-1]} of {min(len(groups), 6)}", f"dots {'.' in seps}"])
                elif c in " -" or c in "()./+" and (c != "+" or j == i):
                    seps.add(c)
                else:
                    break
        if (first in _local) and (i == 0 or text[marks[i] - 1] not in _local):
            j = i
            while j < n and text[marks[j]] in _local:
                j += 1
            if j < n and text[marks[j]] == "@":
                k, dots, last = j + 1, 0, j + 1
                while k < n and (text[marks[k]] in _local and text[marks[k]] not in "_%+") and k - j < MOST_TOKENS:
                    dots += text[marks[k]] == "."
                    k += 1
                    if text[marks[k - 1]] != ".":
                        last = k
                        add(i, k, 0, [f"dots {min(dots, 3)}", f"last {'letter' if text[marks[k] - 1].isalpha() else 'other'}", f"to the end {k == n or text[marks[k]] not in _local}", f"no dot {dots == 0}"])
    return marks, segments


def _scores(segments: list, weights: dict[str, float]) -> list[float]:
    get = weights.get
    return [sum(get(f, 0.0) for f in s[3]) for s in segments]


def decode(n: int, segments: list, scores: list[float]) -> list[tuple[int, int, int]]:
    """The best set of disjoint segments; a token outside of them scores 0. Ties leave tokens outside."""
    ends: dict[int, list[int]] = {}
    for x, (_, j, _, _) in enumerate(segments):
        ends.setdefault(j, []).append(x)
    best, back = [0.0] * (n + 1), [-1] * (n + 1)
    for j in range(1, n + 1):
        best[j] = best[j - 1]
        for x in ends.get(j, ()):
            v = best[segments[x][0]] + scores[x]
            if v > best[j] + 1e-12:
                best[j], back[j] = v, x
    out, j = [], n
    while j > 0:
        if back[j] < 0:
            j -= 1
        else:
            i, j2, kind, _ = segments[back[j]]
            out.append((i, j2, kind))
            j = i
    return out[::-1]


def _log_add(a: float, b: float) -> float:
    if a < b:
        a, b = b, a
    return a + math.log1p(math.exp(b - a))


def marginals(n: int, segments: list, scores: list[float]) -> tuple[float, list[float]]:
    """Log partition sum and each segment's probability."""
    ends: dict[int, list[int]] = {}
    starts: dict[int, list[int]] = {}
    for x, (i, j, _, _) in enumerate(segments):
        ends.setdefault(j, []).append(x)
        starts.setdefault(i, []).append(x)
    a, b = [0.0] * (n + 1), [0.0] * (n + 1)
    for j in range(1, n + 1):
        a[j] = a[j - 1]
        for x in ends.get(j, ()):
            a[j] = _log_add(a[j], a[segments[x][0]] + scores[x])
    for i in range(n - 1, -1, -1):
        b[i] = b[i + 1]
        for x in starts.get(i, ()):
            b[i] = _log_add(b[i], b[segments[x][1]] + scores[x])
    z = a[n]
    return z, [math.exp(a[i] + scores[x] + b[j] - z) for x, (i, j, _, _) in enumerate(segments)]


def _seeds() -> tuple[list[str], list[str]]:
    """Zones that every training sees: with base spans of each kind, and without personal data."""
    rng = random.Random(7)
    fill = lambda shape: re.sub("#", lambda _: rng.choice("0123456789"), shape)

    def card(valid: bool, length: int) -> str:
        while luhn(n := rng.choice("3456") + fill("#" * (length - 1))) != valid:
            pass
        return n

    held = [f(k) for k in range(12) for f in (lambda k: f"u{k}.{fill('##')}@mail{k}.example.com", lambda _: card(True, 16), lambda _: card(True, 15), lambda _: fill("+1 (###) ###-####"), lambda _: fill("+44 ## #### ####"), lambda _: fill("+49 ## #######"))]
    shapes = ["20##-0#-1#", "1#.0#.20##", "0#/1#/20##", "20##-0#-1# 1#", "19##-20##", "19##-19## 20##-20##", "978-#-##-######-#", "#-###-#####-#", "#.###.###", "# ### ###", "# ### ### ###", "##.###.### ##.###.###", "0.########", "#.#########", "#.##########", "##.########", "#.############", "#.#.#.####", "###-###", "####-####", "# # # # # # # #", "20## 20## 20## 20##", "## ## ## ## ## ## ##", "0x########", "pack@##", "#@#", "a@#", *("#" * n for n in range(7, 21))]
    free = [fill(x) for x in shapes for _ in range(4)] + [card(False, 16) for _ in range(8)]
    return held, free


def labels(text: str, start: int, end: int) -> list[tuple[int, int, int]]:
    """Base spans of a zone, and of its words where the zone as a whole has none (numbers that run together)."""
    found = [(start + s, k, start + e) for s, k, e in base_spans(text[start:end])]
    if not found:
        found = [(m.start() + s, k, m.start() + e) for m in re.compile(r"[^\x20]+").finditer(text, start, end) for s, k, e in base_spans(m.group())]
    return found


def views(span: str, kind: int) -> list[tuple[str, str]]:
    """``(words before, span)``: a base span written anew so that no pattern finds it."""
    out = []
    if kind == 0:
        local, _, host = span.partition("@")
        names = host.split(".")
        out = [("", f"{local}@{n}") for n in names if n[-1:].isalpha()][:2]
        out += [("mail ", v) for _, v in out[:1]]
    elif kind == 2:
        d = _digits(span)
        wrong = d[:-1] + str((int(d[-1]) + 1) % 10)
        fours = lambda x, by: by.join(x[i : i + 4] for i in range(0, len(x), 4))
        out = [("", fours(wrong, " ")), ("", fours(d, ".")), ("", fours(wrong, "-")), ("card ", wrong), ("card ", fours(wrong, " "))]
    elif kind == 3:
        groups = re.findall("[0-9]+", span)
        out = [("", span[1:]), ("", span[1:].lstrip("0123456789").lstrip(" .-"))]
        out += [("", by.join(g)) for by in "- ." for g in (groups[1:], groups)]
        out += [("phone ", "".join(groups)), ("call ", " ".join(groups[1:]))]
        out = [(c, v) for c, v in out if len(_digits(v)) >= 7 and (c or len(re.findall("[0-9]+", v)) > 1)]
    return [(c, v) for c, v in out if not base_spans(v)]


def examples(zones: list) -> list[tuple[int, list, list[bool]]]:
    """Tokens, segments and which of these are labels, for each zone that has segments and is decided.

    A zone is a text or ``(text before, zone, text after)``. Each label gives its zone, and ``VIEWS`` of its views in turn.
    """
    held, free = _seeds()
    ready, open_, seen, turn = [], [], set(), [0] * len(KINDS)

    def learn(text: str, start: int, end: int, gold: list[tuple[int, int, int]]) -> None:
        marks, segments = candidates(text, start, end)
        at, chosen, last = {m: i for i, m in enumerate(marks)}, set(), start
        for s, kind, e in sorted(gold, key=lambda x: (x[0], -x[2])):
            if s >= last and s in at and e in at:
                chosen.add((at[s], at[e], kind))
                last = e
        if segments:
            ready.append((len(marks) - 1, segments, [x[:3] in chosen for x in segments]))

    shown = lambda segment: (segment[2], next((f for f in segment[3] if " shape " in f or " no dot " in f), ""))
    for z in [*held, *zones]:
        before, z, after = ("", z, "") if isinstance(z, str) else z
        text, start, end = before + z + after, len(before), len(before) + len(z)
        gold = labels(text, start, end)
        if gold:
            learn(text, start, end, gold)
        for s, kind, e in gold:
            made = views(text[s:e], kind)
            for cue, v in [made[(turn[kind] + x) % len(made)] for x in range(min(VIEWS, len(made)))]:
                changed = text[:s] + cue + v + text[e:]
                learn(changed, s + len(cue), s + len(cue) + len(v), [(s + len(cue), kind, s + len(cue) + len(v))])
            turn[kind] += VIEWS
            for _, v in made:
                marks, segments = candidates(v, 0, len(v))
                seen.update(shown(x) for x in segments if x[0] == 0 and x[1] == len(marks) - 1 and x[2] == kind and " " in v.strip() + " " * (kind == 0 or len(re.findall("[0-9]+", v)) > 1))
        if not gold:
            open_.append((text, start, end))
    for text, start, end in open_:
        marks, segments = candidates(text, start, end)
        named = [x for x in segments if f"{KINDS[x[2]]} cued True" in x[3]]
        if named:
            first = min(named, key=lambda x: (x[0], -x[1]))
            learn(text, start, end, [(marks[first[0]], first[2], marks[first[1]])])
        elif "@" not in text[start:end] and "+" not in text[start:end] and not any(shown(x) in seen for x in segments):
            learn(text, start, end, [])
    for z in free:
        learn(z, 0, len(z), [])
    random.Random(5).shuffle(ready)
    return ready


def train(zones: list, epochs: int = 12, rate: float = 0.5, ridge: float = 1e-3) -> dict[str, float]:
    """Weights from zones, by the labels of ``examples``."""
    ready = examples(zones)
    weights: dict[str, float] = {}
    square: dict[str, float] = {}
    for _ in range(epochs):
        for n, segments, gold in ready:
            _, p = marginals(n, segments, _scores(segments, weights))
            step: dict[str, float] = {}
            for (_, _, _, features), want, have in zip(segments, gold, p, strict=True):
                for f in features:
                    step[f] = step.get(f, 0.0) + want - have
            for f, g in step.items():
                g -= ridge * weights.get(f, 0.0)
                square[f] = square.get(f, 0.0) + g * g
                weights[f] = weights.get(f, 0.0) + rate * g / math.sqrt(square[f] + 1e-8)
    return weights


def spans(text: str, weights: dict[str, float]) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """Base spans, and all spans, as ``(start, kind number, end)``."""
    if not _any.search(text):
        return [], []
    base = base_spans(text)
    added = []
    k = 0
    for m in _zone.finditer(text):
        s, e = m.span()
        while k < len(base) and base[k][2] <= s:
            k += 1
        held = [x for x in base[k:] if x[0] < e] if k < len(base) and base[k][0] < e else []
        marks, segments = candidates(text, s, e)
        free = [x for x in segments if not any(marks[x[0]] < h[2] and h[0] < marks[x[1]] for h in held)]
        if free:
            added += [(marks[i], kind, marks[j]) for i, j, kind in decode(len(marks) - 1, free, _scores(free, weights))]
    return base, sorted(base + added)


def fit(docs: DataFrame, zones: int = SAMPLE_ZONES) -> dict[str, float]:
    """Weights learned from at most ``zones`` zones of ``docs``: as many of each kind, and without any, by their hash.

    A task keeps only its own first zones of each kind, which hold the first of all.
    """
    each = zones // (len(KINDS) + 1)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[dict] = [{} for _ in range(len(KINDS) + 1)]

        def first(found: dict) -> dict:
            return dict(sorted(found.items(), key=lambda x: (x[1][0], x[0]))[:each])

        for b in slices(batches):
            for t in b.column("text").to_pylist():
                if not t or not _any.search(t):
                    continue
                for m in _zone.finditer(t):
                    s, e = m.span()
                    if not 6 <= e - s <= ZONE_CHARS:
                        continue
                    z, around = m.group(), (t[max(0, s - LEAD) : s], t[e : e + 2])
                    for kind in {k for _, k, _ in labels(t, s, e)} | _cued(t, s) or {len(KINDS)}:
                        h, *old = held[kind].get(z, (None, None))
                        if h is None:
                            h, old = xxhash.xxh64_intdigest(z.encode("utf-8", "surrogatepass")) >> 1, [around]
                        held[kind][z] = (h, min(old[0], around))
                        if len(held[kind]) > 4 * each:
                            held[kind] = first(held[kind])
        rows = [(kind, h, z, *around) for kind, found in enumerate(held) for z, (h, around) in first(found).items()]
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int64(), *[pa.string()] * 3), strict=True)], names=["kind", "h", "z", "lead", "tail"])

    found = cut_lineage(docs.select("text").mapInArrow(work, "kind int, h long, z string, lead string, tail string"))
    rows = []
    for kind in range(len(KINDS) + 1):
        once = found.where(F.col("kind") == kind).groupBy("h", "z").agg(F.min(F.struct("lead", "tail")).alias("around"))
        rows += once.orderBy("h", "z").limit(each).collect()
    return train([(r["around"]["lead"], r["z"], r["around"]["tail"]) for r in rows])


def detect(docs: DataFrame, weights: dict[str, float] | None = None, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns, ``base`` and ``found``: arrays of (start, kind, end) for every row.

    A null text counts as empty; very long texts are searched whole, repeated rows give repeated rows. Columns
    beside ``keep`` are ignored, also where they bear the name of a result. Ties leave tokens outside of spans. An
    empty table gives an empty result (and learns nothing).
    """
    weights = fit(docs) if weights is None else weights
    named = {c: f"_k{i}" for i, c in enumerate(keep)}
    src = docs.select(*(F.col(c).alias(n) for c, n in named.items()), "text")
    span = "array<struct<start: int, kind: string, end: int>>"
    schema = src.sparkSession.createDataFrame([], f"base {span}, found {span}").schema
    schema = type(schema)([*src.drop("text").schema.fields, *schema.fields])
    as_arrow = pa.list_(pa.struct([("start", pa.int32()), ("kind", pa.string()), ("end", pa.int32())]))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        show = lambda x: [{"start": s, "kind": KINDS[k], "end": e} for s, k, e in x]
        for b in slices(batches):
            both = [spans(t or "", weights) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(b.column(n) for n in named.values()), pa.array([show(x) for x, _ in both], as_arrow), pa.array([show(x) for _, x in both], as_arrow)], names=schema.names)

    return src.mapInArrow(work, schema).withColumnsRenamed({n: c for c, n in named.items()})


def digest(found: DataFrame) -> DataFrame:
    """The columns of the query."""
    joined = lambda c: F.concat_ws(",", F.transform(c, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))))
    counts = [F.expr(f"CAST(size(filter(base, x -> x.kind = '{k}')) AS BIGINT)").alias(f"n_{k}") for k in KINDS]
    return found.select("doc_id", *counts, F.sha2(joined("base"), 256).alias("base_sha256"), joined("found").alias("spans"))


def redact(docs: DataFrame, weights: dict[str, float] | None = None) -> DataFrame:
    """``docs`` with each span of ``text`` replaced by its kind in brackets; a null text stays null.

    All other columns stay, repeated rows too; an empty table gives an empty result.
    """
    weights = fit(docs) if weights is None else weights

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            texts = [t if t is None else masked(t, spans(t, weights)[1]) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(texts, pa.string()) if c == "text" else b.column(c) for c in b.schema.names], names=b.schema.names)

    return docs.mapInArrow(work, docs.schema)


def masked(text: str, found: list[tuple[int, int, int]]) -> str:
    out, at = [], 0
    for s, kind, e in found:
        if s >= at:
            out += [text[at:s], f"[{KINDS[kind].upper()}]"]
        at = max(at, e)
    return "".join(out) + text[at:]


def sha(spans_: list[tuple[int, int, int]]) -> str:
    return hashlib.sha256(",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans_).encode()).hexdigest()
