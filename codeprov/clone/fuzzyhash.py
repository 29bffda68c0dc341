"""Fuzzy hashes of tokens: a small change of the text changes a small part of the fingerprint.

``token64`` gives each token one of 64 letters from its md5, in SQL that any engine can repeat.
``ctph`` cuts the token's bytes where a rolling hash of seven bytes hits a trigger and gives each piece a
letter; ``fixed7`` cuts it every seven bytes. Both run as Arrow batches.
"""

from __future__ import annotations

from functools import lru_cache

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The base-64 alphabet (a fixed value).
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"
VARIANTS = ("token64", "ctph", "fixed7")
#: Constants of the published piecewise hash (fixed values): offset and prime of the piece hash, window and least block.
FNV_OFFSET, FNV_PRIME, WINDOW, LEAST_BLOCK = 0x28021967, 0x01000193, 7, 3


def hash_piece(data: bytes) -> str:
    h = FNV_OFFSET
    for b in data:
        h = (h * FNV_PRIME ^ b) & 0xFFFFFFFF
    return ALPHABET[h & 63]


def fixed7(data: bytes) -> str:
    """A letter for each seven bytes."""
    return "".join(hash_piece(data[i : i + WINDOW]) for i in range(0, len(data), WINDOW))


def ctph(data: bytes, block: int = LEAST_BLOCK) -> str:
    """A letter for each piece that ends where the rolling sum of the last seven bytes hits the block's trigger."""
    window = [0] * WINDOW
    h1 = h2 = h3 = 0
    out, h, fresh = [], FNV_OFFSET, False
    for i, b in enumerate(data):
        h2 = h2 - h1 + WINDOW * b & 0xFFFFFFFF
        h1 = h1 + b - window[i % WINDOW] & 0xFFFFFFFF
        window[i % WINDOW] = b
        h3 = (h3 << 5 ^ b) & 0xFFFFFFFF
        h = (h * FNV_PRIME ^ b) & 0xFFFFFFFF
        fresh = True
        if (h1 + h2 + h3 & 0xFFFFFFFF) % block == block - 1:
            out.append(ALPHABET[h & 63])
            h, fresh = FNV_OFFSET, False
    if fresh:
        out.append(ALPHABET[h & 63])
    return "".join(out)


@lru_cache(1 << 17)
def letters_of(token: str, variant: str) -> str:
    """``ctph`` or ``fixed7`` of one token; a worker keeps those it met last, as words come again and again."""
    return (ctph if variant == "ctph" else fixed7)(token.encode())


def part_letters(parts: Column, variant: str) -> Column:
    """Letters of each part (an array of tokens), without parts that have none."""

    @F.udf("array<string>", useArrow=True)
    def hashed(rows):
        return [s for s in ("".join(letters_of(t, variant) for t in r) for r in rows) if s]

    return hashed(parts)


def _arrow(function):
    @F.udf("string", useArrow=True)
    def hashed(tokens):
        return None if tokens is None else "".join(function(t.encode()) for t in tokens)

    return hashed


def hash_tokens(tokens: Column, variant: str = "token64") -> Column:
    """Letters of all tokens of an array, one after another."""
    if variant == "token64":
        return F.array_join(F.transform(tokens, _letter), "")
    if variant not in VARIANTS:
        raise ValueError(f"variant must be one of {VARIANTS}")
    return _arrow(ctph if variant == "ctph" else fixed7)(tokens)


def _letter(x: Column) -> Column:
    code = F.conv(F.substring(F.md5(x.cast("binary")), 1, 4), 16, 10).cast("int") % 64
    return F.substr(F.lit(ALPHABET), code + 1, F.lit(1))


def hash_sequence(col: Column | str, variant: str = "ctph") -> Column:
    """The hash of the undivided text, as the rival that a change of one token may shift from end to end."""
    c = F.col(col) if isinstance(col, str) else col
    return hash_tokens(F.array(c), variant)
