"""The keyed uniform draws of ``keyed`` for Arrow batches: the same numbers, many digests at a time.

MD5 of a text below 56 bytes is one block, so its rounds run as array operations over thousands of texts. Longer texts and SHA-256
go through hashlib one by one.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Sequence
from functools import cache, lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from dpgrid.functions.keyed import _STEPS, DIGITS

#: Texts hashed together: their words stay in a core's cache, and array calls cost little beside them.
CHUNK = 16384
#: Numbers below this have their digits, and the bit that ends a text, in one table.
TABLED = 10_000
_SINES = [np.uint32(int(abs(math.sin(i + 1)) * 2**32)) for i in range(64)]
_TURNS = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def _round(i: int, a, b, c, d, word):
    """What round ``i`` makes of four whole numbers."""
    kind = i // 16
    f = (d ^ (b & (c ^ d)), c ^ (d & (b ^ c)), b ^ c ^ d, c ^ (b | ~d & 0xFFFFFFFF))[kind]
    f = (f + a + int(_SINES[i]) + word) & 0xFFFFFFFF
    turn = _TURNS[kind][i % 4]
    return d, (((f << turn) | (f >> (32 - turn))) + b) & 0xFFFFFFFF, b, c


@lru_cache(1024)
def _constant(x: int) -> np.ndarray:
    """An array without axes: array calls take it with less ado than a number."""
    return np.array(x, np.uint32)


def _first_words(words: Sequence[np.ndarray | int], n: int) -> np.ndarray:
    """The first 8 bytes, as big-endian integers, of the digests of ``n`` blocks of 16 words; a word that all blocks share is an integer."""
    state, i = _START, 0
    while i < 16 and isinstance(words[i], int):  # before the first word that differs, one computation serves all
        state, i = _round(i, *state, words[i]), i + 1
    a, b, c, d = (np.full(n, x, np.uint32) for x in state)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    xor, both, either, add, left, right = np.bitwise_xor, np.bitwise_and, np.bitwise_or, np.add, np.left_shift, np.right_shift
    for i in range(i, 64):
        kind = i // 16
        if kind == 0:
            xor(c, d, f)
            both(f, b, f)
            xor(f, d, f)
            g = i
        elif kind == 1:
            xor(b, c, f)
            both(f, d, f)
            xor(f, c, f)
            g = (5 * i + 1) % 16
        elif kind == 2:
            if i % 2 == 0:  # of two rounds in a row, the second has the two values in common that the first begins with
                xor(b, c, t)
                xor(t, d, f)
            else:
                xor(b, pair, f)
            g = (3 * i + 5) % 16
        else:
            np.invert(d, f)
            either(f, b, f)
            xor(f, c, f)
            g = 7 * i % 16
        if kind == 2 and i % 2 == 0:
            t, pair = pair if i > 32 else np.empty(n, np.uint32), t
        word = words[g]
        add(f, a, f)
        if isinstance(word, int):
            add(f, _constant((int(_SINES[i]) + word) & 0xFFFFFFFF), f)
        else:
            add(f, _constant(int(_SINES[i])), f)
            add(f, word, f)
        turn = _TURNS[kind][i % 4]
        left(f, _constant(turn), t)
        right(f, _constant(32 - turn), f)
        either(f, t, f)
        add(f, b, f)
        a, d, c, b, f = d, c, b, f, a
    a += np.uint32(_START[0])
    b += np.uint32(_START[1])
    return (a.byteswap().astype(np.uint64) << np.uint64(32)) | b.byteswap()


def _digits(numbers: np.ndarray) -> np.ndarray:
    made = np.ones(len(numbers), np.int64)
    limit = 10
    while limit <= int(numbers.max(initial=0)):
        made += numbers >= limit
        limit *= 10
    return made


@cache
def _tails() -> tuple[np.ndarray, np.ndarray]:
    """The bytes of each number below ``TABLED`` and of the bit after it, as a little-endian integer; and how many digits it has."""
    made = [int.from_bytes(b"%d\x80" % k, "little") for k in range(TABLED)]
    return np.array(made, np.uint64), np.array([len(str(k)) for k in range(TABLED)], np.uint32)


def _short_words(table: np.ndarray, same: list[bool], size: np.ndarray, r: np.ndarray, k: np.ndarray) -> list[np.ndarray | int]:
    """The 16 words of the texts ``table[r]`` (their words by place) followed by the numbers ``k``, all below ``TABLED``."""
    tails, digits = _tails()
    ends = size[r]
    at, tail = ends >> 2, tails[k] << ((ends & 3) << 3).astype(np.uint64)
    low, high = tail.astype(np.uint32), (tail >> np.uint64(32)).astype(np.uint32)
    first, last = int(at.min()), int(at.max())
    words: list[np.ndarray | int] = []
    for g in range(14):
        if g < first or g > last + 1:
            words.append(int(table[g, 0]) if same[g] else table[g][r])
            continue
        word = table[g][r]
        if first == last:
            word |= low if g == first else high
        else:
            word |= np.where(at == g, low, np.uint32(0))
            word |= np.where(at == g - 1, high, np.uint32(0))
        words.append(word)
    length = (ends.astype(np.uint32) + digits[k]) << np.uint32(3)
    # A text of 52 bytes or more ends in the words before the length's; the length itself never meets it.
    return [*words, length, 0]


def _long_words(table: np.ndarray, size: np.ndarray, r: np.ndarray, k: np.ndarray) -> list[np.ndarray | int]:
    """The same for numbers of any size."""
    text, line, count = np.ascontiguousarray(table.T).view(np.uint8)[r], np.arange(len(r)), _digits(k)
    end, rest = size[r] + count, k
    for place in range(int(count.max())):
        rest, digit = np.divmod(rest, 10)
        here = count > place
        text[line[here], end[here] - 1 - place] = digit[here] + 48
    text[line, end] = 128
    text[:, 56], text[:, 57] = end * 8 & 255, end * 8 >> 8
    return list(np.ascontiguousarray(text.view("<u4").T))


def _padded(heads: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Sizes of the texts in bytes, and their 16 words by place; texts of 64 bytes and more have no words."""
    size = pc.binary_length(heads).to_numpy(zero_copy_only=False).astype(np.int64)
    if size.max(initial=0) >= 64:
        return size, np.zeros((16, 0), np.uint32)
    text = np.zeros((len(size), 64), np.uint8)
    text[np.arange(64) < size[:, None]] = np.frombuffer(pc.binary_join(pa.ListArray.from_arrays(pa.array([0, len(heads)], pa.int32()), heads), b"")[0].as_py(), np.uint8)
    return size, np.ascontiguousarray(text.view("<u4").T)


def uniforms(key: str, purpose: str, places: pa.Array, rows: np.ndarray, numbers: np.ndarray, source: str = "keyed") -> np.ndarray:
    """``keyed_uniform(key, purpose, place, number)`` for ``places[rows]`` and as many non-negative ``numbers``."""
    if source not in ("keyed", "secret"):
        raise ValueError(f"noise source {source!r}")
    made = np.empty(len(rows), np.uint64)
    if not len(rows):
        return made.astype(np.float64)
    heads = pc.binary_join_element_wise(f"{key}|{purpose}|".encode(), places.cast(pa.binary()), b"|", b"")
    size, table = _padded(heads)
    short = source == "keyed" and size.max() + len(str(int(numbers.max()))) <= 55
    if not short:
        digest, heads = hashlib.md5 if source == "keyed" else hashlib.sha256, heads.to_pylist()
        for i, (r, k) in enumerate(zip(rows.tolist(), numbers.tolist(), strict=True)):
            made[i] = int(digest(heads[r] + b"%d" % k).hexdigest()[:DIGITS], 16)
        return (made.astype(np.float64) + 0.5) / _STEPS
    same = [bool((w == w[0]).all()) for w in table]
    for at in range(0, len(rows), CHUNK):
        r, k = rows[at : at + CHUNK], numbers[at : at + CHUNK]
        words = _short_words(table, same, size, r, k) if int(k.max()) < TABLED else _long_words(table, size, r, k)
        made[at : at + CHUNK] = _first_words(words, len(r))
    return ((made >> np.uint64(64 - 4 * DIGITS)).astype(np.float64) + 0.5) / _STEPS


def laplace(u: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """Laplace draws of that scale by the inverse distribution function."""
    d = 0.5 - u  # never 0, as no draw is one half
    made = np.abs(d)
    made *= -2.0
    made += 1.0
    np.log(made, made)
    made *= np.copysign(scale, d, d)
    return made
