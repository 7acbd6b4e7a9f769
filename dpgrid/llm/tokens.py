"""Token ids for whole texts, one dictionary lookup per repeated word.

A text falls into units that the tokenizer never looks across. Each distinct unit is encoded once per
worker (by the ``tokenizers`` library, or by a function given) and kept in a bounded cache; ids of whole
texts are then gathered with numpy. Texts for which the cut is not provably harmless go to the library whole.
"""

from __future__ import annotations

import json
import re
from collections.abc import Callable
from functools import lru_cache
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: A worker forgets its cache when it holds more units than this.
CACHE_UNITS = 1_000_000

Encode = Callable[[list[str]], tuple[np.ndarray, np.ndarray]]


class UnitCache:
    """Distinct units → ids, stored flat. ``encode(units)`` returns (all ids, count per unit)."""

    def __init__(self, encode: Encode, limit: int = CACHE_UNITS):
        self.encode, self.limit = encode, limit
        self.clear()

    def clear(self) -> None:
        self.index: dict[str, int] = {}
        self.flat = np.empty(1 << 16, np.uint32)
        self.starts = np.empty(1 << 14, np.int64)
        self.sizes = np.empty(1 << 14, np.int32)
        self.used = 0

    @staticmethod
    def _room(a: np.ndarray, n: int) -> np.ndarray:
        if n <= len(a):
            return a
        grown = np.empty(max(n, len(a) * 3 // 2), a.dtype)
        grown[: len(a)] = a
        return grown

    def find(self, units: list[str]) -> np.ndarray:
        """Index of every unit; unknown ones are encoded first."""
        at = np.fromiter(map(self.index.get, units, repeat(-1)), np.int64, len(units))
        holes = np.flatnonzero(at < 0)
        if len(holes):
            if len(self.index) + len(holes) > self.limit and self.index:
                self.clear()
                return self.find(units)
            new = list(dict.fromkeys(units[i] for i in holes))
            ids, sizes = self.encode(new)
            n, k = len(self.index), len(new)
            self.flat = self._room(self.flat, self.used + len(ids))
            self.starts, self.sizes = self._room(self.starts, n + k), self._room(self.sizes, n + k)
            self.flat[self.used : self.used + len(ids)] = ids
            self.sizes[n : n + k] = sizes
            self.starts[n : n + k] = self.used + np.cumsum(sizes) - sizes
            self.used += len(ids)
            self.index.update(zip(new, range(n, n + k), strict=True))
            at[holes] = np.fromiter(map(self.index.__getitem__, (units[i] for i in holes)), np.int64, len(holes))
        return at

    def gather(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all units at these indices in a row, and the count per unit."""
        sizes = self.sizes[at].astype(np.int64)
        ends = np.cumsum(sizes)
        where = np.repeat(self.starts[at] - (ends - sizes), sizes)
        where += np.arange(len(where))
        return self.flat[where], sizes


class TextEncoder:
    """Whole texts → ids.

    ``prepare`` turns a text into its units parted by blanks, or gives None where only ``whole`` may encode it. Parting and
    finding the distinct units of a batch run in Arrow, so that Python sees each distinct unit once.
    """

    def __init__(self, prepare: Callable[[str], str | None], encode: Encode, whole: Callable[[str], np.ndarray]):
        self.prepare, self.whole, self.cache = prepare, whole, UnitCache(encode)

    def __call__(self, texts: list[str | None]) -> list[np.ndarray]:
        prepared, odd = [], {}
        for i, text in enumerate(texts):
            own = self.prepare(text) if text else ""
            if own is None:
                odd[i] = self.whole(text)
            prepared.append(own or None)
        parts = pc.split_pattern(pa.array(prepared, pa.string()), " ")
        units = parts.flatten().dictionary_encode()
        counts = pc.fill_null(pc.list_value_length(parts), 0).to_numpy(zero_copy_only=False)
        flat, sizes = np.empty(0, np.uint32), np.empty(0, np.int64)
        if len(units):
            at = self.cache.find(units.dictionary.to_numpy(zero_copy_only=False).tolist())
            flat, sizes = self.cache.gather(at[units.indices.to_numpy()])
        ends = np.concatenate([[0], np.cumsum(sizes)])[np.cumsum(counts)]
        rows = np.split(flat, ends[:-1]) if len(texts) else []
        for i, ids in odd.items():
            rows[i] = ids
        return rows


_ODD_FOR_WORDS = re.compile("[\x1c-\x1f]")
_ODD_FOR_BYTES = re.compile(r"[^\S \n]|[ \n]{2}|\A[ \n]|[ \n]\Z")
#: ASCII without separators that libraries disagree about, and the letters of Latin-1: stable under NFC.
_NOT_PLAIN = re.compile("[^\x00-\x1b\x20-\x7e\xc0-\xd6\xd8-\xf6\xf8-\xff]")
#: Kinds of Latin-1 characters: a letter or digit, a blank or line feed, other white space, stop or comma, other.
_KIND = bytes(ord("a" if c >= 0xC0 or chr(c).isalnum() else " " if c in b" \n" else "_" if chr(c).isspace() else "." if c in b".," else "!") for c in range(256))


def _kinds(text: str) -> bytes | None:
    """Kinds of a plain text's characters; None for other texts and those that may hold special tokens."""
    return None if "<|" in text or _NOT_PLAIN.search(text) else text.encode("latin-1").translate(_KIND)


def part_words(text: str) -> str | None:
    """Units for lower-casing vocabularies that drop white space: words, and stops with what follows them.

    A stop or comma of a plain text is cut off where every one of them follows a letter, a digit or white space.
    """
    kinds = _kinds(text)
    if kinds is None:
        return None if _ODD_FOR_WORDS.search(text) else " ".join(text.split())
    text = text.lower()
    if b".." not in kinds and b"!." not in kinds:
        text = text.replace(".", " .").replace(",", " ,")
    return text.replace("\n", " ") if b"_" not in kinds else " ".join(text.split())


def part_spaced(text: str) -> str | None:
    """Units for byte-level vocabularies: words that own the blank before them, line feeds, and stops.

    A lone blank or line feed between two other characters always begins a piece of its own, as does a
    stop after a letter or digit, so the cuts are harmless; texts with other white space go whole. A return marks units
    without a blank before them, as such texts cannot hold one.
    """
    kinds = _kinds(text)
    if kinds is None:
        if _ODD_FOR_BYTES.search(text):
            return None
    elif b"_" in kinds or b"  " in kinds or kinds[:1] == b" " or kinds[-1:] == b" ":
        return None
    elif not (b".." in kinds or b"!." in kinds or b" ." in kinds or kinds[:1] == b"."):
        text = text.replace(".", " \r.").replace(",", " \r,")
    return "\r" + text.replace("\n", " \r\n \r")


def _own_text(unit: str) -> str:
    return unit[1:] if unit[0] == "\r" else " " + unit


def byte_alphabet() -> list[str]:
    """The printable stand-in of each byte: itself if visible in Latin-1, else the next free code point from 256."""
    visible = {*range(33, 127), *range(161, 173), *range(174, 256)}
    free = iter(range(256, 512))
    return [chr(b) if b in visible else chr(next(free)) for b in range(256)]


@lru_cache(maxsize=4)
def library_encoder(path: str) -> TextEncoder:
    """Encoder on the ``tokenizers`` library for the vocabulary file at ``path``.

    Byte-level vocabularies without a word-end suffix keep blanks; the others drop white space.
    """
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(path)
    tok.no_padding()
    tok.no_truncation()
    spaced = not getattr(tok.model, "end_of_word_suffix", None)
    # The same vocabulary without the steps that leave small ASCII letters as they are.
    with open(path, encoding="utf-8") as f:
        bare = Tokenizer.from_str(json.dumps(json.load(f) | {"normalizer": None, "pre_tokenizer": None, "post_processor": None, "truncation": None, "padding": None}))

    alphabet = byte_alphabet()
    blank = alphabet[32]
    stand_in = {c: "".join(alphabet[b] for b in chr(c).encode()) for c in range(0xC0, 0x100)}
    plain_word = re.compile("[A-Za-z\xc0-\xd6\xd8-\xf6\xf8-\xff]+" if spaced else "[a-z\xdf-\xf6\xf8-\xff]+").fullmatch
    # Ids that open a word after a blank, or that close a word: they part the ids of many plain words.
    edge = np.zeros(tok.get_vocab_size(with_added_tokens=True), bool)
    edge[[i for s, i in tok.get_vocab(with_added_tokens=False).items() if (s[0] == blank if spaced else s.endswith(tok.model.end_of_word_suffix))]] = True

    def words(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of plain words, given in the byte alphabet."""
        if not texts:
            return np.empty(0, np.uint32), np.empty(0, np.int64)
        ids = np.array(bare.encode_batch_fast([texts], is_pretokenized=True, add_special_tokens=False)[0].ids, np.uint32)
        at = np.flatnonzero(edge[ids])
        return ids, np.diff(at, append=len(ids)) if spaced else np.diff(at, prepend=-1)

    def together(library: Tokenizer, texts: list[str]) -> tuple[np.ndarray, np.ndarray] | None:
        enc = library.encode(texts, is_pretokenized=True, add_special_tokens=False)
        words = enc.word_ids
        if None in words:  # a special token's text carries no word index
            return None
        return np.array(enc.ids, np.uint32), np.bincount(np.array(words, np.int64), minlength=len(texts))

    def encode(units: list[str]) -> tuple[np.ndarray, np.ndarray]:
        plain = [plain_word(u) is not None for u in units]
        easy = [u if u.isascii() else u.translate(stand_in) for u, p in zip(units, plain, strict=True) if p]
        if spaced:
            easy = [blank + u for u in easy]
        hard = [(_own_text(u) if spaced else u) for u, p in zip(units, plain, strict=True) if not p]
        a = words(easy)
        b = together(tok, hard)
        if b is None:
            each = [np.array(tok.encode(u, add_special_tokens=False).ids, np.uint32) for u in hard]
            b = np.concatenate(each), np.array([len(x) for x in each], np.int64)
        sizes = np.empty(len(units), np.int64)
        mask = np.array(plain, bool)
        sizes[mask], sizes[~mask] = a[1], b[1]
        ids = np.empty(int(sizes.sum()), np.uint32)
        owner = np.repeat(mask, sizes)
        ids[owner], ids[~owner] = a[0], b[0]
        return ids, sizes

    def whole(text: str) -> np.ndarray:
        return np.array(tok.encode(text, add_special_tokens=False).ids, np.uint32)

    return TextEncoder(part_spaced if spaced else part_words, encode, whole)


@lru_cache(maxsize=4)
def vocabulary_size(path: str) -> int:
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path).get_vocab_size(with_added_tokens=True)
