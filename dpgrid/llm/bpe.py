"""BPE encoding and decoding with contiguous rank arrays.

A word is a row of symbol ids with the rank of each adjacent pair beside it. The least rank is found by a scan,
its pair is joined, the boundary between deleted from the row, and the two neighbouring ranks looked up again.
Words are short, so scanning a few cells beats any heap; the scan runs over many distinct words at once, as rows of one
array. Long words use a linked list with a heap of the same ranks.

Word splitting, case and byte alphabet follow the vocabulary file. Units that hold characters outside
ASCII get the file's own normalizer and pre-tokenizer; ASCII ones a pattern of the same meaning.

Edge cases: null and empty texts have no ids; texts of special tokens become their ids, as in the library; any
length of text or word works; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import os
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dpgrid.llm.arrow import ENCODE_BYTES, chunks, column, out, strings
from dpgrid.llm.tokens import TextEncoder, byte_alphabet, part_words

#: Words of more symbols than this use the heap.
SHORT = 40
#: Rows of the array that are scanned together.
ROWS = 4096
_NONE = np.int32(2**31 - 1)
_ASCII_PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^a-z0-9 \t\n\x0b\x0c\r]+")


class RankBpe:
    """Merges and vocabulary of one file, as sorted pair keys for vectorised lookup."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        vocab: dict[str, int] = model["vocab"]
        self.suffix = model.get("end_of_word_suffix") or ""
        self.specials = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.size = max([*vocab.values(), *self.specials.values()]) + 1
        self.strings = [""] * self.size
        for s, i in [*vocab.items(), *self.specials.items()]:
            self.strings[i] = s
        alphabet = byte_alphabet()
        self.inner = np.array([vocab[a] for a in alphabet], np.int32)
        self.last = np.array([vocab[a + self.suffix] for a in alphabet], np.int32)
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        keys = np.array([vocab[a] * self.size + vocab[b] for a, b in pairs], np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], np.int32)
        order = np.argsort(keys)
        self.keys, self.ranks, self.made = keys[order], order.astype(np.int32), made[order]
        self.pairs = {int(k): (r, int(m)) for r, (k, m) in enumerate(zip(keys, made, strict=True))}
        self.split_special = re.compile("(" + "|".join(map(re.escape, sorted(self.specials, key=len, reverse=True))) + ")") if self.specials else None

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.to_byte = {a: b for b, a in enumerate(alphabet)}

    def lookup(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank and joined id of each pair; the rank is the largest integer where no merge joins them."""
        keys = a.astype(np.int64) * self.size + b
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        hit = (self.keys[at] == keys) & (a >= 0) & (b >= 0)
        return np.where(hit, self.ranks[at], _NONE), self.made[at]

    def short_words(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words of at most ``SHORT`` bytes, in a row, and their counts: all rows are scanned together."""
        n = len(words)
        size = np.array([len(w) for w in words], np.int64)
        wide = int(size.max())
        cells = np.arange(wide)
        filled = cells < size[:, None]
        sym = np.full((n, wide), -1, np.int32)
        sym[filled] = self.inner[np.frombuffer(b"".join(words), np.uint8)]
        tails = np.array([w[-1] for w in words], np.uint8)
        sym[np.arange(n), size - 1] = self.last[tails]
        rank = np.full((n, wide), _NONE, np.int32)
        rank[:, :-1] = self.lookup(sym[:, :-1].ravel(), sym[:, 1:].ravel())[0].reshape(n, wide - 1)
        live = np.arange(n)
        s, r, z = sym, rank, size.copy()
        while True:
            j = r.argmin(1)
            row = np.arange(len(live))
            go = r[row, j] < _NONE
            if not go.all():
                done = ~go
                sym[live[done], : s.shape[1]] = s[done]
                size[live[done]] = z[done]
                live, s, r, z, j = live[go], s[go], r[go], z[go], j[go]
                if not len(live):
                    break
                row = np.arange(len(live))
            joined = self.lookup(s[row, j], s[row, j + 1])[1]
            shift = np.minimum(cells[: s.shape[1]] + (cells[: s.shape[1]] > j[:, None]), s.shape[1] - 1)
            s = np.take_along_axis(s, shift, 1)
            z -= 1
            s[row, j] = joined
            full = z == s.shape[1]
            if not full.any():
                s[row, z] = -1
            r = np.take_along_axis(r, shift, 1)
            right = np.minimum(j + 1, s.shape[1] - 1)
            r[row, j] = np.where(j + 1 < z, self.lookup(s[row, j], s[row, right])[0], _NONE)
            left = np.flatnonzero(j > 0)
            if len(left):
                r[left, j[left] - 1] = self.lookup(s[left, j[left] - 1], s[left, j[left]])[0]
            top = int(z.max())
            if top < s.shape[1]:
                s, r = s[:, : max(top, 1)].copy(), r[:, : max(top, 1)].copy()
                r[:, -1] = np.where(z >= s.shape[1], _NONE, r[:, -1])
        return sym[cells < size[:, None]].astype(np.uint32), size

    def long_word(self, word: bytes) -> np.ndarray:
        """Ids of a word of any length: linked list and heap of (rank, place)."""
        n = len(word)
        sym = self.inner[np.frombuffer(word, np.uint8)].tolist()
        sym[-1] = int(self.last[word[-1]])
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(p[0], i, sym[i], sym[i + 1]) for i in range(n - 1) if (p := self.pairs.get(sym[i] * self.size + sym[i + 1]))]
        heapq.heapify(heap)
        while heap:
            _, i, a, b = heapq.heappop(heap)
            k = after[i]
            if sym[i] != a or k >= n or sym[k] != b:
                continue
            sym[i], sym[k] = self.pairs[a * self.size + b][1], -1
            after[i] = after[k]
            if after[i] < n:
                before[after[i]] = i
            for x, y in ((before[i], i), (i, after[i])):
                if x >= 0 and y < n and (p := self.pairs.get(sym[x] * self.size + sym[y])):
                    heapq.heappush(heap, (p[0], x, sym[x], sym[y]))
        return np.array([x for x in sym if x >= 0], np.uint32)

    def pieces(self, unit: str) -> list[bytes | int]:
        """Words of a unit as bytes, and ids of special tokens within it."""
        if self.split_special and "<|" in unit:
            found: list[bytes | int] = []
            for part in self.split_special.split(unit):
                if part:
                    found += [self.specials[part]] if part in self.specials else self._plain(part)
            return found
        return self._plain(unit)

    def _plain(self, text: str) -> list[bytes | int]:
        if text.isascii():
            return [w.encode() for w in _ASCII_PIECES.findall(text.lower())]
        made = self.library.pre_tokenizer.pre_tokenize_str(self.library.normalizer.normalize_str(text))
        return [bytes(map(self.to_byte.__getitem__, w)) for w, _ in made]

    def encode_units(self, units: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all units in a row, and the count per unit."""
        pieces = [self.pieces(u) for u in units]
        words = list(dict.fromkeys(p for own in pieces for p in own if not isinstance(p, int)))
        done: dict[bytes | int, np.ndarray] = {}
        short = sorted((w for w in words if len(w) <= SHORT), key=len)
        for i in range(0, len(short), ROWS):
            part = short[i : i + ROWS]
            ids, sizes = self.short_words(part)
            done.update(zip(part, np.split(ids, np.cumsum(sizes)[:-1]), strict=True))
        for w in words:
            if len(w) > SHORT:
                done[w] = self.long_word(w)
        flat = [p if not isinstance(p, int) else None for own in pieces for p in own]
        marks = [p for own in pieces for p in own]
        rows = [done[p] if p is not None else np.array([marks[i]], np.uint32) for i, p in enumerate(flat)]
        per_piece = np.array([len(r) for r in rows], np.int64)
        counts = np.array([len(own) for own in pieces], np.int64)
        ends = np.concatenate([[0], np.cumsum(per_piece)])[np.cumsum(counts)]
        return (np.concatenate(rows) if rows else np.empty(0, np.uint32)), np.diff(ends, prepend=0)

    def encode_text(self, text: str) -> np.ndarray:
        return self.encode_units([text])[0]

    def decode(self, ids: np.ndarray) -> str:
        """The file names no decoder: the ids' strings, parted by blanks, special tokens included."""
        return " ".join(map(self.strings.__getitem__, ids.tolist()))


@lru_cache(maxsize=2)
def rank_encoder(path: str) -> tuple[RankBpe, TextEncoder]:
    bpe = RankBpe(path)
    return bpe, TextEncoder(part_words, bpe.encode_units, bpe.encode_text)


def bpe_round_trip(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: doc_id, ids (array), decoded text."""
    return _mapped(docs, tokenizer, id_col, text_col, digest=False)


def bpe_digests(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document: doc_id, n_tokens, and SHA-256 of its ids (little-endian uint32) and of its decoded text."""
    return _mapped(docs, tokenizer, id_col, text_col, digest=True)


def _mapped(docs: DataFrame, tokenizer: str, id_col: str, text_col: str, digest: bool) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe, encode = rank_encoder(tokenizer)
        for piece in chunks(batches, "text", ENCODE_BYTES):
            rows = encode(strings(piece, "text"))
            doc = column(piece, "doc_id")
            if not digest:
                yield out(["doc_id", "ids", "decoded"], doc, pa.array([r.astype(np.int32) for r in rows], pa.list_(pa.int32())), [bpe.decode(r) for r in rows])
                continue
            made = [hashlib.sha256(r.astype("<u4").tobytes()).hexdigest() for r in rows]
            back = [hashlib.sha256(bpe.decode(r).encode("utf-8")).hexdigest() for r in rows]
            yield out(["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"], doc, np.array([len(r) for r in rows], np.int64), made, back)

    plain = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return plain.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" if digest else "doc_id long, ids array<int>, decoded string")
