"""Unit cuts, caches, packing of ids, and rank arrays against the tokenizers library."""

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from dpgrid.llm.bpe import RankBpe, rank_encoder
from dpgrid.llm.token_files import TokenFile, bits_for, file_bytes, pack, unpack
from dpgrid.llm.tokens import TextEncoder, library_encoder, part_words

ODD = [
    "", "a", " ", "  a  b", "x\n\ny", "a<|endoftext|>b c <|endoftext|> d <|startoftext|>", "a\x1cb", "Don't I'll\nwe've 's it'D", "ΑΣ ΟΔΟΣ", "日本語 テスト", "a b",
    "é x", "a \nb", "tab\tx", "İstanbul", "x" * 5000, "the" * 90, "😀 👍🏽 ok", "1234 12a3", "a_b--c==d!!!!???", "a\x00b \x7f", "Å ﬁ ½", "e.g. one.two,three ...,x .y", ".start", "a .b", "ß ÿ µ ª", "Élan vital. Über, alles",
]


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_library_encoder_equals_library(name):
    path = public_tokenizers.path(name)
    tok = Tokenizer.from_file(path)
    for text, ids in zip(ODD, library_encoder(path)(ODD), strict=True):
        assert ids.tolist() == tok.encode(text, add_special_tokens=False).ids, text


@settings(max_examples=150, deadline=None)
@given(st.text(alphabet=st.sampled_from("abzAZ019 .,'!|<>\n\t\r\x0b\x1c\x85\xa0éßÅΣ日́_-$s"), max_size=40))
def test_random_texts(text):
    for name in ("word_bpe_49k.json", "byte_bpe_50k.json"):
        path = public_tokenizers.path(name)
        want = Tokenizer.from_file(path) if name not in CACHE else CACHE[name]
        CACHE[name] = want
        assert library_encoder(path)([text])[0].tolist() == want.encode(text, add_special_tokens=False).ids
    bpe, encode = rank_encoder(public_tokenizers.path("word_bpe_49k.json"))
    ids = encode([text])[0]
    assert ids.tolist() == CACHE["word_bpe_49k.json"].encode(text, add_special_tokens=False).ids
    assert bpe.decode(ids) == CACHE["word_bpe_49k.json"].decode(ids.tolist(), skip_special_tokens=False)


CACHE: dict[str, Tokenizer] = {}


def test_rank_arrays_equal_library_on_odd_texts():
    path = public_tokenizers.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    bpe, encode = rank_encoder(path)
    for text, ids in zip(ODD, encode(ODD), strict=True):
        assert ids.tolist() == tok.encode(text, add_special_tokens=False).ids, text
        assert bpe.decode(ids) == tok.decode(ids.tolist(), skip_special_tokens=False)


def test_short_and_long_words_agree():
    bpe = RankBpe(public_tokenizers.path("word_bpe_49k.json"))
    words = [b"internationalisation", b"a", b"thethethe", b"zzzzzzz", "größe".encode(), b"strengths"]
    ids, sizes = bpe.short_words(words)
    for word, own in zip(words, np.split(ids, np.cumsum(sizes)[:-1]), strict=True):
        assert own.tolist() == bpe.long_word(word).tolist()


def test_cache_clears_without_changing_results():
    path = public_tokenizers.path("word_bpe_49k.json")
    bpe, _ = rank_encoder(path)
    small = TextEncoder(part_words, bpe.encode_units, bpe.encode_text)
    small.cache.limit = 3
    texts = ["one two three four", "five six one", "", None, "seven one two"]
    assert [x.tolist() for x in small(texts)] == [bpe.encode_text(t or "").tolist() for t in texts]


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 32), st.lists(st.integers(0, 2**32 - 1), max_size=50))
def test_pack_round_trip(bits, values):
    ids = np.array(values, np.uint64) & np.uint64(2**bits - 1)
    ids = ids.astype(np.uint32)
    assert unpack(pack(ids, bits), len(ids), bits).tolist() == ids.tolist()
    assert len(pack(ids, bits)) == -(-len(ids) * bits // 8)


def test_token_file_random_access():
    rng = np.random.default_rng(0)
    rows = [rng.integers(0, 49408, n).astype(np.uint32) for n in (0, 1, 5000, 3, 9000)]
    file = TokenFile(file_bytes([5, None, 7, 8, 9], rows, bits_for(49408), block=1000))
    assert bits_for(49408) == 16 and bits_for(50257) == 16 and bits_for(2) == 1
    for k, row in enumerate(rows):
        assert file.document(k).tolist() == row.tolist()
    every = np.concatenate(rows)
    assert file.read(990, 2010).tolist() == every[990:2010].tolist()
    assert file.doc_ids.tolist() == [5, 0, 7, 8, 9] and file.known.tolist() == [True, False, True, True, True]
