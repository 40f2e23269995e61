import gzip
import math
import os
import zlib
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings, strategies as st

from rankpress.functions.codecs import CODECS, LZ77Codec, canonical, code_lengths
from rankpress.functions.serializers import SERIALIZERS

CASES = [b"", b"a", bytes(range(256)), b"abracadabra" * 40, b"\0" * 20_000, os.urandom(2000), b"3.0.0.12.7" * 30, "naïve 漢字 🙂\r\n".encode() * 20]


@pytest.mark.parametrize("name", CODECS)
def test_round_trip(name):
    c = CODECS[name]
    for x in CASES:
        assert c.decode(c.encode(x)) == x


@pytest.mark.parametrize("name", ["arithmetic", "arithmetic_static", "huffman", "adaptive_huffman", "lz77", "lzw", "lz77_huffman", "bwt"])
@settings(max_examples=40, deadline=None)
@given(x=st.binary(max_size=300) | st.text(alphabet="ab .", max_size=300).map(str.encode))
def test_round_trip_any(name, x):
    assert CODECS[name].decode(CODECS[name].encode(x)) == x


def test_stock_decoders_read_own_streams():
    assert gzip.decompress(CODECS["gzip"].encode(CASES[3])) == CASES[3]
    assert zlib.decompress(CODECS["raw_deflate"].encode(CASES[3]), -15) == CASES[3]
    assert CODECS["gzip"].encode(b"x" * 99) == CODECS["gzip"].encode(b"x" * 99)


def test_huffman_code_is_complete_and_near_entropy():
    n = Counter(b"this is an example of a huffman tree")
    lengths = code_lengths(n)
    assert sum(2.0**-v for v in lengths.values()) == 1
    total = sum(n.values())
    h = -sum(c / total * math.log2(c / total) for c in n.values())
    mean = sum(n[s] * lengths[s] for s in n) / total
    assert h <= mean < h + 1
    codes = sorted(canonical(lengths).values())
    assert all(not b.startswith(a) for a, b in zip(codes, codes[1:]))


def test_arithmetic_is_near_the_ideal():
    x = bytes(np.random.default_rng(0).choice([65, 66, 67, 68], p=[0.7, 0.2, 0.05, 0.05], size=5000).astype(np.uint8))
    n = np.bincount(np.frombuffer(x, np.uint8))
    n = n[n > 0]
    ideal = -(n * np.log2(n / n.sum())).sum() / 8
    assert ideal <= len(CODECS["arithmetic_static"].encode(x)) < ideal + 40
    assert len(CODECS["arithmetic"].encode(x)) < ideal * 1.05 + 150


def test_dictionary_coders_on_a_repeated_phrase():
    found = list(LZ77Codec().parse(b"abcabcabcabc"))
    assert found == [(b"abc", 9, 3), (b"", 0, 0)]
    assert len(CODECS["lzw"].encode(b"ab" * 500)) < 120


@pytest.mark.parametrize("name", SERIALIZERS)
@settings(max_examples=60, deadline=None)
@given(r=st.lists(st.integers(0, 70_000) | st.just(0), max_size=80))
def test_serializers(name, r):
    put, get = SERIALIZERS[name]
    assert get(put(r)).tolist() == r


def test_dotted_form():
    assert SERIALIZERS["dotted"][0]([3, 0, 0, 12]) == b"3.0.0.12"


def test_arithmetic_coding_of_many_texts_in_step(monkeypatch):
    """many texts at once give the streams that each gives alone, past several halvings of the frequencies, and come back."""
    c, rng = CODECS["arithmetic"], np.random.default_rng(0)
    texts = [*CASES, b"\xff" * 9_000, rng.integers(0, 256, 12_000, np.uint8).tobytes(), rng.geometric(0.3, 11_000).astype(np.uint8).tobytes(), b"", *(b"abc"[:n] for n in range(4))]
    want = [c.encode(x) for x in texts]
    monkeypatch.setattr(type(c), "encode", None)
    monkeypatch.setattr(type(c), "decode", None)
    assert c.encode_many(texts) == want and c.decode_many(want) == texts
    assert c.encode_many([]) == [] == c.decode_many([]) and c.decode_many(c.encode_many([b""])) == [b""]
    monkeypatch.undo()
    static = CODECS["arithmetic_static"]
    assert static.decode_many(static.encode_many(texts)) == texts
