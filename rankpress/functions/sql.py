"""The engine's functions for SQL: scalar, aggregate and table functions over Arrow batches.

    register(spark)
    spark.sql("select rp_compress(text, 'brotli') from documents")
    spark.sql("select t.token, count(*) from documents, lateral rp_tokens(text, 'byte') t group by t.token")

Nulls give null (no rows from the table function). The aggregates take counts, one row a symbol, never the symbols themselves:
what a group brings to one task is as large as its alphabet.
"""

from __future__ import annotations

import heapq
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession, functions as F

from .codecs import CODECS
from .tokenizers import tokenizer

_tokenizer = lru_cache(maxsize=8)(tokenizer)


def _each(f, *columns) -> pd.Series:
    return pd.Series([None if any(v is None for v in row) else f(*row) for row in zip(*columns)], dtype=object)


def compress(text: pd.Series, codec: pd.Series) -> pd.Series:
    return _each(lambda t, c: CODECS[c].encode(t.encode("utf-8", "surrogatepass")), text, codec)


def decompress(data: pd.Series, codec: pd.Series) -> pd.Series:
    return _each(lambda b, c: CODECS[c].decode(bytes(b)).decode("utf-8", "surrogatepass"), data, codec)


def encode(text: pd.Series, name: pd.Series) -> pd.Series:
    return _each(lambda t, n: _tokenizer(n).encode(t).tolist(), text, name)


def decode(ids: pd.Series, name: pd.Series) -> pd.Series:
    return _each(lambda x, n: _tokenizer(n).decode(x), ids, name)


def total_huffman_bits(counts) -> int:
    """Bits of a message with these counts: each merge of the two lightest trees adds a bit to all that is below."""
    heap = sorted(int(c) for c in counts if c > 0)
    if len(heap) == 1:
        return heap[0]
    bits = 0
    while len(heap) > 1:
        both = heapq.heappop(heap) + heapq.heappop(heap)
        bits += both
        heapq.heappush(heap, both)
    return bits


def huffman_bits(counts: pd.Series) -> int:
    return total_huffman_bits(counts.dropna())


def entropy(counts: pd.Series) -> float:
    n = counts.dropna().to_numpy(float)
    p = n[n > 0] / n.sum()
    return float(-(p * np.log2(p)).sum())


class Tokens:
    """(pos, token) of a text."""

    def eval(self, text: str, name: str):
        if text is not None and name is not None:
            yield from enumerate(_tokenizer(name).encode(text).tolist())


def register(spark: SparkSession) -> None:
    """Makes rp_compress, rp_decompress, rp_encode, rp_decode, rp_huffman_bits, rp_entropy and the table function rp_tokens known."""
    for name, f, kind in (("rp_compress", compress, "binary"), ("rp_decompress", decompress, "string"), ("rp_encode", encode, "array<int>"), ("rp_decode", decode, "string"), ("rp_huffman_bits", huffman_bits, "long"), ("rp_entropy", entropy, "double")):
        spark.udf.register(name, F.pandas_udf(f, kind))
    spark.udtf.register("rp_tokens", F.udtf(Tokens, returnType="pos int, token int", useArrow=True))
