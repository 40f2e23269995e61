"""Tokenizers: lossless maps between texts and sequences of ids below vocab_size.

Byte-pair merges are those of a public vocabulary file, cut to its first merges: a vocabulary of V has the 256 bytes and the
first V - 256 merges, which need no later ones. Nothing is trained.
"""

from __future__ import annotations

import base64
import re

import numpy as np

MERGES_PATH = "/opt/tokenizers/byte_bpe_multi_50k.tiktoken"
#: How a text is cut before merging: letters, digits, other signs, white space, each with a space in front; or words; or not at all.
PRE = {"category": r" ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+", "whitespace": r"\s*\S+|\s+$", "none": r"[\s\S]+"}


class ByteTokenizer:
    """UTF-8 bytes."""

    name, vocab_size = "byte", 256

    def encode(self, text: str) -> np.ndarray:
        return np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8).astype(np.int32)

    def decode(self, ids) -> str:
        return np.asarray(ids, np.uint8).tobytes().decode("utf-8", "surrogatepass")


class CharTokenizer:
    """Code points."""

    name, vocab_size = "char", 0x110000

    def encode(self, text: str) -> np.ndarray:
        return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int32)

    def decode(self, ids) -> str:
        return np.asarray(ids, np.uint32).tobytes().decode("utf-32-le", "surrogatepass")


class BpeTokenizer:
    """Byte-level byte-pair encoding with the first merges of a public file; built in each worker at first use."""

    def __init__(self, vocab_size: int = 1024, pre: str = "category", path: str = MERGES_PATH):
        self.vocab_size, self.pre, self.path, self.name, self._made = vocab_size, pre, path, f"bpe{vocab_size}" + ("" if pre == "category" else f"-{pre}"), None
        self.merges = self._read()

    def _read(self) -> dict[bytes, int]:
        with open(self.path) as f:
            pairs = (line.split() for line in f if line.strip())
            return {base64.b64decode(p): int(r) for p, r in pairs if int(r) < self.vocab_size}

    def __getstate__(self):
        return self.__dict__ | {"_made": None}

    def _encoding(self):
        if self._made is None:
            import tiktoken

            self._made = tiktoken.Encoding(self.name, pat_str=PRE[self.pre], mergeable_ranks=self.merges, special_tokens={})
        return self._made

    def encode(self, text: str) -> np.ndarray:
        return np.array(self._encoding().encode_ordinary(text), np.int32)

    def decode(self, ids) -> str:
        return self._encoding().decode_bytes(np.asarray(ids).tolist()).decode("utf-8", "surrogatepass")


class Framed:
    """Another tokenizer's ids between two ids of their own, above its vocabulary: BEGIN, which also pads, and END."""

    def __init__(self, inner):
        self.inner, self.name, self.vocab_size = inner, f"{inner.name}+ends", inner.vocab_size + 2
        self.begin, self.end = inner.vocab_size, inner.vocab_size + 1

    def encode(self, text: str) -> np.ndarray:
        return np.concatenate([[self.begin], self.inner.encode(text), [self.end]]).astype(np.int32)

    def decode(self, ids) -> str:
        """The text up to the first END; BEGIN is passed over wherever it stands, as padding."""
        ids = np.asarray(ids)
        stop = np.flatnonzero(ids == self.end)
        ids = ids[: stop[0]] if len(stop) else ids
        return self.inner.decode(ids[ids != self.begin])


def tokenizer(name: str):
    """byte, char, bpeN or bpeN-pre; with +ends, framed."""
    if name.endswith("+ends"):
        return Framed(tokenizer(name[:-5]))
    if name in ("byte", "char"):
        return ByteTokenizer() if name == "byte" else CharTokenizer()
    m = re.fullmatch(r"bpe(\d+)(?:-(\w+))?", name)
    if not m:
        raise ValueError(f"no tokenizer {name!r}")
    return BpeTokenizer(int(m[1]), m[2] or "category")
