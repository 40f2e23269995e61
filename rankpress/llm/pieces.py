"""SentencePiece encoding and decoding (operator 2).

An Aho-Corasick automaton over the pieces reads a text once; at each position it reports, along its output links, every piece
that ends there, and each relaxes the best path to that position. What "best" means depends on the model file:

- unigram: the largest sum of scores (the Viterbi path); of equal sums the one whose last piece is longest stays;
- bpe: the largest sum of scores over lawful paths: a piece may follow the last piece of the path to its start only if merging the two alone gives the two again. The
  prefix then has exactly one such path, which is the one that merging pairs by score gives, so the ids are those of the
  usual library. (A plain sum of this model's scores, which are negative ranks of merges, would give other ids.)

White space becomes U+2581 and one stands before the text. Characters outside the vocabulary become byte pieces. Where no piece
spans the start of a word, words are encoded alone and short ones remembered, up to a bound; a long word costs time in
proportion to its length.

Each text's score is the sum of its pieces' scores. Null text: null ids, 0 pieces, null score. Empty text: no ids, score 0. U+2581 in a text decodes to a space, as in the library: round_trip is then
false. Repeated rows are encoded one by one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import spared, table

MODEL_PATH = "/opt/tokenizers/piece_bpe_32k.model"
SPACE = "▁"
_REMEMBER = 500_000
_NEVER = -1e300


class Pieces:
    """Pieces and scores of a model, in plain lists so that it travels to the executors."""

    def __init__(self, pieces: list[str | None], scores: list[float], byte_ids: list[int], bpe: bool, unk: int = 0):
        self.pieces, self.scores, self.byte_ids, self.bpe, self.unk = pieces, scores, byte_ids, bpe, unk

    @classmethod
    def load(cls, path: str = MODEL_PATH, bpe: bool = True) -> Pieces:
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        n = range(m.get_piece_size())
        usual = [not (m.is_byte(i) or m.is_control(i) or m.is_unknown(i) or m.is_unused(i)) for i in n]
        byte_ids = [m.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        if not all(m.is_byte(i) for i in byte_ids):
            byte_ids = []
        return cls([m.id_to_piece(i) if u else None for i, u in zip(n, usual)], [m.get_score(i) for i in n], byte_ids, bpe, m.unk_id())

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if not k.startswith("_")}

    def _ready(self) -> Pieces:
        if not hasattr(self, "_auto"):
            self._id = {p: i for i, p in enumerate(self.pieces) if p}
            self._size = [len(p or "") for p in self.pieces]
            self._chars = {p for p in self._id if len(p) == 1}
            self._pairs: dict[int, bool] = {}
            self._auto = ahocorasick.Automaton()
            for p, i in self._id.items():
                if not self.bpe or len(p) < 3 or self._merged(list(p)) == [p]:  # else merging never makes the piece
                    self._auto.add_word(p, (i, len(p)))
            self._auto.make_automaton()
            self._words: dict[str, bytes] = {}
            inner = any(re.search(f"[^{SPACE}]{SPACE}", p) for p in self._id)
            self._split = None if inner else re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+")
            self._low = min(self.scores) - 10
            spell = [(p or "").replace(SPACE, " ").encode() for p in self.pieces]
            for b, i in enumerate(self.byte_ids):
                spell[i] = bytes([b])
            self._spell = spell
            self._score_of = np.array(self.scores)
        return self

    # ------------------------------------------------------------ one word

    def _merged(self, symbols: list[str]) -> list[str]:
        """Merge the adjacent pair with the best score, the leftmost first, until none is a piece: short inputs only."""
        while True:
            best = max(((self.scores[i], -k) for k in range(len(symbols) - 1) if (i := self._id.get(symbols[k] + symbols[k + 1])) is not None), default=None)
            if best is None:
                return symbols
            k = -best[1]
            symbols[k : k + 2] = [symbols[k] + symbols[k + 1]]

    def _stands(self, left: int, right: int) -> bool:
        """Whether merging keeps the two pieces apart."""
        key = left << 32 | right
        got = self._pairs.get(key)
        if got is None:
            a, b = self.pieces[left], self.pieces[right]
            got = self._merged(list(a + b)) == [a, b]
            if len(self._pairs) > _REMEMBER:
                self._pairs.clear()
            self._pairs[key] = got
        return got

    def _word(self, word: str) -> list[int]:
        """One pass of the automaton with relaxation; unknown characters are steps of their own."""
        n = len(word)
        known = self._chars.issuperset(word)
        last = [-2] * (n + 1)  # the piece that ends the best path here; -1: the start or an unknown character; -2: not reached
        last[0] = -1
        if not known:
            for k in [k for k, c in enumerate(word) if c not in self._chars]:
                last[k + 1] = -1
        score = [0.0] + [_NEVER] * n
        if not known:
            for k in range(n):
                if last[k + 1] == -1:  # an unknown character is no part of a piece, so all paths meet on both sides of it
                    score[k + 1] = self._low
        for end, (i, size) in self._auto.iter(word):  # along the output links, the longest piece first
            before = last[end + 1 - size]
            if before == -2 or (self.bpe and last[end + 1] != -2):  # in a bpe model one lawful path leads here, and none can better it
                continue
            if self.bpe and before >= 0 and not self._stands(before, i):
                continue
            if (s := score[end + 1 - size] + self.scores[i]) > score[end + 1]:
                score[end + 1], last[end + 1] = s, i
        out: list[int] = []
        at = n
        while at:
            i = last[at]
            if i < 0:
                out += [self.byte_ids[b] for b in reversed(word[at - 1].encode("utf-8", "surrogatepass"))] if self.byte_ids else [self.unk]
                at -= 1
            else:
                out.append(i)
                at -= self._size[i]
        return out[::-1]

    # ------------------------------------------------------------ whole texts

    def encode(self, text: str) -> np.ndarray:
        """int32 ids of a whole text."""
        self._ready()
        if not text:
            return np.zeros(0, np.int32)
        s = SPACE + text.replace(" ", SPACE)
        known, parts = self._words, []
        for w in self._split.findall(s) if self._split else [s]:
            got = known.get(w)
            if got is None:
                got = np.array(self._word(w), np.int32).tobytes()
                if len(w) <= 48:
                    if len(known) >= _REMEMBER:
                        known.clear()
                    known[w] = got
            parts.append(got)
        return np.frombuffer(b"".join(parts), np.int32)

    def score(self, ids: np.ndarray) -> float:
        """The sum of the scores of ids."""
        return self._ready()._score_of[ids].sum()

    def decode(self, ids) -> str:
        """The text of ids; the space that encoding puts in front goes. Bytes that aren't UTF-8 become U+FFFD."""
        self._ready()
        spell = self._spell
        raw = b"".join([spell[i] for i in (ids.tolist() if isinstance(ids, np.ndarray) else ids)])
        raw = raw.removeprefix(b" ")
        try:
            return raw.decode("utf-8", "surrogatepass")
        except UnicodeDecodeError:
            return raw.decode("utf-8", "replace")


def encoded(docs: DataFrame, model: Pieces, keep: list[str] | None = None) -> DataFrame:
    """The columns `keep` of docs (doc_id if not given) with ids, n_pieces, round_trip (decoding gives the text again) and piece_score."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    keep = keep or ["doc_id"]
    d = docs.select(*keep, F.col("text").alias("_text"))

    def run(batches):
        m = held.value
        for b in spared(batches):
            for i in range(0, b.num_rows, 256):
                part = b.slice(i, 256)
                texts = part.column(part.num_columns - 1).to_pylist()
                got = [None if t is None else m.encode(t) for t in texts]
                size = np.array([0 if g is None else len(g) for g in got], np.int64)
                offsets = np.concatenate(([0], np.cumsum(size))).astype(np.int32)
                flat = np.concatenate([g for g in got if g is not None] or [np.zeros(0, np.int32)])
                ids = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat, pa.int32()), mask=pa.array([g is None for g in got]))
                same = [t is None or m.decode(g) == t for t, g in zip(texts, got)]
                sums = pa.array([None if g is None else float(m.score(g)) for g in got], pa.float64())
                yield pa.RecordBatch.from_arrays([*part.columns[:-1], ids, pa.array(size), pa.array(same, pa.bool_()), sums], names=[*part.schema.names[:-1], "ids", "n_pieces", "round_trip", "piece_score"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in d.schema.fields[:-1])
    return d.mapInArrow(run, f"{schema}, ids array<int>, n_pieces long, round_trip boolean, piece_score double")


def decoded(rows: DataFrame, model: Pieces, key: str = "doc_id") -> DataFrame:
    """(key, text) of rows with ids; null ids give null."""
    held = rows.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            texts = [None if i is None else held.value.decode(i) for i in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], names=[key, "text"])

    return rows.select(key, "ids").mapInArrow(run, f"{key} {rows.schema[key].dataType.simpleString()}, text string")


def op2(spark, sf_dir):
    return encoded(table(spark, sf_dir, "documents"), Pieces.load())


QUERIES = {"op2_sentencepiece": op2}
SQL: dict[str, str] = {}
