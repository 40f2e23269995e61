"""Language identification by error-correcting output codes (operator 1).

Each learned language has a codeword of bits; each bit has a binary n-gram classifier, the log-odds of hashed byte n-grams (one
to four bytes of lower-cased text) between the languages that have the bit and those that don't, averaged over the text and
calibrated. Decoding adds up the losses of all bits against each codeword, weighted by how well a bit's classifier does on the
language in training, and takes the codeword with the least loss; a small lead over the next one flags the text as ambiguous.

Up to seven languages get the exhaustive code, more get random codewords spread by choice of the best of several draws.
Training texts are a bounded sample of each language (a parameter). Learning and scoring read whole texts, however long.

Null texts and texts without a letter: `und`, score 0. Ties go to the first language by code point. Without any training text
every language is `und`; with one language, that one. Repeated rows are scored one by one; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import as_bytes, chunks, fold, held_out, near_bound, table

DIM, ORDERS = 1 << 16, 4
_PAD = b" " * ORDERS
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[[b for b in range(128) if not 97 <= b <= 122]] = 32
_MUL = np.array([2654435761, 2246822519, 3266489917, 668265263], np.uint32)


def grams(texts: list):
    """For each order, (bucket of the n-gram at every byte, whether it counts); and where each text starts.

    Everything but letters reads as a space; an n-gram counts where it starts with a letter or goes from a space to one.
    """
    data, starts = as_bytes([(t or "").lower() for t in texts], _PAD)
    data = _FOLD[data]
    letter = data != 32
    n = len(data)
    x = np.concatenate([data, np.full(ORDERS, 32, np.uint8)]).astype(np.uint32)
    code, out = np.zeros(n, np.uint32), []
    counts = letter | np.concatenate([letter[1:], [False]])
    counts[starts[1:] - 1] = False  # what follows there is another text
    for k in range(ORDERS):
        code = code << np.uint32(8) | x[k : k + n]
        out.append(((code * _MUL[k] + np.uint32(k)) >> np.uint32(16), letter if k == 0 else counts))
    return out, starts


def codewords(n: int, seed: int = 3) -> np.ndarray:
    """n rows of +1 and -1, rows and columns well apart."""
    if n <= 7:
        cols = [[1, *(1 if b >> i & 1 else -1 for i in range(n - 1))] for b in range(2 ** (n - 1) - 1)] or [[1]]
        return np.array(cols, float).T
    bits = int(4 * np.ceil(np.log2(n))) + 3
    rng = np.random.default_rng(seed)
    best, apart = None, -1
    for _ in range(200):
        m = np.where(rng.random((n, bits)) < 0.5, -1.0, 1.0)
        m = m[:, np.abs(m.sum(0)) < n]
        least = int((m.shape[1] - (m @ m.T)[~np.eye(n, dtype=bool)].max()) // 2)
        if least > apart:
            best, apart = m, least
    return best


class CodeModel:
    def __init__(self, langs: list[str]):
        self.langs = langs

    def margins(self, texts: list) -> np.ndarray:
        """The mean log-odds of each bit in each text."""
        out = np.zeros((len(texts), self.weights.shape[1]))
        for i, j in chunks(texts, 1 << 19):
            found, starts = grams(texts[i:j])
            total, n = 0, 0
            for bucket, counts in found:
                w = self.weights[bucket]
                w[~counts] = 0
                total = total + np.add.reduceat(w, starts[:-1], axis=0, dtype=np.float64)
                n = n + np.add.reduceat(counts, starts[:-1], dtype=np.int64)
            out[i:j] = total / np.maximum(n, 1)[:, None]
        return out

    def weigh(self, freq: np.ndarray) -> CodeModel:
        """The weights of each bit from the n-gram counts of each language."""
        k = len(self.langs)
        share = (freq + 0.5) / (freq.sum(1, keepdims=True) + 0.5 * DIM)  # each language counts alike
        self.code = codewords(k)
        yes, no = (self.code > 0).astype(float), (self.code < 0).astype(float)
        self.weights = np.log((yes.T @ share) / np.maximum(yes.sum(0), 1)[:, None] / ((no.T @ share) / np.maximum(no.sum(0), 1)[:, None])).T.astype(np.float32) if k > 1 else np.zeros((DIM, 1), np.float32)
        return self

    def calibrate(self, f: np.ndarray, lang: np.ndarray) -> CodeModel:
        """Slopes, shifts and trust from the margins of texts of known languages."""
        k, sign = len(self.langs), self.code[lang]
        self.slope = np.ones(f.shape[1])
        self.shift = np.zeros(f.shape[1])
        for b in range(f.shape[1]):  # a bit's margin becomes a log-odds: Newton steps of a logistic fit in two numbers
            x = np.stack([f[:, b] * 20, np.ones(len(f))], axis=1)
            w = np.array([1.0, 0.0])
            for _ in range(25 if k > 1 else 0):
                p = 0.5 * (1 + np.tanh(0.5 * np.clip(x @ w, -40, 40)))
                h = (x * (p * (1 - p))[:, None]).T @ x + 0.5 * np.eye(2)
                w = w - np.clip(np.linalg.solve(h, x.T @ (p - (sign[:, b] > 0)) + 0.5 * w), -0.5, 0.5)
            self.slope[b], self.shift[b] = 20 * w[0], w[1]
        right = (f * self.slope + self.shift) * sign > 0
        acc = np.array([right[lang == i].mean(0) if (lang == i).any() else np.ones(f.shape[1]) for i in range(k)])
        self.trust = acc / acc.sum(1, keepdims=True)
        return self

    def decode(self, texts: list, lead: float = 0.1) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(language, score, ambiguous) of each text."""
        z = self.margins(texts) * self.slope + self.shift
        loss = np.stack([(np.logaddexp(0, -z * c) * t).sum(1) for c, t in zip(self.code, self.trust)], axis=1)
        p = np.exp(-(loss - loss.min(1, keepdims=True)) * 2)
        p /= p.sum(1, keepdims=True)
        top = np.sort(p, axis=1)
        best = loss.argmin(1)
        gap = top[:, -1] - top[:, -2] if len(self.langs) > 1 else np.ones(len(p))
        return best, p[np.arange(len(p)), best], gap < lead


def counts(texts: list) -> np.ndarray:
    """The n-grams of all texts by bucket."""
    freq = np.zeros(DIM, np.int64)
    for i, j in chunks(texts):
        for bucket, where in grams(texts[i:j])[0]:
            freq += np.bincount(bucket[where], minlength=DIM)
    return freq


def learn(docs: DataFrame, each: int = 1000) -> CodeModel:
    """Fit on rows outside fold 0 of 5 with a language: about `each` texts of a language (all, where there are fewer), picked by
    a hash of the id below a threshold, each whole however long.

    The executors count n-grams, then take margins; the driver gets the counts of each language and the margins of each text,
    once for rows that are the same.
    """
    d = docs.where("doc_id is not null and lang is not null and text is not null").where(fold("doc_id", 5) != 0).select("doc_id", "lang", "text")
    texts = near_bound(d, "doc_id", "lang", each)

    def count(batches):
        freq = {}
        for b in batches:
            names = b.column(0).to_pylist()
            for g in set(names):
                freq[g] = freq.get(g, 0) + counts([t for t, x in zip(b.column(1).to_pylist(), names) if x == g])
        for g, n in freq.items():
            at = np.union1d(np.flatnonzero(n), [0])  # a row even for a language without a letter
            yield pa.RecordBatch.from_arrays([pa.array([g] * len(at), pa.string()), pa.array(at), pa.array(n[at])], names=["lang", "bucket", "n"])

    got = texts.select("lang", "text").mapInArrow(count, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toArrow()
    langs = sorted(set(got.column("lang").to_pylist()))
    model = CodeModel(langs)
    if not langs:
        return model
    freq = np.zeros((len(langs), DIM))
    freq[[langs.index(g) for g in got.column("lang").to_pylist()], got.column("bucket").to_numpy()] = got.column("n").to_numpy()
    held = docs.sparkSession.sparkContext.broadcast(model.weigh(freq))

    def margins(batches):
        for b in batches:
            f = held.value.margins(b.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(f.tolist(), pa.list_(pa.float64()))], names=["doc_id", "lang", "f"])

    kind = dict(docs.dtypes)["doc_id"]
    rows = texts.select("doc_id", "lang", "text").mapInArrow(margins, f"doc_id {kind}, lang string, f array<double>").distinct().collect()
    rows.sort(key=lambda r: (r.lang, r.doc_id, r.f))
    return model.calibrate(np.array([r.f for r in rows]), np.array([langs.index(r.lang) for r in rows]))


def predict(docs: DataFrame, model: CodeModel) -> DataFrame:
    """doc_id, lang_pred, score, ambiguous for each row of docs."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = held.value
        for b in batches:
            texts, n = b.column(1).to_pylist(), b.num_rows
            best, score, unsure = m.decode(texts) if m.langs and n else (np.zeros(n, int), np.zeros(n), np.zeros(n, bool))
            ok = np.array(b.column(2)) if m.langs else np.zeros(n, bool)
            names = [m.langs[i] if y else "und" for i, y in zip(best.tolist(), ok)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(names, pa.string()), pa.array(np.where(ok, score, 0.0)), pa.array(unsure & ok)], names=["doc_id", "lang_pred", "score", "ambiguous"])

    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.coalesce(F.col("text").rlike("\\p{L}"), F.lit(False)).alias("ok"))
    return d.mapInArrow(run, "doc_id long, lang_pred string, score double, ambiguous boolean")


def op1(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return predict(docs, learn(docs)).select("doc_id", held_out("doc_id", 5).alias("held_out"), "lang_pred", "score", "ambiguous")


QUERIES = {"op1_language": op1}
SQL: dict[str, str] = {}
