"""Toxicity by non-negative positive-unlabelled learning (operator 8).

Training sees confirmed toxic texts (P) and all texts of the training folds whatever their label (U); the class
prior is the toxic share of the labelled rows of the training folds. A linear model over the presence of hashed words and
word beginnings minimises the corrected risk  prior*R_P(+) + max(0, R_U(-) - prior*R_P(-)):  where the bracket turns negative,
which is the sign of overfitting on U, the step ascends it instead. Features that P does not hold clearly more often, or
less often, than U are left out first, so that long clean texts gather no noise.

P is every toxic text of the training folds, and U is everything: the texts of U are dealt to chunks of equal size and those of P to
groups of a few thousand by their ids. Each chunk minimises the risk with one group of P against its own share of U, the groups taking turns, and
the weights are averaged over the chunks by their numbers of texts, so the work grows with the corpus and stays in the tasks. Learning and
scoring read whole texts.

Null and empty texts have no features and get the score of the bias; a doc_id with labels 0 and 1 counts as toxic; without a
toxic example, or without any text, everything scores 0; repeated rows are scored one by one; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import SpanHasher, as_bytes, chunks, cut, fold, held_out, mix, spared, table, word_spans

DIM = 1 << 18
SCALE = 1 << 20  # weights are summed as whole parts of this, so that sums do not depend on their order
PREFIXES = (4, 5, 6)
SENT = 1 << 19  # ids of toxic texts up to so many are sent to all tasks; more meet the texts in a shuffle
AT_ONCE = 256  # texts whose features are in memory together
_LETTER = np.zeros(256, bool)
_LETTER[97:123] = True
_LETTER[128:] = True


def features(texts: list) -> tuple[np.ndarray, np.ndarray]:
    """(row, feature) of every feature present, once each, all hashed.

    Features are words in lower case, their first letters, and each of these once more as a frequent one where it makes up
    a hundredth of the text's words or more: a rare chance hit in a long text then differs from a habit.
    """
    rows, cols = [], []
    for i, j in chunks(texts, 1 << 19):
        data, starts = as_bytes([(t or "").lower() for t in texts[i:j]], b" ")
        data = np.where(_LETTER[data], data, 32).astype(np.uint8)
        a, b = word_spans(data)
        if not len(a):
            continue
        h = SpanHasher(data)
        doc = np.searchsorted(starts, a, "right") - 1
        found = [doc * DIM + (h(a, b) % np.uint64(DIM)).astype(np.int64)]
        for k in PREFIXES:
            m = b - a > k
            found.append(doc[m] * DIM + (mix(h(a[m], a[m] + k) + np.uint64(k)) % np.uint64(DIM)).astype(np.int64))
        key, n = np.unique(np.concatenate(found), return_counts=True)
        row, col = key // DIM, key % DIM
        often = n >= np.maximum(2, 0.01 * np.bincount(doc, minlength=j - i)[row])
        rows += [row + i, row[often] + i]
        cols += [col, (mix(col[often].astype(np.uint64)) % np.uint64(DIM)).astype(np.int64)]
    if not rows:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(rows), np.concatenate(cols)


def strongest(with_p: np.ndarray, with_u: np.ndarray, n_p: int, n_u: int, most: int) -> np.ndarray:
    """Features whose share in P and in U differs by far more than chance, the strongest `most` of them, from the numbers of texts
    that have each feature."""
    p = (with_p + 0.5) / (n_p + 1)
    u = (with_u + 0.5) / (n_u + 1)
    z = np.log(p / u) * np.sqrt(np.maximum(p * n_p, u * n_u * np.minimum(1, n_p / max(n_u, 1))))
    keep = np.flatnonzero((np.abs(np.log(p / u)) > 0.7) & (np.abs(z) > 5))
    return np.sort(keep[np.argsort(-np.abs(z[keep]), kind="stable")][:most])


def train(x_p: np.ndarray, x_u: np.ndarray, prior: float, steps: int = 200, rate: float = 0.08, decay: float = 1e-4) -> tuple[np.ndarray, float, list[float]]:
    """Weights, bias and the risk at each step, by full-batch Adam on the non-negative risk with logistic loss.

    The last column of both matrices is the constant one of the bias.
    """
    x = (x_p, x_u)
    w = np.zeros(x_p.shape[1], np.float32)
    w[-1] = np.log(prior / (1 - prior))
    m, v, course = np.zeros_like(w), np.zeros_like(w), []
    sigma = lambda z: 0.5 * (1 + np.tanh(0.5 * z))
    for t in range(1, steps + 1):
        zp, zu = x[0] @ w, x[1] @ w
        negative = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
        g_neg = x[1].T @ sigma(zu) / len(zu) - prior * (x[0].T @ sigma(zp) / len(zp))
        g_pos = prior * (x[0].T @ (-sigma(-zp)) / len(zp))
        g = g_pos + g_neg if negative >= 0 else -g_neg
        course.append(prior * np.logaddexp(0, -zp).mean() + max(0.0, negative))
        g[:-1] += decay * w[:-1]
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
    return w[:-1].astype(np.float32), float(w[-1]), course


class PuModel:
    """Selected feature weights as a table over all hash values, and the bias; bias None: nothing learned."""

    def __init__(self, weights: np.ndarray, bias: float | None):
        self.weights, self.bias = weights, bias

    def scores(self, texts: list | pa.Array) -> np.ndarray:
        if self.bias is None:
            return np.zeros(len(texts))
        z = np.full(len(texts), self.bias)
        for i in range(0, len(texts), AT_ONCE):
            part = texts[i : i + AT_ONCE]
            part = part.to_pylist() if isinstance(part, pa.Array) else part
            rows, cols = features(part)
            z[i : i + AT_ONCE] += np.bincount(rows, self.weights[cols], len(part))
        return 0.5 * (1 + np.tanh(0.5 * z))


def fit(rows: np.ndarray, cols: np.ndarray, n_p: int, n_u: int, prior: float, most: int = 1024) -> PuModel:
    """From features() of n_p positive texts followed by n_u unlabelled ones, in memory."""
    keep = strongest(np.bincount(cols[rows < n_p], minlength=DIM), np.bincount(cols[rows >= n_p], minlength=DIM), n_p, n_u, most)
    order = np.argsort(rows, kind="stable")
    lists = pa.ListArray.from_arrays(pa.array(np.searchsorted(rows[order], np.arange(n_p + n_u + 1)).astype(np.int32)), pa.array(cols[order].astype(np.int32)))
    x, weights = dense(lists, keep), np.zeros(DIM, np.float32)
    weights[keep], bias, _ = train(x[:n_p], x[n_p:], min(max(prior, 1e-4), 0.9))
    return PuModel(weights, bias)


def dense(lists: pa.ListArray, keep: np.ndarray) -> np.ndarray:
    """A 0/1 row for each list over the features `keep`, and the constant one."""
    at = np.full(DIM, -1, np.int32)
    at[keep] = np.arange(len(keep))
    x = np.zeros((len(lists), len(keep) + 1), np.float32)
    x[:, -1] = 1
    rows = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
    cols = at[lists.flatten().to_numpy()]
    x[rows[cols >= 0], cols[cols >= 0]] = 1
    return x


def _lists(texts: list) -> pa.ListArray:
    """features() as a list for each text."""
    rows, cols = features(texts)
    offsets = np.searchsorted(np.sort(rows), np.arange(len(texts) + 1)).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(cols[np.argsort(rows, kind="stable")].astype(np.int32)))


def _having(df: DataFrame) -> tuple[np.ndarray, int]:
    """(number of texts that have each feature, number of texts) of a column of texts, counted within tasks first."""

    def run(batches):
        n, size = np.zeros(DIM, np.int64), 0
        for b in spared(batches):
            for i in range(0, b.num_rows, AT_ONCE):
                n += np.bincount(features(b.column(0).slice(i, AT_ONCE).to_pylist())[1], minlength=DIM)
            size += b.num_rows
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(n[at], size))], names=["c", "n"])

    got = df.mapInArrow(run, "c long, n long").groupBy("c").agg(F.sum("n").alias("n")).toArrow()
    c, n = got.column("c").to_numpy(), got.column("n").to_numpy()
    out = np.zeros(DIM, np.int64)
    out[c[c >= 0]] = n[c >= 0]
    return out, int(n[c < 0].sum())


def learn(docs: DataFrame, labels: DataFrame, n_p: int = 2000, chunk: int = 4096, most: int = 1024) -> PuModel:
    """Fit on rows outside fold 0 of 5: all toxic texts in groups of n_p to twice as many (one, if there are fewer), and all texts in chunks of
    about `chunk`, each whole however long."""
    nothing = PuModel(np.zeros(DIM, np.float32), None)
    known = labels.where("toxic is not null and doc_id is not null").where(fold("doc_id", 5) != 0).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    total, toxic = known.agg(F.count("*"), F.sum(F.when(F.col("toxic") == 1, 1).otherwise(0))).first()
    if not toxic:
        return nothing
    sc = docs.sparkSession.sparkContext
    ids = known.where("toxic = 1").select("doc_id")
    p = cut(docs.select("doc_id", "text").join(F.broadcast(ids) if toxic <= SENT else ids, "doc_id").dropDuplicates(["doc_id"]))
    u = docs.where("doc_id is not null").where(fold("doc_id", 5) != 0).select("text")
    (with_p, size_p), (with_u, size_u) = _having(p.select("text")), _having(u)
    if not size_p or not size_u:
        return nothing
    keep = strongest(with_p, with_u, size_p, size_u, most)
    chosen = sc.broadcast(np.isin(np.arange(DIM), keep))

    def reduce(batches):
        for b in spared(batches):
            for i in range(0, b.num_rows, AT_ONCE):
                part = b.slice(i, AT_ONCE)
                f = _lists(part.column(0).to_pylist())
                cols = f.flatten().to_numpy()
                m = chosen.value[cols]
                offsets = np.concatenate([[0], np.cumsum(m)])[f.offsets.to_numpy()].astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(offsets), pa.array(cols[m])), part.column(1)], names=["f", "k"])

    prior = min(max(toxic / total, 1e-4), 0.9)
    chunks_ = max(1, round(size_u / chunk))
    groups = max(1, min(chunks_, size_p // n_p))

    def share(t: pa.Table, toxic_: pa.Table) -> pa.Table:
        if not t.num_rows or not toxic_.num_rows:
            return pa.table({"i": np.zeros(0, np.int64), "w": np.zeros(0, np.int64), "n": np.zeros(0, np.int64)})
        x = dense(t.column("f").combine_chunks(), keep)
        x = x[np.lexsort(x.T[::-1][:32])]  # the same sums whatever order the rows come in
        w, bias, _ = train(dense(pa.array(sorted(toxic_.column("f").to_pylist()), pa.list_(pa.int32())), keep), x, prior)
        return pa.table({"i": np.arange(len(w) + 1), "w": np.rint(np.append(w, bias).astype(float) * SCALE).astype(np.int64) * len(x), "n": np.full(len(w) + 1, len(x))})

    dealt = u.select("text", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(chunks_)).alias("k")).mapInArrow(reduce, "f array<int>, k long")
    grouped = p.select("text", F.pmod(F.xxhash64("doc_id"), F.lit(groups)).alias("k")).mapInArrow(reduce, "f array<int>, k long")
    grouped = grouped.select("f", F.explode(F.sequence("k", F.lit(chunks_ - 1).cast("long"), F.lit(groups).cast("long"))).alias("k"))
    got = dealt.groupBy("k").cogroup(grouped.groupBy("k")).applyInArrow(share, "i long, w long, n long").groupBy("i").agg(F.sum(F.col("w").cast("decimal(38,0)")).cast("double").alias("w"), F.sum("n").alias("n")).orderBy("i").toArrow()
    mean = got.column("w").to_numpy() / got.column("n").to_numpy() / SCALE
    weights = np.zeros(DIM, np.float32)
    weights[keep] = mean[:-1]
    return PuModel(weights, float(mean[-1]))


def score(docs: DataFrame, model: PuModel) -> DataFrame:
    """(doc_id, score double): one row per row of docs."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in spared(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(held.value.scores(b.column(1)))], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")


def kept(docs: DataFrame, model: PuModel, limit: float = 0.5) -> DataFrame:
    """The rows of docs, all columns, that score below the limit."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def scores(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for t in spared(parts):
            yield pa.array(held.value.scores(t))

    return docs.where(F.arrow_udf(scores, "double")(F.coalesce("text", F.lit(""))) < limit)


def op8(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    s = score(docs, learn(docs, table(spark, sf_dir, "labels")))
    return s.select("doc_id", held_out("doc_id", 5).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


QUERIES = {"op8_toxicity": op8}
SQL: dict[str, str] = {}
