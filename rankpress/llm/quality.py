"""Quality by regularised quadratic discriminant analysis (operator 5).

Every whole text becomes a short vector of transformed statistics (shares of character classes, word lengths, repetition of
words, neighbours, lines and five-word runs). Each class has a mean and a covariance, shrunk towards the pooled covariance
and towards its own diagonal; a score is the posterior from the difference of the two Gaussian log-densities, whose Mahalanobis
terms use Cholesky factors that are computed once.

All labelled rows outside the held-out fold are learned from: means and covariances come from sums, which are made in the tasks in whole
numbers, so that no order of rows matters, and of which the driver sees a few hundred. Learning and scoring read whole texts.

Null and empty texts have the statistics of an empty text and are scored like any other; a doc_id with labels 0 and 1 counts
as 0; if a class has no example, everything scores the share of label 1 (0.5 without labels); repeated rows are scored one by
one; other columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import fold, held_out, spared, table

UNIT = 1 << 18  # sums are of whole parts of this
SENT = 1 << 19  # labels up to so many are sent to all tasks; more meet the texts in a shuffle

#: The statistics in their order.
NAMES = ("word_length", "upper", "digits", "exclaim", "bars", "marks", "stops", "breaks", "neighbours", "distinct", "commonest", "lines_again", "runs_again", "trust")


def statistics(text: str | None) -> list[float]:
    """The vector of one text: a logarithm and variance-stabilised shares (square roots).

    Counts are divided by a size plus a constant, which damps the shares of very short texts. The last entry, words over
    words plus 20, says how far the rest can be trusted: deviations from the overall mean are multiplied by it.
    """
    raw = (text or "").encode("utf-8", "surrogatepass")
    h = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    n = max(1, len(raw) - int(h[128:192].sum()))  # continuation bytes don't count
    words = raw.split()
    k = len(words) + 20
    seen = Counter(words)
    lines = [x for x in raw.split(b"\n") if x]
    runs = list(zip(words, words[1:], words[2:], words[3:], words[4:])) if len(words) > 4 else []
    upper, lower = int(h[65:91].sum()), int(h[97:123].sum())
    share = [
        upper / (upper + lower + 100),
        h[48:58].sum() / (n + 200),
        h[33] / k,
        h[124] / k,
        h[[35, 36, 37, 38, 42, 43, 60, 61, 62, 64, 91, 92, 93, 94, 95, 123, 125, 126]].sum() / (n + 100),
        h[[44, 46, 58, 59, 63]].sum() / k,
        h[10] / k,
        sum(map(eq, words, words[1:])) / k,
        (len(seen) + 20) / k,
        max(seen.values(), default=0) / k,
        1 - len(set(lines)) / max(1, len(lines)),
        1 - len(set(runs)) / max(1, len(runs)),
    ]
    return [np.log1p(sum(map(len, words)) / max(1, len(words))) if words else 1.7, *np.sqrt(np.array(share, float)), len(words) / k]


class Discriminant:
    """Two shrunken Gaussians; after fit, scores() is the posterior of class 1."""

    def __init__(self, shrink: float = 0.1, to_diagonal: float = 0.2, floor: float = 0.02):
        self.shrink, self.to_diagonal, self.floor = shrink, to_diagonal, floor
        self.prior, self.parts = 0.5, None

    def fit(self, x: np.ndarray, y: np.ndarray) -> Discriminant:
        if len(y):
            self.prior = float(np.mean(y == 1))
        if len(np.unique(y)) < 2:
            return self
        self.centre, self.scale = x[:, :-1].mean(0), np.maximum(x[:, :-1].std(0), 1e-3)
        z = self._standard(x)
        groups = [z[y == c] for c in (0, 1)]
        return self._shrunk([(len(g), g.mean(0), np.cov(g, rowvar=False, bias=True) if len(g) > 1 else np.eye(z.shape[1])) for g in groups])

    def fit_sums(self, sums: dict[int, np.ndarray]) -> Discriminant:
        """As fit(), from sums() of the rows of each class."""
        total = sum(sums.values(), np.zeros(_SUMS))
        if total[0]:
            self.prior = float(sums.get(1, np.zeros(1))[0] / total[0])
        if len(sums) < 2:
            return self
        k = len(NAMES)
        self.centre = total[1:k] / total[0]
        self.scale = np.maximum(np.sqrt(np.maximum(total[k : 2 * k - 1] / total[0] - self.centre**2, 0)), 1e-3)
        own = []
        for c in (0, 1):
            n, first, second = sums[c][0], sums[c][2 * k - 1 : 3 * k - 1], sums[c][3 * k - 1 :].reshape(k, k)
            to_z = np.hstack([np.diag(1 / self.scale), (-self.centre / self.scale)[:, None]])  # damped statistics and the trust to z
            mean = to_z @ first / n
            own.append((n, mean, to_z @ second @ to_z.T / n - np.outer(mean, mean) if n > 1 else np.eye(k - 1)))
        return self._shrunk(own)

    def _shrunk(self, own: list[tuple]) -> Discriminant:
        """From the number of rows, mean and covariance of each class."""
        pooled = sum(n * c for n, _, c in own) / sum(n for n, _, _ in own)
        self.parts = []
        for _, mean, c in own:
            c = (1 - self.shrink) * c + self.shrink * pooled
            c = (1 - self.to_diagonal) * c + self.to_diagonal * np.diag(np.diag(c)) + self.floor * np.eye(len(c))
            low = np.linalg.cholesky(c)
            self.parts.append((mean, np.linalg.inv(low), 2 * np.log(np.diag(low)).sum()))
        return self

    def _standard(self, x: np.ndarray) -> np.ndarray:
        return (x[:, :-1] - self.centre) / self.scale * x[:, -1:]

    def scores(self, x: np.ndarray) -> np.ndarray:
        if self.parts is None:
            return np.full(len(x), self.prior)
        z = self._standard(x)
        dens = [-0.5 * (np.square((z - m) @ inv.T).sum(1) + logdet) for m, inv, logdet in self.parts]
        odds = dens[1] - dens[0] + np.log(self.prior / (1 - self.prior))
        return 0.5 * (1 + np.tanh(0.5 * odds))


def _vectors(df: DataFrame, schema: str, of) -> DataFrame:
    """Arrow pass over (key, text): `of` maps the matrix of statistics to an Arrow array."""

    def run(batches):
        for b in spared(batches):
            x = np.array([statistics(t) for t in b.column(1).to_pylist()], float).reshape(-1, len(NAMES))
            yield pa.RecordBatch.from_arrays([b.column(0), of(x)], names=schema.replace(",", "").split(" ")[0::2])

    return df.mapInArrow(run, schema)


_SUMS = 2 * len(NAMES) - 1 + len(NAMES) + len(NAMES) ** 2


def sums(x: np.ndarray) -> np.ndarray:
    """Of rows of statistics, in whole parts of UNIT or of its square: their number, sums and squares of each, sums of the damped ones with
    the trust, and the products of these."""
    v = x[:, :-1]
    whole, damped = (np.rint(y * UNIT).astype(np.int64) for y in (v, np.c_[v * x[:, -1:], x[:, -1:]]))
    return np.concatenate([[len(x)], whole.sum(0), (whole * whole).sum(0), damped.sum(0), (damped.T @ damped).ravel()])


_SCALE = np.concatenate([[1], np.full(len(NAMES) - 1, UNIT), np.full(len(NAMES) - 1, UNIT**2), np.full(len(NAMES), UNIT), np.full(len(NAMES) ** 2, UNIT**2)]).astype(float)


def learn(docs: DataFrame, labels: DataFrame) -> Discriminant:
    """Fit on all labelled rows outside fold 0 of 5; their statistics and the sums of these are made on the executors."""
    known = labels.where("quality is not null and doc_id is not null").where(fold("doc_id", 5) != 0).groupBy("doc_id").agg(F.min("quality").alias("y"))
    known = F.broadcast(known) if known.count() <= SENT else known

    def run(batches):
        for b in spared(batches):
            y, texts = b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_pylist()
            x = np.array([statistics(t) for t in texts], float).reshape(-1, len(NAMES))
            for c in np.unique(y):
                got = sums(x[y == c])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(got), c, np.int32)), pa.array(np.arange(len(got), dtype=np.int32)), pa.array(got)], names=["y", "i", "s"])

    rows = docs.select("doc_id", "text").join(known, "doc_id").select(F.col("y").cast("int"), "text").mapInArrow(run, "y int, i int, s long")
    found: dict[int, np.ndarray] = {}
    for r in rows.groupBy("y", "i").agg(F.sum(F.col("s").cast("decimal(38,0)")).cast("double").alias("s")).collect():
        found.setdefault(r.y, np.zeros(_SUMS))[r.i] = r.s
    return Discriminant().fit_sums({c: v / _SCALE for c, v in found.items()})


def score(docs: DataFrame, model: Discriminant) -> DataFrame:
    """(doc_id, score double): one row per row of docs."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return _vectors(d, "doc_id long, score double", lambda x: pa.array(held.value.scores(x)))


def kept(docs: DataFrame, model: Discriminant, limit: float = 0.3) -> DataFrame:
    """The rows of docs, all columns, that score at least the limit."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def scores(parts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for t in spared(parts):
            yield pa.array(held.value.scores(np.array([statistics(x.as_py()) for x in t], float).reshape(-1, len(NAMES))))

    return docs.where(F.arrow_udf(scores, "double")(F.coalesce("text", F.lit(""))) >= limit)


def op5(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    s = score(docs, learn(docs, table(spark, sf_dir, "labels")))
    return s.select("doc_id", held_out("doc_id", 5).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


QUERIES = {"op5_quality": op5}
SQL: dict[str, str] = {}
