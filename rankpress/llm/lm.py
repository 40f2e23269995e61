"""Language-model scores by a log-bilinear model with noise-contrastive training (operator 4).

A token's context is its three predecessors; its prediction vector is the sum of their vectors, each scaled by position. The
vocabulary has two levels of equal standing, both log-bilinear in the prediction vector: classes, and outputs within a class.
Outputs are the commonest words and, for all other words, groups by their last letters; a word of a group has the group's
probability times its smoothed share of the group. So the probabilities of all words, with one unseen word for each group, add
up to one, and normalising a token takes a sum over classes and one over a class: two batched matrix products.

Counts are taken over every training text. The commonest words up to a bound are sent to all tasks with their counts; the rest
meet their counts in a join, so nothing that grows with the corpus is broadcast. The network is fitted in numpy by telling true
classes and words from noise drawn from the unigrams, and it too sees every training text: these are dealt to chunks of about two
million tokens, each chunk trains the network from the same start, and the weights are averaged over the chunks by their tokens, some
chunks at a time. Work and number of chunks grow with the corpus; what a task holds does not.

Words are known by a 64-bit hash of their bytes. Null and empty texts have one token, the end, in training too. Without training texts all
counts are zero, and scores too are finite. Repeated rows are scored one by one; other columns are ignored.
"""

from __future__ import annotations

import copy

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import SpanHasher, as_bytes, chunks, cut, fold, held_out, lower_ascii, mix, table, word_spans

END = np.uint64(0x5EED0FE2D)  # stands for the hash of the end token
GROUPS = 256
CONTEXT = 3


def tokens(texts: list) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, group, row) of all tokens in order; each text ends with the end token, whose group is 0."""
    data, starts = as_bytes(texts, b" ")
    data = lower_ascii(data)
    a, b = word_spans(data)
    h = SpanHasher(data)
    group = (mix(h(np.maximum(a, b - 3), b) + np.uint64(1)) % np.uint64(GROUPS)).astype(np.int64)
    n = np.diff(np.searchsorted(a, starts))
    end = np.cumsum(n + 1) - 1
    out_h, out_g = np.insert(h(a, b), end - np.arange(len(n)), END), np.insert(group, end - np.arange(len(n)), 0)
    return out_h, out_g, np.repeat(np.arange(len(texts)), n + 1)


def counts(docs: DataFrame) -> DataFrame:
    """(h, g, c): each token of the texts with its group and count; counted within tasks before the shuffle."""

    def run(batches):
        h, g, c, size = [], [], [], 0

        def packed():
            hs, at, back = np.unique(np.concatenate(h), return_index=True, return_inverse=True)
            return hs, np.concatenate(g)[at], np.bincount(back, np.concatenate(c)).astype(np.int64)

        emit = lambda t: pa.RecordBatch.from_arrays([pa.array(t[0].view(np.int64)), pa.array(t[1]), pa.array(t[2])], names=["h", "g", "c"])
        for b in batches:
            texts = b.column(0).to_pylist()
            for i, j in chunks(texts):
                x, y, _ = tokens(texts[i:j])
                x, at, n = np.unique(x, return_index=True, return_counts=True)
                h.append(x), g.append(y[at]), c.append(n)
                size += len(x)
                if size > 2_000_000:
                    t = packed()
                    h, g, c, size = [t[0]], [t[1]], [t[2]], len(t[0])
                    if size > 1_500_000:
                        yield emit(t)
                        h, g, c, size = [], [], [], 0
        if size:
            yield emit(packed())

    return docs.select("text").mapInArrow(run, "h long, g long, c long").groupBy("h", "g").agg(F.sum("c").alias("c"))


class LogBilinear:
    """The model with its dictionary; travels to the tasks as plain arrays."""

    def __init__(self, known: np.ndarray, count: np.ndarray, mass: np.ndarray, n: int, v: int, head: int, classes: int = 64, dim: int = 24, seed: int = 5):
        """known, count: hashes in order and counts. mass: of each group, counts plus 0.1 a word, one unseen one included,
        of the words outside the head. head: number of words that are outputs of their own."""
        self.known, self.count, self.n, self.v = known, count, n, v
        top = np.lexsort((known, -count))[:head]
        self.head = np.full(len(known), -1)
        self.head[top] = np.arange(len(top))
        self.n_head = len(top)
        self.log_mass = np.log10(mass)
        size = -(-(self.n_head + GROUPS) // classes)
        weight = np.concatenate([count[top] + 0.1, mass])
        order = np.argsort(-weight, kind="stable")
        place = np.empty(len(order), int)
        place[order] = np.arange(len(order))
        self.class_of, self.slot_of = place % classes, place // classes
        w = np.zeros((classes, size))
        w[self.class_of, self.slot_of] = weight
        self.class_p, self.slot_w = w.sum(1) / w.sum(), w / np.maximum(w.sum(1, keepdims=True), 1e-300)
        rng = np.random.default_rng(seed)
        inputs = len(order) + 1  # the last is the start of a text
        self.r = rng.normal(0, 0.1, (inputs, dim)).astype(np.float32)
        self.scale = np.ones((CONTEXT, dim), np.float32) * np.array([1, 0.7, 0.5], np.float32)[:CONTEXT, None]
        self.class_r, self.class_b = np.zeros((classes, dim), np.float32), np.log(np.maximum(self.class_p, 1e-30)).astype(np.float32)
        self.word_r = np.zeros((classes, size, dim), np.float32)
        self.word_b = np.log(np.maximum(self.slot_w, 1e-30)).astype(np.float32)

    def look_up(self, h: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place in the dictionary or -1, output) of tokens."""
        if not len(self.known):
            return np.full(len(h), -1), self.n_head + g
        at = np.minimum(np.searchsorted(self.known, h), len(self.known) - 1)
        at = np.where(self.known[at] == h, at, -1)
        head = np.where(at >= 0, self.head[at], -1)
        return at, np.where(head >= 0, head, self.n_head + g)

    def contexts(self, out: np.ndarray, row: np.ndarray) -> np.ndarray:
        """The CONTEXT inputs before each token, the nearest first; places before a text hold its start."""
        c = np.full((len(out), CONTEXT), len(self.r) - 1)
        for k in range(1, CONTEXT + 1):
            same = row[k:] == row[:-k]
            c[k:, k - 1][same] = out[:-k][same]
        return c

    PARTS = ("r", "scale", "class_r", "class_b", "word_r", "word_b")

    def weights(self) -> np.ndarray:
        """All trained weights in one array."""
        return np.concatenate([getattr(self, k).ravel() for k in self.PARTS]).astype(np.float32)

    def with_weights(self, w: np.ndarray) -> LogBilinear:
        """This model with other weights; the dictionary is shared."""
        other, at = copy.copy(self), 0
        for k in self.PARTS:
            p = getattr(self, k)
            setattr(other, k, w[at : at + p.size].reshape(p.shape).astype(np.float32))
            at += p.size
        return other

    def train(self, texts: list, **how) -> LogBilinear:
        """fit() on texts in memory."""
        parts, base = [], 0
        for i, j in chunks(texts):
            h, g, row = tokens(texts[i:j])
            parts.append((self.look_up(h, g)[1], row + base))
            base += j - i
        return self.fit(*(np.concatenate(x) for x in zip(*parts)), **how) if parts else self

    def fit(self, out: np.ndarray, row: np.ndarray, epochs: int = 1, batch: int = 4096, noise: int = 64, inside: int = 8, rate: float = 0.2, seed: int = 11) -> LogBilinear:
        """Noise-contrastive estimation with Adagrad on the outputs of whole texts; the noise for a class is shared by a batch, and
        the noise within a class by the batch's tokens of the class."""
        if not len(out):
            return self
        ctx, rng = self.contexts(out, row), np.random.default_rng(seed)
        acc = {k: np.full_like(getattr(self, k), 1e-2) for k in self.PARTS}
        sig = lambda z: np.float32(0.5) * (1 + np.tanh(np.float32(0.5) * z))
        log_p, log_w = np.log(np.maximum(self.class_p, 1e-30)).astype(np.float32), np.log(np.maximum(self.slot_w, 1e-30)).astype(np.float32)
        classes, size = self.word_b.shape
        cum = np.cumsum(self.class_p)
        cum_in = (np.minimum(np.cumsum(self.slot_w, axis=1), 1) + np.arange(classes)[:, None]).ravel()  # one sorted line for all classes
        key_of = (self.class_of * size + self.slot_of).astype(np.int16 if classes * size < 1 << 15 else np.int32)  # short keys sort fast
        dim = self.r.shape[1]

        def step(p, s, at, total):
            total = total * n
            s[at] = moved = s[at] + total * total
            p[at] -= rate * total / np.sqrt(moved)

        def summed(at, x):
            """Distinct places, and the sums of the rows of x that go to them."""
            order = np.argsort(at, kind="stable")
            at = at[order]
            first = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
            return at[first], np.add.reduceat(x.take(order, axis=0), first)

        word_r, word_b = self.word_r.reshape(classes * size, dim), self.word_b.reshape(-1)
        acc_wr, acc_wb, flat_w = acc["word_r"].reshape(classes * size, dim), acc["word_b"].reshape(-1), log_w.reshape(-1)
        lags = np.ascontiguousarray(ctx.T.astype(np.int16 if len(self.r) < 1 << 15 else np.int32))
        for _ in range(epochs):
            for b in np.array_split(rng.permutation(len(out)), max(1, len(out) // batch)):
                key = key_of[out[b]]
                order = np.argsort(key, kind="stable")
                b, key = b[order], key[order]  # by class and slot, so that sums over either are over runs
                c, key = [x.take(b) for x in lags], key.astype(np.int64)
                cls = key // size
                e = [self.r.take(x, axis=0) for x in c]
                q = e[0] * self.scale[0]
                for k in range(1, CONTEXT):
                    q += e[k] * self.scale[k]
                at_word = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
                at_cls = np.flatnonzero(np.concatenate([[True], cls[1:] != cls[:-1]]))
                words, have = key[at_word], cls[at_cls]
                n = np.float32(1 / np.sqrt(len(b)))
                # classes: the true one against noise that the batch shares
                fake, times = np.unique(np.minimum(np.searchsorted(cum, rng.random(noise)), classes - 1), return_counts=True)
                cr = self.class_r.take(cls, axis=0)
                d_true = sig(np.einsum("bd,bd->b", q, cr) + (self.class_b - log_p - np.float32(np.log(noise)))[cls]) - 1
                d_fake = sig(q @ self.class_r[fake].T + (self.class_b - log_p)[fake] - np.float32(np.log(noise))) * times.astype(np.float32)
                gq = d_true[:, None] * cr + d_fake @ self.class_r[fake]
                # words: the true one against noise that the batch's tokens of the class share
                wr = word_r.take(key, axis=0)
                d_word = sig(np.einsum("bd,bd->b", q, wr) + (word_b - flat_w - np.float32(np.log(inside)))[key]) - 1
                gq += d_word[:, None] * wr
                drawn = np.minimum(np.searchsorted(cum_in, rng.random((len(have), inside)) + have[:, None]), have[:, None] * size + size - 1)
                wn, bias = word_r[drawn], (word_b - flat_w)[drawn] - np.float32(np.log(inside))
                spans = list(zip(at_cls.tolist(), [*at_cls[1:].tolist(), len(b)]))
                z = np.empty((len(b), inside), np.float32)
                for x, (i, j) in enumerate(spans):
                    np.matmul(q[i:j], wn[x].T, out=z[i:j])
                z = sig(z + np.repeat(bias, np.diff([*at_cls, len(b)]), axis=0))
                g_noise = np.empty_like(wn)
                for x, (i, j) in enumerate(spans):
                    gq[i:j] += z[i:j] @ wn[x]
                    np.matmul(z[i:j].T, q[i:j], out=g_noise[x])
                step(self.class_r, acc["class_r"], have, np.add.reduceat(d_true[:, None] * q, at_cls))
                step(self.class_b, acc["class_b"], have, np.add.reduceat(d_true, at_cls))
                step(self.class_r, acc["class_r"], fake, d_fake.T @ q)
                step(self.class_b, acc["class_b"], fake, d_fake.sum(0))
                step(word_r, acc_wr, words, np.add.reduceat(d_word[:, None] * q, at_word))
                step(word_b, acc_wb, words, np.add.reduceat(d_word, at_word))
                step(word_r, acc_wr, *summed(drawn.ravel(), g_noise.reshape(-1, dim)))
                step(word_b, acc_wb, *summed(drawn.ravel(), np.add.reduceat(z, at_cls).ravel()))
                gs = np.empty_like(self.scale)
                for k in range(CONTEXT):
                    gs[k] = np.einsum("bd,bd->d", gq, e[k]) * n
                    who, total = summed(c[k], gq)
                    step(self.r, acc["r"], who, total * self.scale[k])
                acc["scale"] += gs * gs
                self.scale -= 0.2 * rate * gs / np.sqrt(acc["scale"])
        return self

    def log_probs(self, out: np.ndarray, ctx: np.ndarray) -> np.ndarray:
        """Natural log-probability of each output, normalised over all outputs."""
        tabs = [self.r * s for s in self.scale]
        cls = self.class_of[out]
        order = np.argsort(cls.astype(np.uint8 if len(self.class_b) < 256 else np.int32), kind="stable")  # a class's tokens side by side
        ctx, cls, slot = ctx[order], cls[order], self.slot_of[out[order]]
        q = tabs[0].take(ctx[:, 0], axis=0)
        for k in range(1, CONTEXT):
            q += tabs[k].take(ctx[:, k], axis=0)
        lp = np.zeros(len(out))

        def add(i, j, r, b, at):
            """The log-probabilities of the choices `at` among the rows of r for the tokens i to j."""
            for x in range(i, j, 1 << 12):
                y = min(j, x + (1 << 12))
                z = q[x:y] @ r.T
                z += b
                high = z.max(axis=1, keepdims=True)
                if high.max() > 60 or high.min() < -60:  # else no exponential overflows, and no row's sum vanishes
                    z -= high
                picked = np.take_along_axis(z, at[x:y, None], 1)[:, 0]
                np.exp(z, out=z)
                lp[x:y] += picked - np.log(z @ np.ones(z.shape[1], np.float32))

        add(0, len(out), self.class_r, self.class_b, cls)
        edge = np.searchsorted(cls, np.arange(len(self.class_b) + 1))
        for c in range(len(self.class_b)):
            add(int(edge[c]), int(edge[c + 1]), self.word_r[c], self.word_b[c], slot)
        back = np.empty(len(out))
        back[order] = lp
        return back

    def score(self, texts: list) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, tuple[np.ndarray, np.ndarray]]:
        """Of each text: tokens, known ones, base and model log10 sums, but for tokens outside the dictionary, of which
        (row, hash) are returned: their log10(count + 0.1) is due to both sums."""
        h, g, row = tokens(texts)
        at, out = self.look_up(h, g)
        m = len(texts)
        lp = self.log_probs(out, self.contexts(out, row)) / np.log(10)
        inside, tail = at >= 0, out >= self.n_head
        lp[tail] -= self.log_mass[out[tail] - self.n_head]
        own = np.zeros(len(h))
        own[inside] = np.log10(self.count[at[inside]] + 0.1)
        n_tokens = np.bincount(row, minlength=m)
        base = np.bincount(row, own, m) - n_tokens * np.log10(self.n + 0.1 * (self.v + 1))
        model = np.bincount(row, lp + np.where(tail, own, 0), m)
        return n_tokens, np.bincount(row, inside, m).astype(np.int64), base, model, (row[~inside], h[~inside])


def learn(docs: DataFrame, counted: DataFrame, words: int = 1 << 20, head: int = 3840, chunk: int = 2_000_000) -> tuple[LogBilinear, int]:
    """The model, and the least count of a dictionary word.

    docs: training texts; counted: counts(docs). words: bound of the dictionary. chunk: tokens that one task trains on.
    """
    step = F.floor(F.log2("c") * 8).cast("int")
    hist = counted.groupBy(step.alias("s")).agg(F.count("*").alias("n"), F.sum("c").alias("c")).orderBy(F.desc("s")).collect()
    n, v, taken, least = sum(r.c for r in hist), sum(r.n for r in hist), 0, 10**9
    for r in hist:
        taken += r.n
        if taken > words:
            break
        least = r.s
    got = counted.where(step >= least).toArrow()
    h, c, g = (got.column(k).to_numpy() for k in ("h", "c", "g"))
    order = np.argsort(h.view(np.uint64), kind="stable")
    h, c, g = h.view(np.uint64)[order], c[order], g[order]
    mass = np.full(GROUPS, 0.1)
    for r in counted.groupBy("g").agg((F.sum("c") + 0.1 * F.count("*")).alias("m")).collect():
        mass[r.g] += r.m
    top = np.lexsort((h, -c))[:head]
    mass = np.maximum(mass - np.bincount(g[top], c[top] + 0.1, GROUPS), 0.1)
    model = LogBilinear(h, c, mass, n, v, head)
    return fitted(docs, model, chunk), least


def fitted(docs: DataFrame, model: LogBilinear, chunk: int) -> LogBilinear:
    """The model trained on all texts, chunk by chunk from the same start, its weights averaged."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def outputs(batches):
        for b in batches:
            texts = b.column(1).to_pylist()
            for i, j in chunks(texts):
                h, g, row = tokens(texts[i:j])
                out = held.value.look_up(h, g)[1].astype(np.int16 if held.value.n_head + GROUPS < 1 << 15 else np.int32)
                offsets = np.searchsorted(row, np.arange(j - i + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), pa.ListArray.from_arrays(pa.array(offsets), pa.array(out))], names=["row", "out"])

    def one(t: pa.Table) -> pa.Table:
        t = t.sort_by("row")
        out = t.column("out").combine_chunks()
        row = np.repeat(np.arange(len(out)), np.diff(out.offsets.to_numpy()))
        m = held.value
        w = m.with_weights(m.weights()).fit(out.flatten().to_numpy().astype(np.int64), row).weights()
        return pa.table({"k": t.column("k").slice(0, 1), "n": pa.array([len(row)], pa.int64()), "w": pa.array([w.tobytes()], pa.binary())})

    def merge(t: pa.Table) -> pa.Table:
        t = t.sort_by("k")
        n = t.column("n").to_numpy()
        w = np.zeros(len(m0), np.float64)
        for x, y in zip(t.column("w"), n):
            w += np.frombuffer(x.as_py(), np.float32) * (y / n.sum())
        return pa.table({"k": t.column("k").slice(0, 1), "n": pa.array([n.sum()], pa.int64()), "w": pa.array([w.astype(np.float32).tobytes()], pa.binary())})

    m0 = model.weights()
    n = max(1, round(model.n / chunk))
    kind = "smallint" if model.n_head + GROUPS < 1 << 15 else "int"
    d = docs.select(F.monotonically_increasing_id().alias("row"), "text").mapInArrow(outputs, f"row long, out array<{kind}>")
    d = d.withColumn("k", F.pmod(F.xxhash64("row"), F.lit(n)))
    got, schema = d.groupBy("k").applyInArrow(one, "k long, n long, w binary"), "k long, n long, w binary"
    while n > 16:  # sixteen models at a time, so that no task holds more
        got, n = got.withColumn("k", F.expr("k div 16")).groupBy("k").applyInArrow(merge, schema), -(-n // 16)
    got = got.toArrow()
    return model.with_weights(np.frombuffer(merge(got).column("w")[0].as_py(), np.float32)) if got.num_rows else model


def scores(docs: DataFrame, train: DataFrame, **bounds) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score for each row of docs, learning from the texts of train."""
    counted = cut(counts(train))
    model, least = learn(train, counted, **bounds)
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            texts = b.column(2).to_pylist()
            for i, j in chunks(texts):
                n, known, base, score, (row, h) = held.value.score(texts[i:j])
                order = np.lexsort((h, row))
                row, h = row[order], h[order]
                first = np.flatnonzero(np.concatenate([[True], (row[1:] != row[:-1]) | (h[1:] != h[:-1])])) if len(h) else np.zeros(0, np.int64)
                offsets = np.searchsorted(row[first], np.arange(j - i + 1)).astype(np.int32)
                rare = pa.ListArray.from_arrays(pa.array(offsets), pa.StructArray.from_arrays([pa.array(h[first].view(np.int64)), pa.array(np.diff(np.append(first, len(h))))], names=["h", "n"]))
                cols = [b.column(0).slice(i, j - i), b.column(1).slice(i, j - i), pa.array(n), pa.array(known), pa.array(base), pa.array(score), rare]
                yield pa.RecordBatch.from_arrays(cols, names=["row", "doc_id", "n_tokens", "n_known", "base", "score", "rare"])

    schema = "row long, doc_id long, n_tokens long, n_known long, base double, score double, rare array<struct<h: long, n: long>>"
    d = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    first = cut(d.mapInArrow(run, schema))
    rare = first.select("row", F.explode("rare").alias("t")).select("row", "t.h", "t.n")
    small = counted.where(F.floor(F.log2("c") * 8).cast("int") < least).select("h", "c")
    c = F.coalesce("c", F.lit(0))
    due = rare.join(small, "h", "left").groupBy("row").agg(F.sum(F.col("n") * F.log10(c + 0.1)).alias("due"), F.sum(F.when(c > 0, F.col("n")).otherwise(0)).alias("more"))
    due_ = F.coalesce("due", F.lit(0.0))
    out = first.drop("rare").join(due, "row", "left")
    return out.select("doc_id", "n_tokens", (F.col("n_known") + F.coalesce("more", F.lit(0))).alias("n_known"), F.lit(model.n).cast("long").alias("train_tokens"), (F.col("base") + due_).alias("base_score"), (F.col("score") + due_).alias("score"))


def op4(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    s = scores(docs, docs.where(fold("doc_id", 10) != 0))
    return s.select("doc_id", held_out("doc_id", 10).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


QUERIES = {"op4_lm_scores": op4}
SQL: dict[str, str] = {}
