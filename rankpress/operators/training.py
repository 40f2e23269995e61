"""Training of count models, and their fine-tuning and distillation, as aggregates over token windows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from ..functions.predictors import BITS, CountModel, context_keys
from ..functions.spans import chunks
from ..sources.tables import cut

COUNTS = "domain string, level int, ctx long, token int, cnt long"


def counts(df: DataFrame, tokenizer, order: int, domain: str | None = None, text: str = "text") -> DataFrame:
    """(domain, level, ctx, token, cnt) of the texts of df: each token after its contexts of lengths 0..order.

    Windows are counted within Arrow batches; only the sums meet in a shuffle, so even the context of length 0, which all
    tokens share, sends a row for each token of a batch at most.
    """

    def run(batches):
        for b in batches:
            names = b.column(0).to_pylist()
            texts = b.column(1).to_pylist()
            for d in sorted(set(names)):
                parts: list[list[np.ndarray]] = [[] for _ in range(order + 1)]
                ids_all = []
                for n, t in zip(names, texts):
                    if n == d and t:
                        ids = tokenizer.encode(t)
                        ids_all.append(ids.astype(np.int64))
                        for k, key in enumerate(context_keys(ids, order)):
                            parts[k].append(key)
                if not ids_all:
                    continue
                ids_ = np.concatenate(ids_all)
                for k in range(order + 1):
                    ctx = np.concatenate(parts[k])
                    o = np.lexsort((ids_, ctx))
                    c, t = ctx[o], ids_[o]
                    first = np.flatnonzero(np.concatenate(([True], (c[1:] != c[:-1]) | (t[1:] != t[:-1]))))
                    n = np.diff(np.append(first, len(c)))
                    yield pa.RecordBatch.from_arrays([pa.array([d] * len(first), pa.string()), pa.array(np.full(len(first), k, np.int32)), pa.array(c[first]), pa.array(t[first].astype(np.int32)), pa.array(n.astype(np.int64))], names=["domain", "level", "ctx", "token", "cnt"])

    d = df.select((F.col(domain).cast("string") if domain else F.lit("all")).alias("domain"), F.col(text).alias("text")).where("text is not null and domain is not null")
    return d.mapInArrow(run, COUNTS).groupBy("domain", "level", "ctx", "token").agg(F.sum("cnt").alias("cnt"))


def token_lengths(df: DataFrame, tokenizer, text: str = "text") -> DataFrame:
    """The columns of df but the text, with n_chars and n_tokens of it; a narrow pass."""
    keep = [c for c in df.columns if c not in (text, "n_chars", "n_tokens")]

    def run(batches):
        for b in batches:
            texts = b.column(b.num_columns - 1).to_pylist()
            n = pa.array([None if t is None else len(tokenizer.encode(t)) for t in texts], pa.int64())
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array([None if t is None else len(t) for t in texts], pa.int64()), n], names=[*b.schema.names[:-1], "n_chars", "n_tokens"])

    d = df.select(*keep, F.col(text).alias("_text"))
    schema = "".join(f"`{f.name}` {f.dataType.simpleString()}, " for f in d.schema.fields[:-1])
    return d.mapInArrow(run, f"{schema}n_chars long, n_tokens long")


def merged(base: DataFrame, domain: DataFrame, weight: int) -> DataFrame:
    """Fine-tuned counts: base plus `weight` times the domain's, named as the domain. Weight 0 gives the base."""
    b = base.select("level", "ctx", "token", "cnt")
    names = domain.select("domain").distinct()
    both = b.crossJoin(F.broadcast(names)).select("domain", "level", "ctx", "token", "cnt")
    d = domain.select("domain", "level", "ctx", "token", (F.col("cnt") * weight).alias("cnt"))
    return both.unionByName(d).groupBy("domain", "level", "ctx", "token").agg(F.sum("cnt").alias("cnt")).where("cnt > 0")


def delta(domain: DataFrame, weight: int) -> DataFrame:
    """(domain, level, ctx, token, more): what tuning adds to a base, only where it adds something; the base stays as it is."""
    return domain.select("domain", "level", "ctx", "token", (F.col("cnt") * weight).alias("more")).where("more > 0")


def with_delta(base: CountModel, added: DataFrame, order: int, most: int = 1 << 25) -> dict[str, CountModel]:
    """Tuned models from one base and the sparse tables of the domains; the same as collect_models(merged(...))."""
    n = added.count()
    if n > most:
        raise ValueError(f"{n} rows are more than the {most} that are sent to tasks")
    t = added.toArrow()
    names = np.array(t.column("domain").to_pylist(), object)
    new = [t.column(c).to_numpy() for c in ("level", "ctx", "token", "more")]
    old = [np.concatenate(c) for c in zip(*((np.full(len(tok), k), np.repeat(keys, np.diff(first)), tok, cnt) for k, (keys, first, tok, cnt) in enumerate(base.levels)))]
    out = {}
    for d in sorted(set(names)):
        level, ctx, token, cnt = (np.concatenate([a, b[names == d]]) for a, b in zip(old, new))
        o = np.lexsort((token, ctx, level))
        level, ctx, token, cnt = level[o], ctx[o], token[o], cnt[o]
        first = np.flatnonzero(np.concatenate(([True], (level[1:] != level[:-1]) | (ctx[1:] != ctx[:-1]) | (token[1:] != token[:-1]))))
        out[d] = CountModel.from_rows(level[first], ctx[first], token[first], np.add.reduceat(cnt, first), base.vocab_size, order, d)
    return out


def soft(t: CountModel, ctx: np.ndarray, times: np.ndarray, order: int, temperature: float = 1.0, alpha: float = 0.7, top: int = 32, scale: int = 1000):
    """(student's longest context, token, count) of what the teacher says after distinct contexts, as long as the longer of teacher's and
    student's, that come so many times."""
    keys = [ctx & ((1 << (BITS * k)) - 1) for k in range(max(t.order, order) + 1)]
    level, at_level = np.full(len(ctx), -1), np.zeros(len(ctx), np.int64)
    for k in range(t.order, -1, -1):
        i = np.where(level < 0, t.contexts(k, keys[k]), -1)
        level[i >= 0], at_level[i >= 0] = k, i[i >= 0]
    for k in range(t.order + 1):
        at = np.flatnonzero(level == k)
        if not len(at):
            continue
        _, first, tokens, cnt = t.levels[k]
        a = first[at_level[at]]
        n = np.minimum(top, first[at_level[at] + 1] - a)
        begin = np.concatenate([[0], np.cumsum(n)[:-1]])
        flat = np.repeat(a - begin, n) + np.arange(n.sum())
        p = cnt[flat].astype(float) ** (1 / temperature)
        q = (alpha * scale * p / np.repeat(np.add.reduceat(p, begin), n)).astype(np.int64) * np.repeat(times[at], n)
        yield np.repeat(keys[order][at], n)[q > 0], tokens[flat][q > 0].astype(np.int64), q[q > 0]


def distilled(df: DataFrame, teacher: CountModel, tokenizer, student_order: int, domain: str | None = None, temperature: float = 1.0, alpha: float = 0.7, top: int = 32, scale: int = 1000) -> DataFrame:
    """Soft counts of a student: at each position of the domain's texts the teacher's `top` probabilities, to the power
    1/temperature, weigh alpha and the true token 1 - alpha; both are added up by the student's contexts in whole thousandths."""
    held = df.sparkSession.sparkContext.broadcast(teacher)
    own, order = int((1 - alpha) * scale), student_order

    def run(batches):
        t = held.value
        for b in batches:
            names, texts = b.column(0).to_pylist(), b.column(1).to_pylist()
            for name in sorted(set(names), key=str):
                mine = [x for y, x in zip(names, texts) if y == name and x]
                for i, j in chunks(mine, 1 << 19):
                    all_ids = [tokenizer.encode(x) for x in mine[i:j]]
                    per = [context_keys(x, max(t.order, order)) for x in all_ids]
                    ids, keys = np.concatenate(all_ids).astype(np.int64), [np.concatenate(x) for x in zip(*per)]
                    if not len(ids):
                        continue
                    u, times = np.unique(keys[max(t.order, order)], return_counts=True)
                    parts = [(keys[order], ids, np.full(len(ids), own)), *soft(t, u, times, order, temperature, alpha, top, scale)]
                    ctx, token, cnt = (np.concatenate(x) for x in zip(*parts))
                    for k in range(order + 1):
                        c = ctx & ((1 << (BITS * k)) - 1)
                        o = np.lexsort((token, c))
                        c, x = c[o], token[o]
                        first = np.flatnonzero(np.concatenate(([True], (c[1:] != c[:-1]) | (x[1:] != x[:-1]))))
                        yield pa.RecordBatch.from_arrays([pa.array([name] * len(first), pa.string()), pa.array(np.full(len(first), k, np.int32)), pa.array(c[first]), pa.array(x[first].astype(np.int32)), pa.array(np.add.reduceat(cnt[o], first))], names=["domain", "level", "ctx", "token", "cnt"])

    d = df.select((F.col(domain).cast("string") if domain else F.lit("all")).alias("domain"), "text").where("text is not null")
    return d.mapInArrow(run, COUNTS).groupBy("domain", "level", "ctx", "token").agg(F.sum("cnt").alias("cnt")).where("cnt > 0")


def collect_models(counted: DataFrame, vocab_size: int, order: int, most: int = 1 << 25, prefix: str = "") -> dict[str, CountModel]:
    """The models of all domains for broadcasting, every count in them. The number of rows is checked before they come to the
    driver: a table of more than `most` rows is refused, and operators.ranks gives the same ranks by joins at any size."""
    counted = cut(counted)
    n = counted.count()
    if n > most:
        raise ValueError(f"{n} counts are more than the {most} that are sent to tasks; rank them with operators.ranks")
    t, out = counted.toArrow(), {}
    names = pc.unique(t.column("domain")).to_pylist()
    for d in sorted(names):  # rows of one domain at a time, and their names never as Python strings
        own = t if len(names) == 1 else t.filter(pc.equal(t.column("domain"), d))
        out[d] = CountModel.from_rows(*(own.column(c).to_numpy() for c in ("level", "ctx", "token", "cnt")), vocab_size, order, f"{prefix}{d}")
    return out


def empty(vocab_size: int, order: int) -> CountModel:
    """The model of no text: all tokens in the order of their ids."""
    none = np.zeros(0, np.int64)
    return CountModel.from_rows(none, none, none, none, vocab_size, order, "empty")


def truncated(model: CountModel, order: int, name: str) -> CountModel:
    """The smaller model of a ladder: the same counts with shorter contexts."""
    return CountModel(model.levels[: order + 1], model.vocab_size, name)
