"""Count models that no machine holds whole: ranks of blocks under them, bucket by bucket.

Everything that the rank of a token depends on, the lists after its contexts of every length, ends in the same last token. So counts and
the places to be ranked meet in buckets by the last two tokens, and within a bucket a small CountModel of just the contexts
asked for gives the ranks. Only counts of the longest contexts travel; those of two tokens are their sums. The lists after one token go to each
bucket that the token can come to, the list of no context to all tasks; both are bounded by the vocabulary. The driver sees the latter only.
"""

from __future__ import annotations

import math
import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.predictors import BITS, CountModel, context_keys
from ..functions.spans import chunks
from ..sources.tables import cut
from . import training

SALTS = 16  # buckets over which the contexts that end in one token are dealt
SHARE = 1 << 21  # bytes of text to a bucket
AT_ONCE = 1 << 22  # code points that are counted at once
GROUP = 64  # blocks that are put together in one go
TOKEN = (1 << BITS) - 1
COUNTS = "bucket int, part string, level int, n int, data binary"
PLACES, RANKS = "bucket int, gid long, n int, data binary", "gid long, n int, data binary, ms array<double>"


def squeeze(*columns: np.ndarray) -> bytes:
    """Columns as one string of bytes: whole numbers by planes of bytes, so that what is alike stands together."""
    return pa.compress(b"".join(np.ascontiguousarray(c.view(np.uint8).reshape(len(c), c.itemsize).T).tobytes() for c in map(np.ascontiguousarray, columns)), "zstd", asbytes=True)


def unsqueeze(data: bytes, n: int, *kinds) -> list[np.ndarray]:
    widths = [np.dtype(k).itemsize for k in kinds]
    flat, out, at = np.frombuffer(pa.decompress(data, n * sum(widths), "zstd", asbytes=True), np.uint8), [], 0
    for k, w in zip(kinds, widths):
        out.append(np.ascontiguousarray(flat[at : at + n * w].reshape(w, n).T).reshape(-1).view(k))
        at += n * w
    return out


def summed(ctx: np.ndarray, token: np.ndarray, cnt: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ctx, token, cnt) of the distinct pairs, in their order. Tokens get short codes first, so that a pair mostly is one number."""
    if not len(ctx):
        return ctx, token, np.zeros(0, np.int64)
    fields = [(ctx >> (BITS * k)) & TOKEN for k in reversed(range(math.ceil(int(ctx.max()).bit_length() / BITS)))] + [token + 1]
    code = np.zeros(max(int(f.max()) for f in fields) + 1, np.int64)
    for f in fields:
        code[f] = 1
    known = np.flatnonzero(code)
    code[known] = np.arange(len(known))
    bits = max(1, (len(known) - 1).bit_length())
    if bits * len(fields) < 63:
        key = np.zeros(len(ctx), np.int64)
        for f in fields:
            key = key << bits | code[f]
        if cnt is None:
            key.sort()
        else:
            o = np.argsort(key)
            key, cnt = key[o], cnt[o]
        first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        key, short = key[first], (1 << bits) - 1
        back = [known[(key >> (bits * k)) & short] for k in range(len(fields))]
        c = np.zeros(len(key), np.int64)
        for k, f in enumerate(back[1:]):
            c |= f << (BITS * k)
        t = back[0] - 1
    else:
        o = np.lexsort((token, ctx))
        c, t, cnt = ctx[o], token[o], None if cnt is None else cnt[o]
        first = np.flatnonzero(np.concatenate(([True], (c[1:] != c[:-1]) | (t[1:] != t[:-1]))))
        c, t = c[first], t[first]
    return c, t, np.diff(np.append(first, len(ctx))) if cnt is None else np.add.reduceat(cnt, first)


def _mix(x):
    return (x * 2654435761) & 0x7FFFFFFF


def bucket_of(ctx: np.ndarray, n: int) -> np.ndarray:
    """By the last token, dealt by the one before it."""
    return (_mix(ctx & TOKEN) + _mix((ctx >> BITS) & TOKEN) % SALTS) % n


def _dealt(by: np.ndarray):
    """(value, its rows in their order) for each value of `by`."""
    o = np.argsort(by, kind="stable")
    ends = np.flatnonzero(np.diff(by[o])) + 1
    return ((int(by[i[0]]), i) for i in np.split(o, ends)) if len(by) else ()


def _turned(ctx: np.ndarray) -> np.ndarray:
    """A context's three places in the opposite order, so that sorting begins with the last token; its own inverse."""
    return (ctx & TOKEN) << (2 * BITS) | (ctx >> BITS & TOKEN) << BITS | ctx >> (2 * BITS)


ENTRY = (np.int32, np.int32, np.int32, np.int32, np.int64)


def _packed(c, t, n) -> bytes:
    """By the places of the context, those that change least as steps."""
    one, two, three = (c >> (BITS * k) & TOKEN for k in range(3))
    return squeeze(np.diff(one, prepend=0).astype(np.int32), np.diff(two, prepend=0).astype(np.int32), three.astype(np.int32), t.astype(np.int32), n.astype(np.int64))


def _entries(data: bytes, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    one, two, three, t, cnt = (x.astype(np.int64) for x in unsqueeze(data, n, *ENTRY))
    return np.cumsum(one) | np.cumsum(two) << BITS | three << (2 * BITS), t, cnt


def _sorted_out(table: pa.Table) -> dict[tuple[str, int], list]:
    out: dict = {}
    for p, k, n, d in zip(*(table.column(c).to_pylist() for c in ("part", "level", "n", "data"))):
        out.setdefault((p, k), []).append((n, d))
    return out


def _unpacked(rows: dict, part: str, level: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    got = [_entries(d, n) for n, d in rows.get((part, level), ())]
    return tuple(np.concatenate(x) for x in zip(*got)) if got else (np.zeros(0, np.int64),) * 3


@dataclass
class Counted:
    """The counts of some parts of texts, dealt to buckets; counts of no context as {part: (tokens, counts)}."""

    rows: DataFrame
    level0: dict[str, tuple[np.ndarray, np.ndarray]]
    n: int
    order: int
    vocab_size: int


@dataclass(frozen=True)
class Mixed:
    """A model by the parts whose counts it adds up, each so many times, and by the length of its context."""

    parts: tuple[tuple[str, int], ...]
    order: int


def _emitted(part: str, c: np.ndarray, t: np.ndarray, cnt: np.ndarray, order: int, n: int, deep: bool) -> list[tuple]:
    """The rows of COUNTS from counts of contexts of `order` tokens, dealt to n buckets; deep: places there have contexts of two and more."""
    rows = [(-1, part, 0, *_last(*summed(np.zeros(len(c), np.int64), t, cnt)))]
    if order:
        one = summed(c & TOKEN, t, cnt)
        for salt in range(min(SALTS, n) if deep else 1):
            for to, at in _dealt((_mix(one[0]) + salt) % n):
                rows.append((to, part, 1, *_last(*(x[at] for x in one))))
    if order > 1:
        for to, at in _dealt(bucket_of(c, n)):
            rows.append((to, part, order, *_last(c[at], t[at], cnt[at])))
    return rows


def _places(d: DataFrame, tokenizer, order: int, emit) -> DataFrame:
    """COUNTS that `emit` makes of (part, contexts of `order` tokens, tokens, counts) of the texts of d (part, text), in passes."""

    def run(batches):
        for b in batches:
            names, texts = b.column(0).to_pylist(), b.column(1).to_pylist()
            for part in sorted(set(names)):
                mine = [t for p, t in zip(names, texts) if p == part and t]
                for i, j in chunks(mine, AT_ONCE):
                    ids = [tokenizer.encode(t) for t in mine[i:j]]
                    c, t, cnt = summed(_turned(np.concatenate([context_keys(x, order)[order] for x in ids])), np.concatenate(ids).astype(np.int64))
                    if len(c):
                        yield _batch(COUNTS, emit(part, _turned(c), t, cnt))

    return d.where("text is not null and part is not null").select(F.col("part").cast("string").alias("part"), "text").mapInArrow(run, COUNTS)


def _kept(rows: DataFrame, n: int, order: int, vocab_size: int) -> Counted:
    """The rows, kept in the shared folder, and the counts of no context on the driver."""

    def whole(table):
        part = table.column("part")[0].as_py()
        return pa.Table.from_batches([_batch(COUNTS, [(-1, part, 0, *_last(*summed(*_unpacked(_sorted_out(table), part, 0))))])])

    rows = cut(rows)
    level0 = {}
    for r in rows.where("bucket = -1").groupBy("part").applyInArrow(whole, COUNTS).collect():
        level0[r["part"]] = _entries(bytes(r["data"]), r["n"])[1:]
    return Counted(rows, dict(sorted(level0.items())), n, order, vocab_size)


def counted(df: DataFrame, tokenizer, order: int, n: int | None = None, deep: bool = False) -> Counted:
    """Counts of the texts of df (part, text), each token after its contexts of lengths 0..order, kept in the shared folder. n, deep: how many
    buckets, and whether the counts are to stand beside others of longer contexts there; see together()."""
    if n is None:
        n = max(1, math.ceil((df.where("text is not null and part is not null").agg(F.sum(F.octet_length("text"))).first()[0] or 0) / SHARE))
    return _kept(_places(df, tokenizer, order, lambda part, c, t, cnt: _emitted(part, c, t, cnt, order, n, deep or order > 1)), n, order, tokenizer.vocab_size)


def together(*all_: Counted) -> Counted:
    """Counts of different parts, in the same number of buckets, as one."""
    rows = all_[0].rows
    for c in all_[1:]:
        rows = rows.unionByName(c.rows)
    return Counted(rows, {p: x for c in all_ for p, x in c.level0.items()}, all_[0].n, max(c.order for c in all_), all_[0].vocab_size)


def distilled(df: DataFrame, c: Counted, teacher: Mixed, tokenizer, order: int, deep: bool = False, alpha: float = 0.7, scale: int = 1000) -> Counted:
    """training.distilled() of each part of df (part, text) by a teacher that no machine holds whole: places meet the teacher's counts bucket by
    bucket, and the soft counts stay in the buckets. The student's context is no longer than the teacher's."""
    n, top, vocab, own = c.n, c.order, c.vocab_size, int((1 - alpha) * scale)
    level0 = df.sparkSession.sparkContext.broadcast(c.level0)

    def places(part, ctx, t, cnt):
        return [(to, part, top, *_last(ctx[at], t[at], cnt[at])) for to, at in _dealt(bucket_of(ctx, n))]

    def teach(counts, asked):
        if not asked.num_rows:
            return _empty(COUNTS)
        by_part = {}
        for part, size, data in zip(*(asked.column(x).to_pylist() for x in ("part", "n", "data"))):
            by_part.setdefault(part, []).append(_entries(data, size))
        by_part = {p: summed(*(np.concatenate(x) for x in zip(*got))) for p, got in by_part.items()}
        ctx = np.unique(np.concatenate([x[0] for x in by_part.values()]))
        known = [np.unique(ctx & ((1 << (BITS * k)) - 1)) for k in range(top + 1)]
        model = _model_of(_levels(_sorted_out(counts), teacher.parts, level0.value, top), known, vocab, top).shorter(teacher.order)
        rows = []
        for part, (x, t, cnt) in sorted(by_part.items()):
            u, begin = np.unique(x, return_index=True)
            times, mask = np.add.reduceat(cnt, begin), (1 << (BITS * order)) - 1
            soft = [(x & mask, t, cnt * own), *training.soft(model, u, times, order, alpha=alpha, scale=scale)]
            rows += _emitted(part, *summed(*(np.concatenate(y) for y in zip(*soft))), order, n, deep or order > 1)
        return pa.Table.from_batches([_batch(COUNTS, rows)])

    asked = _places(df, tokenizer, top, places)
    return _kept(c.rows.where("bucket >= 0").groupBy("bucket").cogroup(asked.groupBy("bucket")).applyInArrow(teach, COUNTS), n, order, vocab)


def _last(c, t, n):
    return len(c), _packed(c, t, n)


def _batch(schema: str, rows: list[tuple]) -> pa.RecordBatch:
    kinds = {"int": pa.int32(), "long": pa.int64(), "string": pa.string(), "binary": pa.binary(), "array<double>": pa.list_(pa.float64())}
    fields = [f.split() for f in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(list(zip(*rows)) if rows else [()] * len(fields), fields)], names=[n for n, _ in fields])


def _levels(rows: dict, parts, level0, order: int):
    """(ctx, token, cnt) of each length 0..order of a bucket's contexts, for a mix of parts."""
    add = lambda k: summed(*(np.concatenate(x) for x in zip(*((c, t, n * w) for p, w in parts if w for c, t, n in [_unpacked(rows, p, k)]))))
    zero = [(np.zeros(len(t), np.int64), t, n * w) for p, w in parts if w and p in level0 for t, n in [level0[p]]]
    out = {0: summed(*(np.concatenate(x) for x in zip(*zero))) if zero else (np.zeros(0, np.int64),) * 3}
    if order:
        out[1] = add(1)
    for k in range(order, 1, -1):  # counts of longer contexts, and of parts that have none
        out[k] = add(k)
        if k < order:
            longer = out[k + 1][0] & ((1 << (BITS * k)) - 1), *out[k + 1][1:]
            out[k] = summed(*(np.concatenate(x) for x in zip(out[k], longer)))
    return out


def _model_of(levels: dict, known: list[np.ndarray], vocab: int, order: int) -> CountModel:
    """A model of just the known contexts."""
    rows = [(np.full(len(x[0]), k), *x) for k, x in levels.items()]
    rows = [tuple(y[_among(x[1], known[x[0][0]])] for y in x) for x in rows if len(x[0])]
    return CountModel.from_rows(*([np.concatenate(x) for x in zip(*rows)] if rows else [np.zeros(0, np.int64)] * 4), vocab, order)


def _among(values: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Which values are among the known ones, which are in order."""
    return known[np.minimum(np.searchsorted(known, values), len(known) - 1)] == values


def ranks(blocks: DataFrame, c: Counted, models: dict[str, Mixed], tokenizer) -> DataFrame:
    """RANKS of all tokens of blocks (gid, bid, text, want), under all models or, where a model's name has a colon, only in blocks
    that want what stands before it. Within data: bid as steps, pos, and a rank for each model or -1."""
    n, top, vocab = c.n, c.order, c.vocab_size
    wanted = {w: i for i, w in enumerate(sorted({m.split(":")[0] for m in models if ":" in m}))}
    level0 = blocks.sparkSession.sparkContext.broadcast(c.level0)

    def places(batches):
        for b in batches:
            all_ = [r for r in zip(*(b.column(i).to_pylist() for i in range(4))) if r[2]]
            for i, j in chunks([r[2] for r in all_], AT_ONCE):
                mine, rows = all_[i:j], []
                ids = [tokenizer.encode(r[2]) for r in mine]
                size = [len(x) for x in ids]
                if not sum(size):
                    continue
                gid, bid, want = (np.repeat(np.array(x, np.int64), size) for x in zip(*((r[0], r[1], wanted.get(r[3], -1)) for r in mine)))
                pos, ctx = np.concatenate([np.arange(s) for s in size]), np.concatenate([context_keys(x, top)[top] for x in ids])
                token, (groups, at) = np.concatenate(ids), np.unique(gid, return_inverse=True)
                for to, x in _dealt(at * n + bucket_of(ctx, n)):
                    rows.append((to % n, int(groups[to // n]), len(x), squeeze(np.diff(bid[x], prepend=0), pos[x].astype(np.int32), ctx[x], token[x].astype(np.int32), want[x].astype(np.int8))))
                yield _batch(PLACES, rows)

    def rank(counts, asked):
        if not asked.num_rows:
            return _empty(RANKS)
        sizes = asked.column("n").to_pylist()
        got = [unsqueeze(d, k, np.int64, np.int32, np.int64, np.int32, np.int8) for d, k in zip(asked.column("data").to_pylist(), sizes)]
        ctx, token, want = (np.concatenate([g[i] for g in got]) for i in (2, 3, 4))
        keys = [ctx & ((1 << (BITS * k)) - 1) for k in range(top + 1)]
        known = [np.unique(k) for k in keys]
        out, ms = np.full((len(models), len(ctx)), -1, np.int32), []
        made, here = {}, _sorted_out(counts)
        for i, (name, m) in enumerate(models.items()):
            at = np.flatnonzero(want == wanted[name.split(":")[0]]) if ":" in name else slice(None)
            if m.parts not in made:
                made.clear()
                made[m.parts] = _model_of(_levels(here, m.parts, level0.value, top), known, vocab, top)
                made[m.parts].prepare()
            model = made[m.parts].shorter(m.order)
            t = time.perf_counter()
            out[i, at] = model.ranks_at([k[at] for k in keys[: m.order + 1]], token[at])
            ms.append((time.perf_counter() - t) * 1e3 / max(1, len(token[at])))
        ends = np.cumsum([0, *sizes])
        return pa.Table.from_batches([_batch(RANKS, [(g, k, squeeze(np.diff(x[0].cumsum(), prepend=0), x[1], *out[:, a : a + k]), ms) for g, k, x, a in zip(asked.column("gid").to_pylist(), sizes, got, ends)])])

    p = blocks.select("gid", "bid", "text", "want").mapInArrow(places, PLACES)
    return c.rows.where("bucket >= 0").groupBy("bucket").cogroup(p.groupBy("bucket")).applyInArrow(rank, RANKS)


def _empty(schema: str) -> pa.Table:
    return pa.Table.from_batches([_batch(schema, [])])


def by_block(table: pa.Table, names: list[str]) -> dict[int, tuple[dict[str, np.ndarray], dict[str, float]]]:
    """RANKS of one group: block -> (model -> ranks in order, model -> milliseconds)."""
    if not table.num_rows:
        return {}
    sizes = table.column("n").to_pylist()
    got = [unsqueeze(d, k, np.int64, np.int32, *[np.int32] * len(names)) for d, k in zip(table.column("data").to_pylist(), sizes)]
    bid, pos = np.concatenate([np.cumsum(g[0]) for g in got]), np.concatenate([g[1] for g in got])
    o = np.lexsort((pos, bid))
    first = np.flatnonzero(np.concatenate(([True], np.diff(bid[o]) != 0)))
    per = {m: (np.concatenate([g[2 + i] for g in got])[o], np.add.reduceat(np.repeat([x[i] for x in table.column("ms").to_pylist()], sizes)[o], first)) for i, m in enumerate(names)}
    ends = np.append(first, len(o))
    return {int(bid[o[a]]): ({m: r[a:e].astype(np.int64) for m, (r, _) in per.items()}, {m: float(t[i]) for m, (_, t) in per.items()}) for i, (a, e) in enumerate(zip(ends, ends[1:]))}


def sizes(c: Counted, models: dict[str, Mixed]) -> DataFrame:
    """(model, n_params, n_bytes): what each model would hold, as CountModel tells of itself."""
    n, top = c.n, c.order
    level0 = c.rows.sparkSession.sparkContext.broadcast(c.level0)

    def held(table):
        here, rows, own = table.column("bucket")[0].as_py(), [], _sorted_out(table)
        for name, m in models.items():
            got = _levels(own, m.parts, level0.value, top)
            for k in range(m.order + 1):
                ctx = got[k][0]
                ctx = ctx[_mix(ctx) % n == here] if k == 1 else ctx[: len(ctx) * (here == 0)] if k == 0 else ctx
                rows.append((name, len(ctx), len(np.unique(ctx))))
        return pa.table({x: list(y) for x, y in zip(("model", "tokens", "contexts"), zip(*rows))}, pa.schema([("model", pa.string()), ("tokens", pa.int64()), ("contexts", pa.int64())]))

    every = c.rows.where("bucket >= 0").unionByName(c.rows.where("bucket = -1").limit(1).withColumn("bucket", F.lit(0)))
    t = every.groupBy("bucket").applyInArrow(held, "model string, tokens long, contexts long").groupBy("model").agg(F.sum("tokens").alias("n_params"), F.sum("contexts").alias("_c"))
    order = F.create_map(*(F.lit(x) for name, m in models.items() for x in (name, m.order)))
    return t.select("model", "n_params", (12 * F.col("n_params") + 16 * F.col("_c") + 8 * (order[F.col("model")] + 1)).alias("n_bytes"))
