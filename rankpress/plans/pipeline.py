"""End-to-end pipelines: texts to frames and back, and the grid of evaluations.

One Arrow pass does all of a block's work: tokens, ranks, serialised ranks, stock codec. Blocks are independent, so compressing
and decompressing are narrow; only putting a document's blocks together again shuffles.
"""

from __future__ import annotations

import secrets
import time
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.codecs import CODECS
from ..functions.predictors import IdentityRanker, rollout_ranks, rollout_tokens
from ..functions.serializers import SERIALIZERS
from ..operators import buckets
from ..operators.buckets import Counted, Mixed
from ..operators.corpus import blocks
from ..sources.tables import cut

FRAME = "run long, row long, doc_id long, block int, codec string, serializer string, model_id string, tokenizer_id string, flags int, n_chars int, n_bytes int, n_tokens int, seed binary, payload binary, crc32 long"
SEEDED, RAW, VERIFIED = 1, 2, 4
TOGETHER = 256  # blocks that a network ranks in step


def _emit(schema: str, rows: list[tuple]) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "int": pa.int32(), "string": pa.string(), "binary": pa.binary(), "double": pa.float64(), "boolean": pa.bool_()}
    fields = [f.split() for f in schema.split(", ")]
    cols = list(zip(*rows)) if rows else [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(cols, fields)], names=[n for n, _ in fields])


def compress(df: DataFrame, tokenizer=None, model=None, serializer: str = "dotted", codec: str = "gzip", mode: str = "individual", k: int = 8, sample_seed: int | None = None, seed_mode: str = "padded", context_size: int = 100, verify: bool = False, fallback: bool = False, block: int = 10_000) -> DataFrame:
    """Frames of the texts of df (doc_id, text); without a model, the codec alone on raw text.

    seed_mode verbatim keeps the first context_size tokens as they are in the frame's seed and ranks the rest. verify decodes at
    once and stores the raw text, packed, where it differs; fallback stores whichever of the two is shorter. A null text
    gives a frame with a null payload. run and row name the row of df that a frame belongs to: doc_id may be null or repeat.
    """
    pack = CODECS[codec]
    ser = SERIALIZERS[serializer][0]
    held = df.sparkSession.sparkContext.broadcast((tokenizer, model))
    names = (codec, serializer if model else "", model.model_id if model else "", tokenizer.name if tokenizer else "")

    def one(run, row, doc, no, text, packed=None):
        tok, m = held.value
        if text is None:
            return (run, row, doc, no, *names, 0, 0, 0, 0, None, None, None)
        raw = text.encode("utf-8", "surrogatepass")
        flags, seed, n = 0, b"", 0
        if m is None:
            payload = pack.encode(raw) if packed is None else packed
        else:
            ids = tok.encode(text)
            n, lead = len(ids), min(len(ids), context_size) if seed_mode == "verbatim" else 0
            ranks = rollout_ranks(m, ids, k, sample_seed) if mode == "batch" else m.ranks(ids)
            if lead:
                flags, seed = SEEDED, np.asarray(ids[:lead], "<u4").tobytes()
            payload = pack.encode(ser(ranks[lead:]))
        if model is not None and (verify or fallback):
            flags |= VERIFIED if verify else 0
            plain = pack.encode(raw)
            back = _decode(tok, m, pack, serializer, mode, k, sample_seed, flags, seed, payload) if verify else text
            if back != text or (fallback and len(plain) < len(payload) + len(seed)):
                flags, seed, payload = flags & ~SEEDED | RAW, b"", plain
        return (run, row, doc, no, *names, flags, len(text), len(raw), n, seed, payload, zlib.crc32(raw))

    def run(batches):
        for b in batches:
            rows, ready = list(zip(*(b.column(i).to_pylist() for i in range(5)))), {}
            if model is None and hasattr(pack, "encode_many"):  # the batch's blocks in step
                plain = [i for i, r in enumerate(rows) if r[4] is not None]
                ready = dict(zip(plain, pack.encode_many([rows[i][4].encode("utf-8", "surrogatepass") for i in plain])))
            yield _emit(FRAME, [one(*r, ready.get(i)) for i, r in enumerate(rows)])

    d = df.select(*_identity(df), F.col("doc_id").cast("long").alias("doc_id"), "text")
    return blocks(d, block).select("run", "row", "doc_id", "block", "text").mapInArrow(run, FRAME)


def _identity(df: DataFrame) -> tuple:
    """(run, row): two numbers that no other row has. Rows of a stream get both from a fresh identifier, since the numbers of
    rows begin anew in each of its batches; rows of a table are numbered, under a number for this call."""
    if df.isStreaming:
        name = F.expr("uuid()")
        return F.xxhash64(name).alias("run"), F.xxhash64(F.lit(1), name).alias("row")
    return F.lit(secrets.randbits(63)).cast("long").alias("run"), F.monotonically_increasing_id().alias("row")


def _decode(tok, m, pack, serializer, mode, k, sample_seed, flags, seed, payload) -> str:
    data = pack.decode(payload)
    if m is None or flags & RAW:
        return data.decode("utf-8", "surrogatepass")
    ranks = SERIALIZERS[serializer][1](data)
    if flags & SEEDED:
        lead = np.frombuffer(seed, "<u4").astype(np.int32)
        head = rollout_ranks(m, lead, k, sample_seed) if mode == "batch" else m.ranks(lead)
        ranks = np.concatenate([head, ranks])
    return tok.decode(rollout_tokens(m, ranks, k, sample_seed) if mode == "batch" else m.tokens(ranks))


def decompress(frames: DataFrame, tokenizer=None, model=None, mode: str = "individual", k: int = 8, sample_seed: int | None = None) -> DataFrame:
    """(doc_id, text) of frames, a row for each row that was compressed. Frames of another model are refused, and a checksum guards
    each block."""
    parts_ = "doc_id long, block int, text string"
    held = frames.sparkSession.sparkContext.broadcast((tokenizer, model))

    def run(batches):
        tok, m = held.value
        for b in batches:
            rows, all_ = [], b.to_pylist()
            ready = {}
            if hasattr(m, "tokens_many") and mode == "individual":  # a network decodes the batch's blocks in step
                plain = [i for i, r in enumerate(all_) if r["payload"] is not None and r["model_id"] == m.model_id and not r["flags"] & (RAW | SEEDED)]
                ranks = [SERIALIZERS[all_[i]["serializer"]][1](CODECS[all_[i]["codec"]].decode(all_[i]["payload"])) for i in plain]
                ready = {i: tok.decode(t) for i, t in zip(plain, m.tokens_many(ranks))}
            for name in {r["codec"] for r in all_ if hasattr(CODECS[r["codec"]], "decode_many")}:
                plain = [i for i, r in enumerate(all_) if r["codec"] == name and r["payload"] is not None and not r["model_id"]]
                ready |= {i: x.decode("utf-8", "surrogatepass") for i, x in zip(plain, CODECS[name].decode_many([all_[i]["payload"] for i in plain]))}
            for i, r in enumerate(all_):
                if r["payload"] is None:
                    rows.append((r["run"], r["row"], r["doc_id"], r["block"], None))
                    continue
                if r["model_id"] and (m is None or m.model_id != r["model_id"]):
                    raise ValueError(f"frame of model {r['model_id']}, decoder has {m.model_id if m else 'none'}")
                text = ready[i] if i in ready else _decode(tok, m if r["model_id"] else None, CODECS[r["codec"]], r["serializer"], mode, k, sample_seed, r["flags"], r["seed"], r["payload"])
                if zlib.crc32(text.encode("utf-8", "surrogatepass")) != r["crc32"]:
                    raise ValueError(f"checksum of document {r['doc_id']}, block {r['block']}")
                rows.append((r["run"], r["row"], r["doc_id"], r["block"], text))
            yield _emit(f"run long, row long, {parts_}", rows)

    parts = frames.mapInArrow(run, f"run long, row long, {parts_}")
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("block", "text"))), lambda x: x["text"]), "")
    return parts.groupBy("run", "row").agg(F.first("doc_id").alias("doc_id"), F.when(F.count("text") > 0, text).alias("text")).select("doc_id", "text")


def write_frames(frames: DataFrame, path: str) -> None:
    """Frames by model, in the order of documents within files, so that one document is one row group's business."""
    frames.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "block").write.mode("overwrite").partitionBy("model_id").parquet(path)


GRID = "grp string, doc_id long, block int, model string, tokenizer string, serializer string, codec string, mode string, raw_bytes long, raw_chars long, packed_bytes long, n_tokens long, top1 double, rank_entropy double, encode_ms double"


def evaluate(df: DataFrame, models: dict, tokenizers: dict, serializers=("dotted",), codecs=("gzip",), raw=("gzip",), modes=(("individual", 1),), only: str | None = None, counted: Counted | None = None) -> DataFrame:
    """Sizes and times for every block of df (doc_id, block, text, grp) under every setting, in one pass.

    models: name -> (predictor, tokenizer's name); raw: codecs on the text itself (model 'raw'). only: a column of df; a
    block is run under the models whose names begin with its value and a colon, and under those without a colon. Ranks are
    computed once for each model and mode and shared by all serializers and codecs. Predictors of kind Mixed are mixes of `counted`: no
    task gets them whole, their ranks come from operators.buckets and meet the blocks in small groups. A network's encode_ms is a block's share,
    by tokens, of the time that the blocks ranked with it take together.
    """
    far = {n: m for n, (m, _) in models.items() if isinstance(m, Mixed)}
    near = {n: m for n, m in models.items() if n not in far}
    held = df.sparkSession.sparkContext.broadcast((near, {t: tokenizers[t] for t in {t for _, t in near.values()}}))
    pick = F.col(only).cast("string") if only else F.lit("")

    def measured(doc, no, text, grp, want, ready):
        ms, toks = held.value
        data = text.encode("utf-8", "surrogatepass")
        for c in raw:
            t = time.perf_counter()
            size = len(CODECS[c].encode(data))
            yield (grp, doc, no, "raw", "", "", c, "", len(data), len(text), size, 0, None, None, (time.perf_counter() - t) * 1e3)
        ids = {n: tok.encode(text) for n, tok in toks.items()}
        for name, (m, tok) in models.items():
            if ":" in name and only and name.split(":")[0] != want:
                continue
            for mode, k in modes:
                if mode == "individual" and ready and name in ready[0]:
                    ranks, spent = ready[0][name], ready[1][name]
                elif name in far:
                    ranks, spent = np.zeros(0, np.int64), 0.0
                else:
                    m = ms[name][0]
                    t = time.perf_counter()
                    ranks = rollout_ranks(m, ids[tok], k) if mode == "batch" else m.ranks(ids[tok])
                    spent = (time.perf_counter() - t) * 1e3
                _, n = np.unique(ranks, return_counts=True)
                p = n / max(1, len(ranks))
                top1 = float((ranks == 0).mean()) if len(ranks) else None
                for s in serializers:
                    body = SERIALIZERS[s][0](ranks)
                    for c in codecs:
                        t = time.perf_counter()
                        size = len(CODECS[c].encode(body))
                        ms_ = spent + (time.perf_counter() - t) * 1e3
                        yield (grp, doc, no, name, tok, s, c, f"{mode}{k}" if mode == "batch" else mode, len(data), len(text), size, len(ranks), top1, float(-(p * np.log2(p)).sum()), ms_)

    models = {n: (None, t) for n, (_, t) in models.items()}  # what `measured` carries along
    names = list(far)

    def together(rows):
        """(row, ranks and times by model) for each row: networks take many texts in step, and their time is shared out by tokens."""
        ms, toks = held.value
        nets = {n: (m, toks[t]) for n, (m, t) in ms.items() if hasattr(m, "ranks_many") and not (only and ":" in n)} if any(mode == "individual" for mode, _ in modes) else {}
        for at in range(0, len(rows), TOGETHER):
            part = rows[at : at + TOGETHER]
            ready, known = [({}, {}) for _ in part], {}
            for n, (m, tok) in nets.items():
                if (same := (m.model_id, tok.name)) not in known:  # equal networks rank alike
                    t = time.perf_counter()
                    got = m.ranks_many([tok.encode(r[2]) for r in part])
                    known[same] = got, (time.perf_counter() - t) * 1e3 / max(1, sum(map(len, got)))
                got, each = known[same]
                for (ranks, spent), x in zip(ready, got):
                    ranks[n], spent[n] = x, each * len(x)
            yield from zip(part, ready)

    def run(batches):
        for b in batches:
            rows = [r for r in zip(*(b.column(i).to_pylist() for i in range(5))) if r[2] is not None]
            yield _emit(GRID, [x for r, ready in together(rows) for x in measured(*r, ready)])

    def finish(texts, ranked):
        ready = buckets.by_block(ranked, names)
        return pa.Table.from_batches([_emit(GRID, [x for *r, bid in zip(*(texts.column(i).to_pylist() for i in range(6))) for x in measured(*r, ready.get(bid))])])

    d = df.select(F.col("doc_id").cast("long"), "block", "text", F.col("grp").cast("string"), pick.alias("want"))
    if not far:
        return d.mapInArrow(run, GRID)
    if any(mode == "batch" for mode, _ in modes):
        raise ValueError("tokens ahead need a model that is sent to tasks")
    d = cut(d.where("text is not null").withColumn("bid", F.monotonically_increasing_id())).withColumn("gid", F.expr(f"bid div {buckets.GROUP}"))
    own = {t for n, t in models.items() if n in far for t in t[1:]}
    r = buckets.ranks(d, counted, far, tokenizers[own.pop()])
    return d.groupBy("gid").cogroup(r.groupBy("gid")).applyInArrow(finish, GRID)


def ids_model(vocab_size: int):
    """Tokens without prediction, for the ablation."""
    return IdentityRanker(vocab_size)
