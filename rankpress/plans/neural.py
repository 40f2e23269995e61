"""Workloads with trained networks: sizes, tuning, adapters, distillation, the recurrent prior, direct arithmetic coding.

Networks are fitted on the driver on a bounded sample of the training side (the texts with the lowest digests, `chars` characters);
coding runs on every block of the test side, unless a query says otherwise. They are far smaller than published language models and see far less text.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import Window as W, functions as F

from ..functions import neural
from ..operators import metrics
from ..sources.tables import table
from . import pipeline, workloads

TOKENS, STEPS, CONTEXT = "bpe512", 150, 100
#: characters of the sample a network is fitted on; one in so many of the training texts, and at least so many of them.
CHARS = 300_000
#: layers and width of the ladder.
SIZES = {"S": (1, 24), "M": (1, 48), "L": (2, 48), "XL": (2, 64)}
QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def sample(spark, d, where: str = "true", chars: int = CHARS) -> np.ndarray:
    """Ids of a bounded sample of training texts, whatever their lengths: each text of the sample gives at most a twentieth of it, from
    a place that its digest names, so that no long text crowds out the others."""

    def make():
        x = workloads.documents(spark, d).where("split = 'train'").where(where)
        part = chars // 20
        h = F.md5(F.concat_ws("-", F.lit("net"), F.md5("text"), F.col("doc_id").cast("string")))
        begin = 1 + F.pmod(F.conv(F.substring(h, 1, 12), 16, 10).cast("long"), F.greatest(F.lit(1), F.length("text") - part + 1)).cast("int")
        rows = x.select(F.substring("text", begin, F.lit(part)).alias("text"), h.alias("h")).orderBy("h").limit(chars // 200).collect()
        tok, out, n = workloads._tok(TOKENS), [], 0
        for r in rows:
            if n > chars:
                break
            out.append(tok.encode(r.text))
            n += len(r.text)
        return np.concatenate(out) if out else np.zeros(0, np.int32)

    return workloads._once(spark, d, ("sample", where, chars), make)


def trained(spark, d, size: str, where: str = "true", steps: int = STEPS, context: int = CONTEXT) -> neural.Transformer:
    def make():
        layers, dim = SIZES[size]
        m = neural.Transformer(512, layers, dim, context=context)
        m.train(sample(spark, d, where), steps=steps, batch=max(8, 32 * 32 // context))
        return m

    return workloads._once(spark, d, ("net", size, where, steps, context), make)


def copied(m: neural.Transformer) -> neural.Transformer:
    c = neural.Transformer(m.vocab_size, m.layers, m.dim, m.heads, m.context)
    c.p = {k: v.copy() for k, v in m.p.items()}
    return c


def _run(blocks, models, **how):
    return workloads._run(blocks, models, tokens=TOKENS, **how)


@query
def n01_transformer_sizes(spark, d):
    """The ladder of transformers beside ids, a count model on the same sample's side, and the codecs alone."""
    m = {k: trained(spark, d, k).rounded() for k in SIZES}
    m |= {"ids": pipeline.ids_model(512), "counts": workloads.model(spark, d, tokens=TOKENS)}
    r = metrics.summary(_run(workloads.side(spark, d, "test"), m, serializers=("dotted", "varint")), workloads.KEYS)
    sizes = spark.createDataFrame([(k, int(trained(spark, d, k).n_params)) for k in SIZES], "model string, n_params long")
    return r.join(F.broadcast(sizes), "model", "left")


@query
def n02_adaptation(spark, d):
    """English base; tuned on French in full and by adapters; a student taught on French by a teacher that knows it; the
    same student trained plainly. Gains over the base on each language."""

    def make():
        base = trained(spark, d, "M", "lang = 'en'")
        fr = sample(spark, d, "lang = 'fr'")
        full, low = copied(base), copied(base)
        full.train(fr, steps=80, rate=1e-3)
        low.adapt(8)
        low.train(fr, steps=80, rate=3e-3)
        teacher = copied(trained(spark, d, "XL"))
        teacher.train(fr, steps=80, rate=1e-3)
        student, plain = copied(base), copied(full)  # trained plainly is what tuning in full comes to
        student.train(fr, steps=80, rate=1e-3, teacher=teacher)
        return {"base": base, "tuned": full, "adapters": low, "teacher": teacher, "student": student, "plain": plain}

    nets = workloads._once(spark, d, "adaptation", make)
    m = {k: copied(v).rounded() if not v.low else v.rounded() for k, v in nets.items()}
    r = _run(workloads.side(spark, d, "test"), m, raw=())
    return workloads._gains(r, "base", {k: k for k in m if k != "base"})


@query
def n03_recurrent(spark, d):
    """The recurrent prior beside a transformer of about its size."""

    m = {"recurrent": _recurrent(spark, d), "transformer": trained(spark, d, "M").rounded()}
    return metrics.summary(_run(workloads.side(spark, d, "test").where("text <> ''"), m, raw=()), workloads.KEYS)


@query
def n04_direct_arithmetic(spark, d):
    """Bits of direct arithmetic coding, of ranks coded, and the ideal: what ranking loses."""
    from ..functions.codecs import CODECS
    from ..functions.serializers import SERIALIZERS

    tok = workloads._tok(TOKENS)
    held = spark.sparkContext.broadcast(workloads.model(spark, d, tokens=TOKENS))

    def run(batches):
        for b in batches:
            rows = []
            for grp, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                ids = tok.encode(text)
                t = time.perf_counter()
                direct = neural.direct_encode(held.value, ids)
                ms = (time.perf_counter() - t) * 1e3
                ranks = CODECS["arithmetic"].encode(SERIALIZERS["bytes_escape"][0](held.value.ranks(ids)))
                rows.append((grp, len(text.encode()), len(direct), len(ranks), neural.ideal_bits(held.value, ids) / 8, ms))
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)] if rows else [pa.array([], k) for k in (pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64())], names=["grp", "raw", "direct", "ranked", "ideal", "ms"])

    r = workloads.side(spark, d, "test").select("grp", "text").mapInArrow(run, "grp string, raw long, direct long, ranked long, ideal double, ms double")
    over = lambda c: F.sum("raw") / F.sum(c)
    return r.groupBy("grp").agg(F.count("*").alias("n"), over("direct").alias("ratio_direct"), over("ranked").alias("ratio_ranked"), over("ideal").alias("ratio_ideal"), F.avg("ms").alias("ms"))


@query
def n05_context_window(spark, d):
    """Networks of one size with windows of 10 to 100 tokens; the longest also with a window that always is as long as it can be, and with
    one that grows from nothing. Every network ranks every block; those that are short texts count once more by themselves."""
    m = {f"hop{c}": trained(spark, d, "S", context=c).rounded() for c in (10, 25, 50, 100)}
    m |= {f"{window}100": copied(trained(spark, d, "S")).rounded(window) for window in ("growing", "fixed")}
    short = (F.col("block") == 0) & (F.col("raw_chars") < 1500)
    r = _run(workloads.side(spark, d, "test"), m, raw=()).withColumn("texts", F.explode(F.when(short, F.array(F.lit("all"), F.lit("short"))).otherwise(F.array(F.lit("all")))))
    return metrics.summary(r.withColumn("grp", F.lit("all")), ["texts", *workloads.KEYS])


@query
def n06_batch_inference(spark, d):
    """A network that predicts k tokens ahead: rank-0 share, ratio, and predictor calls, with 64 groups to a call."""
    m = {"S": trained(spark, d, "S").rounded()}
    r = _run(workloads.side(spark, d, "test"), m, raw=(), modes=tuple(("batch", k) for k in (1, 2, 4, 8)))
    k = F.regexp_extract("mode", "[0-9]+", 0).cast("int")
    return metrics.summary(r.withColumn("grp", F.lit("all")), workloads.KEYS).withColumn("calls_one_by_one", F.col("n_tokens")).withColumn("groups", F.ceil(F.col("n_tokens") / k))


@query
def n07_checkpoints(spark, d):
    """States along the tuning of a network on French: each one's ratio on `valid`, the best chosen there, and its ratio on `test`."""

    def make():
        m = copied(trained(spark, d, "M", "lang = 'en'"))
        log = m.train(sample(spark, d, "lang = 'fr'"), steps=120, rate=1e-3, every=30)
        out = {}
        for step, _, p in log:
            if p is not None:
                c = copied(m)
                c.p = p
                out[f"step{step}"] = c
        return out

    m = {k: copied(v).rounded() for k, v in workloads._once(spark, d, "checkpoints", make).items()}
    both = workloads.side(spark, d, "valid").withColumn("grp", F.lit("valid")).unionByName(workloads.side(spark, d, "test").withColumn("grp", F.lit("test"))).where("lang = 'fr'")
    r = _run(both, m, raw=(), codecs=("gzip",))
    ratio = lambda g: (F.sum(F.when(F.col("grp") == g, F.col("raw_bytes"))) / F.sum(F.when(F.col("grp") == g, F.col("packed_bytes")))).alias(g)
    t = r.groupBy("model").agg(ratio("valid"), ratio("test"))
    return t.withColumn("chosen", F.col("valid") == F.max("valid").over(W.partitionBy()))


def _trip(net, mode: str = "individual", k: int = 4):
    """Every benchmark text through a network and back."""

    def run(spark, d):
        tok, m = workloads._tok(TOKENS), net(spark, d)
        x = table(spark, d, "benchmark").select(F.col("item_id").alias("doc_id"), "text")
        back = pipeline.decompress(pipeline.compress(x, tok, m, serializer="varint", mode=mode, k=k), tok, m, mode=mode, k=k)
        return back.select(F.col("doc_id").alias("item_id"), F.md5("text").alias("digest"))

    return run


def _recurrent(spark, d):
    def make():
        m = neural.Recurrent(512, 48)
        m.train(sample(spark, d), steps=STEPS)
        return m

    return workloads._once(spark, d, "recurrent", make)


def _french(spark, d):
    def make():
        m = copied(trained(spark, d, "S", "lang = 'en'"))
        m.adapt(8)
        m.train(sample(spark, d, "lang = 'fr'"), steps=60, rate=3e-3)
        return m.rounded()

    return workloads._once(spark, d, "adapters on French", make)


_NETS = {
    "transformer": (lambda spark, d: trained(spark, d, "S").rounded(), "individual"),
    "transformer_ahead": (lambda spark, d: trained(spark, d, "S").rounded(), "batch"),
    "transformer_fixed": (lambda spark, d: copied(trained(spark, d, "S", context=25)).rounded("fixed"), "individual"),
    "transformer_growing": (lambda spark, d: copied(trained(spark, d, "S")).rounded("growing"), "individual"),
    "adapters": (_french, "individual"),
    "recurrent": (_recurrent, "individual"),
}
for _name, (_net, _mode) in _NETS.items():
    QUERIES[f"roundtrip_predictive_{_name}"] = _trip(_net, _mode)
    SQL[f"roundtrip_predictive_{_name}"] = "select item_id, md5(text) digest from benchmark"
