"""The experiments on the given tables. Each returns a tidy table; names of groups stand in for authors and languages.

Documents are split by clusters of near copies; models see `train`, choices were made on `valid`, reports read `test`. All blocks of
the whole side are used. The flagship tokenizer has 16,384 pieces and the flagship model two tokens of context.

Every experiment takes a Setting. FULL is the experiment itself. EXACT is the same run over code points, one symbol of context and stored
sizes, without times: all of it can be stated in SQL, and plans.exact does so, query by query.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from ..functions.codecs import BASELINES, EXTRA
from ..functions.predictors import AdaptiveRanker, CountModel
from ..functions.serializers import SERIALIZERS
from ..functions.tokenizers import tokenizer
from ..operators import buckets, corpus, metrics, training
from ..operators.buckets import Mixed
from ..sources.tables import cut, swept, table
from . import pipeline

TOKENS, ORDER = "bpe16384", 2
QUERIES: dict = {}
SQL: dict[str, str] = {}
_kept: dict = {}


@dataclass(frozen=True)
class Setting:
    """How an experiment runs: tokens; context lengths of the flagship and of the ladder's top; second stages; all or what SQL can state."""

    tokens: str = TOKENS
    order: int = ORDER
    top: int = 3
    codecs: tuple = ("gzip", "brotli")
    serializers: tuple = ("dotted",)
    exact: bool = False

    @property
    def tok(self):
        return tokenizer(self.tokens)


FULL = Setting()
EXACT = Setting("char", 1, 1, ("raw",), ("dotted",), True)


def workload(f):
    QUERIES[f.__name__] = f
    return f


def _version(spark, d) -> tuple:
    """Number, size and newest time of the files of documents: what is kept for a folder goes when they change."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", True).load(f"{d}/documents.parquet").select("path", "length", "modificationTime")
    return tuple(files.agg(F.count("*"), F.sum("length"), F.max(F.unix_micros("modificationTime"))).first())


def _once(spark, d, name, make):
    """Splits and models are made once a session, folder and version of its documents."""
    key = (spark.sparkContext.applicationId, d, _version(spark, d), name)
    if key not in _kept:
        if len(_kept) > 80:
            _kept.clear()
        _kept[key] = make()
    return _kept[key]


def documents(spark, d) -> DataFrame:
    """documents with cluster_id and split, checkpointed."""
    return _once(spark, d, "documents", lambda: swept(cut(corpus.split(table(spark, d, "documents").where("text is not null")))))


def side(spark, d, name: str, grp="lang") -> DataFrame:
    """Blocks of one side of the split."""
    x = documents(spark, d).where(F.col("split") == name)
    return corpus.blocks(x.select("doc_id", "lang", "source", F.col(grp).cast("string").alias("grp"), "text"))


def _tok(name=TOKENS):
    return tokenizer(name)


def model(spark, d, where: str = "true", tokens: str = TOKENS, order: int = ORDER) -> CountModel:
    """A model of the training documents for which `where` holds."""
    t = _tok(tokens)
    make = lambda: training.collect_models(training.counts(documents(spark, d).where("split = 'train'").where(where), t, order), t.vocab_size, order).get("all") or training.empty(t.vocab_size, order)
    return _once(spark, d, ("model", where, tokens, order), make)


def language_models(spark, d, tokens: str = TOKENS, order: int = ORDER) -> dict[str, CountModel]:
    t = _tok(tokens)
    make = lambda: training.collect_models(training.counts(documents(spark, d).where("split = 'train'"), t, order, domain="lang"), t.vocab_size, order)
    return _once(spark, d, ("languages", tokens, order), make)


def ladder(spark, d, tokens: str = TOKENS, top: int = 3) -> dict[str, CountModel]:
    """S, M, L, XL: contexts of 0, 1, 2 and 3 tokens from the same counts; those up to `top`."""
    m = model(spark, d, tokens=tokens, order=top)
    return {name: training.truncated(m, k, name) for k, name in enumerate(("S", "M", "L", "XL")[: top + 1])}


def _counted(spark, d, tokens: str, order: int) -> buckets.Counted:
    """Counts of the training documents, which stay on the tasks' side."""
    make = lambda: buckets.counted(documents(spark, d).where("split = 'train'").select(F.lit("all").alias("part"), "text"), _tok(tokens), order)
    return _once(spark, d, ("counted", tokens, order), make)


def _rungs(s: Setting) -> dict[str, Mixed]:
    """The ladder as contexts over those counts."""
    return {name: Mixed((("all", 1),), k) for k, name in enumerate(("S", "M", "L", "XL")[: s.top + 1])}


def _climb(spark, d, blocks, s: Setting, models=None, **how) -> DataFrame:
    """The blocks under the ladder, none of whose models is sent to a task."""
    return _run(blocks, models or _rungs(s), s=s, counted=_counted(spark, d, s.tokens, s.top), **how)


def _ladder(spark, d, s: Setting) -> dict[str, CountModel]:
    return ladder(spark, d, s.tokens, s.top)


def _flagship(spark, d, s: Setting, where: str = "true") -> CountModel:
    return model(spark, d, where, s.tokens, s.order)


def _run(blocks, models: dict[str, object], tokens: str = TOKENS, s: Setting = FULL, **how) -> DataFrame:
    tokens = s.tokens if s.exact else tokens
    how = {"codecs": s.codecs, "raw": s.codecs, "serializers": s.serializers} | how
    return pipeline.evaluate(blocks, {n: (m, tokens) for n, m in models.items()}, {tokens: _tok(tokens)}, **how)


KEYS = ["grp", "model", "serializer", "codec", "mode"]


def _report(results: DataFrame, by: list[str], s: Setting) -> DataFrame:
    """The summary; without times and rounded where it is to be stated in SQL."""
    return exactly(metrics.summary(results, by), s)


def exactly(df: DataFrame, s: Setting) -> DataFrame:
    if not s.exact:
        return df
    df = df.drop("encode_ms", "all_ms")
    return df.select(*(F.round(c, 6).alias(c) if t == "double" else c for c, t in df.dtypes))


# ------------------------------------------------------------------ W1 ranks


@workload
def w01_rank_distribution(spark, d, s=FULL):
    """Decay of the rank histogram by language, for byte tokens and for the flagship's."""
    out = None
    for name in ("byte", s.tokens):
        held, t = spark.sparkContext.broadcast(model(spark, d, tokens=name, order=s.order)), _tok(name)

        def run(batches, held=held, t=t):
            for b in batches:
                for grp, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                    r, n = np.unique(held.value.ranks(t.encode(text)), return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array([grp] * len(r), pa.string()), pa.array(r.astype(np.int64)), pa.array(n.astype(np.int64))], names=["grp", "rank", "n"])

        h = side(spark, d, "test").select("grp", "text").mapInArrow(run, "grp string, rank long, n long").groupBy("grp", "rank").agg(F.sum("n").alias("n"))
        fit = metrics.decay_fit(h, ["grp"]).withColumn("tokenizer", F.lit(name))
        out = fit if out is None else out.unionByName(fit)
    return exactly(out, s)


# ------------------------------------------------------------------ W2 speed


@workload
def w02_acceleration(spark, d, s=FULL):
    """Seconds for 10,000 characters, stepwise and vectorised, along the ladder; both must give the same ranks."""
    held, t = spark.sparkContext.broadcast(_ladder(spark, d, s)), s.tok

    def run(batches):
        for b in batches:
            for text in b.column(0).to_pylist():
                ids = t.encode(text)
                rows = []
                for name, m in held.value.items():
                    a = time.perf_counter()
                    x = m.ranks_stepwise(ids)
                    z = time.perf_counter()
                    y = m.ranks_vectorised(ids)
                    rows.append((name, m.n_params, len(text), z - a, time.perf_counter() - z, bool((x == y).all())))
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)], names=["model", "n_params", "chars", "slow", "fast", "same"])

    r = side(spark, d, "test").where("text <> ''").select("text").mapInArrow(run, "model string, n_params long, chars long, slow double, fast double, same boolean")
    per = lambda c: (10_000 * F.sum(c) / F.sum("chars"))
    times = () if s.exact else (per("slow").alias("stepwise_s"), per("fast").alias("vectorised_s"), (F.sum("slow") / F.sum("fast")).alias("speed_up"))
    return r.groupBy("model", "n_params").agg(F.count("*").alias("n"), F.sum("chars").alias("chars"), *times, F.bool_and("same").alias("same"))


# ------------------------------------------------------------------ W3 groups


def _stages(spark, d, s: Setting) -> dict:
    return {"ids": pipeline.ids_model(s.tok.vocab_size), "order0": training.truncated(_flagship(spark, d, s), 0, "order0"), "model": _flagship(spark, d, s)}


@workload
def w03_groups(spark, d, s=FULL):
    """Codec on text, on ids, on ranks without context and on predicted ranks, by language and for English sources.

    Blocks are evaluated once; English ones of the four sources then count in two groups.
    """
    both = F.concat_ws("|", "lang", F.when((F.col("lang") == "en") & F.col("source").isin("src0", "src1", "src2", "src3"), F.col("source")))
    r = _run(side(spark, d, "test").withColumn("grp", both), _stages(spark, d, s), s=s)
    return _report(r.withColumn("grp", F.explode(F.split("grp", "[|]"))), KEYS, s)


def _books(spark, d, size: int = 10_000, most: int = 8) -> DataFrame:
    """The first `most` books of `size` characters of each language's test texts, one block each: the groups of eight works."""
    b = corpus.books(documents(spark, d).where("split = 'test'"), "lang", size).where(F.col("book_no") < most)
    return b.select(F.col("book_no").alias("doc_id"), F.lit(0).alias("block"), "text", F.col("lang").alias("grp"))


@workload
def w03_books(spark, d, s=FULL):
    """The same for groups of eight books of 10,000 characters, and over groups: the mean of groups, of books, and of sizes."""
    r = cut(_run(_books(spark, d), _stages(spark, d, s), s=s))
    means = None
    for how in ("macro", "micro", "pooled"):
        m = metrics.average(r, how, "grp").withColumn("mean_of", F.lit(how))
        means = m if means is None else means.unionByName(m)
    per = metrics.summary(r, KEYS).select(F.lit("group").alias("mean_of"), *KEYS, "n", F.col("ratio_bytes").alias("ratio"))
    return exactly(per.unionByName(means.select("mean_of", F.lit("all").alias("grp"), *KEYS[1:], F.lit(None).cast("long").alias("n"), "ratio")), s)


# ------------------------------------------------------------------ W4 to W7 adaptation


def _gains(results: DataFrame, base: str, variants: dict[str, str], s: Setting = FULL) -> DataFrame:
    """grp, codec, variant, ratio_base, ratio_new, gain_pct: sizes are added up once by group, model and codec; the few sums then
    meet the base's over a window."""
    t = results.groupBy("grp", "model", "serializer", "codec").agg((F.sum("raw_bytes") / F.sum("packed_bytes")).alias("ratio_new"))
    t = t.withColumn("ratio_base", F.max(F.when(F.col("model") == base, F.col("ratio_new"))).over(W.partitionBy("grp", "serializer", "codec")))
    names = F.create_map(*(F.lit(x) for name, v in variants.items() for x in (v, name)))
    t = t.withColumn("variant", F.try_element_at(names, F.col("model"))).where("variant is not null")
    return exactly(t.select("grp", "codec", "variant", "ratio_base", "ratio_new", (100 * (F.col("ratio_new") / F.col("ratio_base") - 1)).alias("gain_pct")), s)


def _base(spark, d, share: int = 25, s: Setting = FULL) -> CountModel:
    """A base that has seen a quarter of the training clusters."""
    return _flagship(spark, d, s, f"{BASE_PART} < {share}")


#: A cluster's place among a hundred parts, by other digits of the digest than the split's.
BASE_PART = "cast(conv(substring(md5(cluster_id), 9, 6), 16, 10) as int) % 100"


def _to_rows(spark, m: CountModel) -> DataFrame:
    cols = [[], [], [], []]
    for k, (keys, first, tokens, counts) in enumerate(m.levels):
        for c, x in zip(cols, (np.full(len(tokens), k, np.int32), np.repeat(keys, np.diff(first)), tokens, counts)):
            c.append(x)
    return spark.createDataFrame(pa.table(dict(zip(("level", "ctx", "token", "cnt"), (pa.array(np.concatenate(c)) for c in cols)))))


def tuned(spark, d, domains: DataFrame, column: str, weight: int = 4, s: Setting = FULL) -> dict[str, CountModel]:
    """The base with `weight` times each domain's counts."""
    own = training.counts(domains, s.tok, s.order, domain=column)
    return training.collect_models(training.merged(_to_rows(spark, _base(spark, d, s=s)), own, weight), s.tok.vocab_size, s.order)


def students(spark, d, domains: DataFrame, column: str, order: int = 1, s: Setting = FULL, deep: bool = False) -> buckets.Counted:
    """Small models that a larger teacher has taught on each domain, as counts of parts in the teacher's buckets; none comes to the driver."""
    teacher = _counted(spark, d, s.tokens, s.top)
    return buckets.distilled(domains.select(F.col(column).alias("part"), "text"), teacher, Mixed((("all", 1),), s.top), s.tok, order, deep)


@workload
def w04_fine_tuning(spark, d, s=FULL):
    """Tuned on French or German, tested on every language: gain over the base in per cent."""
    tr = documents(spark, d).where("split = 'train' and lang in ('fr', 'de')")
    m = tuned(spark, d, tr, "lang", s=s)
    r = _run(side(spark, d, "test"), {"base": _base(spark, d, s=s)} | {f"tuned_{k}": v for k, v in m.items()}, s=s)
    return _gains(r, "base", {f"tuned on {k}": f"tuned_{k}" for k in m}, s)


@workload
def w05_distillation(spark, d, s=FULL):
    """Students of one token of context: taught, trained plainly on the same texts, and the undistilled base of that size."""
    tr = documents(spark, d).where("split = 'train' and lang in ('fr', 'de')")
    named = lambda kind: tr.select(F.concat(F.lit(f"{kind}_"), "lang").alias("part"), "text")
    base = documents(spark, d).where("split = 'train'").where(f"{BASE_PART} < 25").select(F.lit("base").alias("part"), "text")
    taught = students(spark, d, named("taught"), "part", s=s)
    c = buckets.together(buckets.counted(base.unionByName(named("plain")), s.tok, 1, taught.n), taught)
    m = {"base": Mixed((("base", 1),), 1)} | {k: Mixed(((k, 1),), 1) for k in c.level0 if k != "base"}
    r = _run(side(spark, d, "test"), m, s=s, counted=c)
    return _gains(r, "base", {k.replace("_", " on ", 1): k for k in m if k != "base"}, s)


def _order_lines(spark, d, s: Setting) -> DataFrame:
    columns = ["o_orderkey", "o_custkey", "o_orderstatus", *([] if s.exact else ["o_totalprice"]), "o_orderpriority"]
    return corpus.rows_as_text(table(spark, d, "orders"), ["o_orderkey"], columns)


@workload
def w06_style_mismatch(spark, d, s=FULL):
    """Taught on turns of conversations or on order lines, tested on English prose: a negative control."""
    chat = table(spark, d, "conversations").where("role = 'assistant' and text is not null").select(F.lit("conversations").alias("domain"), "text")
    lines = _order_lines(spark, d, s).select(F.lit("orders").alias("domain"), "text")
    base = documents(spark, d).where("split = 'train'").where(f"{BASE_PART} < 25").select(F.lit("base").alias("domain"), "text")
    c = buckets.counted(base.unionByName(chat).unionByName(lines).withColumnRenamed("domain", "part"), s.tok, s.order)
    m = {k: Mixed((("base", 1), (k, 4)), s.order) for k in c.level0 if k != "base"}
    r = _run(side(spark, d, "test").where("lang = 'en'"), {"base": Mixed((("base", 1),), s.order)} | {f"tuned_{k}": v for k, v in m.items()}, s=s, counted=c)
    return _gains(r, "base", {f"tuned on {k}": f"tuned_{k}" for k in m}, s)


@workload
def w07_no_shift(spark, d, s=FULL):
    """Tuned on English texts of one source, tested on several sources: sources differ in nothing, so gains should be alike."""
    m = tuned(spark, d, documents(spark, d).where("split = 'train' and lang = 'en' and source = 'src0'"), "source", s=s)
    r = _run(side(spark, d, "test", "source").where("lang = 'en'"), {"base": _base(spark, d, s=s)} | {f"tuned_{k}": v for k, v in m.items()}, s=s)
    return _gains(r, "base", {f"tuned on {k}": f"tuned_{k}" for k in m}, s)


# ------------------------------------------------------------------ W8 to W11 sizes and codecs


@workload
def w08_model_sizes(spark, d, s=FULL):
    return _report(_climb(spark, d, side(spark, d, "test"), s), KEYS, s)


@workload
def w08_books(spark, d, s=FULL):
    """Sizes on groups of eight books."""
    return _report(_climb(spark, d, _books(spark, d), s), KEYS, s)


@workload
def w08_amortised(spark, d, s=FULL):
    """The ladder's pooled ratios, and what they come to when the model's bytes are charged to the test side."""
    sizes = buckets.sizes(_counted(spark, d, s.tokens, s.top), _rungs(s))
    return exactly(metrics.amortised(_climb(spark, d, side(spark, d, "test"), s, raw=()), sizes), s)


@workload
def w08_monotonicity(spark, d, s=FULL):
    """Steps down in ratio and in time along the ladder."""
    r = cut(_climb(spark, d, side(spark, d, "test"), s, codecs=s.codecs[:1], raw=()))
    t = metrics.summary(r, ["grp", "model"]).withColumn("place", F.array_position(F.array(*map(F.lit, ("S", "M", "L", "XL"))), F.col("model")))
    a = metrics.monotonicity(t, "place", "ratio_bytes", ["grp"]).withColumn("measure", F.lit("ratio"))
    return a if s.exact else a.unionByName(metrics.monotonicity(t, "place", "encode_ms", ["grp"]).withColumn("measure", F.lit("time")))


@workload
def w09_per_file(spark, d, s=FULL):
    """The longest test document of each language: best ratio and size, time, entropy, tokens."""
    x = documents(spark, d).where("split = 'test'").groupBy("lang").agg(F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("doc_id"))
    b = side(spark, d, "test").join(F.broadcast(x.select("doc_id")), "doc_id", "left_semi").select("doc_id", "lang", "source", "grp", "block", "text")
    t = metrics.summary(_run(b, _ladder(spark, d, s), s=s), ["grp", "model", "codec"])
    net = lambda c: F.when(F.col("model") != "raw", F.col(c))
    best = t.groupBy("grp", "codec").agg(
        F.max(net("ratio_bytes")).alias("best_ratio"), F.max_by(net("model"), F.struct(net("ratio_bytes"), net("model"))).alias("best_model"), F.min(net("bpc")).alias("best_bpc"), F.sum(net("encode_ms")).alias("all_ms"),
        F.max(net("n_tokens")).alias("n_tokens"), F.max_by(net("rank_entropy"), F.struct(net("ratio_bytes"), net("model"))).alias("rank_entropy"), F.max(F.when(F.col("model") == "raw", F.col("ratio_bytes"))).alias("raw_ratio"),
    )
    return exactly(best, s)


def _long(spark, d, size: int, lang: str = "en") -> DataFrame:
    """A language's test books of `size` characters as documents of one block; the last may be shorter."""
    b = corpus.books(documents(spark, d).where("split = 'test'"), "lang", size).where(F.col("lang") == lang)
    return b.select(F.col("book_no").alias("doc_id"), F.lit(0).alias("block"), "text", F.col("lang").alias("grp"))


@workload
def w10_codecs_on_a_book(spark, d, s=FULL):
    return _report(_climb(spark, d, _long(spark, d, 100_000), s, dict([list(_rungs(s).items())[-1]])), KEYS, s)


@workload
def w10_codec_gain(spark, d, s=FULL):
    """What the second codec gains over the first on the same ranks, by model and group."""
    if s.exact:  # one stored size for each of two serializers stands in for the two codecs
        s = Setting(s.tokens, s.order, s.top, s.codecs, ("dotted", "varint"), True)
        return exactly(metrics.codec_gain(_climb(spark, d, side(spark, d, "test"), s, raw=()), "dotted", "varint", "serializer"), s)
    return metrics.codec_gain(_climb(spark, d, side(spark, d, "test"), s, raw=()), "gzip", "brotli")


@workload
def w11_seen_in_part(spark, d, s=FULL):
    """Students of English books that are held out, and of books among which the tested ones are: what a leak is worth."""
    english, teacher, order = documents(spark, d).where("lang = 'en'"), _counted(spark, d, s.tokens, s.top), min(2, s.order)
    named = lambda part, where: english.where(where).select(F.lit(part).alias("part"), "text")
    taught = students(spark, d, named("student", "split = 'train'").unionByName(named("student_leak", "split in ('train', 'test')")), "part", order, s, s.top > 1)
    base = documents(spark, d).where("split = 'train'").where(f"{BASE_PART} < 25").select(F.lit("base").alias("part"), "text")
    c = buckets.together(teacher, buckets.counted(base, s.tok, s.order, teacher.n, s.top > 1), taught)
    m = {"base": Mixed((("base", 1),), s.order), "teacher": Mixed((("all", 1),), s.top)} | {k: Mixed(((k, 1),), order) for k in ("student", "student_leak")}
    return _report(_run(_long(spark, d, 28_851), m, s=s, counted=c), KEYS, s)


# ------------------------------------------------------------------ W12, W13 languages


def _with_far(b: DataFrame) -> DataFrame:
    """The blocks, and the English ones once more in a script that no model of Latin letters has seen."""
    return b.unionByName(corpus.shift_script(b.where("lang = 'en'")).withColumn("grp", F.lit("en shifted")))


def _pieces(spark, d, size: int = 100_000) -> DataFrame:
    """Test books of `size` characters of every language; the last of a language may be shorter."""
    b = corpus.books(documents(spark, d).where("split = 'test'"), "lang", size)
    return b.select(F.col("book_no").alias("doc_id"), F.lit(0).alias("block"), "text", "lang", F.col("lang").alias("grp"))


@workload
def w12_foreign_languages(spark, d, s=FULL):
    """An English model on every language, and on English in a script it has never seen."""
    return _report(_run(_with_far(side(spark, d, "test")), {"english": _flagship(spark, d, s, "lang = 'en'")}, s=s), KEYS, s)


@workload
def w12_long(spark, d, s=FULL):
    """The same on pieces of 100,000 characters."""
    return _report(_run(_with_far(_pieces(spark, d)), {"english": _flagship(spark, d, s, "lang = 'en'")}, s=s), KEYS, s)


def _own(spark, d, blocks, s: Setting) -> DataFrame:
    """The blocks under the model of their own language, and under the English one."""
    train = documents(spark, d).where("split = 'train'")
    parts = train.select(F.col("lang").alias("part"), "text").unionByName(corpus.shift_script(train.where("lang = 'en'")).select(F.lit("en shifted").alias("part"), "text"))
    c = _once(spark, d, ("counted by language", s.tokens, s.order), lambda: buckets.counted(parts, s.tok, s.order))
    models = {f"{k}:own": Mixed(((k, 1),), s.order) for k in c.level0} | {"english": Mixed((("en", 1),), s.order)}
    return _run(blocks, models, s=s, only="grp", counted=c)


@workload
def w13_language_models(spark, d, s=FULL):
    """Each language under its own model, the shifted script too."""
    return _report(_own(spark, d, _with_far(side(spark, d, "test")), s), KEYS, s)


@workload
def w13_long(spark, d, s=FULL):
    """The same on pieces of 100,000 characters."""
    return _report(_own(spark, d, _with_far(_pieces(spark, d)), s), KEYS, s)


# ------------------------------------------------------------------ W14 to W17 ablations


@workload
def w14_baselines(spark, d, s=FULL):
    """Every classical codec on the raw blocks of all documents, pages and turns."""
    docs = corpus.blocks(table(spark, d, "documents").select("doc_id", F.lit("documents").alias("grp"), "text"))
    pages = corpus.blocks(table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), F.lit("pages").alias("grp"), F.col("html").alias("text")))
    turns = corpus.blocks(table(spark, d, "conversations").select(F.col("conv_id").alias("doc_id"), F.lit("conversations").alias("grp"), "text"))
    return _report(pipeline.evaluate(docs.unionByName(pages).unionByName(turns), {}, {}, raw=s.codecs if s.exact else BASELINES + EXTRA), ["grp", "codec"], s)


@workload
def w15_second_stage(spark, d, s=FULL):
    """Ranks under every serializer and codec."""
    sers, codecs = (("dotted", "varint"), s.codecs) if s.exact else (tuple(SERIALIZERS), BASELINES[1:])
    return _report(_run(side(spark, d, "test"), {"model": _flagship(spark, d, s)}, s=s, serializers=sers, codecs=codecs, raw=codecs).withColumn("grp", F.lit("all")), KEYS, s)


@workload
def w15_tokenizers(spark, d, s=FULL):
    """Byte tokens and vocabularies of several sizes, ids and ranks; one pass for each vocabulary."""
    out = None
    for name in ("byte", "char") if s.exact else ("byte", "bpe512", "bpe1024", "bpe4096", "bpe16384", "bpe50256"):
        both = {f"{name} ids": (pipeline.ids_model(_tok(name).vocab_size), name), f"{name} ranks": (Mixed((("all", 1),), s.order), name)}
        r = pipeline.evaluate(side(spark, d, "test"), both, {name: _tok(name)}, serializers=("dotted", "varint"), codecs=s.codecs, raw=(), counted=_counted(spark, d, name, s.order))
        out = r if out is None else out.unionByName(r)
    return _report(out.withColumn("grp", F.lit("all")), KEYS, s)


@workload
def w16_batch_inference(spark, d, s=FULL):
    """k tokens ahead: the share of rank 0 falls as k grows, and so does the number of predictor calls, one for k tokens."""
    r = _run(side(spark, d, "test"), {"model": _flagship(spark, d, s)}, s=s, raw=(), modes=(("individual", 1), *(("batch", k) for k in (1, 2, 4, 8, 16))))
    k = F.coalesce(F.expr("try_cast(regexp_extract(mode, '[0-9]+', 0) as int)"), F.lit(1))
    r = cut(r.withColumns({"grp": F.lit("all"), "calls": F.ceil(F.col("n_tokens") / k)}))
    return _report(r, KEYS, s).join(F.broadcast(r.groupBy("mode").agg(F.sum("calls").alias("calls"))), "mode")


@workload
def w17_context_size(spark, d, s=FULL):
    """Contexts of 0 to 3 tokens, static, and adaptive from the block alone."""
    tokens = s.tokens if s.exact else "byte"
    m = {f"static{k}": Mixed((("all", 1),), k) for k in range(s.top + 1)} | ({} if s.exact else {f"adaptive{k}": AdaptiveRanker(256, k) for k in range(4)})
    return _report(_run(side(spark, d, "test"), m, tokens=tokens, s=s, counted=_counted(spark, d, tokens, s.top)).withColumn("grp", F.lit("all")), KEYS, s)


# ------------------------------------------------------------------ W18 to W21


@workload
def w18_factors(spark, d, s=FULL):
    """What a block's ratio goes with, by label of quality."""
    r = _run(side(spark, d, "test").where("text <> ''"), {"model": _flagship(spark, d, s)}, s=s, raw=())
    q = table(spark, d, "labels").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    r = metrics.factors(r.join(q, "doc_id", "left"), ["quality", "codec"])
    return exactly(r.drop("with_fertility") if s.exact else r, s)  # a token is a character there


@workload
def w19_input_length(spark, d, s=FULL):
    """Books of 1,000 to 100,000 characters, evaluated in one pass."""
    b = None
    for size in (1_000, 3_000, 10_000, 30_000, 100_000):
        x = _long(spark, d, size).where(F.length("text") == size).withColumn("grp", F.lit(str(size)))
        b = x if b is None else b.unionByName(x)
    return _report(_run(b, {"model": _flagship(spark, d, s)}, s=s), KEYS, s)


@workload
def w20_not_prose(spark, d, s=FULL):
    """Markup, order lines, JSON and quantised vectors."""
    pages = table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), F.lit("html").alias("grp"), F.col("html").alias("text"))
    lines = _order_lines(spark, d, s).select(F.col("block").alias("doc_id"), F.lit("order lines").alias("grp"), "text")
    props = table(spark, d, "events").groupBy(F.expr("event_id div 500").alias("doc_id")).agg(F.array_join(F.array_sort(F.collect_list("props")), "\n").alias("text")).select("doc_id", F.lit("json").alias("grp"), "text")
    vecs = table(spark, d, "embeddings").select(F.col("vec_id").alias("doc_id"), F.lit("vectors").alias("grp"), F.array_join(F.transform("embedding", lambda x: F.chr(F.greatest(F.lit(1), F.least(F.lit(126), (x * 100 + 64).cast("int"))))), "").alias("text"))
    b = pages.unionByName(lines).unionByName(props)
    return _report(_run(corpus.blocks(b if s.exact else b.unionByName(vecs)), {"prose model": _flagship(spark, d, s)}, s=s), KEYS, s)


@workload
def w21_contamination(spark, d, s=FULL):
    """Documents that hold benchmark passages, under models trained with and without the benchmark."""
    from .relational import contamination_exact

    hit = cut(contamination_exact(spark, d).withColumn("leaked", F.lit(True)))
    x = documents(spark, d).join(F.broadcast(hit) if hit.count() < 1 << 20 else hit, "doc_id", "left").withColumn("grp", F.when(F.col("leaked"), "leaked").otherwise("clean"))
    b = corpus.blocks(x.where("split = 'test' or leaked").select("doc_id", "grp", "text"))
    clean = x.where("split = 'train' and leaked is null").select("text")
    bench = table(spark, d, "benchmark").select("text")
    fit = lambda df: training.collect_models(training.counts(df, s.tok, s.order), s.tok.vocab_size, s.order)["all"]
    return _report(_run(b, {"without": fit(clean), "with": fit(clean.unionByName(bench))}, s=s), KEYS, s)


@workload
def checkpoint_selection(spark, d, s=FULL):
    """Tuning weights as checkpoints: the best on `valid`, reported on `test`."""
    fr = documents(spark, d).where("split = 'train' and lang = 'fr'")
    m = {f"w{w}": tuned(spark, d, fr, "lang", w, s)["fr"] for w in (0, 1, 4, 16)}
    both = side(spark, d, "valid").withColumn("grp", F.lit("valid")).unionByName(side(spark, d, "test").withColumn("grp", F.lit("test"))).where("lang = 'fr'")
    r = _run(both, m, s=s, codecs=s.codecs[:1], raw=())
    ratio = lambda g: (F.sum(F.when(F.col("grp") == g, F.col("raw_bytes"))) / F.sum(F.when(F.col("grp") == g, F.col("packed_bytes")))).alias(g)
    t = r.groupBy("model").agg(ratio("valid"), ratio("test"))
    return exactly(t.withColumn("chosen", F.col("valid") == F.max("valid").over(W.partitionBy())), s)


# ------------------------------------------------------------------ round trips


def _repeated(spark, d) -> DataFrame:
    """doc_id, text of documents, and once more with ids that collide, with null ids, and repeated as they are."""
    x = table(spark, d, "documents").select("doc_id", "text")
    y = x.select(F.expr("doc_id div 3").alias("doc_id"), "text").where("doc_id % 2 = 0")
    return x.unionAll(y).unionAll(x.where("doc_id % 5 = 0")).unionAll(x.where("doc_id % 7 = 0").withColumn("doc_id", F.lit(None).cast("long")))


@workload
def roundtrip_repeated_rows(spark, d):
    """Rows whose ids repeat, collide or are null, back as a multiset."""
    back = pipeline.decompress(pipeline.compress(_repeated(spark, d), block=700))
    return back.groupBy("doc_id", F.md5("text").alias("digest")).agg(F.count("*").alias("n"))


_AGAIN = "select doc_id, text from documents union all select doc_id // 3, text from documents where (doc_id // 3) % 2 = 0 union all select doc_id, text from documents where doc_id % 5 = 0 union all select null, text from documents where doc_id % 7 = 0"
SQL["roundtrip_repeated_rows"] = f"select doc_id, md5(text) digest, count(*) n from ({_AGAIN}) group by doc_id, md5(text)"


@workload
def split_by_cluster(spark, d):
    """The split over rows whose ids repeat or are null: rows of each id, cluster and side."""
    return corpus.split(_repeated(spark, d)).groupBy("doc_id", "cluster_id", "split").agg(F.count("*").alias("n"))


def _trip(codec: str):
    def run(spark, d):
        x = table(spark, d, "documents").select("doc_id", "text")
        back = pipeline.decompress(pipeline.compress(x, codec=codec))
        return back.select("doc_id", F.md5("text").alias("digest"))

    return run


for _c in BASELINES + EXTRA:
    QUERIES[f"roundtrip_{_c}"] = _trip(_c)
    SQL[f"roundtrip_{_c}"] = "select doc_id, md5(text) digest from documents"


def _predicted(mode: str, seed_mode: str = "padded", order: int = ORDER, adaptive: bool = False):
    def run(spark, d):
        x = table(spark, d, "documents").select("doc_id", "text")
        t = _tok() if not adaptive else _tok("byte")
        m = AdaptiveRanker(256, 2) if adaptive else model(spark, d, order=order)
        f = pipeline.compress(x, t, m, serializer="varint", codec="gzip", mode=mode, k=4, seed_mode=seed_mode)
        return pipeline.decompress(f, t, m, mode=mode, k=4).select("doc_id", F.md5("text").alias("digest"))

    return run


for _n, _how in {"individual": ("individual",), "batch": ("batch",), "verbatim": ("individual", "verbatim"), "order0": ("individual", "padded", 0), "adaptive": ("individual", "padded", 2, True)}.items():
    QUERIES[f"roundtrip_predictive_{_n}"] = _predicted(*_how)
    SQL[f"roundtrip_predictive_{_n}"] = "select doc_id, md5(text) digest from documents"


def _tokens_trip(spark, d):
    """Every tokenizer's ids decoded again."""
    toks = [tokenizer(n) for n in ("byte", "char", "bpe256", "bpe1024", "bpe16384", "bpe4096-whitespace", "bpe4096-none", "bpe1024+ends")]

    def run(batches):
        for b in batches:
            for i, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                back = [t.decode(t.encode(text)) for t in toks]
                yield pa.RecordBatch.from_arrays([pa.array([i] * len(toks)), pa.array([t.name for t in toks]), pa.array(back)], names=["doc_id", "tokenizer", "text"])

    out = table(spark, d, "documents").where("text is not null").select("doc_id", "text").mapInArrow(run, "doc_id long, tokenizer string, text string")
    return out.groupBy("doc_id", F.md5("text").alias("digest")).agg(F.count("*").alias("n"))


QUERIES["roundtrip_tokenizers"] = _tokens_trip
SQL["roundtrip_tokenizers"] = "select doc_id, md5(text) digest, 8::bigint n from documents"
