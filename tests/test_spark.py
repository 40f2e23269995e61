import duckdb
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from rankpress.functions.tokenizers import tokenizer
from rankpress.operators import corpus, metrics, training
from rankpress.plans import pipeline, workloads
from rankpress.streaming import streams

ODD = ["", None, "x", "a" * 25_001, "naïve 漢字\r\n🙂", "The cat. The cat.", "y" * 10_000]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(list(enumerate(ODD)), "doc_id long, text string")


def texts(df):
    return {r.doc_id: r.text for r in df.collect()}


def test_blocks_cover_texts(odd):
    b = corpus.blocks(odd).toPandas()
    for i, t in enumerate(ODD):
        own = b[b.doc_id == i].sort_values("block").text.tolist()
        assert ("".join(own) == t and all(len(x) <= 10_000 for x in own)) if t is not None else pd.isna(own[0])


@pytest.mark.parametrize("how", [{}, {"serializer": "varint", "codec": "brotli"}, {"mode": "batch", "k": 3}, {"seed_mode": "verbatim", "context_size": 5}, {"verify": True}, {"fallback": True}])
def test_frames_give_texts_again(spark, odd, how):
    t = tokenizer("byte")
    m = training.collect_models(training.counts(odd, t, 2), t.vocab_size, 2)["all"]
    f = pipeline.compress(odd, t, m, **how)
    back = pipeline.decompress(f, t, m, mode=how.get("mode", "individual"), k=how.get("k", 8))
    assert texts(back) == dict(enumerate(ODD))
    assert metrics.lossless(odd, back).count() == 0


def test_wrong_model_is_refused(spark, odd):
    t = tokenizer("byte")
    a = training.collect_models(training.counts(odd, t, 1), t.vocab_size, 1)["all"]
    b = training.collect_models(training.counts(odd.where("doc_id = 5"), t, 1), t.vocab_size, 1)["all"]
    with pytest.raises(Exception, match="frame of model"):
        pipeline.decompress(pipeline.compress(odd, t, a), t, b).collect()


def test_partitions_do_not_matter(spark, odd):
    t = tokenizer("byte")
    a = training.counts(odd.repartition(1), t, 2).orderBy("level", "ctx", "token").collect()
    assert a == training.counts(odd.repartition(5), t, 2).orderBy("level", "ctx", "token").collect()


def test_tuning_with_weight_zero_is_the_base(spark, odd):
    t = tokenizer("byte")
    base = training.counts(odd, t, 1).where("domain = 'all'")
    own = training.counts(odd.where("doc_id = 5"), t, 1)
    m = training.merged(base, own, 0).orderBy("level", "ctx", "token").drop("domain").collect()
    assert m == base.orderBy("level", "ctx", "token").drop("domain").collect()


def test_books_are_the_texts_in_order(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    b = corpus.books(d, "lang").orderBy("lang", "book_no").toPandas()
    p = d.toPandas().sort_values("doc_id")
    for lang, g in b.groupby("lang"):
        assert "".join(g.text) == "".join(t + "\n" for t in p[p.lang == lang].text)


def test_copy_clusters(spark):
    base = " ".join(f"w{i}" for i in range(200))
    rows = [(1, base), (2, base), (3, base + " tail"), (4, base.replace("w100 ", "z ")), (5, "something else entirely here now"), (6, None), (7, "")]
    c = {r.doc_id: r.cluster_id for r in corpus.copy_clusters(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert c[1] == c[2] == c[3] == c[4] and len({c[1], c[5], c[6]}) == 3 and c[6] == c[7]


def test_measures(spark):
    s = spark.createDataFrame([("g", chr(i)) for i in range(256)], "grp string, symbol string")
    assert metrics.entropy(s, ["grp"]).first().entropy == pytest.approx(8)
    r = spark.createDataFrame([("a", "raw", 1000, 500), ("a", "m", 1000, 250)], "grp string, model string, raw_bytes long, packed_bytes long")
    assert metrics.improvement(r, F.col("model") == "raw", F.col("model") == "m", ["grp"]).first().gain_pct == pytest.approx(100)


def test_queries_match_their_sql(spark, sf):
    con = duckdb.connect()
    for t in ("documents", "events", "orders", "pages", "labels", "benchmark"):
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    q, s = entry.queries(), entry.oracle_sql()
    for name in ("text_stats_cube", "char_entropy_by_lang", "backoff_ranks_two_level", "dotted_rank_strings", "train_counts_order_2", "session_symbol_strings", "contamination_exact", "roundtrip_huffman"):
        a, b = q[name](spark, sf).toPandas(), con.sql(s[name]).df()
        cols = sorted(a.columns)
        key = lambda x: sorted(tuple(str(v) if not isinstance(v, float) else f"{v:.5f}" for v in r) for r in x[cols].astype(object).where(x[cols].notna(), None).itertuples(index=False))
        assert cols == sorted(b.columns) and key(a) == key(b), name


def test_ladder_grows_and_prediction_beats_ids(spark, sf):
    s = {(r.model, r.codec): r.ratio_bytes for r in metrics.summary(workloads._run(workloads.side(spark, sf, "test").withColumn("grp", F.lit("x")), workloads.ladder(spark, sf) | {"ids": pipeline.ids_model(16384)}), ["model", "codec"]).collect()}
    assert s["ids", "gzip"] < s["S", "gzip"] < s["M", "gzip"]
    assert s["M", "brotli"] > s["raw", "brotli"]


def test_streams(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/events.parquet")
    e.orderBy("ts").coalesce(1).write.parquet(str(tmp_path / "e"))
    live = streams.timed(spark.readStream.schema(e.schema).parquet(str(tmp_path / "e")))
    q = streams.adaptive_ranks(live.select("user_id", "ts", "event_id", "event_type")).writeStream.format("memory").queryName("ranks").start()
    q.processAllAvailable()
    q.stop()
    twin = streams.adaptive_ranks_batch(e)
    assert spark.table("ranks").exceptAll(twin).count() == 0 and twin.count() == spark.table("ranks").count() == e.count()
    h = streams.histogram(live, "1 day").writeStream.format("memory").queryName("hist").outputMode("complete").start()
    h.processAllAvailable()
    h.stop()
    assert spark.table("hist").agg(F.sum("n")).first()[0] == e.count()


def test_stream_of_frames(spark, tmp_path, odd):
    odd.write.parquet(str(tmp_path / "d"))
    live = spark.readStream.schema(odd.schema).parquet(str(tmp_path / "d"))
    q = streams.to_frames(streams.compress(live, codec="gzip"), str(tmp_path / "f"), str(tmp_path / "c"))
    q.processAllAvailable()
    q.stop()
    assert texts(pipeline.decompress(spark.read.parquet(str(tmp_path / "f")).drop("batch"))) == dict(enumerate(ODD))
