"""Repeated and null ids, near copies against all pairs, ranks by joins, teaching against a plain loop, streams, networks in step."""

import collections

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankpress.functions import neural
from rankpress.functions.predictors import context_keys, rollout_ranks, rollout_tokens
from rankpress.functions.tokenizers import tokenizer
from rankpress.operators import corpus, ranks, training
from rankpress.plans import pipeline
from rankpress.sources import tables
from rankpress.streaming import streams

MANY = [(1, "first text"), (1, "second text"), (2, "x"), (2, "x"), (None, "nobody"), (None, "nobody"), (None, "else"), (3, None), (3, ""), (4, "long " * 900)]


@pytest.mark.parametrize("verify", [False, True])
def test_every_row_comes_back(spark, verify):
    d = spark.createDataFrame(MANY, "doc_id long, text string").repartition(3)
    frames = pipeline.compress(d, codec="huffman", block=500, verify=verify)
    two = frames.unionByName(pipeline.compress(d, codec="zstd", block=700))  # frames of two runs lie side by side
    got = collections.Counter((r.doc_id, r.text) for r in pipeline.decompress(two).collect())
    assert got == collections.Counter(MANY + MANY)


def test_split_keeps_every_row_once(spark):
    d = spark.createDataFrame(MANY, "doc_id long, text string")
    s = corpus.split(d).collect()
    assert collections.Counter((r.doc_id, r.text) for r in s) == collections.Counter(MANY)
    side = collections.defaultdict(set)
    for r in s:
        side[r.text or ""].add((r.cluster_id, r.split))
    assert all(len(x) == 1 for x in side.values())


def _shingles(text):
    w = text.lower().split()
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def test_clusters_against_all_pairs(spark):
    """Families whose smallest member is no copy of the others, though it shares many of their shingles."""
    rng = np.random.default_rng(3)
    rows = []
    for f in range(12):
        base = [f"f{f}w{k}" for k in range(120)]
        for v in range(6):
            w = list(base)
            for p in rng.choice(120, [9, 0, 1, 1, 2, 3][v], replace=False):
                w[p] = f"v{v}p{p}"
            rows.append(" ".join(w))
    sets = [_shingles(t) for t in rows]
    group = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                a, b = group[i], group[j]
                group = [b if g == a else g for g in group]
    c = {r.doc_id: r.cluster_id for r in corpus.copy_clusters(spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")).collect()}
    assert all((c[i] == c[j]) == (group[i] == group[j]) for i in range(len(rows)) for j in range(i))
    assert 1 < len(set(c.values())) < len(rows)


@pytest.mark.parametrize("name, order", [("bpe512", 3), ("byte", 2), ("char", 0)])
def test_ranks_by_joins(spark, sf, name, order):
    tok = tokenizer(name)
    d = spark.read.parquet(f"{sf}/documents.parquet").select(F.lit("g").alias("grp"), "doc_id", F.substring("text", 1, 600).alias("text"))
    train, test = d.where("doc_id % 2 = 0"), d.where("doc_id % 2 = 1")
    counts = training.counts(train, tok, order)
    m = training.collect_models(counts, tok.vocab_size, order)["all"]
    want = collections.Counter(x for r in test.collect() for x in m.ranks_stepwise(tok.encode(r.text)).tolist())
    assert {r["rank"]: r.n for r in ranks.histogram(test, counts, tok, order).collect()} == dict(want)
    with pytest.raises(ValueError):
        training.collect_models(counts, tok.vocab_size, order, most=10)


def test_vectorised_ranks_of_lists_that_do_not_nest():
    from rankpress.functions.predictors import CountModel

    m = CountModel.from_rows([0, 0, 1, 1], [0, 0, 3, 3], [1, 2, 2, 5], [3, 1, 2, 4], 8, 1)
    ids = np.array([2, 5, 2, 2, 1, 7, 5])
    assert m.ranks_vectorised(ids).tolist() == m.ranks_stepwise(ids).tolist()


def test_teaching_against_a_loop(spark):
    tok, texts = tokenizer("byte"), ["abab abc", "abcab", "", "b"]
    teacher = training.collect_models(training.counts(spark.createDataFrame([(t,) for t in texts[:2]], "text string"), tok, 2), 256, 2)["all"]
    want = collections.Counter()
    for t in texts:
        ids = tok.encode(t)
        for key, true in zip(np.stack(context_keys(ids, 2), axis=1).tolist() if len(ids) else [], ids.tolist()):
            seen = next((x for k in (2, 1, 0) if (x := teacher._seen(k, key[k]))[0]), ([], {}, []))
            p = np.array(seen[2][:2], float)
            for token, n in [*zip(seen[0][:2], (0.7 * 1000 * p / p.sum()).astype(int).tolist()), (true, 300)]:
                for j in (0, 1):
                    want[j, key[j], token] += n
    got = training.distilled(spark.createDataFrame([(t,) for t in texts] + [(None,)], "text string"), teacher, tok, 1, top=2).collect()
    assert {(r.level, r.ctx, r.token): r.cnt for r in got} == {k: n for k, n in want.items() if n}


def test_a_cluster_needs_a_shared_folder(spark):
    class Conf:
        get = staticmethod(lambda k, d: d)

    class Session:
        conf = Conf
        sparkContext = type("C", (), {"master": "spark://far:7077"})

    with pytest.raises(ValueError):
        tables.shared_folder(Session)


def test_sparse_tuning_is_tuning(spark, sf):
    tok = tokenizer("byte")
    d = spark.read.parquet(f"{sf}/documents.parquet").select("lang", F.substring("text", 1, 400).alias("text"))
    base, own = training.counts(d.where("lang = 'en'"), tok, 2), training.counts(d.where("lang in ('fr', 'de')"), tok, 2, domain="lang")
    want = training.collect_models(training.merged(base, own, 4), 256, 2)
    got = training.with_delta(training.collect_models(base, 256, 2)["all"], training.delta(own, 4), 2)
    assert {k: m.model_id for k, m in got.items()} == {k: m.model_id for k, m in want.items()} and len(got) == 2


# ------------------------------------------------------------------ networks


@pytest.fixture(scope="module")
def net():
    m = neural.Transformer(256, 1, 16, context=12)
    m.train(np.tile(tokenizer("byte").encode("the cat sat on the mat. "), 30), steps=30, batch=8)
    return m


@pytest.mark.parametrize("window", ["hop", "fixed", "growing"])
def test_windows_round_trip(net, window):
    m = neural.WholeTransformer(net, window)
    texts = [np.array(x, np.int64) for x in ([], [5], list(b"the cat sat on the hat and the rat."), list(b"the mat. the"))]
    got = [m.ranks(t) for t in texts]
    assert all((m.ranks(t, batch=1) == r).all() for t, r in zip(texts, got))
    assert [x.tolist() for x in m.tokens_many(got)] == [t.tolist() for t in texts]
    assert m.tokens(got[2]).tolist() == texts[2].tolist()


@pytest.mark.parametrize("k", [1, 3, 40])
def test_network_ahead(net, k):
    m, ids = net.rounded(), np.array(list(b"the cat sat on the hat and"), np.int64)
    r, calls = m._ahead(ids, k, True)
    assert rollout_tokens(m, rollout_ranks(m, ids, k), k).tolist() == ids.tolist()
    assert calls == min(k, len(ids)) and m._ahead(r, k, False)[1] == len(ids)
    if k == 1:
        assert r.tolist() == m.ranks(ids).tolist() or m.window == "hop"


# ------------------------------------------------------------------ streams


def _all(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).start()
    q.processAllAvailable()
    q.stop()
    return q, df.sparkSession.table(name)


@pytest.fixture(scope="module")
def live(spark, sf, tmp_path_factory):
    e = spark.read.parquet(f"{sf}/events.parquet")
    path = str(tmp_path_factory.mktemp("e"))
    e.union(e.limit(50)).coalesce(1).write.mode("overwrite").parquet(path)
    return e, lambda: streams.timed(spark.readStream.schema(e.schema).parquet(path), delay="60 days")


def test_stream_drops_repeats(spark, live):
    e, stream = live
    _, t = _all(streams.dedup(stream()), "once", "append")
    assert t.count() == e.count() == t.select("event_id").distinct().count()


def test_stream_meets_a_table(spark, live):
    e, stream = live
    kinds = spark.createDataFrame([("error", 1), ("click", 0)], "event_type string, bad int")
    x = stream().withColumnRenamed("event_type", "doc_id")
    _, t = _all(streams.with_labels(x, kinds.withColumnRenamed("event_type", "doc_id")), "joined", "append")
    assert t.where("bad = 1").count() == t.where("doc_id = 'error'").count() > 0 and t.count() == e.count() + 50


def test_stream_windows_and_sessions(spark, live):
    e, stream = live
    batch = streams.timed(e.union(e.limit(50)))
    _, t = _all(streams.histogram(stream(), "1 day", "6 hours"), "sliding", "complete")
    want = streams.histogram(batch, "1 day", "6 hours")
    assert t.exceptAll(want).count() == 0 and want.exceptAll(t).count() == 0
    _, t = _all(streams.sessions(stream()).select("user_id", "session_start", F.size("symbols").alias("n")), "sess", "complete")
    want = streams.sessions(batch).select("user_id", "session_start", F.size("symbols").alias("n"))
    assert t.exceptAll(want).count() == 0 and t.count() == want.count()


def test_stream_drift(spark, live):
    _, stream = live
    r = stream().select("ts", F.when(F.dayofmonth("ts") > 15, 100).otherwise(1).alias("rank"))
    _, t = _all(streams.drift(r, "1 day", 3.0), "drift", "complete")
    assert {(x.window.start.day > 15) for x in t.where("alarm").collect()} == {True} and t.where("not alarm").count() > 0


def test_late_rows_are_counted(spark, live, tmp_path):
    e, _ = live
    path = str(tmp_path / "late")
    e.where("day(ts) >= 20").coalesce(1).write.parquet(path)
    h = streams.histogram(streams.timed(spark.readStream.schema(e.schema).parquet(path), delay="1 hour"), "1 hour")
    q = h.writeStream.format("memory").queryName("late").outputMode("update").start()
    q.processAllAvailable()
    e.where("day(ts) < 3").coalesce(1).write.mode("append").parquet(path)
    q.processAllAvailable()
    late = streams.late_report(q)
    q.stop()
    assert late > 0


def test_span_hashes_are_those_of_the_bytes():
    """Equal spans hash alike wherever they stand, in buffers of any length; different ones don't."""
    from rankpress.functions.spans import SpanHasher, as_bytes, lower_ascii, word_spans

    base, mod = 0x9E3779B97F4A7C15, 1 << 64
    rng = np.random.default_rng(5)
    words = ["".join(chr(97 + c) for c in rng.integers(0, 26, rng.integers(1, 9))) for _ in range(3000)]
    for text in (" ".join(words[:7]), " ".join(words), "x " * 3 + " ".join(words[5:40])):
        data, _ = as_bytes([text], b" ")
        data = lower_ascii(data)
        a, b = word_spans(data)
        h, seen = SpanHasher(data), {}
        for w, x in zip(text.split(), h(a, b).tolist()):
            assert seen.setdefault(w, x) == x
        assert len(set(seen.values())) == len(seen)
        raw = [sum((c + 1) * pow(base, i, mod) for i, c in enumerate(w.encode())) % mod for w in text.split()]
        got = (h.s[b] - h.s[a]) * h.inv[a]
        assert got.tolist() == raw
