"""What a reviewer found in round 2, a small case each."""

import duckdb
import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq


ODD_PAGES = [
    "<title>and&amp</title><p>&amp;lt; &lt; &amp &nbsp;x&#39;y</p>",
    "<script>a</STYLE >b</script>c",
    "<scripté>d</script>e <ſtyle>f</style>",
    "  <b>g\x0bh </b>　\n",
    "<!-- i --> j < k",
    "&middot;&copy;&quot;&gt;\r\n\t",
    "",
    None,
]


def test_page_text_digests_decode_what_the_sql_names(spark, tmp_path):
    from rankpress.plans import relational

    pq.write_table(pa.table({"page_id": list(range(len(ODD_PAGES))), "html": pa.array(ODD_PAGES, pa.string())}), tmp_path / "pages.parquet")
    got = {r.page_id: r.digest for r in relational.page_text_digests(spark, str(tmp_path)).collect()}
    con = duckdb.connect()
    con.execute(f"create view pages as select * from '{tmp_path}/pages.parquet'")
    assert got == dict(con.execute(relational.SQL["page_text_digests"]).fetchall())


def test_entries_make_only_pairs_that_their_places_allow(spark):
    """200 texts of a size whose first shared shingle stands too late in all of them: 19,900 pairs before, none now."""
    from rankpress.operators.nearcopies import crossing

    late = spark.range(200).selectExpr("1L t", "id node", "146 n", "20 pos", "id root")
    assert crossing(late, 0.8).count() == 0
    early = late.union(spark.createDataFrame([(2, 900, 100, 3, 900), (2, 901, 110, 5, 901), (2, 902, 160, 5, 902), (2, 903, 100, 3, 900)], late.schema))
    assert {tuple(r) for r in crossing(early, 0.8).collect()} == {(900, 901), (903, 901)}


def test_near_copies_through_places_equal_all_pairs(spark):
    import random

    from rankpress.operators import nearcopies

    rnd = random.Random(5)
    passage = [f"p{i}" for i in range(14)]
    texts = []
    for g in range(30):
        words = [f"w{rnd.randrange(60)}" for _ in range(rnd.randrange(3, 90))]
        for _ in range(rnd.randrange(1, 5)):
            x = list(words)
            for _ in range(rnd.randrange(0, 4)):
                x[rnd.randrange(len(x))] = f"x{rnd.randrange(9)}"
            texts.append(" ".join((passage if g % 2 else []) + x))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sets = [set(s.tolist()) for s in nearcopies.shingles(texts)]
    root = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) - 1e-9 and root[i] != root[j]:
                a, b = max(root[i], root[j]), min(root[i], root[j])
                root = [b if r == a else r for r in root]
    got = {r.doc_id: r.component_id for r in nearcopies.groups(df).collect()}
    assert got == dict(enumerate(root)) and len(set(root)) < len(root)


def test_percent_improvement_reads_a_given_table(spark, sf):
    from rankpress.plans import relational

    df = relational.percent_improvement_from_sizes(spark, sf)
    assert any("documents.parquet" in f for f in df.inputFiles())
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{sf}/documents.parquet'")
    want = con.execute(relational.SQL["percent_improvement_from_sizes"]).fetchall()
    assert sorted(tuple(r) for r in df.collect()) == sorted(want) and len(want) == 4


def test_collected_models_make_no_python_strings_of_their_rows(monkeypatch):
    """Peak of Python's memory for a row of counts, and the same models as from rows picked by hand."""
    import tracemalloc

    import numpy as np

    from rankpress.functions.predictors import CountModel
    from rankpress.operators import training

    n, r = 200_000, np.random.default_rng(1)
    cols = {"level": r.integers(0, 3, n).astype(np.int32), "ctx": r.integers(0, 1 << 30, n), "token": r.integers(0, 500, n).astype(np.int32), "cnt": r.integers(1, 9, n)}

    class Rows:
        def __init__(self, names):
            self.t = pa.table({"domain": pa.array(names)} | {k: pa.array(v) for k, v in cols.items()})

        def count(self):
            return n

        def toArrow(self):  # noqa: N802
            return self.t

    monkeypatch.setattr(training, "cut", lambda x: x)
    both = np.where(r.random(n) < 0.3, "fr", "de")
    got = training.collect_models(Rows(both.tolist()), 500, 2)
    assert list(got) == ["de", "fr"]
    for d, m in got.items():
        assert m.model_id == CountModel.from_rows(*(c[both == d] for c in cols.values()), 500, 2).model_id and m.name == d
    one = Rows(["all"] * n)
    tracemalloc.start()
    training.collect_models(one, 500, 2)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 60 * n, peak / n


def test_bucketed_ranks_and_sizes_equal_those_of_whole_models(spark):
    """Three parts, mixes with weights, contexts of 0 to 3 tokens; empty and repeated blocks; nothing but counts of no context comes to
    the driver. There was no such form before: the ladder's models came to the driver and to every task whole."""
    import random

    import numpy as np
    from pyspark.sql import functions as F

    from rankpress.functions.tokenizers import tokenizer
    from rankpress.operators import buckets, training
    from rankpress.operators.buckets import Mixed
    from rankpress.plans import pipeline

    rnd, tok = random.Random(3), tokenizer("bpe512")
    text = lambda: " ".join(rnd.choice(["the", "house", "of", "late", "é", "rivers", "and", "sing"]) for _ in range(rnd.randrange(0, 60)))
    learnt = spark.createDataFrame([("abc"[i % 3], text()) for i in range(90)], "part string, text string").repartition(3)
    tests = [(i % 7, i % 2, "a" if i % 2 else "b", t) for i, t in enumerate([text() for _ in range(40)] + ["", "", "zebra 😀 qq", None])] * 2
    blocks = spark.createDataFrame(tests, "doc_id long, block int, grp string, text string")
    mixes = {"none": Mixed((("a", 1),), 0), "a:own": Mixed((("a", 1),), 3), "one": Mixed((("a", 1), ("b", 4)), 1), "all": Mixed((("a", 1), ("b", 4), ("c", 2)), 3), "zero": Mixed((("a", 1), ("b", 0)), 2)}
    rows = training.counts(learnt, tok, 3, "part")
    whole = {}
    for n, m in mixes.items():
        by = F.create_map(*(F.lit(x) for p in m.parts for x in p))
        c = rows.withColumn("w", F.try_element_at(by, F.col("domain"))).where("w > 0").select(F.lit("all").alias("domain"), "level", "ctx", "token", (F.col("cnt") * F.col("w")).alias("cnt"))
        c = c.groupBy("domain", "level", "ctx", "token").agg(F.sum("cnt").alias("cnt"))
        whole[n] = training.truncated(training.collect_models(c, tok.vocab_size, 3)["all"], m.order, n)
    for share in (buckets.SHARE, 100):
        was, buckets.SHARE = buckets.SHARE, share
        try:
            held = buckets.counted(learnt, tok, 3)
        finally:
            buckets.SHARE = was
        assert (held.n > 20) == (share == 100)
        how = dict(serializers=("dotted", "varint"), codecs=("gzip",), raw=("gzip",), only="grp")
        got = pipeline.evaluate(blocks, {n: (m, "t") for n, m in mixes.items()}, {"t": tok}, counted=held, **how)
        want = pipeline.evaluate(blocks, {n: (m, "t") for n, m in whole.items()}, {"t": tok}, **how)
        plain = lambda df: sorted(map(repr, df.drop("encode_ms").collect()))
        assert plain(got) == plain(want)
        assert {tuple(r) for r in buckets.sizes(held, mixes).collect()} == {(n, m.n_params, m.n_bytes) for n, m in whole.items()}
    c, t = np.array([5, 1 << 62, 5, 0]), np.array([1 << 20, 2, 1 << 20, 7])
    assert [x.tolist() for x in buckets.summed(c, t)] == [[0, 5, 1 << 62], [7, 1 << 20, 2], [1, 2, 1]]
    assert [x.tolist() for x in buckets.summed(c, t, np.array([3, 4, 5, 6]))] == [[0, 5, 1 << 62], [7, 1 << 20, 2], [6, 8, 4]]


def test_adaptive_ranks_do_not_list_what_stands_behind_them():
    """The same ranks as from whole listings, and back; a listing for each token was made before, which this counts."""
    import numpy as np

    from rankpress.functions.predictors import AdaptiveRanker, context_keys

    assert not hasattr(AdaptiveRanker, "_listing")
    r = np.random.default_rng(4)
    for order in range(4):
        m = AdaptiveRanker(40, order)
        for ids in (r.integers(0, 40, 300), r.zipf(1.6, 500) % 40, np.zeros(0, np.int64), np.array([39, 39, 0])):
            state, want = m._start(), []
            for key, t in zip(np.stack(context_keys(ids, order), axis=1).tolist(), ids.tolist()):
                listed = {}
                for k in range(order, -1, -1):
                    for _, x in state[k][key[k]][0]:
                        listed.setdefault(x, len(listed))
                want.append(listed[t] if t in listed else len(listed) + t - sum(1 for x in listed if x < t))
                m._learn(state, key, t)
            got = m.ranks(ids)
            assert got.tolist() == want and m.tokens(got).tolist() == ids.tolist()


def test_ranks_of_single_places_need_no_listing(monkeypatch):
    """a place's rank or token was found by listing all tokens before it; now by the places of the nested lists alone."""
    from rankpress.functions.predictors import CountModel, context_keys, rollout_ranks, rollout_tokens

    rng = np.random.default_rng(5)
    ids = np.minimum(rng.geometric(0.05, 3000), 60).astype(np.int64)
    keys = context_keys(ids, 2)
    rows = [np.concatenate(x) for x in zip(*((np.full(len(u[0]), k), *u, n) for k in range(3) for u, n in [np.unique(np.stack([keys[k], ids]), axis=1, return_counts=True)]))]
    asked = [(0, 0, 0), *(tuple(int(keys[k][i]) for k in range(3)) for i in range(0, 3000, 60)), tuple(m.keys_after([63, 3])) if (m := CountModel.from_rows(*rows, 64, 2)) else ()]
    want = [[m._token_listed(k, r) for r in range(64)] for k in asked]
    assert all(sorted(w) == list(range(64)) for w in want)
    with monkeypatch.context() as only:
        only.setattr(CountModel, "_token_listed", None)
        only.setattr(CountModel, "_rank_listed", None)
        assert [[m.token_at(k, r) for r in range(64)] for k in asked] == want
        assert all(m.rank(k, t) == r for k, w in zip(asked, want) for r, t in enumerate(w))
        assert (rollout_tokens(m, rollout_ranks(m, ids[:200], 4), 4) == ids[:200]).all()
    loose = CountModel.from_rows(*(x[(rows[0] != 1) | (rows[2] % 3 > 0)] for x in rows), 64, 2)  # lists that don't nest
    for k in asked:
        w = [loose.token_at(k, r) for r in range(64)]
        assert w == [loose._token_listed(k, r) for r in range(64)] and [loose.rank(k, t) for t in w] == list(range(64))


def test_direct_coding_asks_for_one_frequency():
    """each coded token made the frequencies of the whole vocabulary."""
    from rankpress.functions import neural
    from rankpress.functions.predictors import CountModel, context_keys

    rng = np.random.default_rng(6)
    ids = np.minimum(rng.geometric(0.05, 2000), 60).astype(np.int64)
    keys = context_keys(ids, 2)
    rows = [np.concatenate(x) for x in zip(*((np.full(len(u[0]), k), *u, n) for k in range(3) for u, n in [np.unique(np.stack([keys[k], ids]), axis=1, return_counts=True)]))]
    for m in (CountModel.from_rows(*rows, 64, 2), CountModel.from_rows(*(x[rows[0] != 1] for x in rows), 64, 2), CountModel.from_rows(*(x[:0] for x in rows), 64, 2)):
        for k in [(0, 0, 0), tuple(m.keys_after([63, 3])), *(tuple(int(keys[j][i]) for j in range(3)) for i in range(0, 2000, 90))]:
            f = m.frequencies(k)
            assert [m.frequency(k, t) for t in range(64)] == [(int(f[:t].sum()), int(f[t]), int(f.sum())) for t in range(64)]
        data = neural.direct_encode(m, ids[:150])
        assert (neural.direct_decode(m, data) == ids[:150]).all()
