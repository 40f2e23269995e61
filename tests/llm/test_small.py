"""Edge cases and brute-force twins of the operators on small tables."""

import collections
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from rankpress.llm import html, langid, lm, mixing, pieces, quality, simhash, topk, toxicity, vectors
from rankpress.operators import components

DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double, row long, size long, label string"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls everywhere, an empty and a very long text, repeated rows, columns whose names clash with the operators' own."""
    long = "Lorem ipsum dolor " * 20_000
    rows = [(1, "Hello there, general world of words", "en"), (2, None, None), (3, "", "en"), (4, long, "fr"), (1, "Hello there, general world of words", "en"), (5, "Hello there, general world of words", "de"), (None, "no id", "en"), (6, "12345 --- !!", None), (7, "\t\n ", "en")]
    return spark.createDataFrame([(i, t, g, None if i == 2 else "s", None, None, None, None, None) for i, t, g in rows], DOCS)


@pytest.fixture(scope="module")
def none(odd):
    return odd.where("false")


@pytest.fixture(scope="module")
def marks(spark):
    return spark.createDataFrame([(1, 1, 0), (4, 0, 1), (None, 1, 1), (5, None, None)], "doc_id long, quality int, toxic int")


def test_components(spark):
    rng = np.random.default_rng(0)
    e = [(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))] + [(i, i + 1) for i in range(1000, 1060)] + [(5000, 5000), (None, 3)]
    got = {r.node: r.root for r in components.components(spark.createDataFrame(e, "a long, b long")).collect()}
    root = {x: x for p in e for x in p if x is not None}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in e:
        if a is not None and b is not None:
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
    linked = {x for a, b in e if a is not None and b is not None and a != b for x in (a, b)}
    assert got == {x: find(x) for x in linked}


# ------------------------------------------------------------------ SimHash


def slow_fingerprint(text):
    w = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    s = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [b" ".join(w)] if w else []
    h = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


@pytest.mark.parametrize("text", [None, "", " \n", "One", "One two", "A B C D a b c d É", "x y z " * 50, "a\x0bb\x0cc d"])
def test_fingerprint(text):
    assert simhash.fingerprint(text) == slow_fingerprint(text)


@pytest.mark.parametrize("hot", [512, 1])
def test_links_against_all_pairs(spark, hot):
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**63, 30, dtype=np.uint64)
    fps = {0, *base.tolist()}
    for b in base.tolist()[:12]:
        for _ in range(8):
            x = b
            for k in rng.choice(64, rng.integers(1, 5), replace=False):
                x ^= 1 << int(k)
            fps.add(x)
    fps = sorted(fps)
    signed = np.array(fps, np.uint64).view(np.int64).tolist()
    got = {tuple(sorted((r.a, r.b))) for r in simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long"), hot).collect()}
    want = {tuple(sorted((signed[i], signed[j]))) for i in range(len(fps)) for j in range(i) if (fps[i] ^ fps[j]).bit_count() <= 2}
    assert got == want and want


def test_near_copies(odd, none):
    r = {x.doc_id: x for x in simhash.near_duplicates(odd).collect()}
    assert r[5].component_id == r[1].component_id == 1
    assert r[2].component_id == r[3].component_id == r[7].component_id == 2 and r[2].fingerprint == "0" * 16
    kept = simhash.keep_one(odd)
    assert kept.columns == odd.columns
    assert sorted(x.doc_id for x in kept.collect() if x.doc_id is not None) == [1, 1, 2, 4, 6]
    assert simhash.near_duplicates(none).count() == 0


@pytest.mark.parametrize("spread", [256, 2])
def test_components_of_near_copies_against_all_pairs(spark, sf, spread):
    """Real texts, copies of them with a word changed, and rows without an id that link others."""
    texts = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").orderBy("doc_id").limit(60).collect()]
    rng, rows = np.random.default_rng(3), list(texts)
    for i, t in texts[:20]:
        words = t.split(" ")
        for k in range(6):
            words[rng.integers(len(words))] = "other"
            rows.append((None if k % 2 else 1000 + 10 * i + k, " ".join(words)))
    fps = [slow_fingerprint(t) for _, t in rows]
    group = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 2 and group[i] != group[j]:
                old, new = group[i], group[j]
                group = [new if g == old else g for g in group]
    low = {}
    for (i, _), g in zip(rows, group):
        low[g] = min((x for x in (low.get(g), i) if x is not None), default=None)
    want = sorted((str(i), f"{fp:016x}", str(low[g])) for (i, _), fp, g in zip(rows, fps, group))
    got = simhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), spread=spread).collect()
    assert sorted((str(r.doc_id), r.fingerprint, str(r.component_id)) for r in got) == want
    assert len(low) < len(rows) - 20


# ------------------------------------------------------------------ classifiers and scores


def test_toxicity(spark, odd, none, marks):
    m = toxicity.learn(odd, marks)
    s = toxicity.score(odd, m).collect()
    assert len(s) == odd.count() and all(0 <= x.score <= 1 for x in s)
    assert toxicity.kept(odd, m).columns == odd.columns
    assert toxicity.score(none, toxicity.learn(none, marks)).count() == 0
    assert toxicity.learn(odd, marks.where("false")).bias is None


def test_positive_unlabelled_learning():
    rng = np.random.default_rng(0)
    words = [f"word{i}" for i in range(300)]
    text = lambda bad: " ".join([*rng.choice(words, 60), *(rng.choice(["nasty", "vile", "foul"], 3) if bad else [])])
    pos, unl = [text(True) for _ in range(150)], [text(i % 10 == 0) for i in range(600)]
    m = toxicity.fit(*toxicity.features(pos + unl), 150, 600, 0.1)
    s = m.scores([text(True) for _ in range(50)] + [text(False) for _ in range(200)] + [None, ""])
    assert (s[:50] >= 0.5).mean() > 0.95 and (s[50:] >= 0.5).mean() < 0.03
    x = np.ones((20, 3), np.float32)
    assert min(toxicity.train(x, x, 0.5)[2]) >= 0  # the risk never falls below nothing


def test_quality(odd, none, marks):
    m = quality.learn(odd, marks)
    s = quality.score(odd, m).collect()
    assert len(s) == odd.count() and all(0 <= x.score <= 1 for x in s)
    assert quality.kept(odd, m).columns == odd.columns
    assert quality.score(none, quality.learn(none, marks)).count() == 0


def test_discriminant_is_the_quotient_of_densities():
    rng = np.random.default_rng(0)
    x = np.hstack([rng.normal(size=(400, 2)), np.ones((400, 1))])
    y = (rng.random(400) < 0.5).astype(int)
    x[y == 1, 0] += 2
    m = quality.Discriminant(shrink=0, to_diagonal=0, floor=0).fit(x, y)
    z = (x[:, :2] - x[:, :2].mean(0)) / x[:, :2].std(0)
    dens = []
    for c in (0, 1):
        g = z[y == c]
        v = np.cov(g, rowvar=False, bias=True)
        q = np.einsum("ij,jk,ik->i", z - g.mean(0), np.linalg.inv(v), z - g.mean(0))
        dens.append(np.exp(-q / 2) / np.sqrt(np.linalg.det(v)) * np.mean(y == c))
    assert np.allclose(m.scores(x), dens[1] / (dens[0] + dens[1]))
    assert ((m.scores(x) > 0.5) == y).mean() > 0.8


def test_language(odd, none):
    r = langid.predict(odd, langid.learn(odd)).collect()
    assert len(r) == odd.count()
    by = {x.doc_id: x for x in r}
    assert all(by[i].lang_pred == "und" and by[i].score == 0 for i in (2, 3, 6, 7))
    assert langid.predict(odd, langid.learn(none)).where("lang_pred <> 'und'").count() == 0
    assert langid.predict(none, langid.learn(odd)).count() == 0


@pytest.mark.parametrize("n", [1, 2, 4, 7, 12, 30])
def test_codewords_differ(n):
    c = langid.codewords(n)
    assert len({tuple(r) for r in c.tolist()}) == n
    if n > 7:
        assert min((c[i] != c[j]).sum() for i in range(n) for j in range(i)) >= 3


def test_lm_counts_and_sums(odd, none):
    f = lambda i: i is not None and zlib.crc32(str(i).encode()) % 10 != 0
    rows = odd.collect()
    word = re.compile(r"[^\x20\x09-\x0D]+")
    toks = lambda t: [*word.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")), None]
    c = collections.Counter(w for r in rows if r.doc_id is None or f(r.doc_id) for w in toks(r.text))
    n, v = sum(c.values()), len(c)
    train = odd.where(F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 10, F.lit(1)) != 0)
    got = lm.scores(odd, train).collect()
    small = lm.scores(odd, train, words=3, head=2).collect()  # most words meet their counts in the join
    for out in (got, small):
        assert len(out) == len(rows)
        by = {x.doc_id: x for x in out}
        for r in rows:
            t, x = toks(r.text), by[r.doc_id]
            assert (x.n_tokens, x.n_known, x.train_tokens) == (len(t), sum(c[w] > 0 for w in t), n)
            assert x.base_score == pytest.approx(sum(np.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in t))
            assert np.isfinite(x.score) and x.score < 0
    assert lm.scores(none, train).count() == 0
    assert lm.scores(odd, none).count() == len(rows)


def test_lm_is_normalised_and_learns():
    rng = np.random.default_rng(0)
    text = lambda: " ".join(w for _ in range(60) for w in (("red", "apple") if rng.random() < 0.5 else ("blue", "sky")))
    texts = [text() for _ in range(200)]
    h, g, _ = lm.tokens(texts)
    u, at, n = np.unique(h, return_index=True, return_counts=True)
    mass = np.full(lm.GROUPS, 0.1)
    m = lm.LogBilinear(u, n, mass, len(h), len(u), head=10)
    before = m.score(texts)[3].sum()
    m.train(texts, epochs=5)
    assert m.score(texts)[3].sum() > 0.75 * before
    every = np.arange(m.n_head + lm.GROUPS)
    for c in ([0, 1, 2], [3, len(m.r) - 1, len(m.r) - 1]):
        assert np.exp(m.log_probs(every, np.tile(c, (len(every), 1)))).sum() == pytest.approx(1, abs=1e-4)


# ------------------------------------------------------------------ vectors


def clouds(n, seed=0):
    rng = np.random.default_rng(seed)
    centre = rng.normal(size=(12, 16))
    x = centre[rng.integers(0, 12, n)] + rng.normal(size=(n, 16)) * rng.choice([0.05, 0.3, 1.0], (n, 1))
    rows = [(i, [float(np.float32(v)) for v in r], int(i % 3)) for i, r in enumerate(x)]
    rows += [(n, None, 0), (n + 1, [0.0] * 16, 0), (n + 2, [None] * 16, 1), (n + 3, [float("nan")] * 16, 1), (n + 4, rows[0][1], 0), (n + 5, rows[0][1], None), (n + 6, [float("inf")] * 16, 2)]
    return rows


@pytest.mark.parametrize("how", [{}, {"per_cell": 40, "block": 32, "sample": 200}, {"per_cell": 40, "sample": 200, "sent": 0}, {"block": 16}])
def test_embedding_links(spark, how):
    rows = clouds(400)
    e = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").withColumn("v", F.lit(1))
    ok = {i: np.array(v, float) / np.linalg.norm(v) for i, v, g in rows if g is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v)}
    lab = {i: g for i, _, g in rows}
    links = {i: {j for j in ok if j != i and lab[i] == lab[j] and ok[i] @ ok[j] >= 0.93} for i in ok}
    low = {}
    for i in sorted(lab):
        if i not in low:
            todo = [i]
            while todo:
                x = todo.pop()
                if x not in low:
                    low[x] = i
                    todo += links.get(x, ())
    got = vectors.near_duplicates(e, **how).collect()
    assert {r.vec_id: (r.n_links, r.component_id, r.kept) for r in got} == {i: (len(links.get(i, ())), low[i], low[i] == i) for i in lab}
    assert max(map(len, links.values())) > 3


@pytest.mark.parametrize("how", [{}, {"shard": 60, "block_bytes": 7 * 8 * 16}])
def test_top_k(spark, how):
    rows = clouds(300, 1)
    e = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").withColumn("score", F.lit(1))
    ok = {i: [int(np.floor(64 * x)) for x in v] for i, v, _ in rows if v and all(x is not None and np.isfinite(x) for x in v)}
    want = []
    for q in ok:
        if q % 20 == 0:
            s = sorted((-sum(a * b for a, b in zip(ok[q], ok[c])), c) for c in ok if c != q)[:20]
            want += [(q, k + 1, c, -v) for k, (v, c) in enumerate(s)]
    assert sorted(map(tuple, topk.top_k(e, **how).collect())) == sorted(want)


def test_top_k_of_huge_components():
    x = np.array([[2.0**60, 1], [2.0**60, 2], [-(2.0**60), 3]])
    i, j, s = topk.search(np.array([[1.0, 5]]), np.array([0]), np.array([-(2**63)]), x, np.array([1, 2, 3]), 2)
    assert list(zip(j.tolist(), s.tolist())) == [(1, 2**60 + 10), (0, 2**60 + 5)]


def test_cells_of_vectors_of_unequal_length(spark):
    rng = np.random.default_rng(2)
    rows = [(i, [float(np.float32(x)) for x in rng.normal(size=4 if i else 7)], 1) for i in range(90)] + [(100 + i, [1.0, 2.0, 0.5 + i / 100, 1.0, *([0.0] * (i % 4))], 1) for i in range(12)]
    e = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    pad = {i: np.pad(np.array(np.float32(v), float), (0, 7 - len(v))) for i, v, _ in rows}
    want = {i: sum(i != j and pad[i] @ pad[j] / np.linalg.norm(pad[i]) / np.linalg.norm(pad[j]) >= 0.93 for j in pad) for i in pad}
    for how in ({"per_cell": 16, "sample": 30}, {"per_cell": 16, "sample": 30, "sent": 0}):
        assert {r.vec_id: r.n_links for r in vectors.near_duplicates(e, **how).collect()} == want


def test_few_vectors(spark):
    e = spark.createDataFrame([(20, [1.0, 0.5], 1), (40, [1.0], 1)], "vec_id long, embedding array<float>, label int")
    assert sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in topk.top_k(e).collect()) == [(20, 1, 40, 4096), (40, 1, 20, 4096)]
    assert topk.top_k(e.where("false")).count() == 0 and vectors.near_duplicates(e.where("false")).count() == 0


# ------------------------------------------------------------------ mixing


def level(sizes):
    names = sorted(sizes, key=lambda n: (n is None, n))
    w = {n: (3, 1, 2)[k % 3] for k, n in enumerate(names)}
    capped, total = {}, 1.5 * sum(sizes.values())
    while True:
        free = [n for n in names if n not in capped]
        rest = total - sum(capped.values())
        over = [n for n in free if rest * w[n] / sum(w[k] for k in free) > 2 * sizes[n]]
        if not over:
            return capped | {n: rest * w[n] / sum(w[k] for k in free) for n in free}
        capped |= {n: 2 * sizes[n] for n in over}


@pytest.mark.parametrize("slots", [1 << 18, 50])
def test_mix(spark, slots):
    rng = np.random.default_rng(0)
    rows = [(i, " ".join(["w"] * int(rng.integers(0, 60))), None if i % 11 == 0 else f"s{int(rng.zipf(1.5)) % 7}") for i in range(300)] + [(1, "again and again", "s1"), (None, "x y", "s0"), (999, None, "s2")]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumn("target", F.lit("clash"))
    got = mixing.mix(d, slots).join(d.select("doc_id", "source").distinct(), "doc_id").toPandas()
    sizes = collections.Counter()
    for _, t, s in rows:
        sizes[s] += len((t or "").split())
    want = level(sizes)
    again = mixing.mix(d.repartition(3), slots).select("doc_id", "size", "taken")
    assert sorted(map(tuple, mixing.mix(d, slots).select("doc_id", "size", "taken").fillna(-1).collect())) == sorted(map(tuple, again.fillna(-1).collect()))
    for s, g in got.groupby(got.source.fillna("\x7f")):
        s = None if s == "\x7f" else s
        assert g.target.iloc[0] == pytest.approx(want[s])
        if s != "s0":  # whose row without an id isn't joined here
            assert abs(g.taken.sum() - want[s]) <= 1
    assert (got.taken <= 2 * got["size"]).all()
    assert mixing.mixed(d).columns == d.columns
    assert mixing.mix(d.where("false")).count() == 0 and mixing.mix(d.where("text is null")).first().taken == 0


def test_schedule_keeps_the_shares_everywhere(spark):
    rows = [(i, "w " * 10, f"s{i % 3}") for i in range(600)]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string")
    s = mixing.schedule(mixing.plan(mixing.sizes(d), 1024)).toPandas().sort_values("slot")
    share = s.source.value_counts(normalize=True)
    for part in (s.iloc[k:][: len(s) // 8] for k in range(0, len(s) - len(s) // 8, len(s) // 8)):
        assert all(abs((part.source == k).mean() - v) < 0.03 for k, v in share.items())


# ------------------------------------------------------------------ pieces


@pytest.fixture(scope="module")
def model():
    return pieces.Pieces.load()


def test_pieces_against_the_library(model, spark, sf):
    import sentencepiece

    lib = sentencepiece.SentencePieceProcessor(model_file=pieces.MODEL_PATH)
    texts = [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    texts += ["", " ", "a", "  a  b ", "\n\t\x00", "naïve 漢字 🙂 हिन्दी", "<s> </s> <unk> <0x0A>", "a" * 500, "1234567890" * 20, "antidisestablishmentarianism", "①ﬁ x"]
    for t in texts:
        assert model.encode(t).tolist() == lib.encode(t)
        assert model.decode(model.encode(t)) == t


def test_viterbi_against_all_segmentations():
    vocab = ["▁", "a", "b", "▁a", "ab", "ba", "aba", "bb", "▁ab"]
    score = [-3.0, -2.0, -2.5, -2.2, -2.9, -3.3, -4.1, -3.9, -5.0]
    m = pieces.Pieces([None, *vocab], [0.0, *score], [], False)
    at = dict(zip(vocab, score))

    def best(s):
        return 0.0 if not s else max((at[s[:k]] + best(s[k:]) for k in range(1, len(s) + 1) if s[:k] in at), default=-np.inf)

    for t in ("a", "abab", "bbaab", "aba bab", "ab  ba"):
        ids = m.encode(t)
        assert m.decode(ids) == t
        assert sum(m.scores[i] for i in ids) == pytest.approx(best("▁" + t.replace(" ", "▁")))


def test_encoded_rows(odd, none, model):
    r = {x.doc_id: x for x in pieces.encoded(odd, model).collect()}
    assert r[2].ids is None and r[2].n_pieces == 0 and r[3].ids == [] and all(x.round_trip for x in r.values())
    back = {x.doc_id: x.text for x in pieces.decoded(pieces.encoded(odd, model), model).collect()}
    assert back == {x.doc_id: x.text for x in odd.collect()}
    assert pieces.encoded(none, model).count() == 0


# ------------------------------------------------------------------ pages

PAGE = """<html><head><title>T</title><style>p{{}}</style><script>var x="<p>no</p>";</script></head><body><nav><ul><li><a href=x>Home</a></li></ul></nav>
<div class="notice">Closed on Monday</div><article><h1>{h}</h1><p>One &amp; two
 &lt;three&gt;<p><b>{p}</b></p><!-- gone --><ul><li>item</li></ul><div class="comments"><p>Nice!</p></div></article><aside>See also</aside><form><input value=1>Name</form><footer>&copy; 2024</footer></body></html>"""


def test_main_text(spark):
    rows = [(i, f"https://{'a' if i < 6 else f'h{i}'}.org/x{i}", PAGE.format(h=f"Title {i}", p=f"Body of page {i} is longer than that.")) for i in range(9)]
    rows += [(100, None, None), (101, "x", ""), (102, "https://a.org/q", "plain text only"), (103, "https://a.org/z", "<p>open <b>tags<p>and &amp entity &am"), (0, rows[0][1], rows[0][2])]
    d = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit(1))
    r = {x.page_id: x for x in html.main_text(d).collect()}
    for i in range(9):
        assert r[i].text == f"Title {i}\nOne & two <three>\nBody of page {i} is longer than that.\nitem"
        assert r[i].n_chars == len(r[i].text)
    assert r[100].text == r[101].text == "" and r[100].n_chars == 0
    assert r[102].text == "plain text only" and r[103].text == "open tags\nand & entity &am"
    assert html.main_text(d).count() == len(rows) and html.main_text(d.where("false")).count() == 0


def test_template_without_marked_elements(spark):
    page = lambda i: f"<html><body><div id=x1><a href=/>Home</a> <a href=/b>About</a></div><div id=x2><p>Story {i} begins here and goes on for a while.</p><p>It ends on day {i}.</p></div><div id=x3>All rights kept since 1999</div></body></html>"
    d = spark.createDataFrame([(i, "https://plain.org/", page(i)) for i in range(8)], "page_id long, url string, html string")
    for x in html.main_text(d).collect():
        assert x.text == f"Story {x.page_id} begins here and goes on for a while.\nIt ends on day {x.page_id}."


# ------------------------------------------------------------------ pipeline


def test_pipeline(spark, odd, sf, marks, tmp_path):
    import corpus_pipeline as c

    marks.write.parquet(str(tmp_path / "labels.parquet"))
    odd.write.parquet(str(tmp_path / "documents.parquet"))
    docs = odd
    for name, stage in c.STAGES[:-1]:
        out = stage(spark, docs, str(tmp_path))
        assert out.columns == odd.columns, name
        assert stage(spark, docs.where("false"), str(tmp_path)).count() == 0
        out.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
    assert c.run(spark, str(tmp_path)).where("not round_trip").count() == 0
    assert [n for n, _ in c.STAGES] == ["toxicity", "quality", "near_copies", "mixing", "sentencepiece"]


def _unnamed(i: int) -> str:
    words = [f"w{(i * 7 + k * 13) % 101}" for k in range(40)]
    paras = "".join(f"<p>{' '.join(words[k : k + 9])}.</p>" for k in range(0, 9 * (1 + i % 4), 9))
    return f"<html><body><div class=q1><b>Start</b> Wares Contact us</div><div class=q2><h2>About {words[0]}</h2>{paras}</div><div class=q3>Teaser {words[5]} of {words[6]}</div><div class=q4>Kept by the owners since 1999</div></body></html>"


def test_html_template_decides_without_names(spark):
    d = spark.createDataFrame([(i, f"https://{'abc'[i % 3]}.org/{i}", _unnamed(i)) for i in range(120)], "page_id long, url string, html string")
    for x in html.main_text(d, group=16).collect():
        want = [b[2] for b in html.tokens(_unnamed(x.page_id)) if not isinstance(b, str) and "[q2]" in b[0]]
        assert x.text == "\n".join(want) and x.n_chars == len(x.text)
    pages = [html.tokens(_unnamed(i)) for i in range(12)]
    on, off = html.Reader(pages), html.Reader(pages, support=99)  # a support that no token has: no template
    assert len(on.template.classes) > 1 and not off.template.classes
    assert all(on.text(k, p) != off.text(k, p) for k, p in enumerate(pages))


def test_html_classes_against_brute_force():
    from collections import Counter, defaultdict

    pages = [html.tokens(_unnamed(i)) for i in range(10)]
    flat = [[t for x in p for t in ([x] if isinstance(x, str) else [(x[0], w) for w in x[2].split(" ")])] for p in pages]
    counts = [Counter(p) for p in flat]
    groups = defaultdict(set)
    for t in {t for p in flat for t in p}:
        vector = tuple(c[t] for c in counts)
        if sum(v > 0 for v in vector) >= 3:
            groups[vector].add(t)
    t = html.Template(pages)
    assert len(t.classes) > 1
    for c in t.classes:
        vector = tuple(n[c[0]] for n in counts)
        assert set(c) <= groups[vector]
        for p, n in zip(flat, vector):  # one order, round by round
            assert [x for x in p if x in set(c)] == c * n
    root = next(c for c in t.classes if "/html" in c)  # what it leaves out breaks the order of what it holds
    for x in groups[(1,) * 10] - set(root):
        assert any(len({p.index(x) < p.index(y) for p in flat}) == 2 for y in root)
    spans = [[(q.index(c[0]), len(q) - 1 - q[::-1].index(c[-1])) for q in flat if c[0] in q] for c in t.classes]
    assert all(a <= b for s in spans for a, b in s)


def test_html_names_that_vary_and_odd_pages():
    story = lambda i: f"<html><body><div class=tagline><p>Daily {i}</p></div><article id=post-{i}><p>Story {i} goes on for quite a while and then it ends.</p></article></body></html>"
    texts = html.articles(["h"] * 9, [story(i) for i in range(7)] + ["<html><body>gone", None])
    assert texts[:7] == [f"Story {i} goes on for quite a while and then it ends." for i in range(7)] and texts[7:] == ["gone", ""]
