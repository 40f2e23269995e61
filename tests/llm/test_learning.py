"""Learning over all texts: samples by thresholds, chunks, averages; and the risks and statistics against plain forms."""

import collections

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankpress.llm import common, langid, lm, quality, toxicity


def test_sample_by_threshold(spark):
    d = spark.range(30_000).select(F.col("id").alias("doc_id"), F.when(F.col("id") < 20, "rare").when(F.col("id") == 20, None).otherwise("common").alias("lang"))
    got = collections.Counter(r.lang for r in common.near_bound(d, "doc_id", "lang", 1000).collect())
    assert got["rare"] == 20 and 900 < got["common"] < 1100 and None not in got
    once = spark.range(5000).select(F.lit(7).alias("doc_id"), F.lit("x").alias("lang"))  # one id in all rows
    assert common.near_bound(once, "doc_id", "lang", 10).count() == 5000
    assert sorted(r.doc_id for r in common.near_bound(d.repartition(7), "doc_id", "lang", 50).collect()) == sorted(r.doc_id for r in common.near_bound(d, "doc_id", "lang", 50).collect())


def test_language_of_repeated_and_clashing_rows(spark):
    rows = [(i, "the cat and the dog" if i % 2 else "der hund und die katze", "en" if i % 2 else "de") for i in range(60)] * 2
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumns({"f": F.lit(1), "_of": F.lit(2), "_upto": F.lit(3)})
    got = langid.predict(d, langid.learn(d)).collect()
    assert len(got) == 120 and all(r.lang_pred == ("en" if r.doc_id % 2 else "de") for r in got)


def test_risk_has_the_gradient_it_descends():
    """The step of train() against a difference quotient of the corrected risk, where its bracket is positive."""
    rng = np.random.default_rng(1)
    x_p, x_u, prior = np.c_[rng.integers(0, 2, (40, 5)), np.ones(40)], np.c_[rng.integers(0, 2, (90, 5)), np.ones(90)], 0.1
    soft = lambda z: np.logaddexp(0, z)
    risk = lambda w: prior * soft(-x_p @ w).mean() + max(0, soft(x_u @ w).mean() - prior * soft(x_p @ w).mean())
    w, bias, course = toxicity.train(x_p.astype(np.float32), x_u.astype(np.float32), prior, steps=400, decay=0.0)
    full = np.append(w, bias).astype(float)
    assert risk(full) == pytest.approx(min(course), abs=1e-3)
    for k in range(6):
        for step in (0.05, -0.05):
            assert risk(full + step * np.eye(6)[k]) >= risk(full) - 1e-4


def test_toxicity_of_chunks(spark):
    rng = np.random.default_rng(2)
    words = [f"word{i}" for i in range(200)]
    rows = [(i, " ".join([*rng.choice(words, 30), *(["vile", "foul"] * 2 if i % 9 == 0 else [])]), None) for i in range(1500)]
    d = spark.createDataFrame(rows, "doc_id long, text string, score double")
    labels = spark.createDataFrame([(i, int(i % 9 == 0), 0) for i in range(0, 1500, 2)], "doc_id long, toxic int, score int")
    m = toxicity.learn(d, labels, chunk=200)
    again = toxicity.learn(d, labels, chunk=200)
    assert (m.weights == again.weights).all() and m.bias == again.bias  # whole sums: no order of rows matters
    s = {r.doc_id: r.score for r in toxicity.score(d, m).collect()}
    assert np.mean([(s[i] >= 0.5) == (i % 9 == 0) for i in s]) > 0.98


def test_network_sees_every_chunk(spark):
    rng = np.random.default_rng(0)
    text = lambda: " ".join(w for _ in range(40) for w in (("red", "apple") if rng.random() < 0.5 else ("blue", "sky")))
    d = spark.createDataFrame([(i, text()) for i in range(300)] + [(None, None), (301, "")], "doc_id long, text string")
    counted = lm.counts(d).cache()
    one, _ = lm.learn(d, counted, head=10)
    many, _ = lm.learn(d, counted, head=10, chunk=1000)  # some 24 chunks, averaged in two rounds
    texts = [text() for _ in range(20)]
    base, plain, mean = (m.score(texts)[3].sum() for m in (one.with_weights(lm.LogBilinear(one.known, one.count, 10**one.log_mass, one.n, one.v, 10).weights()), one, many))
    assert plain > base and mean > base
    assert (lm.learn(d, counted, head=10, chunk=1000)[0].weights() == many.weights()).all()


def test_statistics_by_hand():
    text = "Ab c1 c1! x|y\n\nAb c1 c1! x|y\nz."
    got = dict(zip(quality.NAMES, quality.statistics(text)))
    words = text.split()
    k, n = len(words) + 20, len(text)
    assert got["word_length"] == pytest.approx(np.log1p(sum(map(len, words)) / len(words)))
    assert got["upper"] ** 2 == pytest.approx(2 / (sum(c.isalpha() for c in text) + 100))
    assert got["digits"] ** 2 == pytest.approx(4 / (n + 200)) and got["exclaim"] ** 2 == pytest.approx(2 / k) and got["bars"] ** 2 == pytest.approx(2 / k)
    assert got["breaks"] ** 2 == pytest.approx(3 / k) and got["stops"] ** 2 == pytest.approx(1 / k)
    assert got["neighbours"] ** 2 == pytest.approx(sum(a == b for a, b in zip(words, words[1:])) / k)
    assert got["distinct"] ** 2 == pytest.approx((len(set(words)) + 20) / k) and got["commonest"] ** 2 == pytest.approx(max(collections.Counter(words).values()) / k)
    lines = [x for x in text.split("\n") if x]
    assert got["lines_again"] ** 2 == pytest.approx(1 - len(set(lines)) / len(lines))
    runs = [tuple(words[i : i + 5]) for i in range(len(words) - 4)]
    assert got["runs_again"] ** 2 == pytest.approx(1 - len(set(runs)) / len(runs)) and got["trust"] == pytest.approx(len(words) / k)


def test_scores_against_a_plain_softmax():
    rng = np.random.default_rng(4)
    texts = [" ".join(f"w{x}" for x in rng.zipf(1.6, 30) if x < 60) for _ in range(40)]
    h, g, _ = lm.tokens(texts)
    u, at, n = np.unique(h, return_index=True, return_counts=True)
    mass = np.full(lm.GROUPS, 0.1)
    np.add.at(mass, g[at][10:], n[10:] + 0.1)
    m = lm.LogBilinear(u, n, mass, len(h), len(u), head=12).train(texts, epochs=2)
    h, g, row = lm.tokens(texts[:3])
    _, out = m.look_up(h, g)
    ctx = m.contexts(out, row)
    got = m.log_probs(out, ctx)
    for t in range(len(out)):
        q = sum(m.r[ctx[t, k]] * m.scale[k] for k in range(lm.CONTEXT)).astype(float)
        zc = m.class_r @ q + m.class_b
        c = m.class_of[out[t]]
        zw = m.word_r[c] @ q + m.word_b[c]
        want = zc[c] - np.log(np.exp(zc).sum()) + zw[m.slot_of[out[t]]] - np.log(np.exp(zw).sum())
        assert got[t] == pytest.approx(want, abs=1e-4)
    m.class_b += 500  # exponentials that would overflow
    assert m.log_probs(out, ctx) == pytest.approx(got, abs=1e-2)


def test_decoding_against_a_loop():
    """Margins from n-grams found one by one, and the codeword with the least weighted loss."""
    rng = np.random.default_rng(6)
    m = langid.CodeModel(["aa", "bb", "cc"])
    m.weigh(rng.integers(0, 5, (3, langid.DIM)).astype(float))
    bits = m.code.shape[1]
    m.slope, m.shift, m.trust = rng.random(bits) + 0.5, rng.normal(0, 0.1, bits), rng.random((3, bits))
    texts = ["One två, 3 trees", "x", "ab ab cd", "été-là"]
    best, score, _ = m.decode(texts)
    found = [langid.grams([t])[0] for t in texts]
    for t, grams, b, s in zip(texts, found, best, score):
        total, n = np.zeros(bits), 0
        for bucket, counts in grams:
            for x, ok in zip(bucket.tolist(), counts.tolist()):
                total += m.weights[x] if ok else 0
                n += bool(ok)
        z = total / max(n, 1) * m.slope + m.shift
        loss = [sum(m.trust[c, k] * np.log1p(np.exp(-z[k] * m.code[c, k])) for k in range(bits)) for c in range(3)]
        p = np.exp(-2 * (np.array(loss) - min(loss)))
        assert b == int(np.argmin(loss)) and s == pytest.approx(p[b] / p.sum())
    letters = [sum(counts.sum() for _, counts in g) for g in found]
    assert all(x > 0 for x in letters)
