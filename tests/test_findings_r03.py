"""What a reviewer found in round 3, a small case each."""

import numpy as np


def test_networks_rank_every_block_of_the_side(spark, sf, monkeypatch):
    """windows for each token and tokens ahead were tried on texts of under 1,500 characters only."""
    from rankpress.functions import neural as nets
    from rankpress.plans import neural, workloads

    monkeypatch.setattr(neural, "trained", lambda spark, d, size, where="true", steps=0, context=20: nets.Transformer(512, 1, 8, context=context))
    side = workloads.side(spark, sf, "test").select("block", "text").collect()
    short = sum(r.block == 0 and len(r.text) < 1500 for r in side)
    assert 0 < short < len(side)
    got = neural.n06_batch_inference(spark, sf).collect()
    assert {r.mode for r in got} == {f"batch{k}" for k in (1, 2, 4, 8)} and all(r.n == len(side) for r in got)
    got = neural.n05_context_window(spark, sf).collect()
    assert {(r.texts, r.model) for r in got} == {(t, m) for t in ("all", "short") for m in ("hop10", "hop25", "hop50", "hop100", "growing100", "fixed100")}
    assert all(r.n == {"all": len(side), "short": short}[r.texts] for r in got)


def test_students_are_taught_bucket_by_bucket(spark, sf, monkeypatch):
    """teacher, students and base came to the driver whole; now in many buckets the soft counts are those of before."""
    import random

    from rankpress.functions.tokenizers import tokenizer
    from rankpress.operators import buckets, training
    from rankpress.operators.buckets import Mixed
    from rankpress.plans import workloads

    rnd, tok = random.Random(7), tokenizer("bpe512")
    text = lambda: " ".join(rnd.choice(["the", "house", "of", "late", "é", "rivers", "and", "sing"]) for _ in range(rnd.randrange(0, 60)))
    learnt = spark.createDataFrame([("all", text()) for _ in range(60)], "part string, text string").repartition(3)
    told = spark.createDataFrame([("ab"[i % 2], t) for i, t in enumerate([text() for _ in range(40)] + ["zebra 😀 qq", "", None])], "part string, text string").repartition(2)
    monkeypatch.setattr(buckets, "SHARE", 100)
    for top, order in ((3, 2), (3, 1), (1, 1)):
        teacher = buckets.counted(learnt, tok, top)
        assert teacher.n > 20
        whole = training.collect_models(training.counts(learnt, tok, top), tok.vocab_size, top)["all"]
        want = {}
        for r in training.distilled(told, whole, tok, order, domain="part").collect():
            want.setdefault((r.domain, r.level), []).append((r.ctx, r.token, r.cnt))
        got = buckets.distilled(told, teacher, Mixed((("all", 1),), top), tok, order, top > 1)
        rows = got.rows.toArrow()
        for p in "ab":
            found = buckets._levels(buckets._sorted_out(rows.filter(np.array(rows.column("bucket").to_pylist()) >= 0)), ((p, 1),), got.level0, order)
            for k in (0, order):
                c, t, n = found[k]
                times = min(buckets.SALTS, teacher.n) if k == 1 and top > 1 else 1  # a list after one token goes to all its buckets
                assert sorted(zip(c.tolist(), t.tolist(), (n // times).tolist())) == sorted(want[p, k])
    monkeypatch.setattr(training, "collect_models", None)
    for name in ("w05_distillation", "w11_seen_in_part"):
        assert workloads.QUERIES[name](spark, sf, workloads.EXACT).count() > 0
