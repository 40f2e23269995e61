"""Cases of a review: what the operators left out."""

import numpy as np
import pytest

from rankpress.llm import langid, nearcopies, toxicity


def grams(t, width=5):
    w = (t or "").encode().lower().split()
    return {b" ".join(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def jaccard(a, b):
    same = len(a & b)
    return same / (len(a) + len(b) - same) if a or b else 1.0


@pytest.mark.parametrize("one_in, least", [(16, 4), (1, 2)])
def test_near_copy_stage_against_all_pairs(spark, one_in, least):
    """Copies with 1 to 9 words changed of 150, chains of copies, a line that most texts share, short and empty texts."""
    import corpus_pipeline as c

    rng = np.random.default_rng(4)
    text = lambda n: [f"w{x}" for x in rng.integers(0, 5000, n)]
    line, rows = text(30), []
    for k in range(25):
        base = text(150)
        rows.append(base + line)
        for m in (1, 3, 5, 7, 9):
            w = list(base)
            for p in rng.choice(150, m, replace=False):
                w[p] = "other"
            rows.append(w + line)
        for p in range(0, 60, 5):  # each copy is changed a little more than the last
            base = [*base[:p], "more", *base[p + 1 :]]
            rows.append(list(base))
    rows = [" ".join(w) for w in rows] + ["One two", "one  TWO", "", None, "x y z v w u", "x y z v w t"]
    rows = [rows[i] for i in rng.permutation(len(rows))]
    group, sets = list(range(len(rows))), [grams(t) for t in rows]
    for i in range(len(rows)):
        for j in range(i):
            if group[i] != group[j] and jaccard(sets[i], sets[j]) >= 0.8:
                old, new = max(group[i], group[j]), min(group[i], group[j])
                group = [new if g == old else g for g in group]
    docs = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in nearcopies.groups(docs, one_in=one_in, least=least).collect()}
    assert got == dict(enumerate(group))
    kept = sorted(r.doc_id for r in c.drop_near_copies(spark, docs, None).collect())
    assert kept == sorted(set(group)) and 25 < len(kept) < len(rows) // 2


@pytest.fixture(scope="module")
def long_first(spark):
    """Texts of two languages, some toxic, and one of 25 million characters whose id hashes before all others."""
    from pyspark.sql import functions as F

    ids = [r.id for r in spark.range(4000).where(F.pmod(F.crc32(F.col("id").cast("string").cast("binary")), F.lit(5)) != 0).orderBy(F.xxhash64("id")).limit(301).collect()]
    words = {"xx": "river stone green morning", "yy": "zug qwark vlim brox"}
    rows = [(ids[0], "river stone " * 2_100_000, "xx")]
    rows += [(i, f"{words['xx' if k % 2 else 'yy']} {'vile scum ' * 3 if k % 5 == 0 else 'plain fair '}" * 10, "xx" if k % 2 else "yy") for k, i in enumerate(ids[1:])]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(4)
    labels = spark.createDataFrame([(i, int("vile" in t or i == ids[0])) for i, t, _ in rows], "doc_id long, toxic int")
    return docs, labels


def test_toxicity_learns_behind_a_long_text(spark, long_first):
    docs, labels = long_first
    s = {r.doc_id: r.score for r in toxicity.score(docs, toxicity.learn(docs, labels)).collect()}
    vile = [s[r.doc_id] for r in docs.where("text like '%vile%'").collect()]
    fair = [s[r.doc_id] for r in docs.where("text like '%plain%'").collect()]
    assert min(vile) > 0.5 > max(fair)


def test_language_learns_behind_a_long_text(spark, long_first):
    docs, _ = long_first
    got = {r.doc_id: r.lang_pred for r in langid.predict(docs, langid.learn(docs)).collect()}
    assert got == {r.doc_id: r.lang for r in docs.select("doc_id", "lang").collect()}
