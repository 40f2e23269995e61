"""What a reviewer found in round 3 of the pipeline, a small case each."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rankpress.llm import common, quality, toxicity


def test_quality_learns_from_every_labelled_row(spark):
    """F16: the pipeline's second stage learned from the 12,000 labelled rows with the lowest hashes."""
    rng = np.random.default_rng(1)
    texts = [f"{'Word ' * n} {'! x|y 12 ' * m}" for n, m in zip(rng.integers(0, 40, 16_000).tolist(), rng.integers(0, 6, 16_000).tolist())]
    marks = rng.integers(0, 2, len(texts)).tolist()
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame(list(enumerate(marks)), "doc_id long, quality int")
    ids = [r.doc_id for r in docs.where(common.fold("doc_id", 5) != 0).select("doc_id").collect()]
    want = quality.Discriminant().fit(np.array([quality.statistics(texts[i]) for i in ids]), np.array([marks[i] for i in ids]))
    got = quality.learn(docs, labels)
    assert len(ids) > 12_000 and got.prior == want.prior
    assert got.centre == pytest.approx(want.centre, abs=1e-5) and got.scale == pytest.approx(want.scale, abs=1e-5)
    for a, b in zip(got.parts, want.parts):
        assert all(np.allclose(x, y, atol=1e-2) for x, y in zip(a, b))
    x = np.array([quality.statistics(t) for t in texts[:500]])
    assert np.allclose(got.scores(x), want.scores(x), atol=1e-3)
    again = quality.learn(docs.repartition(7), labels)
    assert (again.scores(x) == got.scores(x)).all()  # whole sums: no order of rows matters


def test_toxicity_learns_from_every_toxic_row(spark):
    """F16: the pipeline's first stage learned from the 2,000 toxic rows with the lowest hashes; here the others have a word of their own."""
    ids = [r.id for r in spark.range(12_000).where(common.fold("id", 5) != 0).orderBy(F.xxhash64("id"), "id").collect()]
    rows = [(i, f"river stone {'vile' if k < 2000 else 'scum'} morning" if k < 2600 else "river stone morning") for k, i in enumerate(ids)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    labels = spark.createDataFrame([(i, int(k < 2600)) for k, i in enumerate(ids)], "doc_id long, toxic int")
    m = toxicity.learn(docs, labels)
    assert (m.scores(["river stone vile morning", "river stone scum morning", "river stone morning"]) > 0.5).tolist() == [True, True, False]
    two = toxicity.learn(docs, labels, n_p=1000)  # groups that take turns
    assert (two.scores(["river stone vile morning", "river stone scum morning", "river stone morning"]) > 0.5).tolist() == [True, True, False]
