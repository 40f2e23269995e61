"""What a reviewer found in round 2 of the operators and the pipeline, a small case each."""

import re
import tracemalloc
from pathlib import Path

import numpy as np

from rankpress.functions import spans
from rankpress.llm import toxicity


def test_near_copy_stage_goes_through_operator_7(spark, sf, monkeypatch):
    """The stage asks operator 7 over five-word shingles, compares what it links, and adds what its fingerprints don't show."""
    import corpus_pipeline
    from rankpress.llm import simhash

    asked, real = [], simhash.near_duplicates
    monkeypatch.setattr(simhash, "near_duplicates", lambda docs, width=3, **k: asked.append(width) or real(docs, width, **k))
    words = [f"w{i}" for i in range(200)]
    far = [*words[:60], "x", *words[61:140], "y", *words[141:]]  # similar by 0.9
    rows = [(1, " ".join(words)), (2, " ".join(words)), (3, " ".join(far)), (4, "one two three four five six"), (5, "six five four three two one")]
    a, b = (simhash.fingerprint(" ".join(x), 5) for x in (words, far))
    assert (a ^ b).bit_count() > 2
    left = corpus_pipeline.drop_near_copies(spark, spark.createDataFrame(rows, "doc_id long, text string"), sf)
    assert sorted(r.doc_id for r in left.collect()) == [1, 4, 5] and asked == [5]


def test_toxicity_scores_a_large_batch_in_little_memory():
    """The pipeline's first stage took an executor over its limit: a batch's features were all in memory at once."""
    rng = np.random.default_rng(3)
    words = ["".join(w) for w in rng.choice(list("abcdefghijklmnop"), (5000, 7))]
    texts = [" ".join(rng.choice(words, 150)) for _ in range(6000)]
    model = toxicity.PuModel(rng.normal(size=toxicity.DIM).astype(np.float32), 0.1)
    model.scores(texts[:1000])
    tracemalloc.start()
    got = model.scores(texts)
    peak = tracemalloc.get_traced_memory()[1] / 1e6
    tracemalloc.stop()
    rows, cols = toxicity.features(texts)
    assert np.array_equal(got, 0.5 * (1 + np.tanh(0.5 * (0.1 + np.bincount(rows, model.weights[cols], len(texts))))))
    assert peak < 100, peak


def test_freed_memory_goes_back_between_batches():
    held = lambda: int(re.search(r"RssAnon:\s+(\d+)", Path("/proc/self/status").read_text())[1]) / 1024
    small = [np.ones(8_000) for _ in range(4_000)]  # under the size that the allocator maps by itself
    pin, full = [np.ones(8_000)], held()  # lies above them, so that they stay when freed
    small.clear()
    assert list(spans.spared(iter([1, 2]))) == [1, 2]
    assert held() < full - 150 and len(pin)
