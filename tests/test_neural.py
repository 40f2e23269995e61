import time

import numpy as np
import pytest

from rankpress.functions.neural import Recurrent, Transformer, direct_decode, direct_encode, ideal_bits
from rankpress.functions.tokenizers import tokenizer
from tests.test_predictors import fit

TEXT = "the cat sat on the mat and the dog sat on the log. " * 60


def numeric(f, a, at, eps):
    old = a[at]
    a[at] = old + eps
    up = f()
    a[at] = old - eps
    down = f()
    a[at] = old
    return (up - down) / (2 * eps)


@pytest.mark.parametrize("soft", [False, True])
def test_transformer_gradients(soft):
    m = Transformer(11, layers=2, dim=8, heads=2, context=6, dtype=np.float64)
    rng = np.random.default_rng(0)
    x, y = rng.integers(0, 12, (3, 6)), rng.integers(0, 11, (3, 6))
    y = rng.dirichlet(np.ones(11), (3, 6)) if soft else y
    _, g = m.gradients(x, y)
    for k, a in m.p.items():
        for at in [tuple(rng.integers(0, s) for s in a.shape) for _ in range(3)]:
            assert g[k][at] == pytest.approx(numeric(lambda: m.gradients(x, y)[0], a, at, 1e-6), abs=1e-6)


def test_adapter_gradients_and_freezing():
    m = Transformer(7, layers=1, dim=8, heads=2, context=5, dtype=np.float64)
    m.adapt(2)
    rng = np.random.default_rng(0)
    for a in m.low.values():
        a += rng.normal(0, 0.1, a.shape)
    x, y = rng.integers(0, 7, (2, 5)), rng.integers(0, 7, (2, 5))
    _, g = m.gradients(x, y)
    assert set(g) == set(m.low)
    for k, a in m.low.items():
        at = tuple(rng.integers(0, s) for s in a.shape)
        assert g[k][at] == pytest.approx(numeric(lambda: m.gradients(x, y)[0], a, at, 1e-6), abs=1e-6)


def test_recurrent_gradients():
    m = Recurrent(9, dim=6)
    m.p = {k: v.astype(np.float64) for k, v in m.p.items()}
    rng = np.random.default_rng(0)
    x, y = rng.integers(0, 10, (2, 5)), rng.integers(0, 9, (2, 5))
    _, g = m.gradients(x, y)
    for k, a in m.p.items():
        at = tuple(rng.integers(0, s) for s in a.shape)
        assert g[k][at] == pytest.approx(numeric(lambda: m.gradients(x, y)[0], a, at, 1e-4), abs=1e-4)


@pytest.fixture(scope="module")
def trained():
    t = tokenizer("byte")
    m = Transformer(256, layers=1, dim=32, heads=2, context=16)
    log = m.train(t.encode(TEXT), steps=120, batch=16, every=60)
    assert log[-1][1] < 0.5 * log[0][1] and sum(p is not None for _, _, p in log) == 2
    return t, m


def test_whole_numbers_do_not_depend_on_the_batch(trained):
    t, m = trained
    w = m.rounded()
    ids = t.encode("the dog sat on the cat; naïve")
    r = w.ranks(ids)
    assert (w.ranks(ids, batch=1) == r).all() and (w.ranks(ids, batch=7) == r).all()
    assert t.decode(w.tokens(r)) == "the dog sat on the cat; naïve"
    assert (r == 0).mean() > 0.4 and all(float(v).is_integer() for v in w.forward(ids[None, :16])[0, 3])


def test_students_and_adapters(trained):
    t, teacher = trained
    ids = t.encode(TEXT)
    s = Transformer(256, layers=1, dim=16, heads=2, context=16, seed=3)
    log = s.train(ids, steps=60, batch=16, teacher=teacher)
    assert log[-1][1] < log[0][1]
    s.adapt(4)
    fixed = {k: v.copy() for k, v in s.p.items()}
    s.train(ids, steps=5, batch=8)
    assert all((fixed[k] == s.p[k]).all() for k in fixed)
    s.merge()
    assert not s.low and any((fixed[k] != s.p[k]).any() for k in fixed)


def test_recurrent_round_trip():
    t = tokenizer("byte")
    m = Recurrent(256, 24)
    log = m.train(t.encode(TEXT), steps=80)
    assert log[-1] < log[0]
    ids = t.encode("the cat, the log")
    assert (m.tokens(m.ranks(ids)) == ids).all()


def test_direct_coding():
    t, m = fit([TEXT])
    for x in ("", "the mat sat", "Zürich"):
        ids = t.encode(x)
        data = direct_encode(m, ids)
        assert (direct_decode(m, data) == ids).all()
        assert len(data) * 8 < ideal_bits(m, ids) + 60


def _by_whole_windows(w, ids):
    """Ranks from whole windows, a token at a time."""
    return [int(w._rank(w.forward(x[None])[0, row : row + 1], ids[at : at + 1])[0]) for at in range(len(ids)) for x, row in [w._window(ids, at)]]


@pytest.mark.parametrize("layers,window", [(1, "hop"), (2, "hop"), (2, "fixed"), (2, "growing")])
def test_many_texts_in_step_rank_as_whole_windows_do(layers, window, monkeypatch):
    """only the rows asked for are made, for many texts at once, and no row outside them."""
    from rankpress.functions.neural import WholeTransformer

    w = Transformer(70, layers=layers, dim=8, heads=2, context=10).rounded(window)
    rng = np.random.default_rng(1)
    texts = [rng.integers(0, 70, n) for n in (0, 1, 4, 5, 6, 9, 10, 11, 14, 15, 16, 43)]
    want = [_by_whole_windows(w, x) for x in texts]
    monkeypatch.setattr(WholeTransformer, "forward", None)
    assert [r.tolist() for r in w.ranks_many(texts)] == want
    assert [w.ranks(x).tolist() for x in texts] == want and w.ranks_many([]) == []


@pytest.mark.parametrize("layers,k", [(1, 1), (1, 2), (2, 3), (2, 4), (1, 5)])
def test_tokens_ahead_need_a_row_for_each_guess(layers, k, monkeypatch):
    """the ranks of whole windows for each guess, without running them."""
    from rankpress.functions.neural import WholeTransformer

    w = Transformer(70, layers=layers, dim=8, heads=2, context=10).rounded()
    rng = np.random.default_rng(2)
    texts = [rng.integers(0, 70, n) for n in (0, 1, 2, 4, 5, 6, 9, 10, 11, 14, 15, 16, 43)]
    want = [w._ahead(x, k, True)[0].tolist() for x in texts]
    monkeypatch.setattr(WholeTransformer, "forward", None)
    assert [w.ranks_ahead(x, k).tolist() for x in texts] == want
    assert [w.ranks_ahead(x, k, batch=1).tolist() for x in texts] == want


def test_recurrent_ranks_of_many_texts_in_step():
    """a step for all texts at once, with the ranks that each has alone, and those of the net in floating point."""
    t = tokenizer("byte")
    m = Recurrent(256, 24)
    m.train(t.encode(TEXT), steps=40)
    texts = [t.encode(x) for x in ("the cat, the log", "", "t", TEXT[:300], "naïve dogs sat")]
    calls, moved = [], m._moved
    m._moved = lambda *x: calls.append(1) or moved(*x)
    got = m.ranks_many(texts, batch=7)
    assert len(calls) == 300 and m.ranks_many([]) == []
    assert all((m.ranks(x) == r).all() and len(r) == len(x) for x, r in zip(texts, got))
    assert all((y == x).all() for x, y in zip(texts, m.tokens_many(got)))
    h, x, want = np.zeros((1, 24), np.float32), 256, []
    for token in texts[3].tolist():
        h, _ = m._step(np.array([x]), h)
        z = h[0].astype(float) @ m.p["emb"][:256].T.astype(float) * 1024
        want.append(((z > z[token] + 2).sum(), (z >= z[token] - 2).sum()))  # but for near ties
        x = token
    assert all(low <= r <= high for r, (low, high) in zip(got[3], want))


def test_plain_student_is_the_tuned_net():
    """both are the base, trained alike, so that one training does for both."""
    from rankpress.plans.neural import copied

    base = Transformer(256, layers=1, dim=8, heads=2, context=8)
    ids = tokenizer("byte").encode(TEXT)
    a, b = copied(base), copied(base)
    a.train(ids, steps=20, rate=1e-3)
    b.train(ids, steps=20, rate=1e-3)
    assert copied(a).rounded().model_id == b.rounded().model_id != base.rounded().model_id


class Counting:
    def __init__(self, net, folder):
        self.net, self.model_id, self.folder = net, net.model_id, folder

    def ranks_many(self, many):
        open(f"{self.folder}/{time.monotonic_ns()}", "w").close()
        return self.net.ranks_many(many)


def test_equal_networks_are_run_once(spark, tmp_path):
    """networks of one model_id share their ranks within a batch."""
    from rankpress.plans import pipeline
    from rankpress.plans.neural import copied

    net = Transformer(256, layers=1, dim=8, heads=2, context=8)
    df = spark.createDataFrame([(1, 0, "the cat", "x"), (2, 0, "", "x"), (3, 0, None, "y")], "doc_id long, block int, text string, grp string").coalesce(1)
    models = {k: (Counting(copied(net).rounded(), str(tmp_path)), "byte") for k in ("a", "b")}
    rows = pipeline.evaluate(df, models, {"byte": tokenizer("byte")}, raw=()).collect()
    got = {k: sorted((r.doc_id, r.packed_bytes, r.n_tokens, r.top1) for r in rows if r.model == k and r.doc_id == 1) for k in ("a", "b")}
    assert got["a"] == got["b"] and got["a"][0][2] == 7 and len(rows) == 4
    assert len(list(tmp_path.iterdir())) == 1
