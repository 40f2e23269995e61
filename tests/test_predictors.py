import pickle
from collections import Counter

import numpy as np
import pytest

from rankpress.functions.predictors import AdaptiveRanker, CountModel, context_keys, rollout_ranks, rollout_tokens
from rankpress.functions.tokenizers import tokenizer


def fit(texts, order=2, tok="byte"):
    t = tokenizer(tok)
    c = Counter()
    for x in texts:
        ids = t.encode(x)
        for k, key in enumerate(context_keys(ids, order)):
            c.update(zip([k] * len(ids), key.tolist(), ids.tolist()))
    a = np.array(list(c), np.int64)
    return t, CountModel.from_rows(a[:, 0], a[:, 1], a[:, 2], np.array(list(c.values())), t.vocab_size, order)


@pytest.fixture(scope="module")
def small():
    return fit(["the cat sat on the mat. the cat ate.", "on the other hand the hat"])


def brute(m, keys):
    """The whole vocabulary in order."""
    out = []
    for k in range(m.order, -1, -1):
        out += [t for t in m._seen(k, keys[k])[0] if t not in out]
    return out + [t for t in range(m.vocab_size) if t not in set(out)]


def test_ranks_are_places_in_the_full_order(small):
    t, m = small
    ids = t.encode("the bat on Zanzibaré!")
    keys = np.stack(context_keys(ids, 2), axis=1).tolist()
    ranks = m.ranks(ids)
    for k, tok, r in zip(keys, ids.tolist(), ranks.tolist()):
        order = brute(m, k)
        assert order[r] == tok
        assert sorted(order) == list(range(256))
        assert [m.token_at(k, i) for i in range(256)] == order


def test_first_guess_is_rank_zero(small):
    t, m = small
    assert m.ranks(t.encode("the"))[1:].tolist() == [0, 0]


@pytest.mark.parametrize("text", ["", "t", "the cat", "हिन्दी", "🙂🙂", "x" * 500, "a\r\nb\x00"])
def test_decoding_gives_the_text(small, text):
    t, m = small
    ids = t.encode(text)
    r = m.ranks(ids)
    assert t.decode(m.tokens(r)) == text
    assert (m.ranks_stepwise(ids) == r).all()
    a = AdaptiveRanker(256, 2)
    assert t.decode(a.tokens(a.ranks(ids))) == text


def test_looking_ahead(small):
    t, m = small
    ids = t.encode("the cat sat on the hat and the mat")
    assert (rollout_ranks(m, ids, 1) == m.ranks(ids)).all()
    for k, seed in ((2, None), (5, None), (5, 3)):
        r = rollout_ranks(m, ids, k, seed)
        assert (rollout_tokens(m, r, k, seed) == ids).all()
    assert (rollout_ranks(m, ids, 8) == 0).sum() <= (m.ranks(ids) == 0).sum()


def test_model_travels(small):
    t, m = small
    ids = t.encode("the cat")
    m.ranks(ids)
    n = pickle.loads(pickle.dumps(m))
    assert n.model_id == m.model_id and (n.ranks(ids) == m.ranks(ids)).all()


def test_one_token_vocabulary():
    m = CountModel.from_rows([0], [0], [0], [5], 1, 0)
    assert m.ranks(np.zeros(4, np.int32)).tolist() == [0] * 4


@pytest.mark.parametrize("name", ["byte", "char", "bpe256", "bpe1024", "bpe16384", "bpe4096-whitespace", "bpe4096-none"])
@pytest.mark.parametrize("text", ["", " ", "Hello  world\n\n\tx", "naïve 漢字 🙂 हिन्दी", "it's 12.50!", "a" * 1000])
def test_tokenizers(name, text):
    t = tokenizer(name)
    ids = t.encode(text)
    assert t.decode(ids) == text
    assert all(0 <= i < t.vocab_size for i in ids.tolist())


def test_frequencies_are_positive_and_follow_counts(small):
    t, m = small
    keys = m.keys_after(t.encode("th").tolist())
    f = m.frequencies(keys)
    assert f.min() >= 1 and f.argmax() == ord("e")
