"""Count-based predictors that order the whole vocabulary after a context, exactly and reproducibly.

The order after a context: the tokens seen after its longest known suffix by falling count, then those of the next shorter
suffix that aren't listed yet, and so on down to no context; then the unseen tokens. Equal counts go to the smaller id. Only
integers decide, so encoder and decoder agree on any machine.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left, bisect_right, insort
from collections import defaultdict

import numpy as np

BITS = 21  # of a packed context's tokens; three fit in a long
MAX_ORDER = 3


def pack(tokens) -> int:
    """A context as one number; a token before the text is 0, others are one more than their id."""
    key = 0
    for t in tokens:
        key = key << BITS | (t + 1)
    return key


def context_keys(ids: np.ndarray, order: int) -> list[np.ndarray]:
    """Packed contexts of lengths 0..order at every position."""
    keys = [np.zeros(len(ids), np.int64)]
    shifted = ids.astype(np.int64) + 1
    for k in range(1, order + 1):
        lag = np.zeros(len(ids), np.int64)
        lag[k:] = shifted[:-k] if k < len(ids) else shifted[:0]
        keys.append(keys[-1] | lag << (BITS * (k - 1)))
    return keys


class CountModel:
    """Ranked tokens for each context of each length, as sorted arrays.

    levels[k] = (contexts in order, where each begins, tokens ranked within a context, counts).
    """

    kind = "count"

    def __init__(self, levels: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]], vocab_size: int, name: str = "count"):
        self.levels, self.vocab_size, self.name = levels, vocab_size, name
        self.order = len(levels) - 1
        self._clear()

    @classmethod
    def from_rows(cls, level, ctx, token, cnt, vocab_size: int, order: int, name: str = "count") -> CountModel:
        """From columns of counts in any order; contexts of a length that was never seen give an empty level."""
        levels = []
        for k in range(order + 1):
            m = np.asarray(level) == k
            c, t, n = np.asarray(ctx)[m], np.asarray(token)[m], np.asarray(cnt)[m]
            o = np.lexsort((t, -n, c))
            c, t, n = c[o], t[o], n[o]
            keys, first = np.unique(c, return_index=True)
            levels.append((keys.astype(np.int64), np.append(first, len(c)).astype(np.int64), t.astype(np.int32), n.astype(np.int64)))
        return cls(levels, vocab_size, name)

    def _clear(self):
        self._lists: list[dict] = [{} for _ in self.levels]
        self._inner: list[dict] = [{} for _ in self.levels]
        self._shares: dict = {}
        self._g = self._index = self._up = None

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("_lists", "_inner", "_shares", "_g", "_inv", "_index", "_up")}

    def __setstate__(self, state):
        self.__dict__ |= state
        self._clear()

    @property
    def n_params(self) -> int:
        return sum(len(lv[2]) for lv in self.levels)

    @property
    def n_bytes(self) -> int:
        return sum(a.nbytes for lv in self.levels for a in lv)

    @property
    def model_id(self) -> str:
        h = hashlib.sha256(str(self.vocab_size).encode())
        for lv in self.levels:
            for a in lv[:3]:
                h.update(np.ascontiguousarray(a).tobytes())
        return h.hexdigest()[:16]

    def _seen(self, k: int, key: int) -> tuple[list[int], dict[int, int], list[int]]:
        got = self._lists[k].get(key)
        if got is None:
            keys, first, tokens, counts = self.levels[k]
            i = bisect_left(keys, key)
            if i < len(keys) and keys[i] == key:
                t = tokens[first[i] : first[i + 1]].tolist()
                got = (t, {x: j for j, x in enumerate(t)}, counts[first[i] : first[i + 1]].tolist())
            else:
                got = ([], {}, [])
            if len(self._lists[k]) > 200_000:
                self._lists[k].clear()
            self._lists[k][key] = got
        return got

    def _places(self):
        """Place of each token without context: seen ones by count, then the unseen by id. Sparse, for huge vocabularies."""
        if self._g is None:
            t = self._seen(0, 0)[0]
            self._g = {x: j for j, x in enumerate(t)}
            self._inv = (t, sorted(t))
        return self._g

    def _place(self, token: int) -> int:
        g = self._places().get(token)
        return g if g is not None else len(self._inv[0]) + token - bisect_left(self._inv[1], token)

    def _at_place(self, place: int) -> int:
        self._places()
        ranked, by_id = self._inv
        if place < len(ranked):
            return ranked[place]
        want = place - len(ranked)  # the want-th id that isn't in by_id
        lo, hi = 0, len(by_id)
        while lo < hi:
            mid = (lo + hi) // 2
            if by_id[mid] - mid <= want:
                lo = mid + 1
            else:
                hi = mid
        return want + lo

    def _within(self, k: int, keys) -> tuple[list[int], list[int]] | None:
        """Where the tokens listed after the context of length k stand in the list of the one a token shorter: their places in order,
        and how many others stand before each. None if one isn't listed there."""
        try:
            return self._inner[k][keys[k]]
        except KeyError:
            pass
        t = self._seen(k, keys[k])[0]
        if k == 1:
            places = sorted(map(self._place, t))
        else:
            at = self._seen(k - 1, keys[k - 1])[1]
            places = sorted(at[x] for x in t) if all(x in at for x in t) else None
        got = None if places is None else (places, [g - i for i, g in enumerate(places)])
        if len(self._inner[k]) > 200_000:
            self._inner[k].clear()
        self._inner[k][keys[k]] = got
        return got

    def rank(self, keys, token: int) -> int:
        """Rank of a token; keys are the packed contexts of lengths 0..order. Lists nest, so before it stand the list of the longer context and what
        comes earlier in the own list and isn't in that one."""
        inner: tuple = ([], [])
        for k in range(self.order, -1, -1):
            t, at, _ = self._seen(k, keys[k]) if k else ((), None, None)
            if k and not t and not inner[0]:
                continue
            j = at.get(token) if k else self._place(token)
            if j is not None:
                return len(inner[0]) + j - bisect_left(inner[0], j)
            inner = self._within(k, keys)
            if inner is None:
                return self._rank_listed(keys, token)

    def token_at(self, keys, rank: int) -> int:
        inner: tuple = ([], [])
        for k in range(self.order, -1, -1):
            t = self._seen(k, keys[k])[0] if k else ()
            if k and not t and not inner[0]:
                continue
            if not k or rank < len(t):
                place = rank - len(inner[0])
                place += bisect_right(inner[1], place)
                return t[place] if k else self._at_place(place)
            inner = self._within(k, keys)
            if inner is None:
                return self._token_listed(keys, rank)

    def _rank_listed(self, keys, token: int) -> int:
        """rank() by listing the tokens, for lists that don't nest."""
        listed: set[int] = set()
        for k in range(self.order, 0, -1):
            t, at, _ = self._seen(k, keys[k])
            if not t:
                continue
            j = at.get(token)
            if j is not None:
                return len(listed) + (j if not listed else j - sum(1 for x in t[:j] if x in listed))
            listed = listed.union(t) if listed else set(t)
        g = self._place(token)
        return len(listed) + g - sum(1 for x in listed if self._place(x) < g)

    def _token_listed(self, keys, rank: int) -> int:
        listed: set[int] = set()
        for k in range(self.order, 0, -1):
            t = self._seen(k, keys[k])[0]
            for x in t:
                if x not in listed:
                    if len(listed) == rank:
                        return x
                    listed.add(x)
        place = rank - len(listed)
        for g in sorted(self._place(x) for x in listed):
            if g <= place:
                place += 1
        return self._at_place(place)

    def ranks(self, ids: np.ndarray) -> np.ndarray:
        """Ranks of a block, all contexts known."""
        return self.ranks_vectorised(ids)

    def ranks_stepwise(self, ids: np.ndarray) -> np.ndarray:
        """The same ranks by one predictor call a token that knows only what came before, as a decoder works."""
        done: list[int] = []
        out = []
        for t in ids.tolist():
            out.append(self.rank(self.keys_after(done), t))
            done.append(t)
        return np.array(out, np.int64)

    def contexts(self, k: int, ctx: np.ndarray) -> np.ndarray:
        """Which context of length k each packed one is, or -1."""
        keys = self.levels[k][0]
        if not len(keys) or not len(ctx):
            return np.full(len(ctx), -1)
        i = np.minimum(np.searchsorted(keys, ctx), len(keys) - 1)
        return np.where(keys[i] == ctx, i, -1)

    def _look_up(self, k: int, ctx: np.ndarray, tokens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(which context of length k, or -1; place of the token in its list, or -1)."""
        keys, first, listed, _ = self.levels[k]
        if self._index is None:
            self._index = [None] * len(self.levels)
        if self._index[k] is None:
            at = np.repeat(np.arange(len(keys)), np.diff(first)) * self.vocab_size + listed
            order = np.argsort(at, kind="stable")
            self._index[k] = (at[order], order)
        i = self.contexts(k, ctx)
        if not len(keys) or not len(ctx):
            return i, i
        pairs, order = self._index[k]
        want = np.where(i >= 0, i * self.vocab_size + tokens, -1)
        j = np.minimum(np.searchsorted(pairs, want), len(pairs) - 1)
        return i, np.where(pairs[j] == want, order[j] - first[i], -1)

    def _nesting(self) -> list[np.ndarray] | None:
        """For each length k >= 1, the places of its listed tokens in the lists of the context one shorter; None if a token isn't
        listed there, which counting texts never brings about."""
        if self._up is None:
            up = [np.zeros(0, np.int64)]
            for k in range(1, self.order + 1):
                keys, first, listed, _ = self.levels[k]
                shorter = np.repeat(keys & ((1 << (BITS * (k - 1))) - 1), np.diff(first))
                up.append(self._look_up(k - 1, shorter, listed)[1])
            self._up = (not any((u < 0).any() for u in up), up)
        return self._up[1] if self._up[0] else None

    def prepare(self):
        """Makes the indexes that ranks are looked up in."""
        self._look_up(self.order, np.zeros(0, np.int64), np.zeros(0, np.int64))
        self._nesting()

    def shorter(self, order: int) -> CountModel:
        """The same with shorter contexts; it shares the indexes."""
        got = CountModel(self.levels[: order + 1], self.vocab_size, self.name)
        if self._up is not None and self._up[0]:
            got._index, got._up = self._index[: order + 1], (True, self._up[1][: order + 1])
        return got

    def ranks_vectorised(self, ids: np.ndarray) -> np.ndarray:
        """The same ranks, a context length at a time for all tokens that no longer context lists."""
        return self.ranks_at(context_keys(ids, self.order), ids)

    def ranks_at(self, keys: list[np.ndarray], ids: np.ndarray) -> np.ndarray:
        """Ranks of tokens at any places, each with its packed contexts of lengths 0..order.

        Lists nest, so what stands before a token found at length k is the whole list of the longer context, and of the own list
        what comes earlier and isn't in that one: its place, and one for each token of the longer context's list behind it here.
        """
        up = self._nesting()
        if up is None:
            return np.array([self.rank(k, t) for k, t in zip(np.stack(keys, axis=1).tolist(), ids.tolist())], np.int64)
        ids = ids.astype(np.int64)
        out, left = np.full(len(ids), -1, np.int64), np.arange(len(ids))
        above = np.full(len(ids), -1)  # the context one longer, where it is known
        for k in range(self.order, -1, -1):
            i, place = self._look_up(k, keys[k][left], ids[left])
            if k == 0 and len(left):  # unseen tokens stand behind all others, by id
                seen = np.sort(self.levels[0][2])
                place = np.where(place >= 0, place, len(seen) + ids[left] - np.searchsorted(seen, ids[left]))
            hit = place >= 0
            got, over, p = left[hit], above[hit], place[hit]
            out[got] = p
            more = np.flatnonzero(over >= 0)
            if len(more):
                first = self.levels[k + 1][1]
                a, n = first[over[more]], np.diff(first)[over[more]]
                begin = np.concatenate([[0], np.cumsum(n)[:-1]])
                flat = np.repeat(a - begin, n) + np.arange(n.sum())
                out[got[more]] += np.add.reduceat(up[k + 1][flat] > np.repeat(p[more], n), begin, dtype=np.int64)
            left, above = left[~hit], i[~hit]
        return out

    def tokens(self, ranks) -> np.ndarray:
        out: list[int] = []
        for r in np.asarray(ranks).tolist():
            out.append(self.token_at(self.keys_after(out), r))
        return np.array(out, np.int32)

    def keys_after(self, ids: list[int]) -> list[int]:
        keys, key = [0], 0
        for k in range(1, self.order + 1):
            key |= (ids[-k] + 1 if len(ids) >= k else 0) << (BITS * (k - 1))
            keys.append(key)
        return keys

    def frequencies(self, keys, total: int = 1 << 15) -> np.ndarray:
        """Positive integer frequencies of all tokens, mixed over the context lengths in integers only.

        Each known length k adds total * 4**k / (sum of 4**j over known lengths) in proportion to its counts.
        """
        known = [(k, self._seen(k, keys[k])) for k in range(self.order + 1)]
        known = [(k, t, c) for k, (t, _, c) in known if t]
        out = np.ones(self.vocab_size, np.int64)
        parts = sum(4**k for k, _, _ in known) or 1
        for k, t, c in known:
            out[t] += np.array(c, np.int64) * (total * 4**k // parts) // sum(c)
        return out

    def frequency(self, keys, token: int, total: int = 1 << 15) -> tuple[int, int, int]:
        """Of frequencies(), the sum of those of smaller ids, the token's, and the sum of all; each context's shares are added up once."""
        known = [k for k in range(self.order + 1) if self._seen(k, keys[k])[0]]
        parts = sum(4**k for k in known) or 1
        below, own, all_ = token, 1, self.vocab_size
        for k in known:
            got = self._shares.get((k, keys[k], parts, total))
            if got is None:
                t, _, c = self._seen(k, keys[k])
                by_id = np.argsort(t)
                n = np.array(c, np.int64)[by_id] * (total * 4**k // parts) // sum(c)
                got = (np.array(t)[by_id].tolist(), [0, *np.cumsum(n).tolist()])
                if len(self._shares) > 200_000:
                    self._shares.clear()
                self._shares[k, keys[k], parts, total] = got
            t, upto = got
            i = bisect_left(t, token)
            below += upto[i]
            own += upto[i + 1] - upto[i] if i < len(t) and t[i] == token else 0
            all_ += upto[-1]
        return below, own, all_


class AdaptiveRanker:
    """One pass, no table: the same order from what the block has shown so far."""

    kind, model_id, name = "adaptive", "adaptive", "adaptive"

    def __init__(self, vocab_size: int, order: int = 2):
        self.vocab_size, self.order = vocab_size, order

    def _start(self):
        # for each context: tokens sorted by (-count, id), and counts
        return [defaultdict(lambda: ([], {})) for _ in range(self.order + 1)]

    def _learn(self, state, keys, token):
        for k in range(self.order + 1):
            ranked, count = state[k][keys[k]]
            n = count.get(token, 0)
            if n:
                ranked.pop(bisect_left(ranked, (-n, token)))
            count[token] = n + 1
            insort(ranked, (-n - 1, token))

    def _rank(self, state, keys, token) -> int:
        """Lists nest here too, so the first that has the token settles its rank: its place, less what the longer list has put before it."""
        above: dict = {}
        for k in range(self.order, -1, -1):
            ranked, count = state[k].get(keys[k], ((), {}))
            n = count.get(token)
            if n:
                at = (-n, token)
                return len(above) + bisect_left(ranked, at) - sum(1 for x in above if (-count[x], x) < at)
            above = count or above
        return len(above) + token - sum(1 for x in above if x < token)

    def _token(self, state, keys, rank) -> int:
        above: dict = {}
        for k in range(self.order, -1, -1):
            ranked, count = state[k].get(keys[k], ((), {}))
            left = rank - len(above)
            if left < len(ranked) - len(above):
                if not above:
                    return ranked[left][1]
                for _, x in ranked:
                    if x not in above:
                        if not left:
                            return x
                        left -= 1
            above = count or above
        token = rank - len(above)
        for x in sorted(above):
            if x <= token:
                token += 1
        return token

    def ranks(self, ids: np.ndarray) -> np.ndarray:
        state, keys, out = self._start(), np.stack(context_keys(ids, self.order), axis=1).tolist(), []
        for key, t in zip(keys, ids.tolist()):
            out.append(self._rank(state, key, t))
            self._learn(state, key, t)
        return np.array(out, np.int64)

    def tokens(self, ranks) -> np.ndarray:
        state, out = self._start(), []
        for r in np.asarray(ranks).tolist():
            key = CountModel.keys_after(self, out)
            t = self._token(state, key, r)
            self._learn(state, key, t)
            out.append(t)
        return np.array(out, np.int32)


class IdentityRanker:
    """No prediction: the rank is the id."""

    kind, model_id, name = "ids", "ids", "ids"

    def __init__(self, vocab_size: int):
        self.vocab_size, self.order = vocab_size, 0

    def ranks(self, ids):
        return np.asarray(ids, np.int64)

    def tokens(self, ranks):
        return np.asarray(ranks, np.int32)


def rollout_ranks(model, ids: np.ndarray, k: int, seed: int | None = None, noise: float = 0.1) -> np.ndarray:
    """Ranks when k tokens are predicted ahead: within a group of k the model reads its own guesses, not the text.

    The guess is the first token of the order, or with a seed now and then the second, drawn from a counter-based generator.
    A network does its groups in step, see ranks_ahead().
    """
    if hasattr(model, "ranks_ahead"):
        return model.ranks_ahead(ids, k)
    return _rollout(model, ids.tolist(), k, seed, noise, True)


def rollout_tokens(model, ranks, k: int, seed: int | None = None, noise: float = 0.1) -> np.ndarray:
    if hasattr(model, "tokens_ahead"):
        return model.tokens_ahead(ranks, k)
    return _rollout(model, np.asarray(ranks).tolist(), k, seed, noise, False).astype(np.int32)


def _rollout(model, given: list[int], k: int, seed, noise: float, encode: bool) -> np.ndarray:
    true: list[int] = []
    out: list[int] = []
    for at in range(0, len(given), k):
        guess = true[-model.order :] if model.order else []
        for i in range(at, min(at + k, len(given))):
            keys = model.keys_after(guess)
            if encode:
                true.append(given[i])
                out.append(model.rank(keys, given[i]))
            else:
                true.append(model.token_at(keys, given[i]))
                out.append(true[-1])
            second = seed is not None and np.random.Philox(key=seed, counter=i).random_raw(1)[0] / 2.0**64 < noise
            guess = [*guess, model.token_at(keys, 1 if second and model.vocab_size > 1 else 0)]
    return np.array(out, np.int64)
