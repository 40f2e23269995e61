"""Small neural predictors in numpy: a decoder-only transformer and a gated recurrent net, trained in floating point.

For coding, encoder and decoder must order the vocabulary alike on any machine and in any batch. The transformer is therefore
rounded after training: weights and activations are whole numbers held in doubles, so every sum of a matrix product is exact
below 2**53 whatever its order; division and square root are correctly rounded by the floating-point standard; exponentials
come from a table made with decimal arithmetic; equal scores go to the smaller id.
"""

from __future__ import annotations

import hashlib
from decimal import Decimal

import numpy as np

EPS = 1e-5


def softmax(z: np.ndarray) -> np.ndarray:
    z = np.exp(z - z.max(axis=-1, keepdims=True))
    return z / z.sum(axis=-1, keepdims=True)


class Adam:
    def __init__(self, rate: float):
        self.rate, self.t, self.m, self.v = rate, 0, {}, {}

    def step(self, params: dict, grads: dict) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] = 0.9 * self.m.get(k, 0) + 0.1 * g
            self.v[k] = 0.999 * self.v.get(k, 0) + 0.001 * g * g
            params[k] = (params[k] - self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)).astype(params[k].dtype)


class Transformer:
    """Pre-norm decoder with learned positions and an output layer tied to the embedding.

    Windows have a fixed length; a window's first half is context of the second, so that every token but those at a text's
    start sees half a window at least. Id vocab_size stands before a text.
    """

    kind = "transformer"

    def __init__(self, vocab_size: int, layers: int = 2, dim: int = 64, heads: int = 2, context: int = 32, seed: int = 0, dtype=np.float32):
        self.vocab_size, self.layers, self.dim, self.heads, self.context, self.name = vocab_size, layers, dim, heads, context, f"transformer{layers}x{dim}"
        r = np.random.default_rng(seed)
        w = lambda *s, k=0.05: r.normal(0, k, s).astype(dtype)
        p = {"emb": w(vocab_size + 1, dim), "pos": w(context, dim), "gf": np.ones(dim, dtype)}
        for i in range(layers):
            p |= {f"g{i}a": np.ones(dim, dtype), f"g{i}b": np.ones(dim, dtype), f"qkv{i}": w(dim, 3 * dim), f"out{i}": w(dim, dim), f"up{i}": w(dim, 4 * dim), f"down{i}": w(4 * dim, dim)}
        self.p, self.low = p, {}

    @property
    def n_params(self) -> int:
        return sum(a.size for a in self.p.values()) + sum(a.size for a in self.low.values())

    # ------------------------------------------------------------ training

    def _w(self, k: str) -> np.ndarray:
        return self.p[k] + self.low[f"{k}<"] @ self.low[f"{k}>"] if f"{k}<" in self.low else self.p[k]

    def adapt(self, rank: int, seed: int = 1) -> None:
        """From now on only low-rank additions to the feed-forward and attention matrices are trained."""
        r = np.random.default_rng(seed)
        for i in range(self.layers):
            for k in (f"qkv{i}", f"up{i}", f"down{i}"):
                a, b = self.p[k].shape
                self.low[f"{k}<"], self.low[f"{k}>"] = r.normal(0, 0.05, (a, rank)).astype(self.p[k].dtype), np.zeros((rank, b), self.p[k].dtype)

    def forward(self, x: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """Logits (batch, time, vocab) of windows of ids."""
        n, t = x.shape
        h = self.p["emb"][x] + self.p["pos"][:t]
        mask = np.triu(np.full((t, t), -1e9, h.dtype), 1)
        d = self.dim // self.heads

        def norm(h, g, k):
            c = h - h.mean(-1, keepdims=True)
            s = 1 / np.sqrt((c * c).mean(-1, keepdims=True) + EPS)
            if keep is not None:
                keep[k] = (c * s, s)
            return c * s * self.p[g]

        for i in range(self.layers):
            a = norm(h, f"g{i}a", f"n{i}a")
            q, k, v = (z.reshape(n, t, self.heads, d).transpose(0, 2, 1, 3) for z in np.split(a @ self._w(f"qkv{i}"), 3, axis=-1))
            att = softmax(q @ k.transpose(0, 1, 3, 2) / np.sqrt(d).astype(h.dtype) + mask)
            o = (att @ v).transpose(0, 2, 1, 3).reshape(n, t, -1)
            h = h + o @ self.p[f"out{i}"]
            b = norm(h, f"g{i}b", f"n{i}b")
            u = b @ self._w(f"up{i}")
            f = np.maximum(u, 0)
            h = h + f @ self._w(f"down{i}")
            if keep is not None:
                keep[i] = (a, q, k, v, att, o, b, u, f)
        z = norm(h, "gf", "nf")
        if keep is not None:
            keep["z"] = z
        return z @ self.p["emb"][: self.vocab_size].T

    def gradients(self, x: np.ndarray, target: np.ndarray, weight: np.ndarray | None = None) -> tuple[float, dict]:
        """(mean cross-entropy, gradients); target: ids (batch, time), or probabilities (batch, time, vocab)."""
        kept: dict = {}
        logits = self.forward(x, kept)
        prob = softmax(logits)
        n, t = x.shape
        d = self.dim // self.heads
        if target.ndim == 2:
            loss = -np.log(np.take_along_axis(prob, target[..., None], 2) + 1e-30).mean()
            dl = prob
            np.put_along_axis(dl, target[..., None], np.take_along_axis(dl, target[..., None], 2) - 1, 2)
        else:
            loss = -(target * np.log(prob + 1e-30)).sum(-1).mean()
            dl = prob - target
        dl /= n * t
        g = {k: np.zeros_like(v) for k, v in self.p.items()}
        flat = lambda a: a.reshape(-1, a.shape[-1])
        g["emb"][: self.vocab_size] = flat(dl).T @ flat(kept["z"])
        dz = dl @ self.p["emb"][: self.vocab_size]

        def norm_back(dy, gain, key):
            y, s = kept[key]
            g[gain] += flat(dy * y).sum(0)
            dy = dy * self.p[gain]
            return s * (dy - dy.mean(-1, keepdims=True) - y * (dy * y).mean(-1, keepdims=True))

        dh = norm_back(dz, "gf", "nf")
        for i in reversed(range(self.layers)):
            a, q, k, v, att, o, b, u, f = kept[i]
            g[f"down{i}"] = flat(f).T @ flat(dh)
            du = (dh @ self._w(f"down{i}").T) * (u > 0)
            g[f"up{i}"] = flat(b).T @ flat(du)
            dh = dh + norm_back(du @ self._w(f"up{i}").T, f"g{i}b", f"n{i}b")
            g[f"out{i}"] = flat(o).T @ flat(dh)
            do = (dh @ self.p[f"out{i}"].T).reshape(n, t, self.heads, d).transpose(0, 2, 1, 3)
            dv = att.transpose(0, 1, 3, 2) @ do
            da = do @ v.transpose(0, 1, 3, 2)
            ds = att * (da - (da * att).sum(-1, keepdims=True)) / np.sqrt(d).astype(dh.dtype)
            dq, dk = ds @ k, ds.transpose(0, 1, 3, 2) @ q
            dqkv = np.concatenate([z.transpose(0, 2, 1, 3).reshape(n, t, -1) for z in (dq, dk, dv)], axis=-1)
            g[f"qkv{i}"] = flat(a).T @ flat(dqkv)
            dh = dh + norm_back(dqkv @ self._w(f"qkv{i}").T, f"g{i}a", f"n{i}a")
        np.add.at(g["emb"], x.ravel(), flat(dh))
        g["pos"][:t] = dh.sum(0)
        if self.low:
            g = {f"{k}{s}": (g[k] @ self.low[f"{k}>"].T if s == "<" else self.low[f"{k}<"].T @ g[k]) for k in {n[:-1] for n in self.low} for s in "<>"}
        return float(loss), g

    def windows(self, ids: np.ndarray) -> np.ndarray:
        """Rows of context + 1 ids: a window and what follows each of its places."""
        c = self.context
        x = np.concatenate([[self.vocab_size], ids])
        n = (len(x) - 1) // c
        return np.stack([x[i * c : i * c + c + 1] for i in range(n)]) if n else np.zeros((0, c + 1), int)

    def train(self, ids: np.ndarray, steps: int = 300, batch: int = 32, rate: float = 3e-3, teacher=None, alpha: float = 0.7, temperature: float = 1.0, every: int = 0, seed: int = 0) -> list[tuple[int, float, dict | None]]:
        """Adam on random windows; with a teacher, on a mixture of its probabilities and the text.

        Returns (step, loss, parameters at that step where `every` divides it): the checkpoints to choose from.
        """
        w, rng, opt, log = self.windows(ids), np.random.default_rng(seed), Adam(rate), []
        for s in range(1, steps + 1 if len(w) else 1):
            b = w[rng.integers(0, len(w), batch)]
            x, y = b[:, :-1], b[:, 1:]
            if teacher is not None:
                soft = alpha * softmax(teacher.forward(x) / temperature)
                np.put_along_axis(soft, y[..., None], np.take_along_axis(soft, y[..., None], 2) + 1 - alpha, 2)
                y = soft
            opt.rate = rate * min(1, s / 20) * (1 - 0.9 * s / steps)
            loss, g = self.gradients(x, y)
            opt.step(self.low or self.p, g)
            log.append((s, loss, {k: v.copy() for k, v in self.p.items()} if every and s % every == 0 else None))
        return log

    def merge(self) -> None:
        """Put low-rank additions into the weights."""
        for k in {n[:-1] for n in self.low}:
            self.p[k] = self._w(k)
        self.low = {}

    def rounded(self, window: str = "hop") -> WholeTransformer:
        self.merge()
        return WholeTransformer(self, window)


def _exp_table(step: int, places: int, top: int) -> np.ndarray:
    """round(2**places * exp(-i / step)) for i in 0..top, by decimal arithmetic."""
    return np.array([int((Decimal(-i) / step).exp() * 2**places + Decimal("0.5")) for i in range(top + 1)], float)


class WholeTransformer:
    """A transformer in whole numbers, for coding: weights in 1/2**10, activations in 1/2**8, ranks by exact scores."""

    W, A, kind = 10, 8, "transformer"

    def __init__(self, m: Transformer, window: str = "hop"):
        self.window = window
        self.vocab_size, self.layers, self.dim, self.heads, self.context, self.name, self.n_params = m.vocab_size, m.layers, m.dim, m.heads, m.context, m.name, m.n_params
        self.order = 0
        self.p = {k: np.rint(v.astype(float) * 2**self.W) for k, v in m.p.items()}
        self.exp = _exp_table(32, 16, 32 * 12)
        self.model_id = hashlib.sha256(window.encode() + b"".join(k.encode() + self.p[k].tobytes() for k in sorted(self.p))).hexdigest()[:16]

    def _round(self, x, shift):
        return np.rint(x / 2.0**shift)

    def _norm(self, h, gain):
        """To activations of unit variance. Whole sums are exact; sqrt and division round alike everywhere."""
        c = h * self.dim - h.sum(-1, keepdims=True)
        root = np.sqrt((c * c).sum(-1, keepdims=True) + 1)
        return self._round(np.rint(c * np.sqrt(float(self.dim)) * 2**self.A / root) * self.p[gain], self.W)

    def forward(self, x: np.ndarray) -> np.ndarray:
        n, t = x.shape
        d = self.dim // self.heads
        h = self._round(self.p["emb"][x] + self.p["pos"][:t], self.W - self.A)
        late = np.triu(np.ones((t, t), bool), 1)
        for i in range(self.layers):
            a = self._norm(h, f"g{i}a")
            q, k, v = (z.reshape(n, t, self.heads, d).transpose(0, 2, 1, 3) for z in np.split(self._round(a @ self.p[f"qkv{i}"], self.W), 3, axis=-1))
            s = np.rint((q @ k.transpose(0, 1, 3, 2)) / np.sqrt(float(d)) / 2.0 ** (2 * self.A - 5))  # in 1/32, as the table
            s[..., late] = -1e15
            far = np.minimum(s.max(-1, keepdims=True) - s, len(self.exp) - 1).astype(int)
            e = np.where(late, 0, self.exp[far])
            o = np.rint((e @ v) / e.sum(-1, keepdims=True))
            h = h + self._round(o.transpose(0, 2, 1, 3).reshape(n, t, -1) @ self.p[f"out{i}"], self.W)
            u = np.maximum(self._round(self._norm(h, f"g{i}b") @ self.p[f"up{i}"], self.W), 0)
            h = h + self._round(u @ self.p[f"down{i}"], self.W)
        return self._norm(h, "gf") @ self.p["emb"][: self.vocab_size].T

    def _window(self, ids, at: int) -> tuple[np.ndarray, int]:
        """The window in which the token at a place is predicted, and the place's row in it.

        hop: windows begin at every half of a window, and grow from half to whole. fixed: the window ends at the place, always
        as long as there is text. growing: it begins at the last whole multiple of the window's length, and grows from nothing.
        """
        c = self.context
        start = {"hop": max(0, (at // (c // 2) - 1) * (c // 2)), "fixed": max(0, at - c + 1), "growing": at // c * c}[self.window]
        x = np.concatenate([[self.vocab_size], ids[max(0, start - 1) : start + c]])[: c + 1]
        x = x[1:] if start else x[:-1] if len(x) > c else x
        return np.pad(x, (0, c - len(x)), constant_values=self.vocab_size), at - start

    def _rank(self, logits: np.ndarray, true: np.ndarray) -> np.ndarray:
        own = logits[np.arange(len(true)), true][:, None]
        return (logits > own).sum(1) + ((logits == own) & (np.arange(self.vocab_size) < true[:, None])).sum(1)

    def _listed(self, logits: np.ndarray, ranks) -> np.ndarray:
        """The tokens at the ranks, a row each."""
        order = np.lexsort((np.broadcast_to(np.arange(self.vocab_size), logits.shape), -logits), axis=-1)
        return order[np.arange(len(order)), ranks]

    def ranks(self, ids: np.ndarray, batch: int = 16) -> np.ndarray:
        return self.ranks_many([ids], batch)[0]

    def ranks_many(self, many: list, batch: int = 0) -> list[np.ndarray]:
        """The ranks of several texts; `batch` windows, of any of them, to a call."""
        c, hop = self.context, self.context // 2
        many = [np.asarray(ids, np.int64) for ids in many]
        begin = np.cumsum([0, *(len(ids) + 1 for ids in many)])
        text = np.concatenate([x for ids in many for x in ([self.vocab_size], ids)] + [np.full(c, self.vocab_size)])
        parts = []  # where a window begins, its first row that is asked for, how many are
        for at, ids in zip(begin, many):
            n = len(ids)
            first, step, row = {"hop": (2 * hop, hop, hop), "fixed": (c, 1, c - 1), "growing": (c, c, 0)}[self.window]
            s = np.arange(first, n, step)
            parts.append(np.stack([at + s - row, np.full(len(s), row), np.minimum(step, n - s)], 1))
            parts.append(np.array([[at, 0, min(first, n)]] if n else np.zeros((0, 3)), int))
        parts = np.concatenate(parts) if parts else np.zeros((0, 3), int)
        parts = parts[np.lexsort((-parts[:, 2], parts[:, 1]))]
        out, size = np.zeros(len(text), np.int64), batch or max(16, 1600 // c)
        for low in np.unique(parts[:, 1]):
            own = parts[parts[:, 1] == low]
            for b in range(0, len(own), size):
                w, n = own[b : b + size, 0], own[b : b + size, 2]
                x = text[w[:, None] + np.arange(low + n[0])]
                at = (w[:, None] + low + np.arange(n[0]))[np.arange(n[0]) < n[:, None]]
                h = self._layers(x, low)[0][:, low:][np.arange(n[0]) < n[:, None]]
                for i in range(0, len(h), 256):  # scores that stay in the processor's cache
                    out[at[i : i + 256]] = self._above(self._last(h[i : i + 256]), text[at[i : i + 256] + 1])
        return [out[at : at + len(ids)] for at, ids in zip(begin, many)]

    # ------------------------------------------------------------ the same whole numbers, of only the rows that are asked for

    def _weights(self, x: np.ndarray, k: str) -> np.ndarray:
        y = x.reshape(-1, x.shape[-1]) @ self.p[k]
        y *= 2.0**-self.W
        return np.rint(y, out=y).reshape(*x.shape[:-1], -1)

    def _scaled(self, s: np.ndarray) -> np.ndarray:
        s /= np.sqrt(float(self.dim // self.heads)) * 2.0 ** (2 * self.A - 5)
        return np.rint(s, out=s)

    def _exps(self, top: np.ndarray, s: np.ndarray) -> np.ndarray:
        """The table ends in zero, so that places out of sight, at -1e15, get none."""
        return self.exp.take(np.subtract(top, s, out=s).astype(np.intp), mode="clip")

    def _finish(self, h: np.ndarray, o: np.ndarray, i: int) -> np.ndarray:
        h = h + self._weights(o, f"out{i}")
        u = self._weights(self._norm(h, f"g{i}b"), f"up{i}")
        return h + self._weights(np.maximum(u, 0, out=u), f"down{i}")

    def _layers(self, x: np.ndarray, low: int = 0) -> tuple[np.ndarray, list]:
        """What the last layer gives for the rows from `low` on (those before are not right), and the keys and values of each layer."""
        n, t = x.shape
        d, kept = self.dim // self.heads, []
        h = self._round(self.p["emb"][x] + self.p["pos"][:t], self.W - self.A)
        for i in range(self.layers):
            lo = low if i == self.layers - 1 else 0
            q, k, v = self._weights(self._norm(h, f"g{i}a"), f"qkv{i}").reshape(n, t, 3, self.heads, d).transpose(2, 0, 3, 1, 4)
            kept.append((k, v))
            s = self._scaled(q[:, :, lo:] @ k.transpose(0, 1, 3, 2))
            s += np.triu(np.full((t, t), -1e15), 1)[lo:]
            e = self._exps(s.max(-1, keepdims=True), s)
            o = np.rint((e @ v) / e.sum(-1, keepdims=True)).transpose(0, 2, 1, 3).reshape(n, t - lo, -1)
            g = self._finish(h[:, lo:], o, i)
            h = np.concatenate([h[:, :lo], g], 1) if lo else g
        return h, kept

    def _last(self, h: np.ndarray) -> np.ndarray:
        """Scores that no two tokens share: a whole multiple of the logit, less the token's id."""
        top = np.concatenate([self.p["emb"][: self.vocab_size].T * float(self.vocab_size), -np.arange(float(self.vocab_size))[None]])
        h = self._norm(h, "gf")
        return np.concatenate([h, np.ones((*h.shape[:-1], 1))], -1) @ top

    @staticmethod
    def _above(z: np.ndarray, true: np.ndarray) -> np.ndarray:
        """How many scores of each row are above the token's own."""
        bits = np.packbits(z > np.take_along_axis(z, true[:, None], 1), axis=1)
        return np.bitwise_count(bits).sum(1, dtype=np.int64)

    def _next(self, x: np.ndarray, at: np.ndarray, upto: np.ndarray, kept: list, own: list) -> np.ndarray:
        """One row more for each lane (window, lane): the token x at row `at`, which sees its window's rows below `upto` and the lane's
        own rows, whose keys and values are in `own`, and which it joins."""
        n, g = x.shape
        d = self.dim // self.heads
        h = self._round(self.p["emb"][x] + self.p["pos"][at], self.W - self.A)
        for i, (k, v) in enumerate(kept):
            q, k_, v_ = self._weights(self._norm(h, f"g{i}a"), f"qkv{i}").reshape(n, g, 3, self.heads, d).transpose(2, 0, 3, 1, 4)
            own[i] = tuple(z[..., None, :] if own[i] is None else np.concatenate([y, z[..., None, :]], -2) for y, z in zip(own[i] or (None, None), (k_, v_)))
            s = self._scaled(q @ k.transpose(0, 1, 3, 2))
            s += np.where(np.arange(k.shape[2]) < upto[..., None], 0, -1e15)[:, None]
            r = self._scaled((q[..., None, :] * own[i][0]).sum(-1))
            top = np.maximum(s.max(-1, keepdims=True), r.max(-1, keepdims=True))
            e, f = self._exps(top, s), self._exps(top, r)
            o = (e @ v + (f[..., None] * own[i][1]).sum(-2)) / (e.sum(-1) + f.sum(-1))[..., None]
            h = self._finish(h, np.rint(o).transpose(0, 2, 1, 3).reshape(n, g, -1), i)
        return h

    def tokens(self, ranks) -> np.ndarray:
        return self.tokens_many([ranks])[0]

    def tokens_many(self, many: list) -> list[np.ndarray]:
        """The tokens of several sequences of ranks, decoded in step: one predictor call for the next token of all that go on."""
        many = [np.asarray(r, np.int64) for r in many]
        out = [np.zeros(len(r), np.int64) for r in many]
        for t in range(max(map(len, many), default=0)):
            on = [k for k, r in enumerate(many) if len(r) > t]
            got = [self._window(out[k][:t], t) for k in on]
            rows = np.array([row for _, row in got])
            z = self.forward(np.stack([w for w, _ in got])[:, : rows.max() + 1])
            for k, token in zip(on, self._listed(z[np.arange(len(on)), rows], [many[k][t] for k in on])):
                out[k][t] = token
        return [o.astype(np.int32) for o in out]

    # ------------------------------------------------------------ k tokens ahead

    def _ahead(self, given: np.ndarray, k: int, encode: bool, batch: int = 64) -> tuple[np.ndarray, int]:
        """Ranks (or tokens) when a group of k is predicted from the text before it and the model's own first guesses, and the number of
        predictor calls. The encoder knows all text, so its groups go in step, many to a call; the decoder's follow each other."""
        given = np.asarray(given, np.int64)
        true = given.copy() if encode else np.zeros(len(given), np.int64)
        out, calls = np.zeros(len(given), np.int64), 0
        starts = list(range(0, len(given), k))
        size = batch if encode else 1
        for b in range(0, len(starts), size):
            part = starts[b : b + size]
            seen = [true[:s] for s in part]
            for j in range(k):
                on = [g for g, s in enumerate(part) if s + j < len(given)]
                if not on:
                    break
                got = [self._window(seen[g], part[g] + j) for g in on]
                rows = np.array([row for _, row in got])
                z = self.forward(np.stack([w for w, _ in got])[:, : rows.max() + 1])[np.arange(len(on)), rows]
                at = np.array([part[g] + j for g in on])
                calls += 1
                if encode:
                    out[at] = self._rank(z, true[at])
                else:
                    true[at] = out[at] = self._listed(z, given[at])
                guess = self._listed(z, np.zeros(len(on), int))
                for g, x in zip(on, guess):
                    seen[g] = np.append(seen[g], x)
        return out, calls

    def ranks_ahead(self, ids, k: int, batch: int = 16) -> np.ndarray:
        """As _ahead() has them. The windows of the text itself are run once; each guess is one row more, for all groups of `batch` half windows
        in step. A group that runs into the next half window gives its guesses again there."""
        hop = self.context // 2
        if self.window != "hop" or k > hop:
            return self._ahead(ids, k, True)[0]
        if k == 1:
            return self.ranks(ids)
        ids = np.asarray(ids, np.int64)
        n, c = len(ids), self.context
        text = np.concatenate([[self.vocab_size], ids, np.full(c + k, self.vocab_size)])
        out, guess = np.zeros(n + c + k, np.int64), np.zeros((-(-n // k) + hop, k), np.int64)

        def put(h, at, groups, j, wanted):
            z = self._last(h[wanted])
            guess[groups[wanted], j] = z.argmax(-1)
            out[at[wanted]] = self._above(z, text[at[wanted] + 1])

        for a in range(0, -(-n // hop), batch):
            half = np.arange(a, min(a + batch, -(-n // hop)))
            start = np.maximum(0, (half - 1) * hop)[:, None]
            h, kept = self._layers(text[start + np.arange(c)])
            groups = -(-half * hop // k)[:, None] + np.arange(-(-hop // k))
            s, end = groups * k, np.minimum((half + 1) * hop, n)[:, None]
            row = np.where(s < end, s - start, 0)
            put(np.take_along_axis(h, row[..., None], 1), s, groups, 0, s < end)
            own = [None] * self.layers
            for j in range(1, k):
                z = self._next(guess[np.where(s < end, groups, 0), j - 1], np.where(s + j < end, row + j, 0), row + 1, kept, own)
                put(z, s + j, groups, j, s + j < end)
            groups = (half * hop // k)[:, None]
            s = groups * k
            over = (s < half[:, None] * hop) & (half[:, None] > 0)
            if over.any():
                row, own = np.where(over, s - start, 0), [None] * self.layers
                for j in range(1, k):
                    z = self._next(guess[groups, j - 1], np.where(over, row + j, 0), row + 1, kept, own)
                    put(z, s + j, groups, j, over & (s + j >= half[:, None] * hop) & (s + j < end))
        return out[:n]

    def tokens_ahead(self, ranks, k: int) -> np.ndarray:
        return self._ahead(ranks, k, False)[0].astype(np.int32)


class Recurrent:
    """A gated recurrent net with tied output, trained by truncated back-propagation through time; its ranks come from
    rounded scores with ties to the smaller id. When coding, states and weights are whole multiples of 1 / 2**20: texts go in step, and a text's
    ranks don't depend on those beside it."""

    kind, order = "recurrent", 0

    def __init__(self, vocab_size: int, dim: int = 64, seed: int = 0):
        self.vocab_size, self.dim, self.name = vocab_size, dim, f"recurrent{dim}"
        r = np.random.default_rng(seed)
        w = lambda *s: r.normal(0, 0.1, s).astype(np.float32)
        self.p = {"emb": w(vocab_size + 1, dim), "x": w(dim, 3 * dim), "h": w(dim, 3 * dim), "b": np.zeros(3 * dim, np.float32)}

    @property
    def n_params(self) -> int:
        return sum(a.size for a in self.p.values())

    @property
    def model_id(self) -> str:
        return hashlib.sha256(f"{self.U:.0f}".encode() + b"".join(self.p[k].tobytes() for k in sorted(self.p))).hexdigest()[:16]

    def _step(self, x, h):
        s = lambda z: 0.5 * (1 + np.tanh(0.5 * z))
        a, c, d = self.p["emb"][x] @ self.p["x"] + self.p["b"], h @ self.p["h"], self.dim
        z, r = s(a[:, :d] + c[:, :d]), s(a[:, d : 2 * d] + c[:, d : 2 * d])
        m = np.tanh(a[:, 2 * d :] + r * c[:, 2 * d :])
        return (1 - z) * h + z * m, (x, h, z, r, m, c[:, 2 * d :])

    def gradients(self, x: np.ndarray, y: np.ndarray) -> tuple[float, dict]:
        n, t = x.shape
        d, h, steps, hs = self.dim, np.zeros((n, self.dim), np.float32), [], []
        for i in range(t):
            h, k = self._step(x[:, i], h)
            steps.append(k)
            hs.append(h)
        out = np.stack(hs, 1)
        e = self.p["emb"][: self.vocab_size]
        p = softmax(out @ e.T)
        loss = -np.log(np.take_along_axis(p, y[..., None], 2) + 1e-30).mean()
        np.put_along_axis(p, y[..., None], np.take_along_axis(p, y[..., None], 2) - 1, 2)
        p /= n * t
        g = {k: np.zeros_like(v) for k, v in self.p.items()}
        g["emb"][: self.vocab_size] = p.reshape(-1, self.vocab_size).T @ out.reshape(-1, d)
        dout, dh = p @ e, 0
        for i in reversed(range(t)):
            xi, h, z, r, m, cm = steps[i]
            dh = dh + dout[:, i]
            dm = dh * z * (1 - m * m)
            dz = dh * (m - h) * z * (1 - z)
            dr = dm * cm * r * (1 - r)
            da, dc = np.concatenate([dz, dr, dm], 1), np.concatenate([dz, dr, dm * r], 1)
            g["x"] += self.p["emb"][xi].T @ da
            g["b"] += da.sum(0)
            g["h"] += h.T @ dc
            np.add.at(g["emb"], xi, da @ self.p["x"].T)
            dh = dh * (1 - z) + dc @ self.p["h"].T
        return float(loss), g

    def train(self, ids: np.ndarray, steps: int = 200, batch: int = 32, length: int = 32, rate: float = 3e-3, seed: int = 0) -> list[float]:
        x, rng, opt, log = np.concatenate([[self.vocab_size], ids]), np.random.default_rng(seed), Adam(rate), []
        for _ in range(steps if len(ids) > length else 0):
            s = rng.integers(0, len(x) - length, batch)
            w = np.stack([x[i : i + length + 1] for i in s])
            loss, g = self.gradients(w[:, :-1], w[:, 1:])
            opt.step(self.p, g)
            log.append(loss)
        return log

    # ------------------------------------------------------------ coding

    U = 2.0**20  # states, weights and sums are whole multiples of 1 / U held in doubles

    def _whole(self) -> tuple:
        """What each token adds to the gates, the gates' weights on the state, and the tokens' scores by it, in whole numbers."""
        e, x, h, b = (np.rint(self.p[k].astype(float) * self.U) for k in ("emb", "x", "h", "b"))
        return np.rint(e @ x / self.U) + b, h, e[: self.vocab_size].T

    def _moved(self, a: np.ndarray, h: np.ndarray, w: np.ndarray) -> np.ndarray:
        """States after one token more each, as _step() has them. Sums of whole numbers are exact, so that the texts beside one don't matter."""
        c, d = np.rint(h @ w / self.U), self.dim
        g = 0.5 * (1 + np.tanh((0.5 / self.U) * (a[:, : 2 * d] + c[:, : 2 * d])))
        z, r = g[:, :d], g[:, d:]
        return np.rint((1 - z) * h + z * (self.U * np.tanh((a[:, 2 * d :] + r * c[:, 2 * d :]) / self.U)))

    def _logits(self, h: np.ndarray, e: np.ndarray) -> np.ndarray:
        z = h @ e
        z *= 1024 / self.U**2
        return np.rint(z, out=z)

    def ranks(self, ids: np.ndarray) -> np.ndarray:
        return self.ranks_many([ids])[0]

    def ranks_many(self, many: list, batch: int = 4096) -> list[np.ndarray]:
        """The ranks of several texts, a token of each at a time; scores are made for about `batch` tokens at once."""
        first, w, e = self._whole()
        order = sorted(range(len(many)), key=lambda k: -len(many[k]))
        length = np.array([len(many[k]) for k in order], int)
        ids = np.full((len(many), int(length.max(initial=0)) + 1), self.vocab_size, np.int64)
        for row, k in zip(ids, order):
            row[1 : len(many[k]) + 1] = many[k]
        out, h, states, done = np.zeros(ids.shape, np.int64), np.zeros((len(many), self.dim)), [], 0
        for t in range(ids.shape[1] - 1):
            n = int(np.searchsorted(-length, -t))  # texts that go on
            h = self._moved(first[ids[:n, t]], h[:n], w)
            states.append(h)
            if sum(map(len, states)) >= batch or t == ids.shape[1] - 2:
                rows = np.concatenate([np.arange(len(x)) for x in states])
                at = np.repeat(np.arange(done, t + 1), [len(x) for x in states]) + 1
                h_, true = np.concatenate(states), ids[rows, at]
                for i in range(0, len(rows), 256):
                    z, own = self._logits(h_[i : i + 256], e), true[i : i + 256, None]
                    z = z * self.vocab_size - np.arange(self.vocab_size)  # no two alike: the smaller id comes first
                    bits = np.packbits(z > np.take_along_axis(z, own, 1), axis=1)
                    out[rows[i : i + 256], at[i : i + 256]] = np.bitwise_count(bits).sum(1, dtype=np.int64)
                states, done = [], t + 1
        back = dict(zip(order, out))
        return [back[k][1 : len(many[k]) + 1] for k in range(len(many))]

    def tokens(self, ranks) -> np.ndarray:
        return self.tokens_many([ranks])[0]

    def tokens_many(self, many: list) -> list[np.ndarray]:
        first, w, e = self._whole()
        many = [np.asarray(r, np.int64) for r in many]
        order = sorted(range(len(many)), key=lambda k: -len(many[k]))
        out, h, x = [np.zeros(len(r), np.int32) for r in many], np.zeros((len(many), self.dim)), np.full(len(many), self.vocab_size)
        for t in range(max(map(len, many), default=0)):
            on = [k for k in order if len(many[k]) > t]
            h = self._moved(first[x[: len(on)]], h[: len(on)], w)
            x = np.argsort(-self._logits(h, e), axis=1, kind="stable")[np.arange(len(on)), [many[k][t] for k in on]]
            for k, token in zip(on, x):
                out[k][t] = token
        return out


def direct_encode(model, ids: np.ndarray) -> bytes:
    """Arithmetic coding with the count model's own frequencies, without ranks: what ranking loses shows in comparison."""
    from .codecs import RangeEncoder, put_varint
    from .predictors import context_keys

    enc = RangeEncoder()
    for keys, t in zip(np.stack(context_keys(ids, model.order), axis=1).tolist(), ids.tolist()):
        enc.put(*model.frequency(keys, t))
    return put_varint(len(ids)) + enc.done()


def direct_decode(model, data: bytes) -> np.ndarray:
    from .codecs import RangeDecoder, get_varint

    n, at = get_varint(data)
    dec, out = RangeDecoder(data, at), []
    for _ in range(n):
        f = model.frequencies(model.keys_after(out))
        cum = np.cumsum(f)
        t = int(np.searchsorted(cum, dec.target(int(cum[-1])), side="right"))
        dec.take(int(cum[t] - f[t]), int(f[t]))
        out.append(t)
    return np.array(out, np.int32)


def ideal_bits(model, ids: np.ndarray) -> float:
    """Sum of -log2 of the model's probabilities: what direct coding comes close to."""
    from .predictors import context_keys

    out = 0.0
    for keys, t in zip(np.stack(context_keys(ids, model.order), axis=1).tolist() if len(ids) else [], ids.tolist()):
        _, own, all_ = model.frequency(keys, t)
        out -= np.log2(own / all_)
    return float(out)
