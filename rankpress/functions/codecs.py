"""Lossless codecs bytes -> bytes: the classical baselines, and the second stage after rank prediction.

Own codecs start with the length of the input as a varint, so every output decodes alone. Each codec maps b"" to something that
decodes to b"". None keeps state between calls.
"""

from __future__ import annotations

import bz2
import gzip
import heapq
import lzma
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa

# ------------------------------------------------------------------ bits and numbers


def put_varint(n: int) -> bytes:
    out = bytearray()
    while n > 127:
        out.append(n & 127 | 128)
        n >>= 7
    out.append(n)
    return bytes(out)


def get_varint(data: bytes, at: int = 0) -> tuple[int, int]:
    n = shift = 0
    while True:
        b = data[at]
        at += 1
        n |= (b & 127) << shift
        if b < 128:
            return n, at
        shift += 7


def pack_bits(bits: str) -> bytes:
    return int(bits + "0" * (-len(bits) % 8), 2).to_bytes((len(bits) + 7) // 8, "big") if bits else b""


def unpack_bits(data: bytes) -> str:
    return bin(int.from_bytes(b"\x01" + data, "big"))[3:]


# ------------------------------------------------------------------ range coder


class RangeEncoder:
    """Carry-propagating range coder with 32-bit range and byte output."""

    def __init__(self):
        self.low, self.range, self.cache, self.pending, self.out = 0, 0xFFFFFFFF, 0, 0, bytearray()
        self.first = True

    def put(self, cum: int, freq: int, total: int) -> None:
        r = self.range // total
        self.low += cum * r
        self.range = freq * r
        while self.range < 1 << 24:
            self._shift()
            self.range = self.range << 8 & 0xFFFFFFFF

    def _shift(self) -> None:
        if self.low < 0xFF000000 or self.low > 0xFFFFFFFF:
            carry = self.low >> 32
            if not self.first:
                self.out.append(self.cache + carry & 255)
            self.out += bytes([255 + carry & 255]) * self.pending
            self.first, self.pending, self.cache = False, 0, self.low >> 24 & 255
        else:
            self.pending += 1
        self.low = self.low << 8 & 0xFFFFFFFF

    def done(self) -> bytes:
        for _ in range(5):
            self._shift()
        return bytes(self.out)


class RangeDecoder:
    def __init__(self, data: bytes, at: int = 0):
        self.data, self.at, self.range = data, at + 4, 0xFFFFFFFF
        self.code = int.from_bytes(data[at : at + 4].ljust(4, b"\0"), "big")

    def target(self, total: int) -> int:
        self.r = self.range // total
        return min(total - 1, self.code // self.r)

    def take(self, cum: int, freq: int) -> None:
        self.code -= cum * self.r
        self.range = freq * self.r
        while self.range < 1 << 24:
            nxt = self.data[self.at] if self.at < len(self.data) else 0
            self.code = (self.code << 8 | nxt) & 0xFFFFFFFF
            self.at += 1
            self.range = self.range << 8 & 0xFFFFFFFF


class Fenwick:
    """Adaptive frequencies of n symbols, all one at first, halved at a limit."""

    def __init__(self, n: int, step: int = 32, limit: int = 1 << 16):
        self.n, self.step, self.limit, self.f, self.total = n, step, limit, [1] * n, n
        self._build()

    def _build(self) -> None:
        self.t = [0, *self.f]
        for i in range(1, self.n + 1):
            if (j := i + (i & -i)) <= self.n:
                self.t[j] += self.t[i]

    def below(self, s: int) -> int:
        c = 0
        while s:
            c += self.t[s]
            s &= s - 1
        return c

    def find(self, target: int) -> tuple[int, int]:
        """(symbol, sum below it) for a target in [0, total)."""
        at, c, bit = 0, 0, 1 << self.n.bit_length()
        while bit:
            if (nxt := at + bit) <= self.n and c + self.t[nxt] <= target:
                at, c = nxt, c + self.t[nxt]
            bit >>= 1
        return at, c

    def add(self, s: int) -> None:
        self.f[s] += self.step
        self.total += self.step
        i = s + 1
        while i <= self.n:
            self.t[i] += self.step
            i += i & -i
        if self.total > self.limit:
            self.f = [(x + 1) // 2 for x in self.f]
            self.total = sum(self.f)
            self._build()


class Lanes:
    """Adaptive frequencies of bytes for many texts at once, as Fenwick(256) keeps them for each: sums below each of 16 groups of
    symbols, and within each group."""

    def __init__(self, n: int, step: int = 32, limit: int = 1 << 16):
        self.limit, self.lane = limit, np.arange(n)
        self.high = np.repeat(np.arange(0, 257, 16, dtype=np.int32)[:, None], n, 1)
        self.low = np.tile(np.arange(17, dtype=np.int32), (n * 16, 1))
        self.more = np.tril(np.full((17, 17), step, np.int32), -1)  # what a symbol adds to the sums below each place
        self.rows = np.ascontiguousarray(self.more.T)
        self.total = np.full(n, 256, np.int64)

    @staticmethod
    def _last(sums: np.ndarray, target: np.ndarray) -> np.ndarray:
        """How many sums, of 16, are at most the target."""
        return np.add.reduce((sums <= target).view(np.int8), axis=0, dtype=np.int8).astype(np.intp)

    def find(self, target: np.ndarray) -> np.ndarray:
        n, target = len(target), target.astype(np.int32)
        g = self._last(self.high[1:, :n], target)
        row = np.ascontiguousarray(self.low.take(self.lane[:n] * 16 + g, axis=0).T)
        return g << 4 | self._last(row[1:], target - self.high[g, self.lane[:n]])

    def take(self, s: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(sum below, frequency, total) of a symbol of each of the first lanes, which is then counted."""
        n, g, k = len(s), s >> 4, s & 15
        at = self.lane[:n] * 16 + g
        flat, place = self.low.reshape(-1), at * 17 + k
        below = flat.take(place)
        out = (self.high[g, self.lane[:n]] + below).astype(np.int64), (flat.take(place + 1) - below).astype(np.int64), self.total[:n].copy()
        self.high[:, :n] += self.more.take(g, axis=1)
        self.low[at] = self.low.take(at, axis=0) + self.rows.take(k, axis=0)
        self.total[:n] += self.more[1, 0]
        if self.total[:n].max() > self.limit:
            full = np.flatnonzero(self.total[:n] > self.limit)
            low = self.low.reshape(-1, 16, 17)
            f = (np.diff(low[full], axis=2) + 1) // 2
            low[full, :, 1:] = f.cumsum(2)
            self.high[1:, full] = f.sum(2).cumsum(1).T
            self.total[full] = self.high[16, full]
        return out


def together(sizes: list[int], most: int = 1 << 23, lanes: int = 1024):
    """Texts by size, the largest first, in groups that fit a table of `most` bytes."""
    order = sorted(range(len(sizes)), key=lambda k: -sizes[k])
    while order:
        n = max(1, min(lanes, most // max(1, sizes[order[0]])))
        yield order[:n]
        order = order[n:]


class Codec:
    name = "raw"

    def encode(self, data: bytes) -> bytes:
        return bytes(data)

    def decode(self, data: bytes) -> bytes:
        return bytes(data)


class ArithmeticCodec(Codec):
    """Order-0 arithmetic coding of bytes; adaptive, or static with its table of counts in front."""

    def __init__(self, adaptive: bool = True):
        self.adaptive = adaptive
        self.name = "arithmetic" if adaptive else "arithmetic_static"

    def encode(self, data: bytes) -> bytes:
        enc, head = RangeEncoder(), put_varint(len(data))
        if self.adaptive:
            m = Fenwick(256)
            for s in data:
                enc.put(m.below(s), m.f[s], m.total)
                m.add(s)
            return head + enc.done()
        n = np.bincount(np.frombuffer(data, np.uint8), minlength=256)
        scale = 1 if len(data) < 1 << 16 else (1 << 16) / len(data)  # totals stay within the coder's precision
        f = np.where(n > 0, np.maximum(1, (n * scale).astype(int)), 0).tolist()
        cum = np.concatenate(([0], np.cumsum(f))).tolist()
        used = [s for s in range(256) if f[s]]
        table = put_varint(len(used)) + b"".join(bytes([s]) + put_varint(f[s]) for s in used)
        for s in data:
            enc.put(cum[s], f[s], cum[-1])
        return head + table + enc.done()

    def encode_many(self, many: list[bytes]) -> list[bytes]:
        """encode() of each. Adaptive coders go in step, a byte of each text at a time; digits keep their carries to the end."""
        if not self.adaptive:
            return [self.encode(x) for x in many]
        out = [b""] * len(many)
        for group in together([len(x) for x in many]):
            size = np.array([len(many[k]) for k in group])
            data, digits = np.zeros((size[0], len(group)), np.uint8), np.zeros((len(group), 2 * size[0] + 4), np.int16)
            for i, k in enumerate(group):
                data[: size[i], i] = np.frombuffer(many[k], np.uint8)
            m, count = Lanes(len(group)), np.zeros(len(group), np.intp)
            low, span = np.zeros(len(group), np.int64), np.full(len(group), 0xFFFFFFFF)

            def shift(on):
                digits[on, count[on]] = low[on] >> 24
                count[on] += 1
                low[on] = (low[on] & 0xFFFFFF) << 8

            for t in range(size[0]):
                n = int(np.searchsorted(-size, -t))
                below, f, total = m.take(data[t, :n].astype(np.intp))
                r = span[:n] // total
                low[:n] += below * r
                span[:n] = f * r
                while (on := (span[:n] < 1 << 24).nonzero()[0]).size:
                    shift(on)
                    span[on] <<= 8
            for _ in range(4):
                shift(m.lane)
            while (carry := digits >> 8).any():
                digits &= 255
                digits[:, :-1] += carry[:, 1:]
            for k, n, row in zip(group, count, digits.astype(np.uint8)):
                out[k] = put_varint(len(many[k])) + row[:n].tobytes()
        return out

    def decode_many(self, many: list[bytes]) -> list[bytes]:
        """decode() of each, adaptive coders in step."""
        if not self.adaptive:
            return [self.decode(x) for x in many]
        out, heads = [b""] * len(many), [get_varint(x) for x in many]
        for group in together([n for n, _ in heads]):
            size, begin = np.array([heads[k][0] for k in group]), [heads[k][1] for k in group]
            data = np.zeros((len(group), max(len(many[k]) for k in group) + 8), np.uint8)
            for i, k in enumerate(group):
                data[i, : len(many[k]) - begin[i]] = np.frombuffer(many[k], np.uint8, offset=begin[i])
            m, at, found = Lanes(len(group)), np.full(len(group), 4), np.zeros((size[0], len(group)), np.uint8)
            code, span = data[:, :4].astype(np.int64) @ (1 << np.arange(24, -1, -8)), np.full(len(group), 0xFFFFFFFF)
            for t in range(size[0]):
                n = int(np.searchsorted(-size, -t))
                r = span[:n] // m.total[:n]
                s = m.find(np.minimum(m.total[:n] - 1, code[:n] // r))
                found[t, :n] = s
                below, f, _ = m.take(s)
                code[:n] -= below * r
                span[:n] = f * r
                while (on := (span[:n] < 1 << 24).nonzero()[0]).size:
                    code[on] = (code[on] << 8 | data[on, np.minimum(at[on], data.shape[1] - 1)]) & 0xFFFFFFFF
                    at[on] += 1
                    span[on] <<= 8
            for i, (k, row) in enumerate(zip(group, np.ascontiguousarray(found.T))):
                out[k] = row[: size[i]].tobytes()
        return out

    def decode(self, data: bytes) -> bytes:
        n, at = get_varint(data)
        out = bytearray()
        if self.adaptive:
            m, dec = Fenwick(256), RangeDecoder(data, at)
            for _ in range(n):
                s, c = m.find(dec.target(m.total))
                dec.take(c, m.f[s])
                m.add(s)
                out.append(s)
            return bytes(out)
        k, at = get_varint(data, at)
        f = [0] * 256
        for _ in range(k):
            s = data[at]
            f[s], at = get_varint(data, at + 1)
        cum = np.concatenate(([0], np.cumsum(f)))
        dec, low = RangeDecoder(data, at), cum.tolist()
        for _ in range(n):
            s = int(np.searchsorted(cum, dec.target(low[-1]), side="right")) - 1
            dec.take(low[s], f[s])
            out.append(s)
        return bytes(out)


# ------------------------------------------------------------------ Huffman


def code_lengths(counts: dict[int, int]) -> dict[int, int]:
    """Length of each symbol's code; one symbol alone gets one bit. Ties go to the smaller symbol."""
    if len(counts) == 1:
        return {s: 1 for s in counts}
    heap = [(c, s, (s,)) for s, c in counts.items()]
    heapq.heapify(heap)
    depth = dict.fromkeys(counts, 0)
    while len(heap) > 1:
        (a, x, left), (b, y, right) = heapq.heappop(heap), heapq.heappop(heap)
        for s in left + right:
            depth[s] += 1
        heapq.heappush(heap, (a + b, min(x, y), left + right))
    return depth


def canonical(lengths: dict[int, int]) -> dict[int, str]:
    """Codes in the order of length, then symbol."""
    code = size = 0
    out = {}
    for length, s in sorted((n, s) for s, n in lengths.items()):
        code <<= length - size
        size = length
        out[s] = format(code, f"0{length}b")
        code += 1
    return out


class HuffmanCodec(Codec):
    name = "huffman"

    def encode(self, data: bytes) -> bytes:
        if not data:
            return put_varint(0)
        lengths = code_lengths(Counter(data))
        code = canonical(lengths)
        table = put_varint(len(lengths)) + b"".join(bytes([s, n]) for s, n in sorted(lengths.items()))
        return put_varint(len(data)) + table + pack_bits("".join([code[s] for s in data]))

    def decode(self, data: bytes) -> bytes:
        n, at = get_varint(data)
        if not n:
            return b""
        k, at = get_varint(data, at)
        lengths = {data[at + 2 * i]: data[at + 2 * i + 1] for i in range(k)}
        back = {c: s for s, c in canonical(lengths).items()}
        bits, out, i = unpack_bits(data[at + 2 * k :]), bytearray(), 0
        sizes = sorted(set(lengths.values()))
        for _ in range(n):
            for size in sizes:
                s = back.get(bits[i : i + size])
                if s is not None and len(bits) >= i + size:
                    out.append(s)
                    i += size
                    break
        return bytes(out)


class _SiblingTree:
    """The tree of one-pass Huffman coding: nodes in an order of falling weight in which siblings stand together."""

    def __init__(self):
        self.weight, self.parent, self.kids, self.symbol = [0], [-1], [None], [None]
        self.order, self.rank, self.leaf, self.nyt = [0], [0], {}, 0

    def path(self, node: int) -> str:
        out = []
        while self.parent[node] >= 0:
            out.append("1" if self.kids[self.parent[node]][1] == node else "0")
            node = self.parent[node]
        return "".join(reversed(out))

    def _swap(self, a: int, b: int) -> None:
        pa_, pb = self.parent[a], self.parent[b]
        ka, kb = self.kids[pa_].index(a), self.kids[pb].index(b)
        self.kids[pa_][ka], self.kids[pb][kb] = b, a
        self.parent[a], self.parent[b] = pb, pa_
        ra, rb = self.rank[a], self.rank[b]
        self.order[ra], self.order[rb] = b, a
        self.rank[a], self.rank[b] = rb, ra

    def add(self, s: int) -> None:
        node = self.leaf.get(s)
        if node is None:  # the empty leaf becomes the parent of a new empty leaf and the new symbol
            old, n = self.nyt, len(self.weight)
            for sym in (s, None):
                self.weight.append(0)
                self.parent.append(old)
                self.kids.append(None)
                self.symbol.append(sym)
                self.rank.append(len(self.order))
                self.order.append(len(self.weight) - 1)
            self.kids[old] = [n + 1, n]
            self.leaf[s], self.nyt, node = n, n + 1, n
        while node >= 0:
            w, r = self.weight[node], self.rank[node]
            while r and self.weight[self.order[r - 1]] == w:
                r -= 1
            lead = self.order[r]
            if lead == self.parent[node]:
                lead = self.order[r + 1]
            if lead != node and lead != self.parent[node] and self.parent[lead] >= 0:
                self._swap(node, lead)
            self.weight[node] += 1
            node = self.parent[node]


class AdaptiveHuffmanCodec(Codec):
    """One-pass Huffman coding; a new symbol is the empty leaf's code and eight bits."""

    name = "adaptive_huffman"

    def encode(self, data: bytes) -> bytes:
        tree, out = _SiblingTree(), []
        for s in data:
            node = tree.leaf.get(s)
            out.append(tree.path(tree.nyt) + format(s, "08b") if node is None else tree.path(node))
            tree.add(s)
        return put_varint(len(data)) + pack_bits("".join(out))

    def decode(self, data: bytes) -> bytes:
        n, at = get_varint(data)
        bits, tree, out, i = unpack_bits(data[at:]), _SiblingTree(), bytearray(), 0
        for _ in range(n):
            node = 0
            while tree.kids[node]:
                node = tree.kids[node][int(bits[i])]
                i += 1
            s = tree.symbol[node]
            if node == tree.nyt:
                s = int(bits[i : i + 8], 2)
                i += 8
            out.append(s)
            tree.add(s)
        return bytes(out)


# ------------------------------------------------------------------ dictionaries


class LZ77Codec(Codec):
    """Sliding window with bounded hash chains; runs of literals and (length, distance) pairs, as varints."""

    name = "lz77"

    def __init__(self, window: int = 32768, lookahead: int = 258, min_match: int = 3, chain: int = 32):
        self.window, self.lookahead, self.min_match, self.chain = window, lookahead, min_match, chain

    def parse(self, data: bytes):
        """(literals before it, length, distance) of each match; the last has length 0."""
        heads: dict[bytes, list[int]] = {}
        at, start, n, least = 0, 0, len(data), self.min_match

        def enter(i: int) -> None:
            if i + least <= n:
                heads.setdefault(data[i : i + least], []).append(i)

        while at < n:
            best, where = 0, 0
            for j in reversed(heads.get(data[at : at + least], [])[-self.chain :]) if at + least <= n else ():
                if at - j > self.window:
                    break
                k, top = least, min(self.lookahead, n - at)
                while k < top and data[j + k] == data[at + k]:
                    k += 1
                if k > best:
                    best, where = k, j
            if best >= least:
                yield data[start:at], best, at - where
                for i in range(at, at + best):
                    enter(i)
                at += best
                start = at
            else:
                enter(at)
                at += 1
        yield data[start:], 0, 0

    def encode(self, data: bytes) -> bytes:
        out = bytearray(put_varint(len(data)))
        for literals, length, distance in self.parse(data):
            out += put_varint(len(literals)) + literals
            if length:
                out += put_varint(length) + put_varint(distance)
        return bytes(out)

    def decode(self, data: bytes) -> bytes:
        n, at = get_varint(data)
        out = bytearray()
        while len(out) < n:
            k, at = get_varint(data, at)
            out += data[at : at + k]
            at += k
            if len(out) < n:
                length, at = get_varint(data, at)
                distance, at = get_varint(data, at)
                for _ in range(length):
                    out.append(out[-distance])
        return bytes(out)


class LZWCodec(Codec):
    """Growing dictionary of at most 4096 phrases, 12 bits each, frozen when full."""

    name = "lzw"

    def __init__(self, max_codes: int = 4096):
        self.max_codes, self.bits = max_codes, max(8, (max_codes - 1).bit_length())

    def encode(self, data: bytes) -> bytes:
        known, codes, phrase = {bytes([i]): i for i in range(256)}, [], b""
        for b in data:
            longer = phrase + bytes([b])
            if longer in known:
                phrase = longer
                continue
            codes.append(known[phrase])
            if len(known) < self.max_codes:
                known[longer] = len(known)
            phrase = bytes([b])
        if phrase:
            codes.append(known[phrase])
        return put_varint(len(codes)) + pack_bits("".join([format(c, f"0{self.bits}b") for c in codes]))

    def decode(self, data: bytes) -> bytes:
        n, at = get_varint(data)
        bits, known, out, before = unpack_bits(data[at:]), [bytes([i]) for i in range(256)], [], b""
        for i in range(n):
            c = int(bits[i * self.bits : (i + 1) * self.bits], 2)
            phrase = known[c] if c < len(known) else before + before[:1]
            if before and len(known) < self.max_codes:
                known.append(before + phrase[:1])
            out.append(phrase)
            before = phrase
        return b"".join(out)


class Chain(Codec):
    """Codecs one after the other."""

    def __init__(self, name: str, *parts: Codec):
        self.name, self.parts = name, parts

    def encode(self, data: bytes) -> bytes:
        for p in self.parts:
            data = p.encode(data)
        return data

    def decode(self, data: bytes) -> bytes:
        for p in reversed(self.parts):
            data = p.decode(data)
        return data


class BwtCodec(Codec):
    """Block sorting, move-to-front, runs of zeros as binary digits, adaptive arithmetic coding."""

    name = "bwt"

    @staticmethod
    def sort(data: bytes) -> np.ndarray:
        """Suffix order by doubling; the end counts as the smallest symbol."""
        rank = np.frombuffer(data, np.uint8).astype(np.int64) + 1
        n, k = len(rank), 1
        while True:
            second = np.concatenate([rank[k:], np.zeros(min(k, n), np.int64)])
            order = np.lexsort((second, rank))
            step = np.concatenate(([0], (np.diff(rank[order]) != 0) | (np.diff(second[order]) != 0)))
            new = np.empty(n, np.int64)
            new[order] = np.cumsum(step) + 1
            rank, k = new, 2 * k
            if rank.max(initial=0) == n or k >= 2 * n:
                return order

    def encode(self, data: bytes) -> bytes:
        if not data:
            return put_varint(0)
        order = self.sort(data)
        order = np.concatenate(([len(data)], order))  # the empty suffix comes first
        src = np.frombuffer(data, np.uint8)
        primary = int(np.flatnonzero(order == 0)[0])
        last = src[order[order != 0] - 1]
        table, out, run = list(range(256)), [], 0

        def flush():
            nonlocal run
            while run:  # bijective base 2 with the digits 0 and 1
                out.append(0 if run & 1 else 1)
                run = (run - 1) // 2

        for s in last.tolist():
            i = table.index(s)
            if i == 0:
                run += 1
                continue
            flush()
            out.append(i + 1)
            table.insert(0, table.pop(i))
        flush()
        enc, m = RangeEncoder(), Fenwick(258)
        for s in [*out, 257]:
            enc.put(m.below(s), m.f[s], m.total)
            m.add(s)
        return put_varint(len(data)) + put_varint(primary) + enc.done()

    def decode(self, data: bytes) -> bytes:
        n, at = get_varint(data)
        if not n:
            return b""
        primary, at = get_varint(data, at)
        dec, m, table, last, run, digit = RangeDecoder(data, at), Fenwick(258), list(range(256)), bytearray(), 0, 1
        while True:
            s, c = m.find(dec.target(m.total))
            dec.take(c, m.f[s])
            m.add(s)
            if s < 2:
                run, digit = run + digit * (1 if s == 0 else 2), digit * 2
                continue
            last += bytes([table[0]]) * run
            run, digit = 0, 1
            if s == 257:
                break
            table.insert(0, table.pop(s - 1))
            last.append(table[0])
        # the row of the end is put back, and the last-to-first map is followed
        col = np.insert(np.frombuffer(bytes(last), np.uint8).astype(int), primary, -1)
        first = np.argsort(col, kind="stable")
        out, row = bytearray(), primary
        for _ in range(n):
            row = first[row]
            out.append(col[row])
        return bytes(out)


# ------------------------------------------------------------------ stock codecs


class _Stock(Codec):
    def __init__(self, name: str, enc, dec):
        self.name, self.encode, self.decode = name, enc, dec


class ArrowCodec(Codec):
    """A codec of pyarrow; the size that its decoder needs stands in front."""

    def __init__(self, name: str, level: int | None = None):
        self.name, self.level = name, level

    def _codec(self):
        return pa.Codec(self.name, compression_level=self.level) if self.level is not None else pa.Codec(self.name)

    def encode(self, data: bytes) -> bytes:
        return put_varint(len(data)) + (self._codec().compress(data, asbytes=True) if data else b"")

    def decode(self, data: bytes) -> bytes:
        n, at = get_varint(data)
        return self._codec().decompress(data[at:], decompressed_size=n, asbytes=True) if n else b""


def _raw_deflate(data: bytes) -> bytes:
    c = zlib.compressobj(9, zlib.DEFLATED, -15)
    return c.compress(data) + c.flush()


def _make() -> dict[str, Codec]:
    own = [
        Codec(), ArithmeticCodec(), ArithmeticCodec(False), HuffmanCodec(), AdaptiveHuffmanCodec(), LZ77Codec(), LZWCodec(),
        Chain("lz77_huffman", LZ77Codec(), HuffmanCodec()), BwtCodec(),
        _Stock("gzip", lambda d: gzip.compress(d, 9, mtime=0), gzip.decompress),
        _Stock("raw_deflate", _raw_deflate, lambda d: zlib.decompress(d, -15)),
        ArrowCodec("brotli", 11), ArrowCodec("zstd", 19), ArrowCodec("lz4"), ArrowCodec("snappy"),
        _Stock("bz2", lambda d: bz2.compress(d, 9), bz2.decompress), _Stock("lzma", lzma.compress, lzma.decompress),
    ]
    return {c.name: c for c in own}


CODECS = _make()
#: Classical baselines, and controls beyond them.
BASELINES = ("raw", "arithmetic", "arithmetic_static", "huffman", "adaptive_huffman", "lz77", "lzw", "lz77_huffman", "gzip", "raw_deflate", "brotli", "bwt", "bz2")
EXTRA = ("zstd", "lzma", "lz4", "snappy")
