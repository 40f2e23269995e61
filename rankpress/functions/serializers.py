"""Rank sequences as bytes. Each pair (encode, decode) is reversible for any non-negative ranks."""

from __future__ import annotations

import numpy as np

from .codecs import get_varint, pack_bits, put_varint, unpack_bits


def _dotted(r):
    return ".".join(map(str, np.asarray(r).tolist())).encode()


def _dotted_back(b):
    return np.array(b.split(b"."), np.int64) if b else np.zeros(0, np.int64)


def _varint(r):
    return b"".join([put_varint(x) for x in np.asarray(r).tolist()])


def _varint_back(b):
    out, at = [], 0
    while at < len(b):
        x, at = get_varint(b, at)
        out.append(x)
    return np.array(out, np.int64)


def _escape(r):
    return b"".join([bytes([x]) if x < 255 else b"\xff" + put_varint(x - 255) for x in np.asarray(r).tolist()])


def _escape_back(b):
    out, at = [], 0
    while at < len(b):
        x, at = b[at], at + 1
        if x == 255:
            x, at = get_varint(b, at)
            x += 255
        out.append(x)
    return np.array(out, np.int64)


def _gamma(r):
    bits = [bin(x + 1)[2:] for x in np.asarray(r).tolist()]
    return put_varint(len(bits)) + pack_bits("".join(["0" * (len(x) - 1) + x for x in bits]))


def _gamma_back(b):
    n, at = get_varint(b)
    bits, out, i = unpack_bits(b[at:]), [], 0
    for _ in range(n):
        k = bits.index("1", i) - i
        out.append(int(bits[i + k : i + 2 * k + 1], 2) - 1)
        i += 2 * k + 1
    return np.array(out, np.int64)


def _zero_runs(r):
    """A zero and the rest of its run's length; any other rank as it is."""
    out, run = [], 0
    for x in [*np.asarray(r).tolist(), -1]:
        if x == 0:
            run += 1
            continue
        if run:
            out.append(b"\0" + put_varint(run - 1))
            run = 0
        if x > 0:
            out.append(put_varint(x))
    return b"".join(out)


def _zero_runs_back(b):
    out, at = [], 0
    while at < len(b):
        x, at = get_varint(b, at)
        if x:
            out.append(x)
        else:
            n, at = get_varint(b, at)
            out += [0] * (n + 1)
    return np.array(out, np.int64)


def _u16(r):
    r = np.asarray(r, np.int64)
    wide = r.max(initial=0) > 65535
    return bytes([4 if wide else 2]) + r.astype("<u4" if wide else "<u2").tobytes()


def _u16_back(b):
    return np.frombuffer(b[1:], "<u4" if b[:1] == b"\x04" else "<u2").astype(np.int64)


#: The first is the reference's own form, ranks as digits between full stops.
SERIALIZERS = {"dotted": (_dotted, _dotted_back), "bytes_escape": (_escape, _escape_back), "varint": (_varint, _varint_back), "gamma": (_gamma, _gamma_back), "zero_runs": (_zero_runs, _zero_runs_back), "u16": (_u16, _u16_back)}
