"""The codecs that the trit coders are compared with, list by list: write, read, and the number of bits.

A list is an array of gaps >= 1 whose sum is at most the universe ``u``; its length is known to the reader, as lengths
are coded apart. None of the codes spends a codeword on 0. Where a size has a closed form, ``size`` is that.
"""

from __future__ import annotations

import bz2
import lzma
import zlib
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd

from .arith import Bits
from .trits import bit_lengths


@dataclass(frozen=True)
class Codec:
    name: str
    put: Callable[[Bits, list[int], int], None]
    take: Callable[[Bits, int, int], list[int]]
    size: Callable[[np.ndarray, int], int] | None = None

    def encode(self, gaps, u: int) -> bytes:
        b = Bits()
        self.put(b, [int(g) for g in gaps], int(u))
        return b.bytes()

    def decode(self, data: bytes, n: int, u: int) -> np.ndarray:
        return np.array(self.take(Bits(data), n, int(u)), np.int64)

    def bits(self, gaps: np.ndarray, u: int) -> int:
        gaps = np.asarray(gaps, np.int64)
        if len(gaps) and (gaps < 1).any() or gaps.sum() > u:
            raise ValueError("gaps must be >= 1 and stay inside the universe")
        if self.size is not None:
            return int(self.size(gaps, int(u)))
        b = Bits()
        self.put(b, gaps.tolist(), int(u))
        return 8 * len(b.out) + b.n


CODECS: dict[str, Codec] = {}
#: Sizes of many lists at once, for codecs that have such a form: (gaps of lists put one after another, their lengths, their
#: universes) -> bits of each.
MANY: dict[str, Callable[[np.ndarray, np.ndarray, np.ndarray], np.ndarray]] = {}


def sizes_of(name: str, gaps: np.ndarray, sizes: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Bits of each list of lists put one after another."""
    at = np.concatenate([[0], np.cumsum(sizes)])
    if name not in MANY:
        return np.array([CODECS[name].bits(gaps[at[i] : at[i + 1]], u[i]) for i in range(len(sizes))], np.int64)
    total = np.concatenate([[0], np.cumsum(gaps)])[at]
    if len(gaps) and gaps.min() < 1 or (np.diff(total) > u).any():
        raise ValueError("gaps must be >= 1 and stay inside the universe")
    return MANY[name](gaps, sizes, u) if len(gaps) else np.zeros(len(sizes), np.int64)


#: Bytes of many lists at once: (gaps of lists put one after another, their lengths, their universes) -> bytes of each, the
#: same as list by list; and back: (bytes of each, lengths, universes) -> gaps of all.
MANY_PUT: dict[str, Callable[[np.ndarray, np.ndarray, np.ndarray], list[bytes]]] = {}
MANY_TAKE: dict[str, Callable[[list[bytes], np.ndarray, np.ndarray], np.ndarray]] = {}
#: Bits that are looked at together when lists are read.
CHUNK_BITS = 1 << 20


def bytes_of(name: str, gaps: np.ndarray, sizes: np.ndarray, u: np.ndarray) -> list[bytes]:
    """Each list of lists put one after another as bytes."""
    if name in MANY_PUT and len(gaps) and gaps.min() >= 1 and u.max() < 1 << 31:  # else by the plain way, which has no bounds
        return MANY_PUT[name](gaps, sizes, u)
    at = np.concatenate([[0], np.cumsum(sizes)])
    return [CODECS[name].encode(gaps[at[i] : at[i + 1]].tolist(), int(u[i])) for i in range(len(sizes))]


def lists_from(name: str, data: list[bytes], sizes: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Gaps of all lists, one after another, back from :func:`bytes_of`."""
    if name in MANY_TAKE and len(data) and u.max() < 1 << 31:
        return MANY_TAKE[name](data, sizes, u)
    return np.concatenate([np.empty(0, np.int64), *(CODECS[name].decode(d, n, v) for d, n, v in zip(data, sizes.tolist(), u.tolist(), strict=True))])


def _packed(value: np.ndarray, width: np.ndarray, sizes: np.ndarray) -> list[bytes]:
    """Codewords of at most 63 bits one after another, each list's from a byte of its own on."""
    ends = np.cumsum(width)
    last = np.cumsum(sizes)
    total = np.concatenate([[0], ends])
    bits = total[last] - total[last - sizes]
    length = (bits + 7) // 8
    start = np.cumsum(length) - length
    at = ends - width + np.repeat(8 * start - total[last - sizes], sizes)
    out = np.zeros(int(length.sum()) // 8 + 2, np.uint64)
    word, shift = at >> 6, at & 63
    left = value.astype(np.uint64) << (64 - np.maximum(width, 1)).astype(np.uint64)
    np.add.at(out, word, left >> shift.astype(np.uint64))  # codewords share no bit, so sums are unions
    over = np.flatnonzero(shift + width > 64)
    np.add.at(out, word[over] + 1, left[over] << (64 - shift[over]).astype(np.uint64))
    raw = out.astype(">u8").tobytes()
    return [raw[a : a + n] for a, n in zip(start.tolist(), length.tolist(), strict=True)]


def _windows(raw: bytes) -> np.ndarray:
    """The 64 bits from each byte on, zeros behind the end."""
    b = np.frombuffer(raw + bytes(8), np.uint8)
    out = np.zeros(len(raw) + 1, np.uint64)
    for j in range(8):
        out |= b[j : j + len(out)].astype(np.uint64) << np.uint64(56 - 8 * j)
    return out


def _some(data: list[bytes]) -> list[tuple[int, int]]:
    """Runs of lists of about CHUNK_BITS, or one."""
    total = np.cumsum([len(d) for d in data])
    part = total * 8 // CHUNK_BITS
    cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(data)]
    return list(zip(cuts[:-1], cuts[1:], strict=True))


def codec(name: str, size=None):
    """Registers the pair (put, take) that the decorated function returns."""

    def wrap(make):
        CODECS[name] = Codec(name, *make(), size)
        return make

    return wrap


def each(name: str, put1, get1, size=None) -> None:
    """A code of single gaps; put1 and get1 take (bits, gap, list parameters) and (bits, list parameters)."""

    def put(b, gaps, u):
        p = (len(gaps), u)
        for g in gaps:
            put1(b, g, p)

    CODECS[name] = Codec(name, put, lambda b, n, u: [get1(b, (n, u)) for _ in range(n)], size)


def put_unary(b: Bits, x: int) -> None:
    while x > 64:
        b.put(0, 64)
        x -= 64
    b.put(1, x)


def get_unary(b: Bits) -> int:
    n = 1
    while not b.get(1):
        n += 1
    return n


def put_truncated(b: Bits, x: int, r: int) -> None:
    """One of r values, the small ones short."""
    w = r.bit_length() - 1
    short = (2 << w) - r
    b.put(x, w) if x < short else b.put(x + short, w + 1)


def get_truncated(b: Bits, r: int) -> int:
    w = r.bit_length() - 1
    short = (2 << w) - r
    x = b.get(w)
    return x if x < short else (x << 1 | b.get(1)) - short


def golomb_m(n: int, u: int) -> int:
    return max(1, (69 * u + 50 * n) // (100 * n))


def _zeta_put(b: Bits, g: int, k: int) -> None:
    h = (g.bit_length() - 1) // k
    put_unary(b, h + 1)
    put_truncated(b, g - (1 << h * k), (1 << h * k + k) - (1 << h * k))


def _zeta_get(b: Bits, k: int) -> int:
    h = get_unary(b) - 1
    return (1 << h * k) + get_truncated(b, (1 << h * k + k) - (1 << h * k))


def _vb_put(b: Bits, g: int, step: int) -> None:
    """Chunks of ``step`` bits, low ones first, a stop bit on the last."""
    while g >> step:
        b.put(g & (1 << step) - 1, step + 1)
        g >>= step
    b.put(1 << step | g, step + 1)


def _vb_get(b: Bits, step: int) -> int:
    out = shift = 0
    while True:
        x = b.get(step + 1)
        out |= (x & (1 << step) - 1) << shift
        if x >> step:
            return out
        shift += step


def _gamma_put(b: Bits, g: int) -> None:
    put_unary(b, g.bit_length())
    b.put(g - (1 << g.bit_length() - 1), g.bit_length() - 1)


def _gamma_get(b: Bits) -> int:
    n = get_unary(b)
    return 1 << n - 1 | b.get(n - 1)


def _delta_bits(g: np.ndarray) -> np.ndarray:
    b = bit_lengths(g)
    return b + 2 * bit_lengths(b) - 2


each("unary", lambda b, g, p: put_unary(b, g), lambda b, p: get_unary(b), lambda g, u: g.sum())
each("binary", lambda b, g, p: b.put(g - 1, (p[1] - 1).bit_length()), lambda b, p: b.get((p[1] - 1).bit_length()) + 1, lambda g, u: len(g) * (u - 1).bit_length())
each("raw32", lambda b, g, p: b.put(g & 2**32 - 1, 32), lambda b, p: b.get(32) or 2**32, lambda g, u: 32 * len(g))
each("gamma", lambda b, g, p: _gamma_put(b, g), lambda b, p: _gamma_get(b), lambda g, u: (2 * bit_lengths(g) - 1).sum())
each("delta", lambda b, g, p: b.put_delta(g), lambda b, p: b.get_delta(), lambda g, u: _delta_bits(g).sum())
for _k in (2, 3, 4):
    each(f"zeta{_k}", lambda b, g, p, k=_k: _zeta_put(b, g, k), lambda b, p, k=_k: _zeta_get(b, k))
each("vbyte", lambda b, g, p: _vb_put(b, g, 7), lambda b, p: _vb_get(b, 7), lambda g, u: (8 * -(-bit_lengths(g) // 7)).sum())
each("nibble", lambda b, g, p: _vb_put(b, g, 3), lambda b, p: _vb_get(b, 3), lambda g, u: (4 * -(-bit_lengths(g) // 3)).sum())


def _delta_many(gaps: np.ndarray, sizes: np.ndarray, u: np.ndarray) -> list[bytes]:
    b = bit_lengths(gaps)
    return _packed((b - 1 << b - 1) + gaps, _delta_bits(gaps), sizes)


def _delta_all(data: list[bytes], sizes: np.ndarray, u: np.ndarray) -> np.ndarray:
    """At every bit the codeword that would begin there, and from each list's first bit on those that do."""
    out, done = np.empty(int(sizes.sum()), np.int64), 0
    for a, z in _some(data):
        raw = b"".join(data[a:z])
        window = _windows(raw)
        at = np.arange(8 * len(raw))
        rest = np.repeat(window[: len(raw)], 8) << (at & 7).astype(np.uint64)  # 57 bits or more, a codeword has 40 at most
        n = 65 - bit_lengths_unsigned(rest)
        most = np.minimum(n, 6)  # places in which no codeword begins
        b = np.maximum(rest >> (65 - 2 * most).astype(np.uint64), 1).astype(np.int64)
        after = (at + 2 * most + b - 2).tolist()
        place, where = [], 0
        for d, m in zip(data[a:z], sizes[a:z].tolist(), strict=True):
            p = 8 * where
            for _ in range(m):
                place.append(p)
                p = after[p]
            where += len(d)
        p = np.array(place, np.int64)
        w = np.minimum(b[p] - 1, 40)
        low = rest[p] << (2 * most[p] - 1).astype(np.uint64) >> np.uint64(1) >> (63 - w).astype(np.uint64)
        out[done : done + len(p)] = (np.int64(1) << w) + low.astype(np.int64)
        done += len(p)
    return out


def bit_lengths_unsigned(x: np.ndarray) -> np.ndarray:
    """Of 64-bit numbers with the highest bit or without."""
    high = (x >> np.uint64(32)).astype(np.float64)
    low = (x & np.uint64(2**32 - 1)).astype(np.float64)
    return np.where(high > 0, 32 + np.frexp(high)[1], np.frexp(low)[1]).astype(np.int64)


MANY_PUT["delta"], MANY_TAKE["delta"] = _delta_many, _delta_all


def _rice_put(b, g, p):
    r = golomb_m(*p).bit_length() - 1
    put_unary(b, (g - 1 >> r) + 1)
    b.put(g - 1 & (1 << r) - 1, r)


def _rice_get(b, p):
    r = golomb_m(*p).bit_length() - 1
    return (get_unary(b) - 1 << r | b.get(r)) + 1


def _golomb_put(b, g, p):
    m = golomb_m(*p)
    put_unary(b, (g - 1) // m + 1)
    put_truncated(b, (g - 1) % m, m)


def _golomb_get(b, p):
    m = golomb_m(*p)
    return (get_unary(b) - 1) * m + get_truncated(b, m) + 1


each("rice", _rice_put, _rice_get)
each("golomb", _golomb_put, _golomb_get)


@codec("group_varint")
def _group_varint():
    """Four gaps share a tag byte with their lengths in bytes; gaps above 2**32 are given in a spare 8-byte form."""
    width = lambda g: min(4, max(1, -(-g.bit_length() // 8)))
    wide = 2**32 - 1

    def put(b, gaps, u):
        for i in range(0, len(gaps), 4):
            four = [g if g < wide else wide for g in gaps[i : i + 4]]
            tag = 0
            for g in four:
                tag = tag << 2 | width(g) - 1
            b.put(tag << 2 * (4 - len(four)), 8)
            for g, real in zip(four, gaps[i : i + 4], strict=True):
                b.put(g, 8 * width(g))
                if g == wide:
                    b.put(real, 64)

    def take(b, n, u):
        out = []
        while len(out) < n:
            tag = b.get(8)
            for j in range(min(4, n - len(out))):
                g = b.get(8 * ((tag >> 6 - 2 * j & 3) + 1))
                out.append(b.get(64) if g == wide else g)
        return out

    return put, take


@codec("g8iu")
def _g8iu():
    """Eight data bytes hold whole gaps; a descriptor byte marks the last byte of each."""
    width = lambda g: max(1, -(-g.bit_length() // 8))

    def put(b, gaps, u):
        i = 0
        while i < len(gaps):
            mark, data, used = 0, 0, 0
            while i < len(gaps) and used + width(gaps[i]) <= 8:
                data |= gaps[i] << 8 * used
                used += width(gaps[i])
                mark |= 1 << used - 1
                i += 1
            b.put(mark, 8)
            b.put(data, 64)

    def take(b, n, u):
        out = []
        while len(out) < n:
            mark, data, start = b.get(8), b.get(64), 0
            for j in range(8):
                if mark >> j & 1 and len(out) < n:
                    out.append(data >> 8 * start & (1 << 8 * (j + 1 - start)) - 1)
                    start = j + 1
        return out

    return put, take


# Layouts as (how many, width) runs of the data bits of a word.
SIMPLE9 = [[(28, 1)], [(14, 2)], [(9, 3)], [(7, 4)], [(5, 5)], [(4, 7)], [(3, 9)], [(2, 14)], [(1, 28)]]
SIMPLE16 = [[(28, 1)], [(7, 2), (14, 1)], [(7, 1), (7, 2), (7, 1)], [(14, 1), (7, 2)], [(14, 2)], [(1, 4), (8, 3)], [(1, 3), (4, 4), (3, 3)], [(7, 4)], [(4, 5), (2, 4)], [(2, 4), (4, 5)], [(3, 6), (2, 5)], [(2, 5), (3, 6)], [(4, 7)], [(1, 10), (2, 9)], [(2, 14)], [(1, 28)]]
SIMPLE8B = [[(240, 0)], [(120, 0)], [(60, 1)], [(30, 2)], [(20, 3)], [(15, 4)], [(12, 5)], [(10, 6)], [(8, 7)], [(7, 8)], [(6, 10)], [(5, 12)], [(4, 15)], [(3, 20)], [(2, 30)], [(1, 60)]]


def word_code(name: str, layouts, data_bits: int) -> None:
    """Greedy packing of gap - 1 into words with a 4-bit selector; a last word may hold less than its layout. The value of
    all ones in the one-gap layout announces a gap of 64 bits."""
    widths = [[w for n, w in lay for _ in range(n)] for lay in layouts]
    limits = [[1 << w for w in ws] for ws in widths]
    escape = (1 << data_bits) - 1

    def put(b, gaps, u):
        i, n = 0, len(gaps)
        while i < n:
            for sel, lim in enumerate(limits):
                m = min(len(lim), n - i)
                if (m == len(lim) or lim[0] > 1) and all(gaps[i + j] - 1 < lim[j] for j in range(m)) and not (len(lim) == 1 and gaps[i] - 1 >= escape):
                    b.put(sel, 4)
                    used = 0
                    for j in range(m):
                        b.put(gaps[i + j] - 1, widths[sel][j])
                        used += widths[sel][j]
                    b.put(0, data_bits - used)
                    i += m
                    break
            else:
                b.put(len(layouts) - 1, 4)
                b.put(escape, data_bits)
                b.put(gaps[i], 64)
                i += 1

    def take(b, n, u):
        out = []
        while len(out) < n:
            ws = widths[b.get(4)]
            used = 0
            for w in ws[: n - len(out)]:
                out.append(b.get(w) + 1)
                used += w
            b.get(data_bits - used)
            if len(ws) == 1 and out[-1] - 1 == escape:
                out[-1] = b.get(64)
        return out

    CODECS[name] = Codec(name, put, take)


word_code("simple9", SIMPLE9, 28)
word_code("simple16", SIMPLE16, 28)
word_code("simple8b", SIMPLE8B, 60)

#: Widths of the vector words of 128 bits (fixed values); width 0 stands for 128 gaps of 1.
QMX = (0, 1, 2, 3, 4, 5, 6, 7, 8, 9, 10, 12, 16, 21, 32, 64)


@codec("qmx")
def _qmx():
    """A selector byte (width, run length up to 16) before each run of 128-bit words of one width."""
    room = lambda w: 128 // w if w else 128

    def words(gaps):
        i = 0
        while i < len(gaps):
            for k, w in enumerate(QMX):
                part = gaps[i : i + room(w)]
                if all(g - 1 < 1 << w for g in part) and (w or len(part) == 128):
                    yield k, part
                    i += len(part)
                    break

    def put(b, gaps, u):
        runs: list[tuple[int, list]] = []
        for k, part in words(gaps):
            if runs and runs[-1][0] == k and len(runs[-1][1]) < 16:
                runs[-1][1].append(part)
            else:
                runs.append((k, [part]))
        for k, parts in runs:
            b.put(k << 4 | len(parts) - 1, 8)
            for part in parts if QMX[k] else []:
                for g in part:
                    b.put(g - 1, QMX[k])
                b.put(0, 128 - QMX[k] * len(part))

    def take(b, n, u):
        out = []
        while len(out) < n:
            x = b.get(8)
            w = QMX[x >> 4]
            for _ in range((x & 15) + 1):
                m = min(room(w), n - len(out))
                out += [b.get(w) + 1 for _ in range(m)]
                if w:
                    b.get(128 - w * m)
        return out

    return put, take


BLOCK = 128


def _widths(gaps: np.ndarray) -> list[np.ndarray]:
    b = bit_lengths(gaps - 1 + (gaps == 1)) * (gaps > 1)
    return [b[i : i + BLOCK] for i in range(0, len(b), BLOCK)]


@codec("packing", lambda g, u: sum(8 + len(w) * int(w.max()) for w in _widths(g)))
def _packing():
    """128 gaps at the width of the largest, behind a byte with that width."""

    def put(b, gaps, u):
        for i in range(0, len(gaps), BLOCK):
            part = gaps[i : i + BLOCK]
            w = (max(part) - 1).bit_length()
            b.put(w, 8)
            for g in part:
                b.put(g - 1, w)

    def take(b, n, u):
        out = []
        while len(out) < n:
            w = b.get(8)
            out += [b.get(w) + 1 for _ in range(min(BLOCK, n - len(out)))]
        return out

    return put, take


def _vector_bits(g: np.ndarray, u: int) -> int:
    w = _widths(g)
    return 128 * -(-len(w) // 16) + sum(-(-len(x) * int(x.max()) // 128) * 128 for x in w)


@codec("packing_vector", _vector_bits)
def _packing_vector():
    """As packing, with 16 widths gathered in one vector and blocks aligned to 128 bits."""

    def put(b, gaps, u):
        parts = [gaps[i : i + BLOCK] for i in range(0, len(gaps), BLOCK)]
        for i in range(0, len(parts), 16):
            ws = [(max(p) - 1).bit_length() for p in parts[i : i + 16]]
            for w in ws + [0] * (16 - len(ws)):
                b.put(w, 8)
            for p, w in zip(parts[i : i + 16], ws, strict=True):
                for g in p:
                    b.put(g - 1, w)
                b.put(0, -len(p) * w % 128)

    def take(b, n, u):
        out = []
        while len(out) < n:
            for w in [b.get(8) for _ in range(16)]:
                if len(out) < n:
                    m = min(BLOCK, n - len(out))
                    out += [b.get(w) + 1 for _ in range(m)]
                    b.get(-m * w % 128)
        return out

    return put, take


def patched(name: str, choose) -> None:
    """Blocks of 128 at a width that fits most; of the others the places and what exceeds the width follow in the
    16-layout word code. ``choose`` gives the width from the block's gaps."""
    s16 = CODECS["simple16"]

    def parts(part, w):
        over = [i for i, g in enumerate(part) if g - 1 >> w]
        return over, [i - j for i, j in zip(over, [-1, *over], strict=False)], [part[i] - 1 >> w for i in over]

    def put(b, gaps, u):
        for i in range(0, len(gaps), BLOCK):
            part = gaps[i : i + BLOCK]
            w = choose(part)
            over, steps, high = parts(part, w)
            b.put(w, 8)
            b.put(len(over), 8)
            for g in part:
                b.put(g - 1 & (1 << w) - 1, w)
            s16.put(b, steps, u)
            s16.put(b, high, u)

    def take(b, n, u):
        out = []
        while len(out) < n:
            w, m = b.get(8), b.get(8)
            part = [b.get(w) for _ in range(min(BLOCK, n - len(out)))]
            at = -1
            steps, high = s16.take(b, m, u), s16.take(b, m, u)
            for s, h in zip(steps, high, strict=True):
                at += s
                part[at] |= h << w
            out += [x + 1 for x in part]
        return out

    CODECS[name] = Codec(name, put, take)


def width_new(part) -> int:
    """The smallest that fits 90% of the block."""
    return sorted((g - 1).bit_length() for g in part)[max(0, -(-9 * len(part) // 10) - 1)]


def width_opt(part) -> int:
    """The cheapest, exceptions at 8 bits for the place and their excess width."""
    b = np.array([(g - 1).bit_length() for g in part])
    return min(range(int(b.max()) + 1), key=lambda w: (len(b) * w + int(((b > w) * (8 + b - w)).sum()), w))


def opt_cost_bits(gaps: np.ndarray) -> int:
    """Of the optimised width by block, priced in closed form: 16 bits of header, 8 for a place, the excess width."""
    out = 0
    for b in _widths(gaps):
        out += 16 + min(len(b) * w + int(((b > w) * (8 + b - w)).sum()) for w in range(int(b.max()) + 1))
    return out


patched("pfor_new", width_new)
patched("pfor_opt", width_opt)


@codec("pfor_fast")
def _pfor_fast():
    """Exceptions of all blocks of a list pooled by width: 8 bits for each place, then the pools at their widths."""

    def choose(part):
        b = [(g - 1).bit_length() for g in part]
        top = max(b)
        cost = lambda w: len(b) * w + sum(x > w for x in b) * (8 + top - w) + 8 * (top > w)
        return min(range(top + 1), key=lambda w: (cost(w), w)), top

    def put(b, gaps, u):
        pools: dict[int, list[int]] = {}
        for i in range(0, len(gaps), BLOCK):
            part = gaps[i : i + BLOCK]
            w, top = choose(part)
            over = [j for j, g in enumerate(part) if g - 1 >> w]
            b.put(w, 8)
            b.put(len(over), 8)
            if over:
                b.put(top, 8)
            for j in over:
                b.put(j, 8)
            pools.setdefault(top - w, []).extend(part[j] - 1 >> w for j in over)
            for g in part:
                b.put(g - 1 & (1 << w) - 1, w)
        for width in sorted(pools):
            for x in pools[width]:
                b.put(x, width)

    def take(b, n, u):
        out, holes = [], []
        while len(out) < n:
            w, m = b.get(8), b.get(8)
            top = b.get(8) if m else w
            at = len(out)
            holes += [(top - w, k, at + b.get(8), w) for k in range(m)]
            out += [b.get(w) for _ in range(min(BLOCK, n - len(out)))]
        for width, _, at, w in sorted(holes, key=lambda h: h[0]):
            out[at] |= b.get(width) << w
        return [x + 1 for x in out]

    return put, take


def dynamic_blocks(name: str, lengths: tuple[int, ...], header: int, runs: bool) -> None:
    """Blocks of chosen lengths at their own widths, cut so that the list gets shortest. ``runs``: frames of ones are free
    but for the header. A header names the length and the width."""
    k_bits = (len(lengths) - 1).bit_length()

    def cuts(gaps):
        n = len(gaps)
        b = [(g - 1).bit_length() for g in gaps]
        best, back = [0] + [1 << 60] * n, [0] * (n + 1)
        for i in range(n):
            if best[i] >= 1 << 60:
                continue
            top, j = 0, i
            for k, m in enumerate(lengths):
                end = min(i + m, n)
                while j < end:
                    top = max(top, b[j])
                    j += 1
                cost = best[i] + header + (end - i) * top
                if cost < best[end]:
                    best[end], back[end] = cost, (i, k, top)
                if end == n:
                    break
        out, at = [], n
        while at:
            out.append((*back[at], at))
            at = back[at][0]
        return out[::-1]

    def put(b, gaps, u):
        for i, k, w, end in cuts(gaps):
            b.put(k, k_bits)
            b.put(w, header - k_bits)
            for g in gaps[i:end]:
                b.put(g - 1, w)

    def take(b, n, u):
        out = []
        while len(out) < n:
            m = lengths[b.get(k_bits)]
            w = b.get(header - k_bits)
            out += [b.get(w) + 1 for _ in range(min(m, n - len(out)))]
        return out

    CODECS[name] = Codec(name, put, take)


dynamic_blocks("split_blocks", (1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 14, 16, 20, 24, 32, 64), 10, False)
dynamic_blocks("adaptive_frames", (8, 16, 32, 64), 8, True)


# --- codes of the ids themselves -------------------------------------------------------------------------------------


def truncated_bits(x: np.ndarray, r: np.ndarray, short: str) -> np.ndarray:
    w = bit_lengths(r) - 1
    few = (np.int64(2) << w) - r  # so many values are short
    first = (r - few) // 2 if short == "center" else np.zeros_like(r)
    return w + np.where((x >= first) & (x < first + few), 0, 1)


def midpoint_bits(ids: np.ndarray, u: int, lo: int = 1, short: str = "center", mid: str = "plain") -> int:
    """Bits of the recursive midpoint code of ids inside lo..u."""
    one = (np.array([v], np.int64) for v in (0, len(ids), lo, u))
    return int(midpoint_sizes(np.asarray(ids, np.int64), *one, short, mid)[0])


def midpoint_sizes(ids: np.ndarray, a: np.ndarray, b: np.ndarray, x: np.ndarray, y: np.ndarray, short: str = "center", mid: str = "plain") -> np.ndarray:
    """Bits of each run ids[a:b] inside x..y: level by level, all parts of all runs at once."""
    out, own = np.zeros(len(a), np.int64), np.arange(len(a))
    while len(a):
        open_ = (b > a) & (y - x + 1 > b - a)
        a, b, x, y, own = a[open_], b[open_], x[open_], y[open_], own[open_]
        if not len(a):
            break
        m = _middle(a, b, mid)
        v = ids[m]
        least, most = x + (m - a), y - (b - 1 - m)
        s = "none" if short == "none" else "center"
        bits = truncated_bits(v - least, most - least + 1, s)
        if short == "center+leaf_ends":  # single ids: short codewords at both ends of the range
            leaf = b - a == 1
            r = most - least + 1
            w = bit_lengths(r) - 1
            few = (np.int64(2) << w) - r
            at = v - least
            ends = (at < few - few // 2) | (at >= r - few // 2)
            bits = np.where(leaf, w + np.where(ends, 0, 1), bits)
        np.add.at(out, own, bits)
        a, b, x, y, own = np.concatenate([a, m + 1]), np.concatenate([m, b]), np.concatenate([x, v + 1]), np.concatenate([v - 1, y]), np.concatenate([own, own])
    return out


def _middle(a, b, mid: str):
    if mid == "plain":
        return (a + b) // 2
    n = b - a  # the left part a full tree where possible
    p = np.int64(1) << (bit_lengths(np.maximum(n, 1)) - 1)
    return a + np.where(n + 1 <= p + p // 2, np.maximum(n - p // 2, 0), p - 1).clip(0, np.maximum(n - 1, 0))


def _place(r: int, leaf: bool, short: str) -> int:
    """What is added, modulo r, to a value so that the values with short codewords come first."""
    few = (2 << r.bit_length() - 1) - r
    if short == "none":
        return 0
    return few // 2 if leaf and short == "center+leaf_ends" else -((r - few) // 2)


def put_ids(b: Bits, ids: list[int], x: int, y: int, short: str = "center", mid: str = "plain") -> None:
    """Ascending ids, all in x..y, their number known."""
    todo = [(0, len(ids), x, y)]
    while todo:
        i, j, x, y = todo.pop()
        if j <= i or y - x + 1 == j - i:
            continue
        m = (i + j) // 2 if mid == "plain" else int(_middle(np.array([i]), np.array([j]), mid)[0])
        least, r = x + m - i, y - x + 1 - (j - i) + 1
        put_truncated(b, (ids[m] - least + _place(r, j - i == 1, short)) % r, r)
        todo += [(m + 1, j, ids[m] + 1, y), (i, m, x, ids[m] - 1)]


def take_ids(b: Bits, n: int, x: int, y: int, short: str = "center", mid: str = "plain") -> list[int]:
    ids = [0] * n
    todo = [(0, n, x, y)]
    while todo:
        i, j, x, y = todo.pop()
        if j <= i:
            continue
        if y - x + 1 == j - i:
            ids[i:j] = range(x, y + 1)
            continue
        m = (i + j) // 2 if mid == "plain" else int(_middle(np.array([i]), np.array([j]), mid)[0])
        least, r = x + m - i, y - x + 1 - (j - i) + 1
        ids[m] = least + (get_truncated(b, r) - _place(r, j - i == 1, short)) % r
        todo += [(m + 1, j, ids[m] + 1, y), (i, m, x, ids[m] - 1)]
    return ids


def gaps_from(ids: list[int]) -> list[int]:
    return [p - q for p, q in zip(ids, [0, *ids], strict=False)]


def run_ids(gaps: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all lists, where each list begins) of lists of gaps put one after another."""
    first = np.cumsum(sizes) - sizes
    total = np.concatenate([[0], np.cumsum(gaps)])
    return total[1:] - np.repeat(total[first], sizes), first


def midpoint_code(name: str, short: str, mid: str) -> None:
    def many(gaps, sizes, u):
        ids, first = run_ids(gaps, sizes)
        return midpoint_sizes(ids, first, first + sizes, np.ones_like(u), u, short, mid)

    MANY[name] = many
    CODECS[name] = Codec(name, lambda b, g, u: put_ids(b, np.cumsum(g).tolist(), 1, u, short, mid), lambda b, n, u: gaps_from(take_ids(b, n, 1, u, short, mid)), lambda g, u: midpoint_bits(np.cumsum(g), u, short=short, mid=mid))


midpoint_code("midpoint", "center", "plain")


def _midpoint_many(gaps: np.ndarray, sizes: np.ndarray, u: np.ndarray) -> list[bytes]:
    """Level by level, all parts of all lists at once; an id's codeword stands behind those of the part's ids before it in
    the order in which parts are written: a part's middle, its left, its right."""
    ids, a = run_ids(gaps, sizes)
    value, width = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64)
    b, x, y, turn = a + sizes, np.ones(len(a), np.int64), u.astype(np.int64), a.copy()
    while len(a):
        open_ = (b > a) & (y - x + 1 > b - a)
        a, b, x, y, turn = a[open_], b[open_], x[open_], y[open_], turn[open_]
        m = (a + b) // 2
        v = ids[m]
        least, r = x + m - a, y - x + 1 - (b - a) + 1
        w = bit_lengths(r) - 1
        few = (np.int64(2) << w) - r
        code = (v - least - (r - few) // 2) % r
        long = code >= few
        value[turn], width[turn] = np.where(long, code + few, code), w + long
        a, b, x, y, turn = np.concatenate([a, m + 1]), np.concatenate([m, b]), np.concatenate([x, v + 1]), np.concatenate([v - 1, y]), np.concatenate([turn + 1, turn + 1 + m - a])
    return _packed(value, width, sizes)


def _midpoint_all(data: list[bytes], sizes: np.ndarray, u: np.ndarray) -> np.ndarray:
    out = []
    for a, z in _some(data):
        raw, p = b"".join(data[a:z]), 0
        window, full = _windows(raw).tolist(), (1 << 64) - 1
        for d, n, top in zip(data[a:z], sizes[a:z].tolist(), u[a:z].tolist(), strict=True):
            ids, todo, at = [0] * n, [(0, n, 1, top)], 8 * p
            p += len(d)
            while todo:
                i, j, x, y = todo.pop()
                while j > i:
                    r = y - x + 2 - j + i
                    if r == 1:
                        ids[i:j] = range(x, y + 1)
                        break
                    m = (i + j) // 2
                    w = r.bit_length() - 1
                    few = (2 << w) - r
                    c = (window[at >> 3] << (at & 7) & full) >> 63 - w  # w + 1 bits
                    if c >> 1 < few:
                        c >>= 1
                        at += w
                    else:
                        c -= few
                        at += w + 1
                    v = ids[m] = x + m - i + (c + (r - few) // 2) % r
                    if j > m + 1:
                        todo.append((m + 1, j, v + 1, y))
                    j, y = m, v - 1
            out.append(np.array(ids, np.int64))
    ids = np.concatenate([np.empty(0, np.int64), *out])
    first = (np.cumsum(sizes) - sizes)[sizes > 0]
    gaps = np.diff(ids, prepend=0)
    gaps[first] = ids[first]
    return gaps


MANY_PUT["midpoint"], MANY_TAKE["midpoint"] = _midpoint_many, _midpoint_all
for _short in ("none", "center", "center+leaf_ends"):
    for _mid in ("plain", "pow2"):
        midpoint_code(f"midpoint_:{_short}:{_mid}", _short, _mid)


def blocked_midpoint(gaps: np.ndarray, u: int, block: int = BLOCK, pad: bool = False, skip: str | None = None) -> dict[str, int]:
    """Bits by part of the blocked form: maxima of the blocks as a list of their own, each block inside known bounds with
    its last id free. ``skip``: 'plain' adds a byte-coded span and an offset to each block, 'trimmed' the offset only; what is
    skipped to starts at a byte, so either pads."""
    return {k: int(v[0]) for k, v in blocked_sizes(np.asarray(gaps, np.int64), np.array([len(gaps)]), np.array([u]), block, pad, skip).items()}


def blocked_sizes(gaps: np.ndarray, sizes: np.ndarray, u: np.ndarray, block: int = BLOCK, pad: bool = False, skip: str | None = None) -> dict[str, np.ndarray]:
    """As :func:`blocked_midpoint`, of lists put one after another: all blocks of all lists at once."""
    pad = pad or skip is not None
    ids, first = run_ids(gaps, sizes)
    n = -(-sizes // block)
    top_at = np.cumsum(n) - n  # of each list, among all blocks
    own = np.repeat(np.arange(len(sizes)), n)
    k = np.arange(len(own)) - top_at[own]
    start = first[own] + k * block
    end = np.minimum(start + block, (first + sizes)[own])
    last = ids[end - 1]
    low = np.where(k > 0, np.roll(last, 1) + 1, 1)
    maxima = midpoint_sizes(last, top_at, top_at + n, np.ones_like(u), u)
    bits = midpoint_sizes(ids, start, end - 1, low, last - 1)
    each = lambda x: np.bincount(own, x, len(sizes)).astype(np.int64)  # noqa: E731  whole numbers far below 2**53
    padding = -bits % 8 if pad else np.zeros_like(bits)
    directory = np.zeros_like(bits)
    if skip:
        directory += 8 * np.maximum(1, -(-bit_lengths(-(-bits // 8)) // 7))
        if skip == "plain":
            directory += 8 * -(-bit_lengths(last - low + 1) // 7)
    return {"maxima": maxima, "payload": each(bits), "padding": each(padding), "directory": each(directory)}


def blocked_code(name: str, block: int = BLOCK, pad: bool = False, skip: str | None = None) -> None:
    """The blocked midpoint coder: maxima, then (with ``skip``) the directory, then the blocks."""

    def put(b, gaps, u):
        ids = np.cumsum(gaps).tolist()
        tops = [ids[min(i + block, len(ids)) - 1] for i in range(0, len(ids), block)]
        put_ids(b, tops, 1, u)
        parts, low = [], 1
        for k, top in enumerate(tops):
            own = Bits()
            put_ids(own, ids[k * block : min((k + 1) * block, len(ids)) - 1], low, top - 1)
            n = 8 * len(own.out) + own.n
            if skip:
                _vb_put(b, max(1, -(-n // 8)), 7)  # the next block's offset, less this one's
                if skip == "plain":
                    _vb_put(b, top - low + 1, 7)
            parts.append((own.bytes(), n))
            low = top + 1
        for raw, n in parts:
            for i in range(0, n, 8):
                m = min(8, n - i)
                b.put(raw[i >> 3] >> 8 - m, m)
            b.put(0, -n % 8 if pad or skip else 0)

    def take(b, n, u):
        tops = take_ids(b, -(-n // block), 1, u)
        for _ in tops if skip else []:
            _vb_get(b, 7)
            if skip == "plain":
                _vb_get(b, 7)
        ids, low = [], 1
        for k, top in enumerate(tops):
            start = b.at
            ids += [*take_ids(b, min(block, n - k * block) - 1, low, top - 1), top]
            b.at += -(b.at - start) % 8 if pad or skip else 0
            low = top + 1
        return gaps_from(ids)

    CODECS[name] = Codec(name, put, take, lambda g, u: sum(blocked_midpoint(g, u, block, pad, skip).values()) if len(g) else 0)
    MANY[name] = lambda gaps, sizes, u: sum(blocked_sizes(gaps, sizes, u, block, pad, skip).values())


blocked_code("midpoint_block")
blocked_code("midpoint_block:pad", pad=True)
blocked_code("midpoint_block:plain", skip="plain")
blocked_code("midpoint_block:trimmed", skip="trimmed")


def ef_bits(n: int, u: int) -> int:
    """The closed form for n ids in 1..u."""
    low = (u // n).bit_length() - 1 if u > n else 0
    return n * low + n + (u >> low)


@codec("elias_fano", lambda g, u: ef_bits(len(g), u) if len(g) else 0)
def _elias_fano():
    def put(b, gaps, u):
        ids, n = np.cumsum(gaps).tolist(), len(gaps)
        low = (u // n).bit_length() - 1 if u > n else 0
        for x in ids:
            b.put(x & (1 << low) - 1, low)
        at = 0
        for x in ids:
            b.put(1, (x >> low) - at + 1)
            at = x >> low
        b.put(0, (u >> low) - at)

    def take(b, n, u):
        low = (u // n).bit_length() - 1 if u > n else 0
        lows = [b.get(low) for _ in range(n)]
        ids, at = [], 0
        for x in lows:
            at += get_unary(b) - 1
            ids.append(at << low | x)
        return [p - q for p, q in zip(ids, [0, *ids], strict=False)]

    return put, take


def ef_block_bits(gaps: np.ndarray, block: int = BLOCK) -> int:
    """Each block on its own span: 128 ids, the universe rebased; spans are Delta coded."""
    ids = np.cumsum(gaps)
    out = 0
    for i in range(0, len(ids), block):
        n = min(block, len(ids) - i)
        span = int(ids[i + n - 1] - (ids[i - 1] if i else 0))
        out += ef_bits(n, span) + int(_delta_bits(np.array([span]))[0])
    return out


@codec("ef_block", lambda g, u: ef_block_bits(g))
def _ef_block():
    def put(b, gaps, u):
        for i in range(0, len(gaps), BLOCK):
            part = gaps[i : i + BLOCK]
            b.put_delta(sum(part))
            CODECS["elias_fano"].put(b, part, sum(part))

    def take(b, n, u):
        out = []
        while len(out) < n:
            span, m = b.get_delta(), min(BLOCK, n - len(out))
            out += CODECS["elias_fano"].take(b, m, span)
            b.at += (span >> _ef_low(m, span)) - (sum(out[-m:]) >> _ef_low(m, span))
        return out

    return put, take


def _ef_low(n: int, u: int) -> int:
    return (u // n).bit_length() - 1 if u > n else 0


def part_bits(n: int, span: int, fixed: int) -> int:
    """A part of a partitioned list: nothing if dense, else the shorter of bitmap and Elias-Fano, and its entry."""
    return fixed + (0 if n == span else min(span, ef_bits(n, span)))


def partitions(gaps: np.ndarray, how: str = "approx", eps: float = 0.03, fixed: int = 64, longest: int = 20_000) -> tuple[int, list[int]]:
    """(bits, ends of the parts) of least total over cuts. 'opt' looks at all O(n^2) of them (only lists up to ``longest``),
    'approx' from every place only at those where the cost first passes the next power of 1 + eps."""
    ids = np.concatenate([[0], np.cumsum(gaps)]).astype(np.int64).tolist()
    n = len(ids) - 1
    best, back = [0] + [1 << 62] * n, [0] * (n + 1)
    if how == "opt":
        if n > longest:
            raise ValueError("list too long for the optimal partition")
        for j in range(1, n + 1):
            best[j], back[j] = min((best[i] + part_bits(j - i, ids[j] - ids[i], fixed), i) for i in range(j))
    else:
        bounds = [float(fixed)]
        top = part_bits(n, ids[n], fixed) if n else 0
        while bounds[-1] < top:
            bounds.append(bounds[-1] * (1 + eps))
        ends = [0] * len(bounds)  # of each window, moving right with its start
        for i in range(n):
            for w, limit in enumerate(bounds):
                j = max(ends[w], i + 1)
                while j < n and part_bits(j + 1 - i, ids[j + 1] - ids[i], fixed) <= limit:
                    j += 1
                ends[w] = j
                c = best[i] + part_bits(j - i, ids[j] - ids[i], fixed)
                if c < best[j]:
                    best[j], back[j] = c, i
                if j == n:
                    break
    cuts, at = [], n
    while at:
        cuts.append(at)
        at = back[at]
    return best[n], cuts[::-1]


def _part_bits(n: np.ndarray, span: np.ndarray, fixed: int) -> np.ndarray:
    """As :func:`part_bits`, of many parts."""
    if span.max(initial=0) < 1 << 50:
        low = np.frexp(span / n)[1] - 1  # no quotient below a power of 2 rounds up to it
    else:
        low = bit_lengths((span // n).ravel()).reshape(span.shape) - 1
    own = np.minimum(span, n * (low + 1) + (span >> low))
    own *= n != span
    return own + fixed


def _least_inside(gaps: np.ndarray, first: np.ndarray) -> np.ndarray:
    """What the parts of each list cost at least besides their entries, however it is cut: log2(g) + 1 for each gap g above 1.
    A dense part has none; a bitmap's g is at least that; Elias-Fano takes n (log2(mean) + 1.9) - 1, and a sum of logarithms is
    at most n log2(mean)."""
    bits = np.zeros(len(gaps))
    wide = gaps > 1
    bits[wide] = np.log2(gaps[wide]) + 1
    return np.floor(np.add.reduceat(bits, first) - 1e-6).astype(np.int64)


def partition_sizes(gaps: np.ndarray, sizes: np.ndarray, how: str = "approx", eps: float = 0.03, fixed: int = 64, longest: int = 20_000, cells: int = 1 << 20) -> np.ndarray:
    """The bits of :func:`partitions` for each of the lists put one after another. A list is one part where two entries and the
    least that is inside cost no less. Others go together, those of like length for the optimal partition, each step for all of
    them at once; ``cells`` bounds the numbers held at a time."""
    out = np.zeros(len(sizes), np.int64)
    if how == "opt" and sizes.max(initial=0) > longest:
        raise ValueError("list too long for the optimal partition")
    ids, first = run_ids(gaps, sizes)
    some = np.flatnonzero(sizes)
    if not len(some):
        return out
    out[some] = _part_bits(sizes[some], ids[first[some] + sizes[some] - 1], fixed)
    some = some[out[some] > 2 * fixed + _least_inside(gaps, first[some])]
    order = some[np.argsort(-sizes[some], kind="stable")]
    while len(order):
        n = int(sizes[order[0]])
        if how == "opt":
            some = order[sizes[order] > n // 2][: max(1, cells // (n + 1))]
        else:
            windows = np.cumsum(2 + np.log(out[order[:PAIRS]] / fixed) / np.log1p(eps))
            some = order[: max(1, min(np.searchsorted(windows, PAIRS), np.searchsorted(np.cumsum(sizes[order[:PAIRS]]), cells)))]
        order = order[len(some) :]
        own, place = np.repeat(np.arange(len(some)), sizes[some]), np.concatenate([np.arange(m) for m in sizes[some]])
        held = ids[first[some][own] + place]
        if how == "opt":
            table = np.zeros((len(some), n + 1), np.int64)
            table[own, place + 1] = held
            out[some] = _optimal(table, sizes[some], fixed)
        else:
            out[some] = _approximate(sizes[some], held, eps, fixed)
    return out


def _optimal(ids: np.ndarray, n: np.ndarray, fixed: int) -> np.ndarray:
    """Least bits over all cuts of each row's first n + 1 ids; rows by falling n."""
    best = np.zeros(ids.shape, np.int64)
    for j in range(1, ids.shape[1]):
        m = np.searchsorted(-n, -j, "right")  # rows that are so long
        best[:m, j] = (best[:m, :j] + _part_bits(np.arange(j, 0, -1), ids[:m, j, None] - ids[:m, :j], fixed)).min(1)
    return best[np.arange(len(n)), n]


#: Longest spans that are kept by window and number of ids; where there would be more each is found when it is asked for.
SPANS = 1 << 22
#: More than any id, and pairs of a list and a window (64 to 4,000 a list) that the approximate partition takes together.
BEYOND, PAIRS = 1 << 62, 1 << 15


def _longest_span(n: np.ndarray, room: np.ndarray) -> np.ndarray:
    """The most that n ids may span so that a part, its entry apart, has at most ``room`` bits: what a part costs never falls
    with its span. With low bits of width l Elias-Fano has n (l + 1) + (span >> l), where span >> l lies in n to 2n - 1."""
    low = room // n - 2
    fits = (low >= 0) & (low < 50)
    at = np.where(fits, low, 0)
    span = np.where(fits, (room - n * (at + 1) + 1 << at) - 1, np.where(low < 0, 0, 1 << 62))
    return np.maximum(np.maximum(span, room), n)


def _approximate(n: np.ndarray, ids: np.ndarray, eps: float, fixed: int) -> np.ndarray:
    """Least bits over the cuts that the windows reach, for lists of ``n`` ids each, longest first, put one after another. A
    window's end only moves right; it is kept for each pair of a list and a window. Windows behind the first that has reached a
    list's end have no say and are dropped now and then: their cuts are that one's."""
    rows = len(n)
    off = np.cumsum(n + 2) - (n + 2)  # behind each list stands an id that no window reaches
    flat = np.full(int(n.sum()) + 2 * rows, BEYOND, np.int64)
    flat[off] = 0
    flat[np.arange(len(ids)) + np.repeat(2 * np.arange(rows) + 1, n)] = ids
    top = _part_bits(n, flat[off + n], fixed)
    bounds = [float(fixed)]
    while bounds[-1] < top.max():
        bounds.append(bounds[-1] * (1 + eps))
    limit = np.array(bounds)
    room = np.floor(limit).astype(np.int64) - fixed
    wide = int(n[0]) + 1
    known = np.minimum(_longest_span(np.arange(1, wide + 1), room[:, None]), BEYOND >> 1).ravel() if len(room) * wide <= SPANS else None
    windows = np.searchsorted(limit, top) + 1
    own = np.repeat(np.arange(rows), windows)
    w = np.arange(len(own)) - np.repeat(np.cumsum(windows) - windows, windows)
    here, stops = off[own] - 1, np.cumsum(windows)
    end, row = here + 1, w * wide - here  # where the part ends, and what makes of that the place of its length among the known
    best = np.full(len(flat), 1 << 62, np.int64)
    best[off] = 0
    following = flat[1:]

    def reaches(e, start, row, go):
        if known is not None:
            return following.take(e) - start <= known.take(e + row)
        k, v = e - here[go], w[go]
        return following.take(e) - start <= np.minimum(_longest_span(k + 1, room[v]), BEYOND >> 1)

    for i in range(int(n[0])):
        m = np.searchsorted(-n, -i, "left")  # rows that have an id from here on
        p = stops[m - 1]
        now, e, x, r = slice(p), end[:p], row[:p], own[:p]
        here[now] += 1
        x -= 1
        np.maximum(e, here[now] + 1, out=e)
        first = off[:m] + i
        start = flat[first].take(r)
        ok = reaches(e, start, x, now)
        while 4 * np.count_nonzero(ok) > p:  # all, as long as many go on
            e += ok
            ok &= reaches(e, start, x, now)
        go = np.flatnonzero(ok)
        to, s, x = e[go], start[go], x[go]
        while len(go):
            to += 1
            e[go] = to
            on = np.flatnonzero(reaches(to, s, x, go))
            go, to, s, x = go.take(on), to.take(on), s.take(on), x.take(on)
        cost = _part_bits(e - here[now], flat.take(e) - start, fixed)
        cost += best[first].take(r)
        best[e] = np.minimum(best.take(e), cost)  # a place that is there twice has the same cost twice
        if i % 16 == 15:
            full = following.take(e) == BEYOND
            drop = full[1:] & full[:-1] & (r[1:] == r[:-1])
            if 8 * np.count_nonzero(drop) > p:
                keep = np.concatenate([[True], ~drop, np.ones(len(own) - p, bool)])
                own, w, here, end, row = own[keep], w[keep], here[keep], end[keep], row[keep]
                stops = np.cumsum(np.bincount(own, minlength=rows))
    return best[off + n]


def partitioned_ef_bits(gaps: np.ndarray, how: str = "approx", **more) -> int:
    return partitions(gaps, how, **more)[0]


def partitioned_code(name: str, how: str, fixed: int = 64) -> None:
    """Parts behind entries of 24 bits for the length, 40 for the span and, if ``fixed`` has room, 32 for the offset."""

    def put(b, gaps, u):
        at = 0
        for end in partitions(np.array(gaps, np.int64), how, fixed=fixed)[1]:
            part = gaps[at:end]
            span = sum(part)
            b.put(len(part), 24)
            b.put(span, 40)
            if fixed > 64:
                b.put(part_bits(len(part), span, 0), 32)
            if len(part) < span and span <= ef_bits(len(part), span):
                for g in part:
                    put_unary(b, g)
            elif len(part) < span:
                CODECS["elias_fano"].put(b, part, span)
            at = end

    def take(b, n, u):
        out = []
        while len(out) < n:
            m, span = b.get(24), b.get(40)
            if fixed > 64:
                b.get(32)
            if m == span:
                out += [1] * m
            elif span <= ef_bits(m, span):
                out += [get_unary(b) for _ in range(m)]
            else:
                out += CODECS["elias_fano"].take(b, m, span)
                b.at += (span >> _ef_low(m, span)) - (sum(out[-m:]) >> _ef_low(m, span))
        return out

    CODECS[name] = Codec(name, put, take, lambda g, u: partitioned_ef_bits(g, how, fixed=fixed))
    MANY[name] = lambda gaps, sizes, u: partition_sizes(gaps, sizes, how, fixed=fixed)


partitioned_code("pef_opt", "opt")
partitioned_code("pef_approx", "approx")
partitioned_code("pef_skip", "approx", 96)


def bernoulli_bits(gaps: np.ndarray, u: int) -> float:
    n = len(gaps)
    return n * np.log2(u / n) + ((u - n) * np.log2(u / (u - n)) if u > n else 0.0)


def bitmap_runs_bits(gaps: np.ndarray, u: int, word: int = 32) -> int:
    """Word-aligned run lengths: words that hold an id are literal, runs of empty words share one."""
    w = np.unique((np.cumsum(gaps) - 1) // (word - 1))
    before = np.concatenate([[-1], w[:-1]])
    return int(word * (len(w) + (w - before > 1).sum() + (w[-1] < (u - 1) // (word - 1))))


def bitmap_chunks_bits(gaps: np.ndarray, chunk: int = 1 << 16) -> int:
    """Chunks of 2**16 ids as arrays of 16 bits or bitmaps, whichever is shorter, behind 32 bits each."""
    _, n = np.unique((np.cumsum(gaps) - 1) // chunk, return_counts=True)
    return int((32 + np.minimum(16 * n, chunk)).sum())


@codec("bitmap_runs", lambda g, u: bitmap_runs_bits(g, u) if len(g) else 0)
def _bitmap_runs():
    """Words of 32 bits: a literal one (0 and 31 bits) or a run of empty ones (1 and their number)."""

    def put(b, gaps, u):
        at, word, top = -1, -1, (u - 1) // 31
        held = 0

        def run(n):
            if n:
                b.put(1, 1)
                b.put(n, 31)

        for g in gaps:
            at += g
            if at // 31 != word:
                if held:
                    b.put(held, 32)
                run(at // 31 - word - 1)
                word, held = at // 31, 0
            held |= 1 << 30 - at % 31
        if held:
            b.put(held, 32)
        run(top - word)

    def take(b, n, u):
        ids, word = [], 0
        while len(ids) < n:
            if b.get(1):
                word += b.get(31)
            else:
                x = b.get(31)
                ids += [word * 31 + i + 1 for i in range(31) if x >> 30 - i & 1]
                word += 1
        return gaps_from(ids)

    return put, take


@codec("bitmap_chunks", lambda g, u: bitmap_chunks_bits(g))
def _bitmap_chunks():
    """Behind 16 bits for the chunk (less the last one) and 16 for the number of ids, less one: ids of 16 bits, or a bitmap."""

    def put(b, gaps, u):
        ids, last = (np.cumsum(gaps) - 1).tolist(), 0
        i = 0
        while i < len(ids):
            c, j = ids[i] >> 16, i
            while j < len(ids) and ids[j] >> 16 == c:
                j += 1
            if c - last >= 1 << 16:
                raise ValueError("chunks further apart than 2**32 ids")
            b.put(c - last, 16)
            b.put(j - i - 1, 16)
            if 16 * (j - i) <= 1 << 16:
                for x in ids[i:j]:
                    b.put(x & 65535, 16)
            else:
                at = -1
                for x in ids[i:j]:
                    put_unary(b, (x & 65535) - at)
                    at = x & 65535
                b.put(0, 65535 - at)
            last, i = c, j

    def take(b, n, u):
        ids, c = [], 0
        while len(ids) < n:
            c += b.get(16)
            m = b.get(16) + 1
            if 16 * m <= 1 << 16:
                ids += [(c << 16 | b.get(16)) + 1 for _ in range(m)]
            else:
                ids += [(c << 16) + i + 1 for i in range(1 << 16) if b.get(1)]
        return gaps_from(ids)

    return put, take


def lzma_size(data: bytes) -> int:
    """Bytes that ``lzma.compress`` makes. Of short data the search tree is never deeper than the default's limit, so a small
    dictionary finds the same matches, and none of 8 MB has to be cleared for each list."""
    return len(lzma.compress(data, filters=SMALL_LZMA) if len(data) <= SHORT_LZMA else lzma.compress(data))


#: The default's filter but for the dictionary, for data of at most so many bytes.
SMALL_LZMA = [{"id": lzma.FILTER_LZMA2, "preset": lzma.PRESET_DEFAULT, "dict_size": 4096}]
SHORT_LZMA = 40


def compressor(name: str, pack, unpack, size=None) -> None:
    """Stand-ins for general-purpose compressors, over byte-coded gaps. ``size`` is that of what ``pack`` makes."""
    size = size or (lambda data: len(pack(data)))

    def put(b, gaps, u):
        for x in pack(CODECS["vbyte"].encode(gaps, 1 << 62)):
            b.put(x, 8)

    CODECS[name] = Codec(name, put, lambda b, n, u: CODECS["vbyte"].take(Bits(unpack(b.data)), n, u), lambda g, u: 8 * size(CODECS["vbyte"].encode(g, 1 << 62)))


compressor("zlib", zlib.compress, zlib.decompress)
compressor("bz2", bz2.compress, bz2.decompress)
compressor("lzma", lzma.compress, lzma.decompress, lzma_size)


def compose(name: str, first: str, pack=zlib.compress, unpack=zlib.decompress) -> Codec:
    """A block or list codec with an entropy stage behind it."""
    inner = CODECS[first]

    def put(b, gaps, u):
        for x in pack(inner.encode(gaps, u)):
            b.put(x, 8)

    CODECS[name] = Codec(name, put, lambda b, n, u: inner.take(Bits(unpack(b.data)), n, u))
    return CODECS[name]


compose("simple8b+zlib", "simple8b")
compose("packing+lzma", "packing", lzma.compress, lzma.decompress)


def midpoint_udf():
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("bigint")
    def f(ids: pd.Series, u: pd.Series) -> pd.Series:
        return pd.Series([midpoint_bits(np.asarray(i), int(d)) for i, d in zip(ids, u, strict=True)])

    return f
