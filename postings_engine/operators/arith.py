"""An integer arithmetic coder with carry propagation, and its static and adaptive drivers over trits."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np

from .trits import Context, counts_before, starting_counts, states

TOP, LOW = 1 << 56, 1 << 48  # the range is kept in [LOW, TOP): totals up to 2**30 lose nothing worth naming
MASK = TOP - 1
MAX_TOTAL = 1 << 30
#: Symbols whose places in the range are found together.
CHUNK = 1 << 18


class Encoder:
    def __init__(self):
        self.low, self.range, self.out = 0, TOP, bytearray()

    def put(self, lo: int, n: int, total: int) -> None:
        r = self.range // total
        self.low += r * lo
        self.range = r * n
        while self.range < LOW:
            self._byte()

    def put_all(self, lo: np.ndarray, n: np.ndarray, total: np.ndarray) -> None:
        """:meth:`put` of one after another."""
        low, r = self.low, self.range
        for a, b, t in zip(lo.tolist(), n.tolist(), total.tolist(), strict=True):
            r //= t
            low += r * a
            r *= b
            while r < LOW:
                self.low, self.range = low, r
                self._byte()
                low, r = self.low, self.range
        self.low, self.range = low, r

    def _byte(self) -> None:
        if self.low >= TOP:  # the carry runs through bytes already written
            self.low &= MASK
            out, i = self.out, len(self.out) - 1
            while out[i] == 255:
                out[i] = 0
                i -= 1
            out[i] += 1
        self.out.append(self.low >> 48)
        self.low = self.low << 8 & MASK
        self.range <<= 8

    def finish(self) -> bytes:
        """The shortest number of bytes that tells the last interval; trailing zero bytes are implied."""
        end = self.low + self.range - 1
        for keep in range(1, 8):
            unit = 1 << 56 - 8 * keep
            v = -(-self.low // unit) * unit
            if v <= end:
                break
        self.low, self.range = v, 1
        for _ in range(keep):
            self._byte()
        out = bytes(self.out)
        return out.rstrip(b"\0")


class Decoder:
    def __init__(self, data: bytes):
        self.data, self.at, self.range = data, 7, TOP
        self.code = int.from_bytes(data[:7].ljust(7, b"\0"), "big")

    def get(self, total: int) -> int:
        """A number below total inside the symbol's interval; then call :meth:`drop`."""
        self.unit = self.range // total
        return min(self.code // self.unit, total - 1)

    def drop(self, lo: int, n: int) -> None:
        self.code -= self.unit * lo
        self.range = self.unit * n
        while self.range < LOW:
            self.code = self.code << 8 | (self.data[self.at] if self.at < len(self.data) else 0)
            self.at += 1
            self.range <<= 8


def encode_static(ids: np.ndarray, s: np.ndarray, q: np.ndarray) -> bytes:
    """Symbols with the fractions q[context]; a quantised model codes only what it gave a share."""
    cum = np.concatenate([np.zeros((len(q), 1), np.int64), np.cumsum(q, 1)], 1)
    e = Encoder()
    for a in range(0, len(s), CHUNK):
        i, x = ids[a : a + CHUNK], s[a : a + CHUNK]
        e.put_all(cum[i, x], q[i, x], cum[i, -1])
    return e.finish()


class Tracker:
    """The context of the next symbol while symbols come one by one; the same numbers as :meth:`Context.ids`."""

    def __init__(self, ctx: Context):
        self.ctx = ctx
        self.clear()

    def clear(self) -> None:
        self.past: list[int] = []

    def __call__(self) -> int:
        c, past = self.ctx, self.past
        n = len(past)
        if not c.reach:
            return 0
        if n < c.reach:
            q = min(n, c.k_init)
            b = 2 if c.merge_init else 3
            out = sum(b**i for i in range(q))
            for j in range(1, q + 1):
                x = past[n - j]
                out += ((x == 2) if c.merge_init else min(x, 2)) * b ** (j - 1)
            return out
        b, code = c.base, 0
        for j in range(c.k, 0, -1):
            x = past[n - j]
            code = code * b + ((x == 2) if c.merge else min(x, 2))
        scale, back = b**c.k, c.k
        for w in c.windows:
            code += scale * sum(x == 2 for x in past[n - back - w : n - back])
            scale *= w + 1
            back += w
        return c.initial + code

    def push(self, x: int) -> None:
        self.past.append(x)
        if len(self.past) > 4096 + self.ctx.reach:  # only the last ones count; past keeps at least reach of them
            del self.past[: 4096]


class Counts:
    """Adaptive counts with forgetting, shared by coder and decoder."""

    def __init__(self, size: int, kinds: int, forget: int | None, prior=None, clock: str = "context"):
        self.c = starting_counts(prior, size, kinds).tolist()
        self.steps, self.forget = [0] * size, forget
        self.clock, self.total = clock, 0

    def add(self, i: int, x: int) -> None:
        self.c[i][x] += 1
        if self.forget and self.clock == "global":
            self.total += 1
            if self.total % self.forget == 0:
                self.c = [[max(1, y >> 1) for y in c] for c in self.c]
        elif self.forget:
            self.steps[i] += 1
            if self.steps[i] == self.forget:
                self.steps[i] = 0
                self.c[i] = [max(1, y >> 1) for y in self.c[i]]


def encode_adaptive(ids: np.ndarray, s: np.ndarray, size: int, kinds: int, forget: int | None, prior=None, clock: str = "context") -> bytes:
    e, lo = Encoder(), np.empty((3, len(s)), np.int64 if not forget else np.int32)
    for where, c in counts_before(ids, s, None, size, kinds, forget, prior, clock, CHUNK):
        total = np.cumsum(c, 1)
        row, x = np.arange(len(c)), s[where]
        lo[:, where] = total[row, x] - c[row, x], c[row, x], total[:, -1]
    for a in range(0, len(s), CHUNK):
        e.put_all(*lo[:, a : a + CHUNK])
    return e.finish()


def decode_lists(data: bytes, lengths: Sequence[int] | None, n_lists: int, ctx: Context, q: np.ndarray | None = None, forget: int | None = None, prior=None, clock: str = "context") -> list[np.ndarray]:
    """Gap lists of a segment. With ``q`` the static coder, else the adaptive one; ``lengths`` None with an end symbol."""
    m = Counts(ctx.size, ctx.kinds, forget, prior, clock) if q is None else None
    rows = m.c if m else q.tolist()
    merged = ctx.merge and ctx.merge_init  # then a number tells the past, else the symbols themselves
    track = Tracker(ctx)
    context, top = states(ctx) if merged else (None, 0)
    mask, over = top - 1, top << 1
    every = forget if m and forget and clock != "global" else 0
    steps = m.steps if m else None
    data = data.ljust(7, b"\0")
    code, r, at, end = int.from_bytes(data[:7], "big"), TOP, 7, len(data)
    out = []
    for k in range(n_lists):
        track.clear()
        gaps, g, h = [], 1, 1
        want = lengths[k] if lengths is not None else -1
        while want:
            i = context[h] if merged else track()
            c = rows[i]
            whole = sum(c)
            r //= whole
            v = code // r
            lo = x = 0
            n = c[0]
            if v >= whole:
                v = whole - 1
            while lo + n <= v:
                lo += n
                x += 1
                n = c[x]
            code -= r * lo
            r *= n
            while r < LOW:
                code = code << 8 | (data[at] if at < end else 0)
                at += 1
                r <<= 8
            if every:
                c[x] += 1
                steps[i] += 1
                if steps[i] == every:
                    steps[i] = 0
                    rows[i] = [y >> 1 or 1 for y in c]
            elif m:
                m.add(i, x)
                rows = m.c
            if not merged:
                track.push(x)
            else:
                h = h << 1 | (x == 2)
                if h >= over:
                    h = h & mask | top
            if x == 2:
                gaps.append(g)
                g = 1
                want -= 1
            elif x == 3:
                break
            else:
                g = g << 1 | x
        out.append(np.array(gaps, np.int64))
    return out


class Bits:
    """Bits written into, and read from, bytes."""

    def __init__(self, data: bytes = b""):
        self.value, self.n, self.out, self.data, self.at = 0, 0, bytearray(), data, 0

    def put(self, x: int, width: int) -> None:
        self.value = self.value << width | x
        self.n += width
        while self.n >= 8:
            self.n -= 8
            self.out.append(self.value >> self.n & 255)
        self.value &= (1 << self.n) - 1

    def bytes(self) -> bytes:
        return bytes(self.out) + (bytes([self.value << 8 - self.n & 255]) if self.n else b"")

    def get(self, width: int) -> int:
        out = 0
        for i in range(self.at, self.at + width):
            out = out << 1 | (self.data[i >> 3] >> 7 - (i & 7) & 1)
        self.at += width
        return out

    def put_delta(self, x: int) -> None:
        b = x.bit_length()
        n = b.bit_length()
        self.put(0, n - 1)
        self.put(b, n)
        self.put(x - (1 << b - 1), b - 1)

    def get_delta(self) -> int:
        n = 1
        while not self.get(1):
            n += 1
        b = 1 << n - 1 | self.get(n - 1)
        return 1 << b - 1 | self.get(b - 1)
