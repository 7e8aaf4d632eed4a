"""Array kernels: trits, their contexts, and model sizes. One call handles many lists at once."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np

#: Contexts of at most so long a past are looked up in a table of all pasts.
TABLE_REACH = 16


def bit_lengths(x: np.ndarray) -> np.ndarray:
    """Of positive int64 numbers, exactly."""
    out = np.zeros(len(x), np.int64)
    rest = x.astype(np.int64).copy()
    for s in (32, 16, 8, 4, 2, 1):
        big = rest >= (1 << s)
        out[big] += s
        rest[big] >>= s
    return out + (rest > 0)


def trits_of(gaps: np.ndarray, ends: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(symbols uint8, symbols per gap): digits below the top one, then 2. With ``ends`` (true at each list's last gap)
    a 3 closes each list."""
    if len(gaps) and gaps.min() < 1:
        raise ValueError("gaps are at least 1")
    b = bit_lengths(gaps)
    width = b + (ends.astype(np.int64) if ends is not None else 0)
    at = np.concatenate([[0], np.cumsum(width)])
    out = np.zeros(int(at[-1]), np.uint8)
    for k in range(int(b.max(initial=1)) - 1):  # k-th digit below the top one
        has = b - 1 > k
        out[at[:-1][has] + k] = gaps[has] >> (b[has] - 2 - k) & 1
    out[at[:-1] + b - 1] = 2
    if ends is not None:
        out[at[1:][ends] - 1] = 3
    return out, width


def gaps_of(symbols: np.ndarray) -> np.ndarray:
    """Back from trits (a 3 is skipped)."""
    s = symbols[symbols < 3].astype(np.int64)
    close = np.flatnonzero(s == 2)
    start = np.concatenate([[-1], close[:-1]]) + 1
    width = close - start
    out = np.ones(len(close), np.int64)
    for k in range(int(width.max(initial=0))):
        has = width > k
        out[has] = out[has] << 1 | s[start[has] + k]
    return out


@dataclass(frozen=True)
class Context:
    """Which recent symbols condition the next one.

    ``k`` symbols at once, and the number of terminators in windows before them (``windows``, one or more). ``merge``:
    of the k symbols only whether they are terminators (2 kinds of symbol, else 3). The first k + sum(windows) symbols of
    a list use at most ``k_init`` symbols (merged likewise unless ``merge_init`` is False) and no count.
    """

    k: int
    windows: tuple[int, ...] = ()
    k_init: int = 0
    merge: bool = True
    merge_init: bool = True
    kinds: int = 3  # symbols of the alphabet that is coded: 3, or 4 with an end of list

    @property
    def reach(self) -> int:
        return self.k + sum(self.windows)

    @property
    def base(self) -> int:
        return 2 if self.merge else 3

    @property
    def initial(self) -> int:
        b = 2 if self.merge_init else 3
        return sum(b**i for i in range(self.k_init + 1)) if self.reach else 0

    @property
    def general(self) -> int:
        n = self.base**self.k
        for w in self.windows:
            n *= w + 1
        return n

    @property
    def size(self) -> int:
        return self.initial + self.general

    def model_bits(self, bits: int, stored: int | None = None) -> int:
        return (self.kinds - 1 if stored is None else stored) * bits * self.size

    def ids(self, s: np.ndarray, pos: np.ndarray) -> np.ndarray:
        """Context of each symbol; ``pos`` is its place in its list. The initial ones come first, by length."""
        n, kind = len(s), np.int32 if self.size * 4 < 1 << 31 else np.int64
        z = (s == 2).astype(kind)
        digits = {2: z} if self.merge and self.merge_init else {2: z, 3: np.minimum(s, 2).astype(kind)}
        out = recent(digits[self.base], self.k, self.base)
        if not self.reach:
            return out
        total = np.concatenate([[0], np.cumsum(z)]).astype(kind)
        scale, back = self.base**self.k, self.k
        for w in self.windows:
            a, b = behind(total, back + w, n), behind(total, back, n)
            b -= a
            b *= scale
            out += b
            scale *= w + 1
            back += w
        out += self.initial
        near = np.flatnonzero(pos < self.reach)
        b = 2 if self.merge_init else 3
        q = np.minimum(pos[near], self.k_init)
        powers = np.array([b**i for i in range(self.k_init + 1)], kind)
        before = (np.cumsum(powers) - powers).astype(kind)
        out[near] = before[q] + recent(digits[b], self.k_init, b)[near] % powers[q]
        return out


def recent(digit: np.ndarray, k: int, base: int) -> np.ndarray:
    """The k digits before each place as a number, the nearest lowest; by halves, so log(k) passes."""
    if k < 2:
        out = np.zeros_like(digit)
        if k:
            out[1:] = digit[:-1]
        return out
    half = k // 2
    out = recent(digit, half, base)
    far = out if k == 2 * half else recent(digit, k - half, base)
    far = far[: max(len(digit) - half, 0)] * digit.dtype.type(base**half)
    out[half:] += far
    return out


def behind(total: np.ndarray, back: int, n: int) -> np.ndarray:
    """Of running totals (0 first), the one ``back`` places before each of n places."""
    out = np.zeros(n, total.dtype)
    out[back:] = total[: max(n - back, 0)]
    return out


def none() -> Context:
    return Context(0)


def full(gamma: int) -> Context:
    return Context(gamma, (), gamma, False, False)


def full_count(k: int, w: int, k_init: int | None = None) -> Context:
    return Context(k, (w,), k if k_init is None else k_init, False, False)


def hybrid(k: int, w: int, k_init: int = 0) -> Context:
    return Context(k, (w,), k_init)


def boxes(k: int, windows: tuple[int, ...], k_init: int = 0) -> Context:
    return Context(k, tuple(windows), k_init)


def covering(k: int, d: int, k_init: int = 0) -> Context:
    """A window as long as the longest run without a terminator lets the next one be foretold."""
    return Context(k, (max(1, d.bit_length() - k),), k_init)


def counts(ids: np.ndarray, s: np.ndarray, size: int, kinds: int = 3) -> np.ndarray:
    return np.bincount(ids * kinds + s, minlength=size * kinds).reshape(size, kinds)


def sparse_counts(ids: np.ndarray, s: np.ndarray, kinds: int = 3) -> tuple[np.ndarray, np.ndarray]:
    """(contexts that occur, their counts by symbol), without a table of all contexts."""
    both, times = np.unique(ids * kinds + s, return_counts=True)
    context = both // kinds
    used = np.flatnonzero(np.diff(context, prepend=-1))
    out = np.zeros((len(used), kinds), np.int64)
    out[np.repeat(np.arange(len(used)), np.diff(np.append(used, len(both)))), both % kinds] = times
    return context[used], out


def ideal_bits(n: np.ndarray, q: np.ndarray | None = None) -> float:
    """Of counts n by (context, symbol), coded with the integer fractions q, by default their own frequencies."""
    q = n if q is None else q
    used = n > 0
    total = np.broadcast_to(q.sum(1, keepdims=True), n.shape)
    return float((n[used] * (np.log2(total[used]) - np.log2(q[used]))).sum())


def quantise(n: np.ndarray, bits: int, balanced: bool = False) -> np.ndarray:
    """Counts to numerators over 2**bits - 1: rounded half up, none that occurs at 0; the last symbol takes the rest.

    ``balanced``: one number for symbols 0 and 1 together, of which each gets half."""
    if not 2 <= bits <= 30:
        raise ValueError("bits must lie between 2 and 30")
    m, kinds = (1 << bits) - 1, n.shape[1]
    n = n.astype(np.int64)
    total = n.sum(1)
    safe = np.maximum(total, 1)
    q = np.zeros_like(n)
    if balanced:
        both = (2 * m * (n[:, 0] + n[:, 1]) + safe) // (2 * safe)
        half = np.maximum(both // 2, (n[:, 0] + n[:, 1] > 0).astype(np.int64))
        half = np.minimum(half, (m - (n[:, 2] > 0)) // 2)
        q[:, 0] = q[:, 1] = half
    else:
        for j in range(kinds - 1):
            q[:, j] = np.maximum((2 * m * n[:, j] + safe) // (2 * safe), (n[:, j] > 0).astype(np.int64))
    q[:, -1] = m - q[:, :-1].sum(1)
    lack = np.maximum((n[:, -1] > 0).astype(np.int64) - q[:, -1], 0)
    lack += np.maximum(-(q[:, -1] + lack), 0)
    rows = np.flatnonzero(lack)
    if len(rows):  # taken from the larger of the stored ones
        top = q[rows, :-1].argmax(1)
        q[rows, top] -= lack[rows]
        q[rows, -1] += lack[rows]
    q[total == 0] = 0
    return q


def choose_static(ints: int, share: float = 0.02, bits: int = 8, k_max: int | None = None, most: int | None = None) -> tuple[int, int, int]:
    """(k, w, k_init) with w = k + 1, k_init = ceil(k / 3), k as large as a model of ``share`` of the integers allows, and of
    ``most`` contexts, if that is given."""
    k = 1
    while True:
        c = hybrid(k + 1, k + 2, -(-(k + 1) // 3))
        if c.model_bits(bits) > share * ints or k_max is not None and k >= k_max or most is not None and c.size > most:
            return k, k + 1, -(-k // 3)
        k += 1


def choose_adaptive(ints: int) -> tuple[int, int, int, int]:
    """(k, w, k_init, n): the fitted rule (its two numbers and limits are fixed values)."""
    k = max(int(np.floor(np.log(max(ints, 1)) / 1.67264 - 2.24758 + 0.5)), 7)
    return k, k, min(2 * k - 1, 8), 1 << min(max(k, 8), 16)


def adaptive_bits(ids: np.ndarray, s: np.ndarray, size: int, kinds: int = 3, forget: int | None = 256, halving: str = "context", prior: tuple[int, ...] | np.ndarray | None = None) -> float:
    """Ideal bits of one adaptive stream: counts start at the prior (one row, or one for each context), grow by one, and are halved (floor, at least 1) after
    every ``forget`` steps of a context, or of the whole stream with halving='global'.

    Between two halvings the steps of a context cost the same in any order: log2 of rising products, so of each period only
    its counts matter. All contexts go through their n-th period together; by the global clock, all symbols of a period do.
    """
    first = starting_counts(prior, size, kinds)
    if not len(s):
        return 0.0
    if halving == "global" and forget:
        s = s.astype(np.int64)
        c, out = first.copy(), 0.0
        for a in range(0, len(s), forget):
            i, x = ids[a : a + forget], s[a : a + forget]
            same, all_ = _earlier(i, x, kinds)
            out += float((np.log2(c[i].sum(1) + all_) - np.log2(c[i, x] + same)).sum())
            if len(i) == forget:
                np.add.at(c, (i, x), 1)
                c = np.maximum(c >> 1, 1)
        return out
    n = np.bincount(ids, minlength=size)
    turns = -(-n // forget) if forget else np.minimum(n, 1)
    context = np.repeat(np.arange(size), turns)
    turn = np.arange(len(context)) - np.repeat(np.cumsum(turns) - turns, turns)
    steps = n[context] - turn * forget if forget else n[context]
    steps = np.minimum(steps, forget) if forget else steps
    run = np.repeat(np.arange(len(steps)) * kinds, steps)  # symbols by context and period
    run += s[_by_group(ids, size)]
    total = np.bincount(run, minlength=len(steps) * kinds).reshape(-1, kinds)
    c = np.empty((len(steps), kinds), np.int64)
    order = np.argsort(turn, kind="stable")
    cuts = np.searchsorted(turn[order], np.arange(int(turn.max()) + 2))
    for t in range(len(cuts) - 1):
        own = order[cuts[t] : cuts[t + 1]]
        c[own] = first[context[own]] if t == 0 else np.maximum(c[own - 1] + total[own - 1] >> 1, 1)
    whole = c.sum(1)
    log = np.concatenate([[0.0, 0.0], np.cumsum(np.log2(np.arange(1, int((whole + steps).max()))))])  # of (m - 1)!
    return float((log[whole + steps] - log[whole]).sum() - (log[c + total] - log[c]).sum())


def counts_before(ids: np.ndarray, s: np.ndarray, step: np.ndarray | None, size: int, kinds: int, forget: int | None, prior, clock: str, chunk: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(places, counts of their contexts) of an adaptive stream, some places at a time: the counts as they stood before the
    symbol's step, with all halvings until then. ``step`` grows with the place; None if each symbol is a step of its own. No
    step has more symbols than a period."""
    if not len(s):
        return
    first = starting_counts(prior, size, kinds)
    if clock == "global" and forget:
        began = np.arange(len(s)) if step is None else np.searchsorted(step, step)  # symbols of all steps before
        cuts = np.flatnonzero(np.diff(began // forget, prepend=-1))
        c = first
        for a, b in zip(cuts.tolist(), [*cuts[1:].tolist(), len(s)], strict=True):
            by = np.argsort(ids[a:b], kind="stable")
            i, x = ids[a:b][by], s[a:b][by]
            own = np.flatnonzero(np.diff(i, prepend=-1))  # where a context's symbols of the period begin
            seen = np.repeat(own, np.diff(np.append(own, b - a)))
            yield a + by, c[i] + _between(x, seen, _same_step(i, began[a:b][by]), kinds)
            c = c + np.bincount(ids[a:b] * np.int64(kinds) + s[a:b], minlength=size * kinds).reshape(size, kinds)
            c = np.maximum(c >> 1, 1)
        return
    by = _by_group(ids, size)
    i, x = ids[by], s[by]
    own = np.flatnonzero(np.diff(i, prepend=-1))
    began = np.arange(len(s)) if step is None else _same_step(i, step[by])
    began = began.astype(np.int32)
    period = (began - np.repeat(own.astype(np.int32), np.diff(np.append(own, len(i))))) // np.int32(min(forget or len(s), 2**31 - 1))
    runs = np.flatnonzero((np.diff(i, prepend=-1) != 0) | (np.diff(period, prepend=-1) != 0))
    many = np.diff(np.append(runs, len(i)))
    turn, context = period[runs], i[runs]
    del period
    run = np.repeat(np.arange(len(runs), dtype=np.int32), many)
    total = np.bincount(run.astype(np.int64) * kinds + x, minlength=len(runs) * kinds).reshape(-1, kinds)
    c = np.empty((len(runs), kinds), np.int64)
    order = np.argsort(turn, kind="stable")
    cuts = np.searchsorted(turn[order], np.arange(int(turn.max()) + 2))
    for t in range(len(cuts) - 1):
        now = order[cuts[t] : cuts[t + 1]]
        c[now] = first[context[now]] if t == 0 else np.maximum(c[now - 1] + total[now - 1] >> 1, 1)
    sums = [np.concatenate([[0], np.cumsum(x == j, dtype=np.int32)]).astype(np.int32) for j in range(kinds)]
    for a in range(0, len(s), chunk):
        r, here = run[a : a + chunk], began[a : a + chunk]
        yield by[a : a + chunk], c[r] + np.stack([t[here] - t[runs[r]] for t in sums], 1)


def _same_step(group: np.ndarray, step: np.ndarray) -> np.ndarray:
    """Of places ordered by group, then step: the first place of the same group and step."""
    new = np.flatnonzero((np.diff(group, prepend=-1) != 0) | (np.diff(step, prepend=-1) != 0))
    return np.repeat(new, np.diff(np.append(new, len(group))))


def _between(x: np.ndarray, a: np.ndarray, b: np.ndarray, kinds: int) -> np.ndarray:
    """How often each symbol stands at the places a..b-1."""
    sums = [np.concatenate([[0], np.cumsum(x == j)]) for j in range(kinds)]
    return np.stack([t[b] - t[a] for t in sums], 1)


def states(ctx: Context) -> tuple[list[int] | Seen, int]:
    """(context by state, top) for merged contexts. A state tells which of the last symbols were terminators, at most
    ``reach`` of them, behind a bit that tells how many they are; ``top`` is that bit of a full state."""
    k, top = ctx.k, 1 << ctx.reach
    before = [sum(2**i for i in range(p)) for p in range(ctx.k_init + 1)]

    def of(h: int) -> int:
        if not ctx.reach:
            return 0
        if h < top:
            few = min(h.bit_length() - 1, ctx.k_init)
            return before[few] + (h & (1 << few) - 1)
        i, scale, back = ctx.initial + (h & (1 << k) - 1), 1 << k, k
        for w in ctx.windows:
            i += scale * (h >> back & (1 << w) - 1).bit_count()
            scale *= w + 1
            back += w
        return i

    return [0, *map(of, range(1, 2 * top))] if ctx.reach <= TABLE_REACH else Seen(of), top


class Seen(dict):
    """Values of a function of numbers, kept for the first of them."""

    def __init__(self, f: Callable[[int], int], most: int = 1 << 18):
        super().__init__()
        self.f, self.most = f, most

    def __missing__(self, x: int) -> int:
        out = self.f(x)
        if len(self) < self.most:
            self[x] = out
        return out


def _by_group(ids: np.ndarray, size: int) -> np.ndarray:
    """Places ordered by group, then by place; 16 bits at a time, which are sorted by counting."""
    by = np.argsort((ids & 0xFFFF).astype(np.uint16), kind="stable")
    return by if size <= 1 << 16 else by[np.argsort((ids >> 16).astype(np.uint16)[by], kind="stable")]


def starting_counts(prior, size: int, kinds: int) -> np.ndarray:
    """Counts of all contexts before the first symbol: ones, a row for all, or a table."""
    own = np.ones(kinds, np.int64) if prior is None else np.asarray(prior, np.int64)
    if own.min() < 1:
        raise ValueError("starting counts are at least 1")
    return np.broadcast_to(own, (size, kinds)).copy()


def _earlier(group: np.ndarray, x: np.ndarray, kinds: int) -> tuple[np.ndarray, np.ndarray]:
    """How often each element's symbol, and any symbol, has occurred before in its group."""

    def rank(key):
        by = np.argsort(key, kind="stable")
        k = key[by]
        start = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
        out = np.empty(len(k), np.int64)
        out[by] = np.arange(len(k)) - np.repeat(start, np.diff(np.append(start, len(k))))
        return out

    return rank(group * kinds + x), rank(group)


def order_free_bits(n: np.ndarray, prior: int = 1) -> float:
    """Adaptive bits without forgetting: they depend on the final counts alone."""
    from math import lgamma, log

    kinds, out = n.shape[1], 0.0
    for row in n[n.sum(1) > 0].tolist():
        out += lgamma(sum(row) + kinds * prior) - lgamma(kinds * prior) - sum(lgamma(x + prior) - lgamma(prior) for x in row)
    return out / log(2)


def state_bytes(ctx: Context) -> int:
    return ctx.size * ctx.kinds * 8
