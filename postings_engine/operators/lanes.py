"""Many lists at once through one model: interleaved streams ("lanes") of an asymmetric numeral system in NumPy.

A segment's lists are dealt to lanes, contiguous runs of about as many symbols each. All lanes take a step together:
one symbol in each, all with the model as it stood before the step, whose counts then take in what the lanes have seen.
The coder knows all symbols beforehand, so it finds their shares going forward and writes going backward; the decoder
only goes forward. With one lane the model is that of the sequential coder. A lane costs its last state, 8 bytes.
"""

from __future__ import annotations

import struct

import numpy as np

from .trits import Context, counts_before, gaps_of, starting_counts, states

#: Shares are scaled to this power of two; states lie in [2**31, 2**63) and move 32 bits at a time.
SCALE = 24
LOW = np.uint64(1 << 31)
WORD = np.uint64(32)
#: Symbols that a lane should have at least, so that what it costs stays under a hundredth, and most lanes of a segment;
#: of an adaptive one fewer, so that its model does not lag far behind.
LEAST, MOST, MOST_ADAPTIVE = 16384, 1024, 256
#: Contexts reach back at most so far: a lane's past is one 64-bit number.
REACH = 62
#: Up to so many lanes a step costs less number by number than as arrays (measured: an array step as much as 80 to 100
#: numbers when decoding, 20 to 30 when only states move).
FEW_DECODED, FEW_CODED = 64, 20
#: Symbols whose shares are found together.
CHUNK = 1 << 18


def lanes_for(symbols: int, adaptive: bool) -> int:
    return max(1, min(MOST_ADAPTIVE if adaptive else MOST, symbols // LEAST))


def deal(per_list: np.ndarray, lanes: int) -> np.ndarray:
    """First list of each lane, and the number of lists at the end: runs of about equal numbers of symbols."""
    total = np.concatenate([[0], np.cumsum(per_list)])
    cuts = np.searchsorted(total, total[-1] * np.arange(1, lanes) / lanes)
    return np.unique(np.concatenate([[0], cuts, [len(per_list)]]))


def _bounds(counts: np.ndarray) -> np.ndarray:
    """Cumulative shares, scaled, of rows of counts; each symbol with a count has a share."""
    out = np.zeros((len(counts), counts.shape[1] + 1), np.int64)
    for j in range(counts.shape[1]):  # a sum along so short rows costs more
        np.add(out[:, j], counts[:, j], out=out[:, j + 1])
    whole = np.maximum(out[:, -1:], 1)  # of less than 2**39, so nothing is lost below the highest bit
    total = out[:, 1:]
    total <<= SCALE
    total //= whole
    return out.view(np.uint64)


class Shared:
    """Counts that all lanes share: halved, at least 1, after every ``forget`` steps of a context (or, with ``clock``
    'global', of the stream)."""

    def __init__(self, size: int, kinds: int, forget: int | None, prior=None, clock: str = "context"):
        self.c = starting_counts(prior, size, kinds)
        self.kinds, self.forget, self.clock = kinds, forget, clock
        self.steps, self.seen = np.zeros(size, np.int64), 0

    def bounds(self, ids: np.ndarray) -> np.ndarray:
        return _bounds(self.c[ids])

    def add(self, ids: np.ndarray, s: np.ndarray) -> None:
        np.add.at(self.c.reshape(-1), ids * self.kinds + s, 1)
        if not self.forget:
            return
        if self.clock == "global":
            self.seen += len(ids)
            if self.seen >= self.forget:
                self.seen -= self.forget
                self.c = np.maximum(self.c >> 1, 1)
            return
        np.add.at(self.steps, ids, 1)
        full = ids[self.steps[ids] >= self.forget]
        if len(full):
            full = np.unique(full)
            self.steps[full] -= self.forget
            self.c[full] = np.maximum(self.c[full] >> 1, 1)


def _grid(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Lanes by descending length (``by``), where each starts in the flat arrays, and how many are active at each step."""
    by = np.argsort(-sizes, kind="stable")
    start = (np.cumsum(sizes) - sizes)[by]
    active = np.searchsorted(-sizes[by], -np.arange(int(sizes.max(initial=0))), "left")
    return by, start, active


def _adaptive_shares(ids: np.ndarray, s: np.ndarray, start: np.ndarray, sizes: np.ndarray, active: np.ndarray, ctx: Context, forget, prior, clock: str) -> tuple[np.ndarray, np.ndarray]:
    """(first, width) of each symbol's share in the model as it stood before the symbol's step."""
    lo, f = np.empty(len(s), np.uint32), np.empty(len(s), np.uint32)
    if forget and len(start) > forget:  # a step may then be longer than a period
        model = Shared(ctx.size, ctx.kinds, forget, prior, clock)
        x = s.astype(np.int64)
        for t, m in enumerate(active.tolist()):
            where = start[:m] + t
            i, v = ids[where], x[where]
            b = model.bounds(i)
            row = np.arange(m)
            lo[where] = b[row, v]
            f[where] = b[row, v + 1] - b[row, v]
            model.add(i, v)
        return lo, f
    at = step = None
    if len(start) > 1:  # in the order of steps
        step = (np.arange(len(s)) - np.repeat(np.cumsum(sizes) - sizes, sizes)).astype(np.int32)
        by = np.argsort(step, kind="stable")
        step = step[by]
        at = step + np.repeat(start, sizes)[by]
        del by
        ids, s = ids[at], s[at]
    for where, c in counts_before(ids, s, step, ctx.size, ctx.kinds, forget, prior, clock, CHUNK):
        b, v = _bounds(c), s[where].astype(np.int64)
        row = np.arange(len(v))
        place = where if at is None else at[where]
        lo[place] = b[row, v]
        f[place] = b[row, v + 1] - b[row, v]
    return lo, f


def encode(ids: np.ndarray, s: np.ndarray, per_list: np.ndarray, ctx: Context, q: np.ndarray | None, lanes: int, forget=None, prior=None, clock: str = "context") -> tuple[bytes, float]:
    """(bytes, ideal bits). ``q`` is the static model; without it the adaptive one is used."""
    at = deal(per_list, lanes)
    total = np.concatenate([[0], np.cumsum(per_list)])
    sizes = np.diff(total[at])
    by, start, active = _grid(sizes)
    if q is not None:
        b = _bounds(q)
        lo, f = b[ids, s], b[ids, s.astype(np.int64) + 1] - b[ids, s]
    else:
        lo, f = _adaptive_shares(ids, s, start, sizes[by], active, ctx, forget, prior, clock)
    ideal = float((SCALE - np.log2(f.astype(float))).sum())
    state, flat = (_states_one_by_one if len(by) <= FEW_CODED else _states)(lo, f, start, sizes[by], active)
    last = np.empty(len(by), np.uint64)
    last[by] = state
    head = struct.pack("<I", len(by)) + np.diff(at).astype("<u4").tobytes() + sizes.astype("<u4").tobytes() + last.astype("<u8").tobytes()
    return head + flat.tobytes(), ideal


def _states(lo: np.ndarray, f: np.ndarray, start: np.ndarray, sizes: np.ndarray, active: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(last state of each lane, words in the order in which the decoder asks for them), steps backwards."""
    lo, f = lo.astype(np.uint64), f.astype(np.uint64)
    state = np.full(len(start), LOW, np.uint64)
    words: list[np.ndarray] = []
    for t in range(len(active) - 1, -1, -1):
        m = int(active[t])
        where = start[:m] + t
        fr, x = f[where], state[:m]
        out = x >= fr << np.uint64(63 - SCALE)
        at_ = np.flatnonzero(out)
        if len(at_):
            words.append((x[at_] & np.uint64(2**32 - 1)).astype("<u4"))
            x[at_] >>= WORD
        d, r = np.divmod(x, fr)
        state[:m] = (d << np.uint64(SCALE)) + r + lo[where]
    return state, np.concatenate(words[::-1]) if words else np.empty(0, "<u4")


def _states_one_by_one(lo: np.ndarray, f: np.ndarray, start: np.ndarray, sizes: np.ndarray, active: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """As :func:`_states`, lane after lane; the words are put in order of steps, then of lanes, afterwards."""
    state, words, steps = np.empty(len(start), np.uint64), [], []
    full = 63 - SCALE
    for lane, (a, n) in enumerate(zip(start.tolist(), sizes.tolist(), strict=True)):
        x, own, at = 1 << 31, [], []
        for stop in range(n, 0, -CHUNK):
            begin = max(0, stop - CHUNK)
            for t, first, width in zip(range(stop - 1, begin - 1, -1), lo[a + begin : a + stop][::-1].tolist(), f[a + begin : a + stop][::-1].tolist(), strict=True):
                if x >= width << full:
                    own.append(x & 0xFFFFFFFF)
                    at.append(t)
                    x >>= 32
                x = (x // width << SCALE) + x % width + first
        state[lane] = x
        words.append(np.array(own, np.uint32))
        steps.append(np.array(at, np.int64))
    flat, step = np.concatenate([np.empty(0, np.uint32), *words]), np.concatenate([np.empty(0, np.int64), *steps])
    return state, flat[np.argsort(step, kind="stable")].astype("<u4")


def header_bytes(lanes: int) -> int:
    """What the lanes of a stream cost besides its words: numbers of lists and symbols, states."""
    return 4 + lanes * (4 + 4 + 8)


def decode(data: bytes, lengths: np.ndarray | None, n_lists: int, ctx: Context, q: np.ndarray | None, forget=None, prior=None, clock: str = "context") -> tuple[np.ndarray, np.ndarray]:
    """(gaps of all lists one after another, how many each has)."""
    (lanes,) = struct.unpack_from("<I", data)
    lists, sizes = np.frombuffer(data, "<u4", 2 * lanes, 4).astype(np.int64).reshape(2, lanes)
    by, start, active = _grid(sizes)
    state = np.frombuffer(data, "<u8", lanes, 4 + 8 * lanes).astype(np.uint64)[by]
    words, read = np.frombuffer(data, "<u4", offset=4 + 16 * lanes).astype(np.uint64), 0
    first = (np.cumsum(lists) - lists)[by]  # the list that each lane is at
    if lanes <= FEW_DECODED and ctx.merge and ctx.merge_init and not (forget and lanes > forget):
        out = _symbols_one_by_one(state, words, start, sizes, active, first, lengths, ctx, q, forget, prior, clock)
        return _lists_of(out, lengths)
    out = np.empty(int(sizes.sum()), np.uint8)
    left = None
    if lengths is not None:
        lengths = np.append(np.asarray(lengths, np.int64), 1 << 60)  # behind the last list of all
        left = lengths[first]
    table = _bounds(q) if q is not None else None
    model = Shared(ctx.size, ctx.kinds, forget, prior, clock) if q is None else None
    past, pos, code3 = np.zeros(lanes, np.uint64), np.zeros(lanes, np.int64), np.zeros(lanes, np.int64)
    merged, k, reach, kin = ctx.merge, ctx.k, ctx.reach, ctx.k_init
    keep3 = 3 ** max(k if not merged else 0, kin if not ctx.merge_init else 0)
    base_init = 2 if ctx.merge_init else 3
    initial = np.array([sum(base_init**i for i in range(p)) for p in range(kin + 1)], np.int64)
    power = np.array([base_init**p for p in range(kin + 1)], np.int64)
    low_k, slots = np.uint64((1 << k) - 1), np.uint64((1 << SCALE) - 1)
    one = np.uint64(1)
    for t, m in enumerate(active.tolist()):
        h, p = past[:m], pos[:m]
        if not reach:
            i = np.zeros(m, np.int64)
        else:
            i = (h & low_k).astype(np.int64) if merged else code3[:m] % 3**k
            scale, back = ctx.base**k, k
            for w in ctx.windows:
                i += scale * np.bitwise_count(h >> np.uint64(back) & np.uint64((1 << w) - 1)).astype(np.int64)
                scale *= w + 1
                back += w
            i += ctx.initial
            near = np.flatnonzero(p < reach)
            if len(near):
                few = np.minimum(p[near], kin)
                i[near] = initial[few] + ((h[near] & (one << few.astype(np.uint64)) - one).astype(np.int64) if ctx.merge_init else code3[near] % power[few])
        b = table[i] if table is not None else model.bounds(i)
        x = state[:m]
        slot = x & slots
        v = (slot >= b[:, 1]).astype(np.int64)
        for j in range(2, ctx.kinds):
            v += slot >= b[:, j]
        row = np.arange(m)
        lo = b[row, v]
        x = (b[row, v + 1] - lo) * (x >> np.uint64(SCALE)) + slot - lo
        need = np.flatnonzero(x < LOW)
        if len(need):
            x[need] = x[need] << WORD | words[read : read + len(need)]
            read += len(need)
        state[:m] = x
        out[start[:m] + t] = v
        if model is not None:
            model.add(i, v)
        z = v == 2
        past[:m] = h << one | z.astype(np.uint64)
        pos[:m] += 1
        if keep3 > 1:
            code3[:m] = (code3[:m] * 3 + np.minimum(v, 2)) % keep3
        if left is not None:
            left[:m] -= z
            done = np.flatnonzero(left[:m] == 0)
            if len(done):
                first[done] += 1
                left[done] = lengths[first[done]]
        else:
            done = np.flatnonzero(v == 3)
        pos[done] = 0  # a new list starts without a past
        past[done] = 0
        code3[done] = 0
    return _lists_of(out, None if lengths is None else lengths[:-1])


def _lists_of(out: np.ndarray, lengths) -> tuple[np.ndarray, np.ndarray]:
    """(gaps, how many each list has) of all symbols."""
    gaps = gaps_of(out)
    if lengths is not None:
        return gaps, np.asarray(lengths, np.int64)
    ends = np.flatnonzero(out == 3)
    before = np.cumsum(out == 2)[ends]
    return gaps, np.diff(np.concatenate([[0], before]))


def _symbols_one_by_one(state, words, start, sizes, active, first, lengths, ctx: Context, q: np.ndarray | None, forget, prior, clock: str) -> np.ndarray:
    """All symbols, decoded number by number: the way of few lanes, for contexts of merged symbols."""
    kinds, slots, scale = ctx.kinds, (1 << SCALE) - 1, SCALE
    context, top = states(ctx)
    mask, over = top - 1, top << 1
    fixed = _bounds(q).astype(np.int64).tolist() if q is not None else None
    counts = None if fixed else starting_counts(prior, ctx.size, kinds).tolist()
    steps, turn, forget = [0] * (0 if fixed else ctx.size), 0, forget or 1 << 62  # by the global clock: turns that a context has had
    by_stream, seen, k3 = clock == "global" and forget < 1 << 62, 0, kinds - 1
    lengths = None if lengths is None else [*np.asarray(lengths, np.int64).tolist(), 1 << 60]
    left = None if lengths is None else [lengths[i] for i in first.tolist()]
    first, x_of, words, read = first.tolist(), state.tolist(), words.tolist(), 0
    past, out = [1] * len(x_of), [bytearray() for _ in x_of]  # a bit above the past tells how long it is
    put, pending = [o.append for o in out], []
    for m, times in _stretches(active):
        for _ in range(times):
            for lane in range(m):
                h, x = past[lane], x_of[lane]
                i = context[h]
                slot = x & slots
                if fixed:
                    b = fixed[i]
                    v = 0
                    while v < k3 and slot >= b[v + 1]:
                        v += 1
                    lo, hi = b[v], b[v + 1]
                else:
                    c = counts[i]
                    if by_stream and steps[i] < turn:
                        for _ in range(turn - steps[i]):
                            if max(c) < 2:
                                break
                            c[:] = [y >> 1 or 1 for y in c]
                        steps[i] = turn
                    whole = sum(c)
                    lo, edge = 0, c[0]
                    hi = (edge << scale) // whole
                    v = 0
                    while slot >= hi and v < k3:
                        v += 1
                        edge += c[v]
                        lo, hi = hi, (edge << scale) // whole
                    pending.append((i, v))
                x = (hi - lo) * (x >> scale) + slot - lo
                if x < 0x80000000:
                    x = x << 32 | words[read]
                    read += 1
                x_of[lane] = x
                put[lane](v)
                if v < 2:
                    h <<= 1
                    past[lane] = h if h < over else h & mask | top
                    continue
                if v == 2:
                    h = h << 1 | 1
                    past[lane] = h if h < over else h & mask | top
                    if left is not None:
                        left[lane] -= 1
                        if not left[lane]:
                            first[lane] += 1
                            left[lane] = lengths[first[lane]]
                            past[lane] = 1
                elif left is None:
                    past[lane] = 1
                else:
                    h <<= 1
                    past[lane] = h if h < over else h & mask | top
            if fixed:
                continue
            for i, v in pending:
                counts[i][v] += 1
            if by_stream:
                seen += m
                if seen >= forget:
                    seen -= forget
                    turn += 1
            else:
                for i, _v in pending:
                    steps[i] += 1
                for i, _v in pending:
                    if steps[i] >= forget:
                        steps[i] -= forget
                        counts[i] = [y >> 1 or 1 for y in counts[i]]
            pending.clear()
    flat = np.empty(int(sizes.sum()), np.uint8)
    for a, o in zip(start.tolist(), out, strict=True):
        flat[a : a + len(o)] = np.frombuffer(o, np.uint8)
    return flat


def _stretches(active: np.ndarray):
    """(lanes, steps) of steps with equally many active lanes."""
    edges = np.flatnonzero(np.diff(active, prepend=-1))
    return zip(active[edges].tolist(), np.diff(np.append(edges, len(active))).tolist(), strict=True)
