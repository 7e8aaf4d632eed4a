"""Worked examples, round trips and invariants of the array kernels."""

from dataclasses import replace
from itertools import combinations

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from postings_engine.functions.stem import stem
from postings_engine.operators import arith, codecs, ordering, trits
from postings_engine.operators.codecs import CODECS

MINI = [(12, 16), (2, 7, 8, 10, 11, 13), (2, 3, 4), (11,), (4, 5, 6, 9, 14, 16)]
GAPS = [np.diff([0, *x]) for x in MINI]


def joined(lists, kinds=3):
    gaps, sizes = np.concatenate(lists), np.array([len(x) for x in lists])
    from postings_engine.operators.coders import symbols

    return symbols(gaps, sizes, kinds)


def cases():
    rng = np.random.default_rng(42)
    out = [([1], 1), ([5], 5), ([1] * 20, 20), ([1, 4], 5), ([1] * 200, 200), ([2] * 128, 256), ([2] * 129, 300), ([2**31], 2**31)]
    for d in (64, 1000, 10**6):
        for p in (0.0002, 0.001, 0.01, 0.03, 0.1, 0.2, 0.9):
            ids = np.sort(rng.choice(d, max(1, min(1500, int(d * p))), False)) + 1
            out.append((np.diff(np.concatenate([[0], ids])).tolist(), d))
    return out


@pytest.mark.parametrize(
    ("name", "bits"),
    [("gamma", [12, 16, 5, 7, 18]), ("delta", [13, 19, 6, 8, 20]), ("vbyte", [16, 48, 24, 8, 48]), ("nibble", [12, 24, 12, 8, 24]), ("unary", [16, 13, 4, 11, 16]), ("elias_fano", [10, 20, 13, 6, 20]), ("midpoint", [8, 13, 9, 4, 15])],
)
def test_worked_sizes(name, bits):
    assert [CODECS[name].bits(g, 16) for g in GAPS] == bits


def test_worked_trits():
    assert ["".join(map(str, trits.trits_of(g)[0])) for g in GAPS] == ["1002002", "02012202202", "0222", "0112", "002221201202"]
    assert "".join(map(str, trits.trits_of(np.array([19]))[0])) == "00112"
    s, _ = joined(GAPS)
    assert len(s) == 38 and np.bincount(s).tolist() == [14, 6, 18]
    assert round(trits.ideal_bits(np.bincount(s)[None]), 3) == 55.550


def test_worked_contexts():
    s, pos = joined(GAPS)
    c = trits.hybrid(1, 2, 1)
    n = trits.counts(c.ids(s, pos), s, c.size)
    assert n.tolist() == [[4, 1, 0], [3, 2, 3], [1, 0, 1], [0, 0, 2], [2, 0, 2], [1, 2, 4], [3, 0, 3], [0, 0, 3], [0, 1, 0]]
    assert round(trits.ideal_bits(n), 3) == 37.751
    assert round(trits.ideal_bits(n, trits.quantise(n, 8)), 3) == 37.752
    free = trits.adaptive_bits(c.ids(s, pos), s, c.size, forget=None)
    assert round(free, 3) == 59.918 == round(trits.order_free_bits(n), 3)
    assert c.model_bits(8) == 144
    past = [0, 2, 0, 2, 2, 0, 2, 1]
    t = arith.Tracker(trits.hybrid(3, 5))
    for x in past:
        t.push(x)
    assert t() == 1 + 3 * 8 + 0b010  # not, terminator, not; three terminators in the window before


def test_worked_parameters():
    assert trits.quantise(np.array([[86, 531, 383]]), 16).tolist() == [[5636, 34799, 25100]]
    sizes = (705989, 6169953, 42253227, 119802501, 5979715441, 15641166521)
    assert [trits.choose_static(i)[0] for i in sizes] == [6, 9, 11, 13, 18, 19]
    assert [trits.choose_adaptive(i)[0] for i in sizes] == [7, 7, 8, 9, 11, 12]
    assert trits.hybrid(3, 5, 2).general == 48 and trits.hybrid(3, 5, 2).model_bits(8) == 880
    assert 518412 * 284982 == 147738088584


@pytest.mark.parametrize("name", sorted(CODECS))
def test_round_trip(name):
    c = CODECS[name]
    for g, u in cases():
        if name == "unary" and u > 10**6:
            continue
        data = c.encode(g, u)
        assert c.decode(data, len(g), u).tolist() == list(g)
        assert -(-c.bits(np.array(g), u) // 8) == len(data)


@pytest.mark.parametrize("name", sorted(CODECS))
@settings(max_examples=15, deadline=None)
@given(st.lists(st.integers(1, 5000), min_size=1, max_size=300))
def test_round_trip_any(name, gaps):
    u = sum(gaps) + 3
    c = CODECS[name]
    assert c.decode(c.encode(gaps, u), len(gaps), u).tolist() == gaps


def test_malformed_lists_raise():
    for g in ([0, 1], [3, -1], [2, 0]):
        with pytest.raises(ValueError):
            CODECS["gamma"].bits(np.array(g), 100)
        with pytest.raises(ValueError):
            trits.trits_of(np.array(g))
    with pytest.raises(ValueError):
        CODECS["midpoint"].bits(np.array([5, 5]), 9)


CONTEXTS = [trits.none(), trits.full(2), trits.full_count(2, 3), trits.hybrid(2, 3, 1), trits.boxes(2, (2, 3), 1), trits.hybrid(7, 7, 8), trits.covering(2, 1000, 1)]


@pytest.mark.parametrize("kinds", [3, 4])
@pytest.mark.parametrize("ctx", CONTEXTS, ids=str)
def test_coders(ctx, kinds):
    ctx = replace(ctx, kinds=kinds)
    lists = [np.array(g) for g, _ in cases() if len(g) < 400]
    s, pos = joined(lists, kinds)
    ids = ctx.ids(s, pos)
    n = trits.counts(ids, s, ctx.size, kinds)
    lengths = None if kinds == 4 else [len(x) for x in lists]
    q = trits.quantise(n, 10)
    assert (q.sum(1)[n.sum(1) > 0] == 1023).all() and ((q > 0) | (n == 0)).all()
    for data, ideal, how in ((arith.encode_static(ids, s, q), trits.ideal_bits(n, q), (q, None)), (arith.encode_adaptive(ids, s, ctx.size, kinds, 256), trits.adaptive_bits(ids, s, ctx.size, kinds, 256), (None, 256))):
        back = arith.decode_lists(data, lengths, len(lists), ctx, *how)
        assert all((a == b).all() for a, b in zip(back, lists, strict=True))
        assert -8 <= 8 * len(data) - ideal <= 32 + 0.001 * ideal
    track = arith.Tracker(ctx)
    want = []
    for x, p in zip(s.tolist(), pos.tolist(), strict=True):
        if p == 0:
            track.clear()
        want.append(track())
        track.push(x)
    assert want == ids.tolist()


def test_finer_contexts_never_lose():
    s, pos = joined([np.array(g) for g, _ in cases()])
    size = lambda c: trits.ideal_bits(trits.counts(c.ids(s, pos), s, c.size))
    assert size(trits.Context(4, (5,), 0, False, False)) <= size(trits.Context(4, (5,), 0, True, True)) + 1e-6
    assert size(trits.boxes(4, (2, 3))) <= size(trits.hybrid(4, 5)) + 1e-6
    assert size(trits.hybrid(4, 5)) <= size(trits.none()) + 1e-6


def test_forgetting_keeps_counts_below_twice_the_period():
    m = arith.Counts(1, 3, 16)
    for i in range(1000):
        m.add(0, i * i % 3)
        assert sum(m.c[0]) < 3 * 32 and max(m.c[0]) < 32


def test_partition_is_optimal():
    rng = np.random.default_rng(1)
    for _ in range(20):
        g = rng.integers(1, 200, rng.integers(1, 10))
        ids, n = np.concatenate([[0], np.cumsum(g)]), len(g)
        best = min(sum(codecs.part_bits(b - a, int(ids[b] - ids[a]), 16) for a, b in zip((0, *c), (*c, n), strict=True)) for k in range(n) for c in combinations(range(1, n), k))
        assert codecs.partitioned_ef_bits(g, "opt", fixed=16) == best <= codecs.partitioned_ef_bits(g, fixed=16)


def test_bitmap_contexts_of_many_rows_at_once():
    """Shards with what goes before them, in chunks of rows of any size, each against its row of the matrix."""
    from postings_engine.operators.baselines import bitmap_context_counts

    rng = np.random.default_rng(6)
    k, w, d = 3, 4, 300
    gaps = [rng.geometric(p, n) for p, n in zip(rng.choice([0.9, 0.3, 0.1], 30), rng.integers(1, 9, 30), strict=True)]
    carry = [rng.geometric(0.3, rng.integers(7, 9)).tolist() if i % 3 else [] for i in range(30)]
    before, last = np.array([sum(c) for c in carry]), rng.random(30) < 0.7
    want = np.zeros((2**k * (w + 1), 2), int)
    for g, c, ended in zip(gaps, carry, last, strict=True):
        ids = set(np.cumsum([*c, *g]).tolist())
        bits = [0] * (k + w) + [int(i + 1 in ids) for i in range(d if ended else max(ids))]
        for i in range(k + w + sum(c), len(bits)):
            code = sum(bits[i - j] << j - 1 for j in range(1, k + 1))
            want[code + 2**k * sum(bits[i - k - w : i - k]), bits[i]] += 1
    for cells in (1, 200, 1 << 21):
        got = bitmap_context_counts(np.concatenate(gaps), np.array([len(g) for g in gaps]), d, k, w, before, carry, last, cells=cells)
        assert got.tolist() == want.tolist()


def test_blocks():
    g = np.diff([0, *sorted(np.random.default_rng(3).choice(5000, 300, False) + 1)])
    plain, trimmed = codecs.blocked_midpoint(g, 5000, skip="plain"), codecs.blocked_midpoint(g, 5000, skip="trimmed")
    assert plain["payload"] == trimmed["payload"] and plain["directory"] > trimmed["directory"]
    assert sum(codecs.blocked_midpoint(g, 5000).values()) <= sum(codecs.blocked_midpoint(g, 5000, pad=True).values())


def test_lzma_sizes_of_short_lists(monkeypatch):
    import lzma

    rng = np.random.default_rng(8)
    data = [bytes(rng.integers(0, top, n).astype(np.uint8)) for n in range(1, 60) for top in (1, 2, 3, 256)]
    want = [len(lzma.compress(x)) for x in data]
    plain, small = lzma.compress, []
    monkeypatch.setattr(lzma, "compress", lambda x, **how: small.append("filters" in how) or plain(x, **how))
    assert [codecs.lzma_size(x) for x in data] == want
    assert sum(small) == 4 * codecs.SHORT_LZMA


def test_longest_span_of_a_part():
    n = np.array([1, 2, 3, 7, 39])
    cost = [[codecs.part_bits(m, span, 0) for span in range(m, 900)] for m in n.tolist()]
    for room in range(300):
        want = [max(m + i for i, c in enumerate(own) if c <= room) for m, own in zip(n.tolist(), cost, strict=True)]
        assert np.minimum(codecs._longest_span(n, np.full(5, room)), 899).tolist() == want


def test_short_lists_are_one_part(monkeypatch):
    seen = []
    plain = codecs._approximate
    monkeypatch.setattr(codecs, "_approximate", lambda ids, *more: seen.append(len(ids)) or plain(ids, *more))
    rng = np.random.default_rng(5)
    sizes = np.array([*rng.integers(1, 12, 300), 400, 0, 500])
    lists = [rng.geometric(rng.choice([0.5, 0.02, 0.001]), n) for n in sizes]
    for fixed in (64, 96):
        assert codecs.partition_sizes(np.concatenate(lists), sizes, fixed=fixed).tolist() == [codecs.partitions(g, fixed=fixed)[0] for g in lists]
        monkeypatch.setattr(codecs, "SPANS", 0)
    assert sum(seen) <= 4  # the two long ones, twice


def test_bitmap_contexts_by_brute_force():
    from postings_engine.operators.baselines import bitmap_context_counts

    k, w, d = 2, 3, 16
    want = np.zeros((4 * 4, 2), int)
    for ids in MINI:
        bits = [0] * (k + w) + [int(i + 1 in ids) for i in range(d)]
        for i in range(k + w, len(bits)):
            code = sum(bits[i - j] << j - 1 for j in range(1, k + 1))
            want[code + 4 * sum(bits[i - k - w : i - k]), bits[i]] += 1
    got = bitmap_context_counts(np.concatenate(GAPS), np.array([len(g) for g in GAPS]), d, k, w)
    assert got.tolist() == want.tolist() and got.sum() == 80


def test_bisection_groups_topics():
    rng = np.random.default_rng(0)
    topic = rng.permutation(np.repeat([0, 1], 64))
    docs, terms = zip(*((d, t * 100 + w) for d, t in enumerate(topic) for w in rng.choice(100, 20, False)), strict=True)
    order = ordering.bisect_block(np.array(docs), np.array(terms), 128)
    assert sorted(order) == list(range(128))
    assert abs(topic[order][:64].sum() - 32) > 28


def test_stems():
    pairs = {"caresses": "caress", "flies": "fli", "agreed": "agre", "hopping": "hop", "relational": "relat", "conditional": "condit", "running": "run", "national": "nation", "cats": "cat", "the": "the", "generously": "generous", "sky": "sky", "happiness": "happi", "adjustment": "adjust"}
    assert {w: stem(w) for w in pairs} == pairs


def test_sparse_counts_equal_the_table():
    rng = np.random.default_rng(3)
    for n in (0, 1, 700):
        ids, s = rng.integers(0, 50, n).astype(np.int32), rng.integers(0, 3, n).astype(np.uint8)
        used, got = trits.sparse_counts(ids, s)
        whole = trits.counts(ids, s, 50)
        assert used.tolist() == np.flatnonzero(whole.any(1)).tolist() and np.array_equal(got, whole[used])


def test_adaptive_bits_of_wide_models_with_halving():
    """More than 16 bits of contexts, against counts kept one by one."""
    rng = np.random.default_rng(4)
    size = 1 << 18
    ids, s = rng.choice([5, 70_000, size - 1], 900), rng.integers(0, 3, 900)
    counts, steps, bits = {}, {}, 0.0
    for i, x in zip(ids.tolist(), s.tolist(), strict=True):
        c = counts.setdefault(i, [1, 1, 1])
        bits += np.log2(sum(c) / c[x])
        c[x] += 1
        steps[i] = steps.get(i, 0) + 1
        if steps[i] % 16 == 0:
            counts[i] = [max(1, v >> 1) for v in c]
    assert abs(trits.adaptive_bits(ids, s.astype(np.uint8), size, 3, 16) - bits) < 1e-6
    with pytest.raises(ValueError):
        trits.adaptive_bits(ids, s, size, 3, 16, prior=(0, 1, 1))


@pytest.mark.parametrize("name", ["midpoint", "midpoint_:center+leaf_ends:pow2", "midpoint_block", "midpoint_block:pad", "midpoint_block:plain", "midpoint_block:trimmed", "pef_approx", "pef_skip", "pef_opt"])
def test_sizes_of_many_lists_at_once(name):
    rng = np.random.default_rng(11)
    sizes = np.concatenate([rng.integers(1, 9, 40), rng.integers(100, 300, 5)])
    rng.shuffle(sizes)
    lists = [np.where(rng.random(n) < 0.5, 1, rng.geometric(p, n)).astype(np.int64) for n, p in zip(sizes, rng.choice([0.9, 0.1, 0.001], len(sizes)), strict=True)]
    u = np.array([g.sum() for g in lists]) + rng.integers(0, 40, len(lists))
    assert name in codecs.MANY
    got = codecs.sizes_of(name, np.concatenate(lists), sizes, u)
    assert got.tolist() == [codecs.CODECS[name].bits(g, x) for g, x in zip(lists, u, strict=True)]
    assert (-(-got // 8)).tolist() == [len(codecs.CODECS[name].encode(g, x)) for g, x in zip(lists, u, strict=True)]
    if name.startswith("pef"):
        assert codecs.partition_sizes(np.concatenate(lists), sizes, "opt" if name == "pef_opt" else "approx", fixed=96 if name == "pef_skip" else 64, cells=500).tolist() == got.tolist()
    with pytest.raises(ValueError):
        codecs.sizes_of(name, np.array([3, 3]), np.array([2]), np.array([5]))


def test_bisection_against_a_plain_program():
    def plain(docs, words, rounds, least):
        if len(docs) <= least:
            return docs
        side = {x: int(i >= len(docs) // 2) for i, x in enumerate(docs)}
        s = (len(docs) // 2, len(docs) - len(docs) // 2)
        cost = lambda d, s: d * np.log2(s / (d + 1.0))
        fixed = lambda x: int(np.rint(x * (1 << ordering.FRACTION)))
        for _ in range(rounds):
            degree = [{}, {}]
            for x in docs:
                for t in words[x]:
                    degree[side[x]][t] = degree[side[x]].get(t, 0) + 1
            gain = {}
            for x in docs:
                a, b = side[x], 1 - side[x]
                gain[x] = sum(fixed(cost(degree[a][t], s[a]) - cost(degree[a][t] - 1, s[a])) - fixed(cost(degree[b].get(t, 0) + 1, s[b]) - cost(degree[b].get(t, 0), s[b])) for t in words[x])
            left, right = (sorted((x for x in docs if side[x] == h), key=lambda x: -gain[x]) for h in (0, 1))
            swap = [(x, y) for x, y in zip(left, right, strict=False) if gain[x] + gain[y] > 0]
            if not swap:
                break
            for x, y in swap:
                side[x], side[y] = 1, 0
        return [y for h in (0, 1) for y in plain([x for x in docs if side[x] == h], words, rounds, least)]

    rng = np.random.default_rng(5)
    for n in (1, 9, 37, 100):
        words = [sorted({int(x) for x in rng.zipf(1.5, 12) % 60} | ({1000 + i} if i % 3 else set())) if i % 7 else [] for i in range(n)]
        pairs = np.array([(i, t) for i, own in enumerate(words) for t in own if sum(t in x for x in words) > 1] or np.empty((0, 2)), np.int64)
        known = [[t for i, t in pairs.tolist() if i == x] for x in range(n)]
        for rounds in (1, 6, 20):
            want = plain(list(range(n)), known, rounds, 8)
            assert ordering.bisect_block(pairs[:, 0], pairs[:, 1], n, rounds).tolist() == want
            mixed = pairs[rng.permutation(len(pairs))]  # gains are whole numbers: the order of words is nothing to them
            assert ordering.bisect_block(mixed[:, 0], mixed[:, 1], n, rounds).tolist() == want


@pytest.mark.parametrize("lanes_", [1, 4, 20])
@pytest.mark.parametrize("how", [{}, {"forget": 64}, {"forget": 50, "clock": "global"}, {"prior": (2, 2, 1, 3), "forget": 64}])
def test_few_lanes_take_no_array_steps(lanes_, how, monkeypatch):
    """Symbols go one by one there, and the bytes stay those of the way by arrays."""
    from postings_engine.operators import coders, lanes

    rng = np.random.default_rng(3)
    sizes = np.sort(rng.integers(1, 60, 80))
    gaps = rng.geometric(np.repeat(sizes / 100, sizes)).astype(np.int64)
    for ctx in (trits.hybrid(3, 4, 2), trits.none(), trits.boxes(2, (2, 3), 1), replace(trits.hybrid(2, 3, 1), kinds=4), trits.hybrid(9, 10, 3)):
        s, pos = coders.symbols(gaps, sizes, ctx.kinds)
        ids, per = ctx.ids(s, pos), np.bincount(np.cumsum(pos == 0) - 1)
        args = {"forget": None} | how | ({"prior": how["prior"][: ctx.kinds]} if "prior" in how else {})
        model = lanes.Shared(ctx.size, ctx.kinds, args["forget"], args.get("prior"), args.get("clock", "context"))
        by, start, active = lanes._grid(np.diff(np.concatenate([[0], np.cumsum(per)])[lanes.deal(per, lanes_)]))
        lo, f = np.empty(len(s), np.int64), np.empty(len(s), np.int64)
        for t, m in enumerate(active.tolist()):  # the plain way, a step of all lanes at a time
            at = start[:m] + t
            b, v = model.bounds(ids[at]), s[at].astype(int)
            lo[at], f[at] = b[np.arange(m), v], b[np.arange(m), v + 1] - b[np.arange(m), v]
            model.add(ids[at], v)
        state, words = lanes._states(lo, f, start, None, active)
        with monkeypatch.context() as less:
            less.setattr(lanes, "Shared", None)
            out, _ = lanes.encode(ids, s, per, ctx, None, lanes_, **args)
            assert out.endswith(words.tobytes())
            back, n = lanes.decode(out, None if ctx.kinds == 4 else sizes.tolist(), len(sizes), ctx, None, **args)
        assert back.tolist() == gaps.tolist() and n.tolist() == sizes.tolist()


@pytest.mark.parametrize("name", ["delta", "midpoint"])
def test_many_lists_as_bytes_at_once(name, monkeypatch):
    """The bytes of each list are those that it has alone, and the lists come back, some at a time too."""
    rng = np.random.default_rng(4)
    lists = [rng.geometric(p, n) for p in (0.9, 0.3, 0.01, 1e-6) for n in (1, 2, 3, 17, 500)] + [np.ones(40, int), np.array([2**31 - 2]), np.array([1, 2**30, 5])]
    sizes = np.array([len(x) for x in lists])
    u = np.array([min(int(x.sum()) + extra, 2**31 - 1) for x, extra in zip(lists, [0, 1, 7, 1000] * 6, strict=False)])
    gaps = np.concatenate(lists).astype(np.int64)
    want = [CODECS[name].encode(x, v) for x, v in zip(lists, u, strict=True)]
    plain = codecs.Codec.encode, codecs.Codec.decode
    monkeypatch.setattr(codecs.Codec, "encode", None)  # no list goes by itself
    monkeypatch.setattr(codecs.Codec, "decode", None)
    assert codecs.bytes_of(name, gaps, sizes, u) == want
    for bits in (1 << 20, 300):
        monkeypatch.setattr(codecs, "CHUNK_BITS", bits)
        assert codecs.lists_from(name, want, sizes, u).tolist() == gaps.tolist()
    monkeypatch.setattr(codecs.Codec, "encode", plain[0])
    monkeypatch.setattr(codecs.Codec, "decode", plain[1])
    wide = np.array([1 << 40, 3]), np.array([2]), np.array([1 << 41])
    assert codecs.lists_from(name, codecs.bytes_of(name, *wide), *wide[1:]).tolist() == wide[0].tolist()  # by the plain way
    none = np.empty(0, np.int64)
    assert codecs.bytes_of(name, none, none, none) == [] and codecs.lists_from(name, [], none, none).tolist() == []


def test_lists_of_unlike_length_go_through_the_approximate_partition_together(monkeypatch):
    rng = np.random.default_rng(4)
    lists = [rng.geometric(1 / m, n) for n, m in ((900, 3), (400, 40), (190, 2), (90, 300), (45, 9000))]
    lists = [np.concatenate([x, x * 50]) for x in lists]
    sizes, calls, plain = np.array([len(x) for x in lists]), [], codecs._approximate
    monkeypatch.setattr(codecs, "_approximate", lambda n, *more: calls.append(len(n)) or plain(n, *more))
    got = codecs.partition_sizes(np.concatenate(lists), sizes).tolist()
    assert got == [codecs.partitions(x)[0] for x in lists] and calls == [5]
    monkeypatch.setattr(codecs, "SPANS", 0)  # no table of spans
    assert codecs.partition_sizes(np.concatenate(lists), sizes).tolist() == got
