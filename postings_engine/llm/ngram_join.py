"""N-gram Jaccard self-join by prefix trees, and what near-duplicate removal makes of it.

Plan. (1) One pass over the texts turns each into its set of n-gram hashes, and that into a 128-bit fingerprint and
block signatures: the hash range is cut into K parts, K greater than the greatest possible symmetric difference of two
linked sets, so that linked sets agree on a whole part (pigeonhole) and no link is lost; no counts of the corpus are
needed. (2) Sets with an equal signature are compared by small count sketches, which bound their difference from below
exactly; what these leave open makes coarse groups, of which only spanning links are kept. (3) Each group's sets, globally ordered, go into one radix tree; a set traverses
it sharing the overlap of common beginnings, and subtrees are pruned by what can still come. (4) Groups too large for a
task are first compared with one member each, in a join that Spark can split; the triangle inequality of the Jaccard
distance tells which members need no further comparison. Equal sets are one node throughout.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BitFilter, cut, keyed, mix64, small_batches, typed
from .components import connected

#: Most n-grams (all members' sets together) that one task puts into a tree: 48 MB of hashes.
GROUP_GRAMS = 6_000_000
#: Rounds of comparing large groups with one member, before what is left is compared in pairs of blocks.
LEADER_ROUNDS = 3
#: Sets with one signature up to which they are compared by their sketches; more become one coarse group.
BIG_GROUP = 2048
#: The global order of n-grams goes by counts over so many ranges of hashes: 512 kB for every task, whatever the data.
ORDER_BITS = 16
#: Words whose hashes a worker remembers.
CACHE_WORDS = 250_000
_STEP = 0x9E3779B97F4A7C15
_words: dict[bytes, int] = {}


def gram_hashes(raw: bytes | None, n: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the n-grams of a UTF-8 text's words, A-Z lower-cased."""
    words = raw.lower().split() if raw else []  # bytes.split: space and U+0009 to U+000D
    if not words:
        return np.empty(0, np.uint64)
    known = _words
    if len(known) > CACHE_WORDS:
        known.clear()
    try:
        w = np.array([known[x] for x in words], np.uint64)
    except KeyError:
        for x in words:
            if x not in known:
                known[x] = xxhash.xxh3_64_intdigest(x)
        w = np.array([known[x] for x in words], np.uint64)
    width = min(n, len(w))
    step, total = 1, np.zeros(len(w) - width + 1, np.uint64)
    for j in range(width):
        step = step * _STEP & (2**64 - 1)
        total += w[j : len(w) - width + 1 + j] * np.uint64(step)
    return np.unique(mix64(total + np.uint64(width)))


class Signatures:
    """Block signatures of sets for Jaccard similarity >= pct %.

    A set of n leaves a linked one, if that is no smaller, a symmetric difference of at most spread(n). The smaller set of
    a pair fixes the level, a number of parts greater than that; of these the first spread + 1, and an eighth in reserve
    for empty parts, suffice. A set therefore signs its own level and those of the smaller sets that it may be linked with.
    Where a level has more empty parts than the reserve, which levels this close together keep rare, single grams stand in
    for it, for sets of that level only.
    """

    def __init__(self, pct: int):
        if not 50 <= pct <= 100:
            raise ValueError("pct must lie between 50 and 100")
        self.pct = pct
        self.levels = [2]
        self.known: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def spread(self, n: int) -> int:
        return n * (100 - self.pct) // self.pct

    @staticmethod
    def need(d: int) -> int:
        return d + 1 + -(-d // 8)

    def level(self, d: int) -> int:
        while self.levels[-1] < self.need(d):
            self.levels.append(max(self.levels[-1] + 1, self.levels[-1] * 13 // 10))
        return int(np.searchsorted(self.levels, self.need(d)))

    def reserve(self, level: int) -> int:
        """So many empty parts a set of this level may have before the part that agrees may be an empty one."""
        if not level:
            return 1
        d = (self.levels[level - 1] - 1) * 8 // 9 - 2  # up to the least spread of the level
        while self.need(d) <= self.levels[level - 1]:
            d += 1
        return 1 + -(-d // 8)

    def parts(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        if k not in self.known:
            self.known[k] = np.array([-(-i * 2**64 // k) for i in range(1, k)], np.uint64), mix64(np.arange(k, dtype=np.uint64) + np.uint64(k * 2**32))
        return self.known[k]

    def __call__(self, grams: np.ndarray) -> np.ndarray:
        n = len(grams)
        d = self.spread(n)
        if n * 100 // self.pct == n and d == 0:
            return np.empty(0, np.uint64)  # only equal sets link with it
        out = []
        sums = np.concatenate([[np.uint64(0)], np.cumsum(mix64(grams + np.uint64(_STEP)), dtype=np.uint64)])
        top = self.level(d)
        for level in range(self.level(self.spread(-(-n * self.pct // 100))), top + 1):
            k = self.levels[level]
            m = self.need(d) if level == top else k
            inner, salt = self.parts(k)
            at = np.concatenate([[0], np.searchsorted(grams, inner), [n]])[: m + 1]
            full = np.diff(at) > 0
            out.append(mix64((sums[at[1:]] - sums[at[:-1]])[full] ^ salt[:m][full]))
            if m - int(full.sum()) >= self.reserve(level):  # the first grams in hash order, of which linked sets share one
                out.append(mix64(grams[: n - -(-n * self.pct // 100) + 1] ^ ~salt[0]))
        return np.concatenate(out)


def sketch(grams: np.ndarray) -> bytes:
    """How many of a set's hashes fall into each of M ranges, at most 255: two sets differ in at least as many elements as
    these numbers differ. M is a power of two that grows with the set, so that ranges hold 4 to 8 elements."""
    bits = max(6, (len(grams) // 8).bit_length())
    return np.minimum(np.bincount((grams >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits), 255).astype(np.uint8).tobytes()


def unfolded(sketches: list[bytes]) -> np.ndarray:
    """Sketches as rows of one width, the least of theirs: neighbouring ranges are added up."""
    width = min(map(len, sketches))
    if all(len(x) == width for x in sketches):
        return np.frombuffer(b"".join(sketches), np.uint8).reshape(-1, width).astype(np.int16)
    return np.stack([np.frombuffer(x, np.uint8).reshape(width, -1).sum(1, dtype=np.int16) for x in sketches])


def may_link(n: np.ndarray, m: np.ndarray, apart: np.ndarray, pct: int) -> np.ndarray:
    """Whether sets of n and m elements that differ in at least ``apart`` may still be linked."""
    both = (n + m - apart) // 2
    return 100 * both >= pct * (n + m - both)


def fingerprints(df: DataFrame, n: int, id_col: str, text_col: str) -> DataFrame:
    """(id, n, a, b, sketch): a and b are the halves of the set's fingerprint."""
    small_batches(df.sparkSession)
    data = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").cast("binary").alias("x"))

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            sets = [gram_hashes(raw, n) for raw in batch.column(1).to_pylist()]
            ab = np.frombuffer(b"".join([xxhash.xxh3_128_digest(g.tobytes()) for g in sets]), np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(g) for g in sets], pa.int64()), pa.array(ab[:, 0].copy()), pa.array(ab[:, 1].copy()), pa.array([sketch(g) for g in sets], pa.binary())], names=["id", "n", "a", "b", "sketch"])

    kind = typed(df, id_col).simpleString()
    return data.mapInArrow(run, f"id {kind}, n bigint, a bigint, b bigint, sketch binary")


def signed(df: DataFrame, n: int, pct: int, text_col: str) -> DataFrame:
    """(s, a): the signatures of each text's set. They go straight from the texts into the shuffle; a task sends those of
    equal sets once."""
    data = df.select(F.col(text_col).cast("string").cast("binary").alias("x")).where("x is not null")

    def run(batches: Iterator[pa.RecordBatch]):
        make, seen = Signatures(pct), set()
        for batch in batches:
            sigs, own = [], []
            for raw in batch.column(0).to_pylist():
                g = gram_hashes(raw, n)
                a = int.from_bytes(xxhash.xxh3_128_digest(g.tobytes())[:8], "little", signed=True)
                if not len(g) or a in seen:
                    continue
                if len(seen) >= 1_000_000:
                    seen.clear()
                seen.add(a)
                found = make(g)
                sigs.append(found)
                own.append(np.full(len(found), a, np.int64))
            if sigs:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(sigs).view(np.int64)), pa.array(np.concatenate(own))], names=["s", "a"])

    return data.mapInArrow(run, "s bigint, a bigint")


def shared(rows: DataFrame) -> DataFrame:
    """(s, a, centre) of the (s, a) whose signature several sets have. In groups of more than BIG_GROUP sets ``centre`` is the
    first set of the group, else null. Other groups are named by a hash of their sets, so that groups with the same sets, as
    near copies have by the hundred, become one; a task gives them once, repeats from other tasks remain."""
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    seen: set[int] = set()

    def out(s, a):
        """Of whole runs of equal s, without repeated rows."""
        start = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]]))
        size = np.diff(np.append(start, len(s)))
        name = np.add.reduceat(mix64(a.view(np.uint64)), start).view(np.int64)
        once = np.zeros(len(name), bool)
        once[np.unique(name, return_index=True)[1]] = True
        once &= (size > 1) & np.array([x not in seen for x in name.tolist()])
        if len(seen) > 1_000_000:
            seen.clear()
        seen.update(name[once].tolist())
        keep, small = np.repeat(once | (size > BIG_GROUP), size), np.repeat(size <= BIG_GROUP, size)
        return np.repeat(name, size)[keep], a[keep], np.repeat(a[start], size)[keep], small[keep]

    def run(batches):
        seen.clear()
        held_s = held_a = np.empty(0, np.int64)
        centre = None  # (signature, first set) of a big group that goes on
        for batch in batches:
            s = np.concatenate([held_s, batch.column(0).to_numpy(zero_copy_only=False)])
            a = np.concatenate([held_a, batch.column(1).to_numpy(zero_copy_only=False)])
            if not len(s):
                continue
            fresh = np.ones(len(s), bool)
            fresh[1:] = (s[1:] != s[:-1]) | (a[1:] != a[:-1])
            s, a = s[fresh], a[fresh]
            found = []
            if centre and s[0] == centre[0]:
                m = int(np.searchsorted(s, centre[0], "right"))
                found.append((s[:m], a[:m], np.full(m, centre[1]), np.zeros(m, bool)))
                s, a = s[m:], a[m:]
            held_s = held_a = np.empty(0, np.int64)
            if len(s):
                last = int(np.searchsorted(s, s[-1]))  # the last run may go on
                if len(s) - last > BIG_GROUP:
                    centre = (s[-1], a[last])
                    found.append(out(s, a))
                else:
                    centre = None
                    held_s, held_a = s[last:], a[last:]
                    if last:
                        found.append(out(s[:last], a[:last]))
            for x in found:
                if len(x[0]):
                    yield pa.RecordBatch.from_arrays([pa.array(x[0]), pa.array(x[1]), pa.array(x[2], mask=x[3])], names=["s", "a", "centre"])
        if len(held_s):
            x = out(held_s, held_a)
            yield pa.RecordBatch.from_arrays([pa.array(x[0]), pa.array(x[1]), pa.array(x[2], mask=x[3])], names=["s", "a", "centre"])

    # a signature is a hash of a part's grams, or of one gram where too many parts are empty: its rows are candidates
    return rows.repartition(parts, "s").sortWithinPartitions("s", "a").mapInArrow(run, "s bigint, a bigint, centre bigint")


def coarse_links(df: DataFrame, classes: DataFrame, n: int, pct: int, text_col: str) -> DataFrame:
    """(u, v) of nodes whose components hold all links: in each group of equal signatures a spanning forest of the pairs that
    their sketches don't rule out; in big groups a star of all their sets."""
    rows = cut(shared(signed(df, n, pct, text_col)))
    ids = classes.select("a", "node")
    star = rows.where("centre is not null").select("a", "centre").distinct()
    star = star.join(ids.withColumnRenamed("node", "u"), "a").join(ids.withColumnsRenamed({"a": "centre", "node": "v"}), "centre").select("u", "v")
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    small = rows.where("centre is null").select("s", "a").distinct().join(classes.select("a", "node", "n", "sketch"), "a").select("s", "node", "n", "sketch").repartition(parts, "s").sortWithinPartitions("s", "node")

    def links(node, size, marks):
        root = np.arange(len(node))
        for i in range(1, len(node)):
            near = np.flatnonzero(may_link(size[:i], size[i], np.abs(marks[:i] - marks[i]).sum(1, dtype=np.int64), pct))
            roots = np.unique(root[near])
            if len(roots):
                root[np.isin(root, roots)] = roots[0]
                root[i] = roots[0]
        hit = np.flatnonzero(root != np.arange(len(node)))
        return node[hit], node[root[hit]]

    def run(batches):
        held = None
        for b in batches:
            marks = np.empty(b.num_rows, object)
            marks[:] = b.column(3).to_pylist()
            own = [b.column(i).to_numpy(zero_copy_only=False) for i in range(3)] + [marks]
            held = own if held is None else [np.concatenate(x) for x in zip(held, own, strict=True)]
            last = int(np.searchsorted(held[0], held[0][-1])) if len(held[0]) else 0
            yield from compared(*(x[:last] for x in held))
            held = [x[last:] for x in held]
        if held is not None:
            yield from compared(*held)

    def compared(s, node, size, marks):
        if not len(s):
            return
        start = np.append(np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1]])), len(s))
        two = start[:-1][np.diff(start) == 2]
        width = np.array([min(len(marks[i]), len(marks[i + 1])) for i in two.tolist()], np.int64)
        u, v = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        for w in np.unique(width):
            at = two[width == w]
            x, y = (unfolded([*marks[at + k], bytes(int(w))])[:-1] for k in (0, 1))
            ok = may_link(size[at], size[at + 1], np.abs(x - y).sum(1, dtype=np.int64), pct)
            u.append(node[at[ok] + 1])
            v.append(node[at[ok]])
        for x, y in zip(start[:-1], start[1:], strict=True):
            if y - x > 2:
                p, q = links(node[x:y], size[x:y], unfolded(list(marks[x:y])))
                u.append(p)
                v.append(q)
        e = np.unique(np.stack([np.concatenate(u), np.concatenate(v)], 1), axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(e[:, 0].copy()), pa.array(e[:, 1].copy())], names=["u", "v"])

    return star.unionByName(small.mapInArrow(run, "u bigint, v bigint"))


class Tree:
    """A radix tree of sets given as ascending ranks in one global order."""

    __slots__ = ("ends", "greatest", "kids", "least", "seg")

    def __init__(self, seg: np.ndarray):
        self.seg, self.kids, self.ends = seg, {}, []
        self.least, self.greatest = 1 << 60, 0

    def add(self, ranks: np.ndarray, i: int) -> None:
        node, n = self, len(ranks)
        while True:
            node.least, node.greatest = min(node.least, n), max(node.greatest, n)
            if not len(ranks):
                node.ends.append((i, n))
                return
            kid = node.kids.get(int(ranks[0]))
            if kid is None:
                kid = node.kids[int(ranks[0])] = Tree(ranks)
                kid.least = kid.greatest = n
                kid.ends.append((i, n))
                return
            m = min(len(kid.seg), len(ranks))
            differ = np.flatnonzero(kid.seg[:m] != ranks[:m])
            m = int(differ[0]) if len(differ) else m
            if m < len(kid.seg):  # split: the shared beginning becomes a node of its own
                top = Tree(kid.seg[:m])
                top.least, top.greatest = kid.least, kid.greatest
                kid.seg = kid.seg[m:]
                top.kids[int(kid.seg[0])] = kid
                node.kids[int(ranks[0])] = top
                kid = top
            node, ranks = kid, ranks[m:]

    def linked(self, ranks: np.ndarray, mask: np.ndarray, pct: int) -> Iterator[int]:
        """Members with 100 * overlap >= pct * union; ``mask`` is true at ``ranks``."""
        n = len(ranks)
        stack = [(self, 0, 0)]
        while stack:
            node, overlap, depth = stack.pop()
            for i, m in node.ends:
                if 100 * overlap >= pct * (n + m - overlap):
                    yield i
            for kid in node.kids.values():
                if 100 * kid.greatest < pct * n or 100 * n < pct * kid.least:
                    continue
                got = overlap + int(np.count_nonzero(mask[kid.seg]))
                left = n - int(np.searchsorted(ranks, kid.seg[-1], "right"))
                most = got + min(left, kid.greatest - depth - len(kid.seg))
                if (100 + pct) * most >= pct * (n + kid.least):
                    stack.append((kid, got, depth + len(kid.seg)))


def gram_counts(sets: DataFrame) -> np.ndarray:
    """How often hashes of each of 2**ORDER_BITS ranges occur in all sets (node, grams): with the hash itself for ties, this
    is the one order in which every tree has its grams, frequent ones first. One array of fixed size from each partition."""
    size = 1 << ORDER_BITS

    def run(batches):
        n = np.zeros(size, np.int64)
        for b in batches:
            n += np.bincount((np.frombuffer(b"".join(b.column(0).to_pylist()), np.uint64) >> np.uint64(64 - ORDER_BITS)).astype(np.int64), minlength=size)
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(n[at])], names=["r", "n"])

    out = np.zeros(size, np.int64)
    got = sets.select("grams").mapInArrow(run, "r bigint, n bigint").groupBy("r").agg(F.sum("n").alias("n")).toArrow()
    out[got.column("r").to_numpy()] = got.column("n").to_numpy()
    return out


def tree_links(sets: list[np.ndarray], pct: int, order: np.ndarray) -> list[tuple[int, int]]:
    """A spanning forest of the links among the sets, as (member, root) positions; ``order`` as of :func:`gram_counts`."""
    sizes = [len(s) for s in sets]
    grams, place = np.unique(np.concatenate(sets), return_inverse=True)
    rank = np.empty(len(grams), np.int64)
    rank[np.lexsort((grams, -order[(grams >> np.uint64(64 - ORDER_BITS)).astype(np.int64)]))] = np.arange(len(grams))
    ranks = [np.sort(r) for r in np.split(rank[place.ravel()], np.cumsum(sizes)[:-1])]
    root = list(range(len(sets)))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    tree, mask = Tree(np.empty(0, np.int64)), np.zeros(len(grams), bool)
    marks = unfolded([sketch(x) for x in sets])
    order = sorted(range(len(sets)), key=lambda i: (sizes[i], i))
    marks, by_size = marks[order], np.array(sizes)[order]
    for k, i in enumerate(order):
        first = int(np.searchsorted(by_size, -(-pct * sizes[i] // 100)))  # smaller sets are too small
        near = np.flatnonzero(may_link(by_size[first:k], sizes[i], np.abs(marks[first:k] - marks[k]).sum(1, dtype=np.int64), pct)) + first
        if not any(find(order[j]) != find(i) for j in near.tolist()):
            tree.add(ranks[i], i)  # nothing in the tree that its sketch leaves open and that isn't in its component
            continue
        mask[ranks[i]] = True
        for j in tree.linked(ranks[i], mask, pct):
            a, b = find(i), find(j)
            if a != b:
                root[max(a, b)] = min(a, b)
        mask[ranks[i]] = False
        tree.add(ranks[i], i)
    return [(i, r) for i in range(len(sets)) if (r := find(i)) != i]


def _in_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list[int], list[np.ndarray]]]:
    """Nodes and sets of each run of equal first columns, each node once."""
    key, nodes, sets = None, [], []
    for batch in batches:
        for k, node, raw in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
            if k != key:
                if len(nodes) > 1:
                    yield nodes, sets
                key, nodes, sets, seen = k, [], [], set()
            if node not in seen:
                seen.add(node)
                nodes.append(node)
                sets.append(np.frombuffer(raw, np.uint64))
    if len(nodes) > 1:
        yield nodes, sets


def _trees(rows: DataFrame, pct: int, order: np.ndarray) -> DataFrame:
    """Links (u, v) within each group of (g, node, grams)."""
    shared = rows.sparkSession.sparkContext.broadcast(order)
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(batches):
        for nodes, sets in _in_groups(batches):
            if found := tree_links(sets, pct, shared.value):
                i, j = zip(*found, strict=True)
                yield pa.RecordBatch.from_pydict({"u": pa.array([nodes[x] for x in i], pa.int64()), "v": pa.array([nodes[x] for x in j], pa.int64())})

    return rows.select("g", "node", "grams").repartition(parts, "g").sortWithinPartitions("g").mapInArrow(run, "u bigint, v bigint")


def _needed_sets(df: DataFrame, nodes: DataFrame, count: int, n: int, text_col: str) -> DataFrame:
    """(node, grams BINARY) of the nodes (node, a, b), from a second pass over the texts.

    A bit filter of the wanted fingerprints spares the other texts the shuffle; where it would be too large, none is used
    and the join alone decides. A task sends equal sets once.
    """
    wanted = BitFilter.build(nodes.select("a"), count)
    data = df.select(F.col(text_col).cast("string").cast("binary").alias("x")).where("x is not null")

    def run(batches):
        seen: set[bytes] = set()
        for batch in batches:
            grams = [g for raw in batch.column(0).to_pylist() if len(g := gram_hashes(raw, n))]
            fp = [xxhash.xxh3_128_digest(g.tobytes()) for g in grams]
            ab = np.frombuffer(b"".join(fp), np.int64).reshape(-1, 2)
            ok = wanted.has(ab[:, 0].copy()) if wanted and len(ab) else np.ones(len(ab), bool)
            at = []
            for i in np.flatnonzero(ok):
                if fp[i] not in seen:
                    if len(seen) >= 1_000_000:
                        seen.clear()
                    seen.add(fp[i])
                    at.append(i)
            if at:
                yield pa.RecordBatch.from_arrays([pa.array(ab[at, 0].copy()), pa.array(ab[at, 1].copy()), pa.array([grams[i].tobytes() for i in at], pa.binary())], names=["a", "b", "grams"])

    return data.mapInArrow(run, "a bigint, b bigint, grams binary").join(nodes, ["a", "b"]).select("node", "grams")


def _with_leader(big: DataFrame, sets: DataFrame, pct: int) -> DataFrame:
    """(g, node, n, centre, cn, overlap) for every member of the large groups and its group's centre."""
    centres = big.groupBy("g").agg(F.min("node").alias("centre"))
    led = centres.join(sets.select(F.col("node").alias("centre"), F.col("grams").alias("cgrams")), "centre").dropDuplicates(["g"])
    rows = big.join(sets, "node").join(led, "g").select("g", "node", "n", "centre", "grams", "cgrams")

    def run(batches):
        for b in batches:
            x, y = b.column(4).to_pylist(), b.column(5).to_pylist()
            both = [len(np.intersect1d(np.frombuffer(p, np.uint64), np.frombuffer(q, np.uint64), assume_unique=True)) for p, q in zip(x, y, strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), b.column(3), pa.array([len(q) // 8 for q in y], pa.int64()), pa.array(both, pa.int64())], names=["g", "node", "n", "centre", "cn", "overlap"])

    return rows.mapInArrow(run, "g bigint, node bigint, n bigint, centre bigint, cn bigint, overlap bigint")


def set_links(df: DataFrame, groups: DataFrame, classes: DataFrame, n: int, pct: int, text_col: str) -> DataFrame:
    """Links (u, v) that connect whatever members (g, node) of coarse groups are connected by Jaccard similarity."""
    members = cut(groups.join(classes.select("node", "n", "a", "b"), "node").select("g", "node", "n", "a", "b"))
    total = members.count()
    spark = df.sparkSession
    if not total:
        return spark.createDataFrame([], "u bigint, v bigint")
    sets = cut(_needed_sets(df, members.select("node", "a", "b"), total, n, text_col))
    order = gram_counts(sets)
    rest = members.select("g", "node", "n")
    found = None
    for turn in range(LEADER_ROUNDS + 1):
        weight = rest.groupBy("g").agg(F.sum("n").alias("w"))
        small = rest.join(weight.where(F.col("w") <= GROUP_GRAMS), "g").join(sets, "node")
        large = rest.join(weight.where(F.col("w") > GROUP_GRAMS), "g")
        out = _trees(small, pct, order)
        found = out if found is None else found.unionByName(out)
        large = cut(large)
        if large.isEmpty():
            return found
        if turn == LEADER_ROUNDS:
            break
        seen = cut(_with_leader(large, sets, pct).where("node <> centre").withColumn("union", F.expr("n + cn - overlap")).withColumn("hit", F.expr(f"100 * overlap >= {pct} * union")))
        found = found.unionByName(seen.where("hit").select(F.col("node").alias("u"), F.col("centre").alias("v")))
        far = F.col("union") - F.col("overlap")
        nearest = seen.where("not hit").groupBy("g").agg(F.min(far / F.col("union")).alias("d"))
        # whoever is linked with the centre is settled, unless a member that is not may be within reach
        reach = F.col("d") - (100 - pct) / 100 - 1e-9
        rest = cut(seen.join(nearest, "g").where(~F.col("hit") | (far / F.col("union") >= reach)).select("g", "node", "n").distinct())
    # pairs of blocks: each task holds two of them
    blocks = large.withColumn("k", F.ceil(2 * F.col("w") / GROUP_GRAMS)).withColumn("i", F.pmod(F.xxhash64("node"), "k"))
    pair = F.transform(F.sequence(F.lit(0).cast("long"), F.col("k") - 1), lambda j: F.xxhash64("g", F.least("i", j), F.greatest("i", j)))
    return found.unionByName(_trees(blocks.select(F.explode(pair).alias("g"), "node").join(sets, "node"), pct, order))


def similar_groups(df: DataFrame, n: int = 3, pct: int = 90, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_shingles, component_id) of every row.

    Words are runs of anything but space and U+0009 to U+000D, A-Z lower-cased; a set holds the distinct n-word shingles
    of a whole text, of a text with fewer words the whole sequence. Rows link when 100 * intersection >= pct * union;
    component_id is the smallest id reachable. Texts that are null or without words have an empty set and link with
    nothing. Repeated rows are equal sets; an empty table gives an empty result. Sets are compared by 64-bit hashes.
    """
    docs = cut(fingerprints(df, n, id_col, text_col))
    classes = cut(docs.where("n > 0").groupBy("a", "b").agg(F.min("id").alias("least"), F.max("n").alias("n"), F.first("sketch").alias("sketch")).withColumn("node", F.monotonically_increasing_id()))
    coarse = connected(coarse_links(df, classes, n, pct, text_col)).select("node", F.col("comp").alias("g"))
    comps = cut(connected(set_links(df, coarse, classes, n, pct, text_col)))
    own = classes.select("a", "b", "node", "least").join(comps, "node", "left")
    named = own.where("comp is not null").groupBy("comp").agg(F.min("least").alias("label"))
    labels = own.join(named, "comp", "left").select("a", "b", F.coalesce("label", "least").alias("label"))
    return docs.select("id", "n", "a", "b").join(labels, ["a", "b"], "left").select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("label")).otherwise(F.col("id")).alias("component_id"))


def keep_one(df: DataFrame, n: int = 5, pct: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``df`` less near copies: one row of each component stays, with all its columns.

    It is the row with the smallest id, null last; of rows that share that id the one with the least hash of its columns.
    Rows are told apart by a number of their own: an id may be null or repeat over different texts, all of which stay.
    Texts without words are near to nothing and stay all; an empty table gives an empty result.
    """
    rows = keyed(df)
    plain = [f.name for f in df.schema if "map<" not in f.dataType.simpleString() and f.dataType.simpleString() != "variant"]
    key = F.struct(F.col(id_col).isNull().alias("none"), F.col(id_col).alias("id"), F.xxhash64(*plain).alias("h"), F.col("__row").alias("row"))
    groups = similar_groups(rows.select(key.alias("key"), F.col(text_col).alias("text")), n, pct, "key", "text")
    kept = groups.where(F.col("key.row") == F.col("component_id.row")).select(F.col("key.row").alias("__row"))
    return rows.join(kept, "__row", "left_semi").select(*df.columns)
