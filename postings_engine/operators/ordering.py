"""Orders of documents and of words."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .ids import cut, ranked

#: Parts of at most so many postings are ordered to the end inside one task: as numbers of 8 bytes, then of 4.
LOCAL_POSTINGS = 1 << 24
#: Parts into which that task cuts its documents; each of them is ordered on in a task of its own.
LOCAL_PARTS = 32
#: Bits behind the point of a gain; whole numbers add up to the same in any order.
FRACTION = 24
#: Words that a round looks at together, so that its temporary arrays stay small.
CHUNK = 1 << 18
#: Levels whose degrees of very common words are broadcast; below them a node holds under a thousandth of the documents.
HOT_LEVELS = 10
#: Collections of at most so many documents keep their sides and gains on the driver (9 bytes each and what a sort takes),
#: and words meet them as arrays; beyond, levels go by joins.
ARRAY_DOCS = 1 << 22
#: Postings of a block of words on those levels, about.
BLOCK_POSTINGS = 1 << 20
#: Documents whose gains are added up in a row.
GAIN_ROWS = 1 << 15


def order_by(docs: DataFrame, id_col: str, *columns: str) -> DataFrame:
    """(doc, ord) by the columns given, ties by id."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc"), *(F.col(c).alias(f"c{i}") for i, c in enumerate(columns)))
    return ranked(rows, *(F.col(f"c{i}") for i in range(len(columns))), F.col("doc")).select("doc", "ord")


def order_url(pages: DataFrame, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    return order_by(pages, id_col, url_col)


def order_random(docs: DataFrame, id_col: str, seed: int = 1) -> DataFrame:
    """A control: the order of seeded hashes."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc"))
    return ranked(rows, F.xxhash64("doc", F.lit(seed)), F.col("doc")).select("doc", "ord")


def order_terms(sizes: DataFrame, how: str = "length") -> DataFrame:
    """(term, n, term_id) of (term, n): by list length and then term, or 'desc', 'alpha', 'none' (by hash)."""
    keys = {"length": (F.col("n"), F.col("term")), "desc": (F.desc("n"), F.col("term")), "alpha": (F.col("term"),), "none": (F.xxhash64("term"), F.col("term"))}[how]
    return ranked(sizes.select("term", "n"), *keys, name="term_id").select("term", "n", "term_id")


def bisect_block(docs: np.ndarray, terms: np.ndarray, n: int, rounds: int = 20, least: int = 8) -> np.ndarray:
    """Order (positions of 0..n-1) by recursive bisection of documents, from the pairs (document, term)."""
    by = np.argsort(docs, kind="stable")
    return bisect_runs(*repeated(terms[by], np.bincount(docs, minlength=n)), rounds, least)[0]


def repeated(words: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(words, how many each document has) without those that only one document has."""
    word, lengths, _ = _dense(words, lengths)
    return word, lengths


def _sums(values: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Of each document's run of values."""
    out, full = np.zeros(len(lengths), np.int64), lengths > 0
    if len(values):
        out[full] = np.add.reduceat(values, (np.cumsum(lengths) - lengths)[full], dtype=np.int64)
    return out


def _places(docs: np.ndarray, start: np.ndarray, lengths: np.ndarray) -> Iterator[np.ndarray]:
    """Where the documents' words stand, some documents at a time."""
    step = max(1, CHUNK * len(docs) // max(1, int(lengths[docs].sum())))
    for a in range(0, len(docs), step):
        own = docs[a : a + step]
        n = lengths[own]
        yield np.repeat(start[own] - np.cumsum(n) + n, n) + np.arange(n.sum())


def _dense(word: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(words, lengths, how many each document lost): words of one document only go, the others get numbers from 0."""
    keep = np.bincount(word) > 1
    number = (np.cumsum(keep) - 1).astype(np.int32)
    mine = keep[word]
    left = _sums(mine, lengths)
    return number[word[mine]], left, lengths - left


def _moves(most: int, own: int, other: int) -> tuple[np.ndarray, np.ndarray]:
    """In 2**-FRACTION bits, by degree: what a half of ``own`` documents saves when one occurrence leaves it, and what a half
    of ``other`` documents pays when one comes. Whole numbers, so that sums are the same in any order of words."""
    d = np.arange(most + 2)
    cost = lambda s: d * np.log2(s / (d + 1.0))
    fixed = lambda x: np.rint(np.diff(x) * (1 << FRACTION)).astype(np.int64)
    leaves, comes = fixed(cost(own)), fixed(cost(other))
    return np.concatenate([leaves[:1], leaves]), comes  # nobody leaves a half that has none


def _halves(word: np.ndarray, lengths: np.ndarray, alone: np.ndarray, rounds: int) -> np.ndarray:
    """Which documents go to the right half. ``alone``: words of each document that no other one of the part has."""
    size = len(lengths)
    right = np.arange(size) >= size // 2
    total = np.bincount(word)
    s1, s2 = size // 2, size - size // 2  # swaps leave them as they are
    most = int(total.max(initial=1))
    (out1, in2), (out2, in1) = _moves(most, s1, s2), _moves(most, s2, s1)
    start = np.concatenate([[0], np.cumsum(lengths)])
    cuts = np.unique(np.searchsorted(start, np.arange(0, start[-1] + CHUNK, CHUNK), "right") - 1)
    cuts = np.unique(np.concatenate([[0], cuts, [size]]))
    d2, moved, gain = np.zeros(len(total), np.int64), np.flatnonzero(right), np.empty(size, np.int64)
    saved = np.empty(2 * len(total), np.int64)
    seen: dict[bytes, int] = {}  # what follows a state depends on it alone, so one that comes again begins a circle
    for turn in range(rounds):
        state = np.packbits(right).tobytes()
        if state in seen:
            return _circled(seen, state, turn, rounds, size)
        seen[state] = turn
        for to, sign in ((moved[right[moved]], 1), (moved[~right[moved]], -1)):  # only what has moved changes degrees
            for at in _places(to, start, lengths):
                d2 += sign * np.bincount(word[at], minlength=len(total))
        d1 = total - d2
        saved[0::2], saved[1::2] = out1[d1] - in2[d2], out2[d2] - in1[d1]
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            n = lengths[a:b]
            place = word[start[a] : start[b]] * 2
            place += np.repeat(right[a:b], n)
            gain[a:b] = _sums(saved[place], n)
        gain += alone * np.where(right, out2[1] - in1[0], out1[1] - in2[0])
        moved = _swap(right, gain)
        if not len(moved):
            break
    return right


def _circled(seen: dict[bytes, int], state: bytes, turn: int, rounds: int, size: int) -> np.ndarray:
    """The state after all rounds, if that of this turn has been there before."""
    last = list(seen)[seen[state] + (rounds - turn) % (turn - seen[state])]
    return np.unpackbits(np.frombuffer(last, np.uint8), count=size).astype(bool)


def _swap(right: np.ndarray, gain: np.ndarray) -> np.ndarray:
    """Swaps the best of both halves, in ``right``, as long as that pays; the documents that have moved."""
    left_at, right_at = np.flatnonzero(~right), np.flatnonzero(right)
    left_at = left_at[np.argsort(-gain[left_at], kind="stable")][: len(right_at)]
    right_at = right_at[np.argsort(-gain[right_at], kind="stable")][: len(left_at)]
    swap = gain[left_at] + gain[right_at] > 0
    right[left_at[swap]], right[right_at[swap]] = True, False
    return np.concatenate([left_at[swap], right_at[swap]])


def bisect_runs(words: np.ndarray, lengths: np.ndarray, rounds: int = 20, least: int = 8, alone: np.ndarray | None = None) -> tuple[np.ndarray, list[tuple], np.ndarray]:
    """(order, leaves, alone): documents' positions; the parts of at most ``least`` documents that are left as they are, each
    with its end, words and lengths in that order; and the words that a document shares with no other one of its part, which
    are only counted from then on, since each weighs the same."""
    n = len(lengths)
    alone = np.zeros(n, np.int64) if alone is None else alone.copy()
    order, leaves, todo = np.arange(n), [], [(0, np.arange(n), words, lengths)]
    del words
    while todo:
        a, part, word, lengths = todo.pop()
        if len(part) <= least:
            order[a : a + len(part)] = part
            leaves.append((a + len(part), word, lengths))
            continue
        word, lengths, lost = _dense(word, lengths)
        alone[part] += lost
        right = _halves(word, lengths, alone[part], rounds)
        side, m = np.repeat(right, lengths), int(right.sum())
        todo += [(a, part[~right], word[~side], lengths[~right]), (a + len(part) - m, part[right], word[side], lengths[right])]
    return order, sorted(leaves, key=lambda x: x[0]), alone


def order_bisect(tok: DataFrame, rounds: int = 20, local_postings: int = LOCAL_POSTINGS, hot_share: float = 0.1) -> DataFrame:
    """(doc, ord) by recursive bisection of the documents of (doc, term), distinct pairs.

    Levels are taken on all parts at once until every part holds at most ``local_postings`` postings, by arrays of blocks of
    words (up to ARRAY_DOCS documents) or by joins; each part is then finished inside one task. All words count on every level, as they do inside a task; those in
    more than ``hot_share`` of the documents only go another way, so that no task gets all pairs of one. Tasks get words as
    hashes of 64 bits, one array for each document, so ``tok`` is read once if one task takes all.
    """
    lists = cut(tok.where("doc is not null").groupBy("doc").agg(F.collect_list(F.xxhash64("term")).alias("words")))
    d, w = lists.agg(F.count(F.lit(1)), F.sum(F.size("words"))).first()
    if not d:
        return tok.select("doc", F.lit(0).cast("long").alias("ord")).limit(0)
    levels = 0
    while w >> levels > local_postings and d >> levels > 16:
        levels += 1
    if levels and d <= ARRAY_DOCS:
        grouped = lists.join(_array_levels(lists, d, w, levels, rounds), "doc")
    elif levels:
        docs = ranked(lists.select("doc", F.size("words").cast("long").alias("w")), F.col("doc"), name="pos")
        parts = docs.withColumn("node", F.lit(0).cast("long")).withColumn("at", F.col("pos"))
        hot = tok.groupBy("term").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > max(2, hot_share * d))  # at most mean words of a document / hot_share
        hot = hot.select("term", F.lit(True).alias("hot"))
        pairs = cut(tok.select("doc", "term").join(F.broadcast(hot), "term", "left").withColumn("hot", F.coalesce("hot", F.lit(False))))
        for level in range(levels):
            parts = _level(pairs, parts, rounds, level < HOT_LEVELS)
        grouped = lists.join(parts.select("doc", "node", "at"), "doc")
    else:
        grouped = lists.withColumns({"node": F.lit(0).cast("long"), "at": F.col("doc")})

    def begin(key, t):
        by = np.argsort(t.column("at").to_numpy())
        doc = t.column("doc").to_numpy()[by]
        words, lengths = repeated(*_numbered(t.column("words"), by))
        order, leaves, alone = bisect_runs(words, lengths, rounds, max(8, -(-len(doc) // LOCAL_PARTS)))
        out, a = [], 0
        for part, (b, word, n) in enumerate(leaves):  # a batch for each part
            runs = pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum(n)]).astype(np.int32), pa.array(word.astype(np.int32)))
            own = order[a:b]
            out.append(pa.RecordBatch.from_arrays([pa.array(doc[own]), pa.array([key[0].as_py()] * (b - a), pa.int64()), pa.array([part] * (b - a), pa.int64()), pa.array(np.arange(a, b)), pa.array(alone[own]), runs], names=["doc", "node", "part", "at", "alone", "words"]))
            a = b
        return pa.Table.from_batches(out)

    def finish(key, t):
        t = t.sort_by("at")
        words, lengths = _numbered(t.column("words"), np.arange(t.num_rows))
        order, *_ = bisect_runs(words, lengths, rounds, alone=t.column("alone").to_numpy())
        return pa.table({"doc": t.column("doc").to_numpy()[order], "node": t.column("node"), "at": t.column("at")})

    begun = cut(grouped.groupBy("node").applyInArrow(begin, "doc bigint, node bigint, part bigint, at bigint, alone bigint, words array<int>"))
    begun = begun.repartition(max(LOCAL_PARTS, begun.rdd.getNumPartitions()), "node", "part")
    done = begun.groupBy("node", "part").applyInArrow(finish, "doc bigint, node bigint, at bigint")
    return ranked(done, F.col("node"), F.col("at"), F.col("doc")).select("doc", "ord")


def _array_levels(lists: DataFrame, d: int, w: int, levels: int, rounds: int) -> DataFrame:
    """(doc, node, at) after so many levels, the same halves as inside a task. Words lie in blocks, each with the places of
    all its documents; a round is one pass over the blocks with the documents' halves broadcast, a bit each, and what comes
    back are gains by place."""
    spark = lists.sparkSession
    blocks = max(2, -(-w // BLOCK_POSTINGS), spark.sparkContext.defaultParallelism)
    docs = cut(ranked(lists.select("doc"), F.col("doc"), name="pos"))
    pairs = lists.join(docs, "doc").select((F.col("pos") - 1).cast("int").alias("pos"), F.explode("words").alias("word"))

    def block(t):
        word, pos = t.column("word").to_numpy(), t.column("pos").to_numpy()
        by = np.argsort(word, kind="stable")
        word, pos = word[by], pos[by]
        n = np.diff(np.append(np.flatnonzero(np.diff(word, prepend=~word[:1])), len(word)))
        pos, n = pos[np.repeat(n > 1, n)], n[n > 1]  # words of one document go, as inside a task
        return pa.table({"places": pa.array([pos], pa.list_(pa.int32())), "sizes": pa.array([n], pa.list_(pa.int32()))})

    kept = pairs.withColumn("b", F.pmod(F.xxhash64("word"), F.lit(blocks)).cast("int")).repartition(blocks, "b")
    kept = cut(kept.groupBy("b").applyInArrow(block, "places array<int>, sizes array<int>"))
    order, edges = np.arange(d), np.array([0, d])  # documents in order of their nodes; where nodes begin
    for _ in range(levels):
        rank = np.empty(d, np.int32)
        rank[order] = np.arange(d, dtype=np.int32)
        node = np.repeat(np.arange(len(edges) - 1), np.diff(edges))
        size = np.diff(edges)
        right = np.arange(d) - edges[node] >= size[node] // 2
        open_ = {k: {} for k in range(len(size)) if size[k] > 1}
        ranks = spark.sparkContext.broadcast(rank)
        for turn in range(rounds):
            for k in list(open_):
                own = right[edges[k] : edges[k + 1]]
                state = np.packbits(own).tobytes()
                if state in open_[k]:
                    right[edges[k] : edges[k + 1]] = _circled(open_[k], state, turn, rounds, len(own))
                    del open_[k]
                else:
                    open_[k][state] = turn
            if not open_:
                break
            halves = spark.sparkContext.broadcast((np.packbits(right), edges))
            gain = _block_gains(kept, d, ranks, halves)
            halves.unpersist()
            for k in list(open_):
                part = slice(edges[k], edges[k + 1])
                if not len(_swap(right[part], gain[part])):
                    del open_[k]
        ranks.unpersist()
        by = np.argsort(2 * node + right, kind="stable")
        order, edges = order[by], np.searchsorted((2 * node + right)[by], np.arange(2 * len(size) + 1))
    at = np.empty(d, np.int64)
    at[order] = np.arange(d)
    placed = spark.sparkContext.broadcast((at, np.searchsorted(edges, at, "right") - 1))

    def place(batches):
        for b in batches:
            pos = b.column(1).to_numpy() - 1
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(placed.value[1][pos]), pa.array(placed.value[0][pos])], names=["doc", "node", "at"])

    return docs.select("doc", "pos").mapInArrow(place, "doc bigint, node bigint, at bigint")


def _block_gains(kept: DataFrame, d: int, ranks, state) -> np.ndarray:
    """What each place's document gains by going to its node's other half."""

    def run(batches):
        (right, edges), rank = state.value, ranks.value
        right, gain = np.unpackbits(right, count=d).astype(bool), np.zeros(d, np.int64)
        for b in batches:
            for places, sizes in zip(b.column(0), b.column(1), strict=True):
                at, n = rank[places.values.to_numpy()], sizes.values.to_numpy()
                word = np.repeat(np.arange(len(n), dtype=np.int32), n)
                for k in range(len(edges) - 1):
                    mine = (at >= edges[k]) & (at < edges[k + 1])
                    here, own = at[mine], word[mine]
                    side, s1 = right[here], (edges[k + 1] - edges[k]) // 2
                    total, d2 = np.bincount(own, minlength=len(n)), np.bincount(own[side], minlength=len(n))
                    d1, s2, most = total - d2, edges[k + 1] - edges[k] - s1, int(total.max(initial=1))
                    (out1, in2), (out2, in1) = _moves(most, s1, s2), _moves(most, s2, s1)
                    saved = np.where(side, (out2[d2] - in1[d1])[own], (out1[d1] - in2[d2])[own])
                    # whole numbers below 2**53 add up exactly as floats
                    gain[edges[k] : edges[k + 1]] += np.bincount(here - edges[k], saved, minlength=s1 + s2).astype(np.int64)
        for a in range(0, d, GAIN_ROWS):
            yield pa.RecordBatch.from_arrays([pa.array([a]), pa.array([gain[a : a + GAIN_ROWS]], pa.list_(pa.int64()))], names=["a", "gain"])

    def add(t):
        rows = t.column("gain").combine_chunks()
        return pa.table({"a": t.column("a")[:1], "gain": pa.array([rows.flatten().to_numpy().reshape(t.num_rows, -1).sum(0)], pa.list_(pa.int64()))})

    schema = "a bigint, gain array<bigint>"
    gain = np.empty(d, np.int64)
    for r in kept.mapInArrow(run, schema).groupBy("a").applyInArrow(add, schema).toArrow().to_batches():
        for a, g in zip(r.column(0).to_pylist(), r.column(1), strict=True):
            gain[a : a + len(g)] = g.values.to_numpy()
    return gain


def _numbered(column: pa.ChunkedArray, by: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(numbers of the words, how many each document has) of a column of arrays, its rows taken in the order ``by``."""
    lengths = np.concatenate([np.diff(c.offsets.to_numpy()) for c in column.chunks]).astype(np.int64)
    coded = pa.chunked_array([c.flatten() for c in column.chunks]).dictionary_encode()
    word = np.concatenate([c.indices.to_numpy() for c in coded.chunks])
    start = np.cumsum(lengths) - lengths
    return np.concatenate([np.empty(0, np.int32), *(word[at] for at in _places(by, start, lengths))]), lengths[by]


def _placed(rows: DataFrame, keys: list[str], *order: Column) -> DataFrame:
    """``rows`` with their place ``r``, from 1, in the group of equal ``keys`` and the group's size ``m``: one range sort of
    all groups, so that a group of any size is spread; what is broadcast is two numbers for each group (part of a level)."""
    every = ranked(rows, *map(F.col, keys), *order, name="__g")
    groups = every.groupBy(*keys).agg(F.min("__g").alias("__least"), F.count(F.lit(1)).alias("m"))
    return every.join(F.broadcast(groups), keys).withColumn("r", F.col("__g") - F.col("__least") + 1).drop("__g", "__least")


def _level(pairs: DataFrame, parts: DataFrame, rounds: int, hot_apart: bool) -> DataFrame:
    """Halves every node: degrees by (node, term), gains by document, swaps of the best of both sides.

    With ``hot_apart`` the degrees of hot words are broadcast to their pairs."""
    parts = _placed(parts, ["node"], F.col("at"), F.col("doc"))
    parts = cut(parts.withColumn("side", (F.col("r") * 2 > F.col("m")).cast("int")).drop("r", "m"))
    for _ in range(rounds):
        sizes = parts.groupBy("node").agg(F.sum(1 - F.col("side")).alias("s0"), F.sum("side").alias("s1"))
        owned = pairs.join(parts.select("doc", "node", "side"), "doc")
        degree = owned.groupBy("node", "term", "hot").agg(F.sum(1 - F.col("side")).cast("double").alias("d0"), F.sum("side").cast("double").alias("d1")).join(F.broadcast(sizes), "node")
        cost = lambda a, s: F.col(a) * F.log2(F.col(s) / (F.col(a) + 1))
        moved = lambda a, s, k: (F.col(a) + k) * F.log2(F.col(s) / (F.col(a) + k + 1))
        now = cost("d0", "s0") + cost("d1", "s1")
        degree = degree.select("node", "term", "hot", F.when(F.col("d0") > 0, now - moved("d0", "s0", -1) - moved("d1", "s1", 1)).alias("g0"), F.when(F.col("d1") > 0, now - moved("d1", "s1", -1) - moved("d0", "s0", 1)).alias("g1"))
        keys = ["node", "term", "hot"]
        if hot_apart:
            priced = owned.where("not hot").join(degree.where("not hot"), keys).unionByName(owned.where("hot").join(F.broadcast(degree.where("hot")), keys))
        else:
            priced = owned.join(degree, keys)
        gains = priced.groupBy("doc").agg(F.sum(F.when(F.col("side") == 0, F.col("g0")).otherwise(F.col("g1"))).alias("gain"))
        ranks = _placed(parts.join(gains, "doc", "left").withColumn("gain", F.coalesce("gain", F.lit(0.0))), ["node", "side"], F.desc("gain"), F.col("doc"))
        mate = ranks.select("node", (1 - F.col("side")).alias("side"), "r", F.col("gain").alias("other"))
        swapped = cut(ranks.join(mate, ["node", "side", "r"], "left").withColumn("swap", F.coalesce(F.col("gain") + F.col("other") > 1e-9, F.lit(False))))
        parts = swapped.withColumn("side", F.when(F.col("swap"), 1 - F.col("side")).otherwise(F.col("side"))).select("doc", "w", "pos", "node", "at", "side")
        if swapped.where("swap").isEmpty():
            break
    return cut(parts.withColumn("node", F.col("node") * 2 + F.col("side")).drop("side"))
