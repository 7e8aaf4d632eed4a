"""Sizes of all baselines over a DataFrame of lists: closed forms as plain aggregates, kernels as Arrow passes."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import closed
from . import codecs, trits
from .coders import _arrays
from .ids import cut
from .postings import Lists, long_gaps

#: The optimal partition looks at all cuts of lists (shards) up to this length; longer ones get the approximate partition
#: and are reported as a method of their own.
OPT_LONGEST, OPT_LONG = 2000, "pef_opt_long_approx"
#: More than any symbol of packed blocks: a gap below 2**16, or behind these a width.
SYMBOLS = 1 << 17
#: Integers that kernels take together: a step for all lists of like length pays for many of them.
MERGED = 1 << 20


def merged(batches: Iterable[pa.RecordBatch], ints: int) -> Iterator[pa.RecordBatch]:
    """Batches of lists, their last column, put together until they hold ``ints`` integers."""
    held, n = [], 0
    for b in batches:
        held.append(b)
        col = b.column(b.num_columns - 1)
        n += col.offsets[-1].as_py() - col.offsets[0].as_py()
        if n >= ints:
            yield pa.concat_batches(held)
            held, n = [], 0
    if held:
        yield pa.concat_batches(held)


def gap_code_bits(lists: Lists, by: list[Column] | None = None) -> DataFrame:
    """One row (or one for each group ``by``): bits of every code of single gaps, all in one aggregate of one scan."""
    g, n, u = F.col("gap"), F.col("n"), F.lit(lists.d).cast("long")
    codes = {
        "unary": closed.unary(g), "binary": closed.ceil_log2(u), "gamma": closed.gamma(g), "delta": closed.delta(g), "zeta2": closed.zeta(g, 2), "zeta3": closed.zeta(g, 3), "zeta4": closed.zeta(g, 4),
        "golomb": closed.golomb(g, closed.golomb_parameter(n, u)), "rice": closed.rice(g, closed.rice_parameter(n, u)), "vbyte": closed.vbyte(g), "nibble": closed.nibble(g), "raw32": F.lit(32).cast("long"),
    }
    rows = long_gaps(lists.gaps)
    return rows.groupBy(*(by or [])).agg(F.count(F.lit(1)).alias("ints"), *(F.sum(c).cast("long").alias(f"{k}_bits") for k, c in codes.items()))


def per_list(lists: Lists) -> DataFrame:
    """(term, n): one row for each list."""
    return lists.gaps.where("before = 0").select("term", "n")


def length_bits(lists: Lists, code: str = "delta") -> DataFrame:
    """Bits of all list lengths, by delta, gamma, vbyte, nibble, zeta2, zeta3 or zeta4."""
    n = F.col("n")
    how = {"delta": closed.delta, "gamma": closed.gamma, "vbyte": closed.vbyte, "nibble": closed.nibble, "zeta2": lambda c: closed.zeta(c, 2), "zeta3": lambda c: closed.zeta(c, 3), "zeta4": lambda c: closed.zeta(c, 4)}[code]
    return per_list(lists).agg(F.count(F.lit(1)).alias("words"), F.sum(how(n)).cast("long").alias("length_bits"))


def density_bits(lists: Lists) -> DataFrame:
    """Ideal bits of independent draws at each list's density, and of whole-list Elias-Fano."""
    u = F.lit(lists.d).cast("long")
    return per_list(lists).agg(F.round(F.sum(closed.bernoulli(F.col("n"), u)), 3).alias("bernoulli_bits"), F.sum(closed.elias_fano(F.col("n"), u)).cast("long").alias("ef_bits"))


def packed_blocks(lists: Lists, block: int = 128) -> DataFrame:
    """(term, shard, blk, n, span, widths): blocks of gaps inside shards, with their span and, by width, how many gaps."""
    b = F.when(F.col("gap") > 1, closed.bitlen(F.col("gap") - 1)).otherwise(F.lit(0).cast("long")).cast("int")
    rows = long_gaps(lists.gaps).select("term", "shard", F.floor(F.col("i") / block).cast("int").alias("blk"), "gap", b.alias("b"))
    return rows.groupBy("term", "shard", "blk").agg(F.count(F.lit(1)).alias("n"), F.sum("gap").alias("span"), F.max("b").alias("top"), F.collect_list("b").alias("widths"))


def block_code_bits(lists: Lists) -> DataFrame:
    """Binary packing, the optimised patched form priced in closed form, and Elias-Fano by blocks."""
    cost = lambda w: F.col("n") * w + F.aggregate("widths", F.lit(0).cast("long"), lambda s, b: s + F.when(b > w, 8 + b - w).otherwise(0))
    best = F.array_min(F.transform(F.sequence(F.lit(0), F.col("top")), cost))
    ef = closed.elias_fano(F.col("n"), F.col("span")) + closed.delta(F.col("span"))
    return packed_blocks(lists).agg(F.count(F.lit(1)).alias("blocks"), F.sum(8 + F.col("n") * F.col("top")).cast("long").alias("packing_bits"), F.sum(16 + best).cast("long").alias("pfor_opt_bits"), F.sum(ef).cast("long").alias("ef_block_bits"))


def directory_bits(lists: Lists, block: int = 128) -> int:
    """Skip data of any blocked form: byte-coded span and length of each block of lists with more than one."""
    rows = packed_blocks(Lists(lists.gaps.where(F.size("gaps") > block), lists.d, lists.w, lists.i), block)
    return rows.agg(F.coalesce(F.sum(closed.vbyte(F.col("span")) + closed.vbyte(F.greatest(F.lit(1).cast("long"), F.ceil(F.col("n") * F.greatest(F.col("top"), F.lit(1)) / 8)))), F.lit(0))).first()[0]


def kernel_bits(lists: Lists, names: list[str], by_list: bool = False) -> DataFrame:
    """(codec, bits), or (term, n, shard, codec, bits): kernels over Arrow batches. A shard is coded inside its own span
    if the list has several. With pef_opt, the lists too long for it come as ``OPT_LONG``, if there are any."""
    d = lists.d
    names = list(names)
    if "pef_opt" in names and OPT_LONG not in names:
        names.insert(names.index("pef_opt") + 1, OPT_LONG)
    longest = OPT_LONGEST  # workers get the bound of the caller

    def sizes_by(name: str, gaps: np.ndarray, sizes: np.ndarray, u: np.ndarray) -> np.ndarray:
        if name not in ("pef_opt", OPT_LONG):
            return codecs.sizes_of(name, gaps, sizes, u)
        out, mine = np.zeros(len(sizes), np.int64), (sizes > longest) == (name == OPT_LONG)
        out[mine] = codecs.sizes_of("pef_opt" if name == "pef_opt" else "pef_approx", gaps[np.repeat(mine, sizes)], sizes[mine], u[mine])
        return out

    def run(batches):
        for b in merged(batches, MERGED):
            gaps, sizes = _arrays(pa.Table.from_batches([b]))
            sizes = sizes.astype(np.int64)
            whole = b.column(1).to_numpy(zero_copy_only=False) == sizes
            at = np.concatenate([[0], np.cumsum(sizes)])
            u = np.where(whole, d, np.diff(np.concatenate([[0], np.cumsum(gaps)])[at]))
            out = {n: sizes_by(n, gaps, sizes, u) for n in names}
            if by_list:
                for n in names:
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array([n] * len(sizes), pa.string()), pa.array(out[n])], names=["term", "n", "shard", "codec", "bits"])
            else:
                yield pa.RecordBatch.from_pydict({"codec": pa.array(names, pa.string()), "bits": pa.array([int(out[n].sum()) for n in names], pa.int64())})

    data = lists.gaps.select("term", "n", "shard", "gaps")
    some = (F.col("codec") != OPT_LONG) | (F.col("bits") > 0)
    if by_list:
        return data.mapInArrow(run, "term string, n bigint, shard bigint, codec string, bits bigint").where(some & ((F.col("codec") != "pef_opt") | (F.col("bits") > 0)))
    return data.mapInArrow(run, "codec string, bits bigint").groupBy("codec").agg(F.sum("bits").alias("bits")).where(some)


def optimal_ints(lists: Lists) -> int:
    """Integers in lists (shards) that the optimal partition takes."""
    return lists.gaps.where(F.size("gaps") <= OPT_LONGEST).agg(F.coalesce(F.sum(F.size("gaps")), F.lit(0))).first()[0]


def bit_rows(lists: Lists, reach: int, by: Column | None = None) -> DataFrame:
    """(gaps, before, carry, last, batch) of all shards: ``carry`` holds the ``reach`` gaps before a shard, for the context
    only, ``last`` tells whether the zeros up to d follow it. Of a word's shards only the ends meet in a task."""
    rows = lists.gaps.withColumn("batch", by.cast("int") if by is not None else F.lit(0))
    whole, columns = F.col("n") == F.size("gaps"), ("gaps", "before", "carry", "last", "batch")
    one = rows.where(whole).withColumns({"carry": F.array().cast("array<bigint>"), "last": F.lit(True)}).select(*columns)
    some = rows.where(~whole)
    own, reach = Window.partitionBy("term").orderBy("shard"), max(1, reach)
    ends = some.select("term", "shard", F.slice("gaps", -F.least(F.lit(reach), F.size("gaps")), reach).alias("end"))
    carry = F.flatten(F.collect_list("end").over(own.rowsBetween(-reach, -1)))  # each shard has an id, so these reach back far enough
    ends = ends.select("term", "shard", carry.alias("carry"), F.lead("shard").over(own).isNull().alias("last"))
    ends = ends.withColumn("carry", F.when(F.size("carry") > reach, F.slice("carry", -reach, reach)).otherwise(F.col("carry")))
    return one.unionByName(some.join(ends, ["term", "shard"]).select(*columns))


def bitmap_counts(lists: Lists, k: int, w: int, by: Column | None = None) -> DataFrame:
    """(batch, ctx, zeros, ones) over the rows of the matrix: the last k bits and the ones in the w before them. ``by``
    counts batches apart. A list over several shards is one row: each shard takes the last k + w bits along."""
    return bitmap_counts_of(lists, [(k, w)], by).drop("k", "w")


def bitmap_counts_of(lists: Lists, settings: list[tuple[int, int]], by: Column | None = None) -> DataFrame:
    """As :func:`bitmap_counts`, (k, w, batch, ctx, zeros, ones), for several (k, w) from one pass over the lists."""
    d = lists.d

    def run(batches):
        total: dict[tuple, np.ndarray] = {}
        for b in batches:
            batch = b.column(4).to_numpy(zero_copy_only=False)
            for x in np.unique(batch).tolist():
                part = pa.Table.from_batches([b.filter(pa.array(batch == x))])
                gaps, sizes = _arrays(part)
                before, carry, last = part.column("before").to_numpy(), part.column("carry"), part.column("last").to_numpy()
                carry = carry.to_pylist() if (before > 0).any() else None  # a list's first shard has none
                for k, w in settings:
                    n = bitmap_context_counts(gaps, sizes, d, k, w, before, carry, last)
                    total[k, w, x] = total[k, w, x] + n if (k, w, x) in total else n
        for (k, w, x), n in total.items():
            used = np.flatnonzero(n.sum(1))
            fixed = {name: pa.array(np.full(len(used), v, np.int32)) for name, v in (("k", k), ("w", w), ("batch", x))}
            yield pa.RecordBatch.from_pydict(fixed | {"ctx": pa.array(used), "zeros": pa.array(n[used, 0].copy()), "ones": pa.array(n[used, 1].copy())})

    rows = bit_rows(lists, max(k + w for k, w in settings), by).mapInArrow(run, "k int, w int, batch int, ctx bigint, zeros bigint, ones bigint")
    return rows.groupBy("k", "w", "batch", "ctx").agg(F.sum("zeros").alias("zeros"), F.sum("ones").alias("ones"))


def markov4_counts(lists: Lists, by: Column | None = None) -> DataFrame:
    """(state, zeros, ones), state = the two bits before. The zeros after a list's last id count too. ``by`` counts batches
    apart."""
    c = bitmap_counts(lists, 2, 0, by).withColumn("state", F.lpad(F.bin("ctx"), 2, "0"))
    return c.select(*(["batch"] if by is not None else []), "state", "zeros", "ones")


def entropy_bits(counts: DataFrame, *columns: str) -> Column:
    total = sum((F.col(c) for c in columns[1:]), F.col(columns[0]))
    part = lambda c: F.when(F.col(c) > 0, F.col(c) * F.log2(total / F.col(c))).otherwise(F.lit(0.0))
    return sum((part(c) for c in columns[1:]), part(columns[0]))


def markov4_bits(lists: Lists, by: Column | None = None, bits: int = 16) -> DataFrame:
    """(batch,) payload and model bits of the four-state bitmap coder."""
    return markov4_sizes(markov4_counts(lists, by), ["batch"] if by is not None else [], bits)


def markov4_sizes(counts: DataFrame, keys: list[str], bits: int = 16) -> DataFrame:
    """As :func:`markov4_bits`, of counts that are there."""
    c = counts.groupBy(*keys, "state").agg(F.sum("zeros").alias("zeros"), F.sum("ones").alias("ones"))
    return c.groupBy(*keys).agg(F.round(F.sum(entropy_bits(c, "zeros", "ones")), 3).alias("payload_bits"), F.lit(4 * bits).cast("long").alias("model_bits"))


def bitmap_context_counts(gaps: np.ndarray, sizes: np.ndarray, d: int, k: int, w: int, before: np.ndarray | None = None, carry: list | None = None, last: np.ndarray | None = None, cells: int = 1 << 21) -> np.ndarray:
    """Counts (context, bit) over the rows of the matrix: the last k bits and the ones in the w bits before. Runs of zeros
    longer than k + w stay in one context and are counted in one step. For shards, ``before`` holds the last ids of the
    shards before, ``carry`` the last k + w gaps before (context only) and ``last`` whether the zeros up to d follow. Rows
    go together, behind k + w zeros each, as long as their gaps make at most ``cells`` bits."""
    n = np.zeros(2**k * (w + 1) * 2, np.int64)
    rows = len(sizes)
    sizes = sizes.astype(np.int64)
    known = np.array([len(c) for c in carry], np.int64) if carry is not None else np.zeros(rows, np.int64)
    old = np.array([g for c in carry for g in c], np.int64) if carry is not None else np.empty(0, np.int64)
    ended = np.ones(rows, bool) if last is None else np.asarray(last, bool)
    at, old_at = np.concatenate([[0], np.cumsum(sizes)]), np.concatenate([[0], np.cumsum(known)])
    tail = d - np.diff(np.concatenate([[0], np.cumsum(gaps)])[at]) - (before if before is not None else 0)
    reach = k + w
    room = np.cumsum((sizes + known + 2) * (reach + 1)) // cells
    cuts = np.concatenate([[0], np.flatnonzero(np.diff(room)) + 1, [rows]])
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        # of each row: zeros before it, the gaps before the shard, its gaps, the run behind its last id
        m = known[a:b] + sizes[a:b] + 2
        first = np.cumsum(m) - m
        runs, counted = np.empty(int(m.sum()), np.int64), np.zeros(int(m.sum()), bool)
        own = np.repeat(first + 1 + known[a:b], sizes[a:b]) + np.arange(at[b] - at[a]) - np.repeat(at[a:b] - at[a], sizes[a:b])
        runs[own], counted[own] = gaps[at[a] : at[b]] - 1, True
        runs[np.repeat(first + 1, known[a:b]) + np.arange(old_at[b] - old_at[a]) - np.repeat(old_at[a:b] - old_at[a], known[a:b])] = old[old_at[a] : old_at[b]] - 1
        runs[first] = reach
        end = first + m - 1
        runs[end], counted[end] = np.where(ended[a:b], tail[a:b], 0), ended[a:b]
        short = np.minimum(runs, reach)
        n[0] += int((runs - short)[counted].sum())
        width = short + 1
        width[first] -= 1  # no id closes the first run, nor the last
        width[end] -= 1
        closed_ = np.ones(len(width), bool)
        closed_[first] = closed_[end] = False
        stop = np.cumsum(width)
        bits = np.zeros(int(stop[-1]) if len(stop) else 0, np.int32)
        bits[stop[closed_] - 1] = 1
        use = np.repeat(counted, width)
        ctx = trits.recent(bits, k, 2)
        if w:
            total = np.concatenate([[0], np.cumsum(bits, dtype=np.int32)]).astype(np.int32)
            ctx = ctx + (trits.behind(total, k, len(bits)) - trits.behind(total, reach, len(bits))) * np.int32(2**k)
        n += np.bincount(ctx[use] * 2 + bits[use], minlength=len(n))
    return n.reshape(-1, 2)


def bitmap_context_sizes(lists: Lists, settings: list[tuple[int, int]], bits: int = 8) -> dict[tuple[int, int, bool], tuple[float, int]]:
    """(k, w, adaptive) -> (payload bits, model bits), all from one pass over the lists; adaptive without forgetting is the
    order-free form. At most 2**k * (w + 1) counts of each setting come to the driver."""
    out, counts = {}, {s: [] for s in settings}
    for r in bitmap_counts_of(lists, settings).collect():
        counts[r.k, r.w].append((r.zeros, r.ones))
    for (k, w), own in counts.items():
        rows = np.array(own, np.int64).reshape(-1, 2)
        out[k, w, False] = float(trits.ideal_bits(rows, trits.quantise(rows, max(bits, 2)))), bits * 2**k * (w + 1)
        out[k, w, True] = float(trits.order_free_bits(rows)), 0
    return out


def bitmap_context_bits(lists: Lists, k: int, w: int, adaptive: bool = False, bits: int = 8) -> DataFrame:
    """(payload_bits, model_bits) of (k, w) contexts on bits; adaptive without forgetting is the order-free form.

    A list over several shards is counted as one row of the matrix: each shard takes the last k + w bits along."""
    return lists.gaps.sparkSession.createDataFrame([bitmap_context_sizes(lists, [(k, w)], bits)[k, w, adaptive]], "payload_bits double, model_bits bigint")


def packed_symbols(gaps: np.ndarray, mantissa: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bit lengths, symbols, raw bits) of gaps. 'modelled': a symbol is a whole gap, or from 2**16 on a class behind all
    gaps; 'raw': always a class. What a class leaves open is sent raw."""
    width = trits.bit_lengths(gaps)
    wide = np.ones(len(gaps), bool) if mantissa == "raw" else gaps >= 1 << 16
    return width, np.where(wide, width + (0 if mantissa == "raw" else 1 << 16), gaps), np.where(wide, width - 1, 0)


def raw_bits(symbols: np.ndarray, mantissa: str) -> np.ndarray:
    """What :func:`packed_symbols` sends raw with each symbol: it follows from the symbol."""
    return symbols - 1 if mantissa == "raw" else np.where(symbols >= 1 << 16, symbols - (1 << 16) - 1, 0)


def selector_of(width: np.ndarray, classes: int = 16) -> int:
    cls = np.sort(np.minimum(width - 1, classes - 1))
    return int(cls[(len(cls) - 1) // 2] * classes + cls[-1])


def packed_classes(lists: Lists, block: int = 128, classes: int = 16, mantissa: str = "modelled") -> DataFrame:
    """(selector, symbol, n, raw): how often each symbol occurs in blocks of each selector = (median class, maximum class),
    and the bits sent raw. Symbol -1 counts the selector's blocks."""

    def run(batches):
        for b in batches:
            gaps, sizes = _arrays(pa.Table.from_batches([b]))
            if not len(gaps):
                continue
            place = np.arange(len(gaps)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
            first = np.flatnonzero(place % block == 0)
            n = np.diff(np.append(first, len(gaps)))
            own = np.repeat(np.arange(len(first)), n)
            width, sym, _ = packed_symbols(gaps, mantissa)
            cls = np.minimum(width - 1, classes - 1)
            top = np.maximum.reduceat(cls, first)
            selector = np.sort(own * classes + cls)[first + (n - 1) // 2] % classes * classes + top  # blocks stay apart
            pairs, count = np.unique(selector[own] * SYMBOLS + sym, return_counts=True)
            pairs, sym = np.divmod(pairs, SYMBOLS)
            sent = count * raw_bits(sym, mantissa)
            blocks, m = np.unique(selector, return_counts=True)
            yield pa.RecordBatch.from_pydict({"selector": pa.array(np.concatenate([pairs, blocks])), "symbol": pa.array(np.concatenate([sym, np.full(len(blocks), -1)])), "n": pa.array(np.concatenate([count, m]).astype(np.int64)), "raw": pa.array(np.concatenate([sent, np.zeros(len(blocks), np.int64)]))})

    rows = lists.gaps.select("gaps").mapInArrow(run, "selector bigint, symbol bigint, n bigint, raw bigint")
    return rows.groupBy("selector", "symbol").agg(F.sum("n").alias("n"), F.sum("raw").alias("raw"))


def packed_arith_bits(lists: Lists, selector: str = "arith", mantissa: str = "modelled", bits: int = 12, **how) -> DataFrame:
    """(blocks, selector_bits, payload_bits, model_bits, selector_bits_per_block): order-0 models, one for the selectors
    (or 6 raw bits with 'raw6'), one for each selector's symbols; a model stores a number and a fraction for each symbol."""
    c = cut(packed_classes(lists, mantissa=mantissa, **how))  # few rows, read twice: the lists are read once
    own = Window.partitionBy("selector")
    sym = c.where("symbol >= 0").withColumn("t", F.sum("n").over(own)).agg(F.sum(F.col("n") * F.log2(F.col("t") / F.col("n")) + F.col("raw")).alias("payload"), F.count(F.lit(1)).alias("entries"))
    sel = c.where("symbol = -1").withColumn("t", F.sum("n").over(Window.partitionBy())).agg(F.sum(F.col("n") * F.log2(F.col("t") / F.col("n"))).alias("s"), F.sum("n").alias("blocks"), F.count(F.lit(1)).alias("sel_entries"))
    both = sym.join(F.broadcast(sel))  # one row each
    cost = F.col("s") if selector == "arith" else 6.0 * F.col("blocks")
    return both.select("blocks", F.round(cost, 3).alias("selector_bits"), F.round("payload", 3).alias("payload_bits"), ((F.col("entries") + F.col("sel_entries")) * (8 + bits)).alias("model_bits"), F.round(cost / F.col("blocks"), 4).alias("selector_bits_per_block"))
