"""Measures: bits by part, bits per integer, gains, times."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import baselines, coders
from ..operators.ids import together
from ..operators.postings import Lists

#: The methods of the main comparison.
MAIN = ("midpoint", "midpoint_block", "packed_arith", "trit_static", "trit_adaptive")
GAP_CODES = ("unary", "binary", "gamma", "delta", "zeta2", "zeta3", "zeta4", "golomb", "rice", "vbyte", "nibble", "raw32")


def parts(lists: Lists, method: str, **how) -> DataFrame:
    """(method, part, bits) of one method, list lengths apart."""
    lengths = baselines.length_bits(lists).select(F.lit(method).alias("method"), F.lit("lengths").alias("part"), F.col("length_bits").alias("bits"))
    if method == "trit_static" and not how:
        model, payload = coders.static_bits(lists)
        rows = [(method, "model", model), (method, "payload", payload)] if lists.i else []
        own = lists.gaps.sparkSession.createDataFrame(rows, "method string, part string, bits bigint")
    elif method.startswith("trit_"):
        s = coders.sizes(coders.encode(lists, method, payload=False, **how)).where("part in ('model', 'ideal')")
        own = s.select("method", F.when(F.col("part") == "ideal", "payload").otherwise(F.col("part")).alias("part"), "bits")
    elif method == "packed_arith":
        s = baselines.packed_arith_bits(lists, **how)
        stack = F.explode(F.create_map(F.lit("payload"), F.ceil(F.col("payload_bits") + F.col("selector_bits")).cast("long"), F.lit("model"), F.col("model_bits").cast("long"))).alias("part", "bits")
        own = s.select(F.lit(method).alias("method"), stack)
    elif method in GAP_CODES:
        own = baselines.gap_code_bits(lists).select(F.lit(method).alias("method"), F.lit("payload").alias("part"), F.col(f"{method}_bits").alias("bits"))
    elif method == "bernoulli":
        own = baselines.density_bits(lists).select(F.lit(method).alias("method"), F.lit("payload").alias("part"), F.ceil("bernoulli_bits").cast("long").alias("bits"))
    elif method == "bitmap_markov4":
        s = baselines.markov4_bits(lists)
        stack = F.explode(F.create_map(F.lit("payload"), F.ceil("payload_bits").cast("long"), F.lit("model"), F.col("model_bits"))).alias("part", "bits")
        own = s.select(F.lit(method).alias("method"), stack)
    else:
        own = baselines.kernel_bits(lists, [method]).select(F.lit(method).alias("method"), F.lit("payload").alias("part"), "bits")
    return lengths.unionByName(own)


def compare(lists: Lists, methods: tuple[str, ...] = MAIN) -> DataFrame:
    """(method, part, bits, ints, bpi) for each method."""
    out = None
    for one in together(lambda m: parts(lists, m), methods):
        out = one if out is None else out.unionByName(one)
    i = F.lit(lists.i).cast("long")
    return out.select("method", "part", F.col("bits").cast("long").alias("bits"), i.alias("ints"), (F.col("bits") / i).alias("bpi"))


def totals(measure: DataFrame, *by: str) -> DataFrame:
    """Bits per integer of each method, all parts together."""
    return measure.groupBy(*by, "method").agg(F.sum("bits").alias("bits"), F.max("ints").alias("ints"), F.round(F.sum("bpi"), 4).alias("bpi"))


def gain(total: DataFrame, *by: str) -> DataFrame:
    """(gain_pct): how much shorter the best trit coder is than the midpoint coder, in percent; negative if longer."""
    best = total.groupBy(*by).agg(F.min(F.when(F.col("method").startswith("trit_"), F.col("bits"))).alias("ours"), F.max(F.when(F.col("method") == "midpoint", F.col("bits"))).alias("midpoint"))
    return best.withColumn("gain_pct", F.round(100 * (F.col("midpoint") - F.col("ours")) / F.col("midpoint"), 3))


def by_part(measure: DataFrame) -> DataFrame:
    """Megabytes (10**6 bytes) of each part, side by side."""
    return measure.groupBy("method").pivot("part", ["lengths", "model", "payload"]).agg(F.sum("bits") / 8e6)


def conditional_entropy(counts: DataFrame) -> DataFrame:
    """(trits, bits): what the next trit costs given its context, from counts (model, ctx, n0..n3)."""
    return counts.groupBy("model").agg(F.sum(F.col("n0") + F.col("n1") + F.col("n2") + F.col("n3")).alias("trits"), F.round(F.sum(baselines.entropy_bits(counts, "n0", "n1", "n2", "n3")), 3).alias("bits"))


def clustering_gain(gaps: DataFrame, control: DataFrame) -> DataFrame:
    """Mean log2 of gaps in an order, and in the control order."""
    mean = lambda d, name: d.select(F.explode("gaps").alias("g")).agg(F.round(F.avg(F.log2("g")), 4).alias(name))
    return mean(gaps, "mean_log2_gap").join(mean(control, "control_log2_gap"))


def timed(action: Callable[[], DataFrame], runs: int = 3) -> float:
    """Mean seconds of computing a frame whole."""
    took = []
    for _ in range(runs):
        t = time.perf_counter()
        action().write.format("noop").mode("overwrite").save()
        took.append(time.perf_counter() - t)
    return sum(took) / runs


def verify(lists: Lists, names: list[str]) -> DataFrame:
    """(codec, lists, ints, mismatches, wrong_sizes, bits): every list shard coded and decoded by each codec, in one pass;
    a size is wrong if the bytes are not the priced bits, rounded up."""
    import numpy as np
    import pyarrow as pa

    from ..operators.codecs import CODECS

    d = lists.d

    def run(batches):
        for b in batches:
            rows = [(np.array(g, np.int64), d if n == len(g) else sum(g)) for g, n in zip(b.column(1).to_pylist(), b.column(0).to_pylist(), strict=True)]
            out = []
            for name in names:
                c, bad, wrong, bits = CODECS[name], 0, 0, 0
                for g, u in rows:
                    raw, size = c.encode(g, u), c.bits(g, u)
                    bad += not np.array_equal(c.decode(raw, len(g), u), g)
                    wrong += len(raw) != -(-size // 8)
                    bits += size
                out.append((name, len(rows), sum(len(g) for g, _ in rows), bad, wrong, bits))
            yield pa.RecordBatch.from_arrays([pa.array(list(x)) for x in zip(*out, strict=True)], names=["codec", "lists", "ints", "mismatches", "wrong_sizes", "bits"])

    kind = "codec string, lists bigint, ints bigint, mismatches bigint, wrong_sizes bigint, bits bigint"
    return lists.gaps.select("n", "gaps").mapInArrow(run, kind).groupBy("codec").agg(*(F.sum(c).alias(c) for c in ("lists", "ints", "mismatches", "wrong_sizes", "bits")))


def overheads(lists: Lists) -> DataFrame:
    """(form, bits, ratio): what blocks, padding and skip data add to the midpoint coder, and skip data to partitions."""
    base = {"midpoint_block": "midpoint", "midpoint_block:pad": "midpoint_block", "midpoint_block:plain": "midpoint_block", "midpoint_block:trimmed": "midpoint_block", "pef_skip": "pef_approx"}
    got = baselines.kernel_bits(lists, [*base, "midpoint", "pef_approx"])
    pairs = F.create_map(*(F.lit(x) for kv in base.items() for x in kv))
    own = got.where(F.col("codec").isin(list(base))).withColumn("base", pairs[F.col("codec")])
    return own.join(got.select(F.col("codec").alias("base"), F.col("bits").alias("b")), "base").select(F.col("codec").alias("form"), "base", "bits", F.round(F.col("bits") / F.col("b"), 6).alias("ratio"))


def time_codec(lists: Lists, method: str, runs: int = 10, **how) -> tuple[float, float]:
    """Microseconds per integer to code and to decode, jobs as a whole, mean of ``runs``."""
    from ..operators.ids import cut

    i = max(1, lists.i)
    if method.startswith("trit_"):
        code, back = lambda: coders.encode(lists, method, **how), coders.decode
    else:
        code, back = lambda: list_bytes(lists, method), lambda done: list_gaps(done, method, lists.d)
    up, done = timed(code, runs), cut(code())
    return 1e6 * up / i, 1e6 * timed(lambda: back(done), runs) / i


def list_bytes(lists: Lists, method: str) -> DataFrame:
    """(term, n, shard, before, m, payload): each list shard as bytes by a registered codec."""
    import numpy as np
    import pyarrow as pa

    from ..operators.codecs import bytes_of

    d = lists.d

    def run(batches):
        for b in batches:
            col = b.column(4)
            gaps, m = col.flatten().to_numpy(zero_copy_only=False), np.diff(col.offsets.to_numpy()).astype(np.int64)
            total = np.concatenate([[0], np.cumsum(gaps)])
            ends = np.cumsum(m)
            span = total[ends] - total[ends - m]
            out = bytes_of(method, gaps, m, np.where(b.column(1).to_numpy() == m, d, span))
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(4)), pa.array(m), pa.array(span), pa.array(out, pa.binary())], names=["term", "n", "shard", "before", "m", "span", "payload"])

    return lists.gaps.select("term", "n", "shard", "before", "gaps").mapInArrow(run, "term string, n bigint, shard bigint, before bigint, m bigint, span bigint, payload binary")


def list_gaps(coded: DataFrame, method: str, d: int) -> DataFrame:
    """(term, n, shard, before, gaps) back from :func:`list_bytes`."""
    import numpy as np
    import pyarrow as pa

    from ..operators.codecs import lists_from

    def run(batches):
        for b in batches:
            n, m, span = (b.column(i).to_numpy() for i in (1, 4, 5))
            gaps = lists_from(method, b.column(6).to_pylist(), m, np.where(n == m, d, span))
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(m)]).astype(np.int32)), pa.array(gaps))
            yield pa.RecordBatch.from_arrays([*(b.column(i) for i in range(4)), lists], names=["term", "n", "shard", "before", "gaps"])

    return coded.mapInArrow(run, "term string, n bigint, shard bigint, before bigint, gaps array<bigint>")
