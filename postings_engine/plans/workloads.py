"""The experiments, on the given tables. Each gives rows (workload, dataset, method, params, part, bits, ints, bpi)."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines, clusters, coders, trits
from ..operators.ids import cut, together
from ..operators.postings import Lists, filter_min_len, threshold_for_share, to_ids
from ..sources.tables import read_table
from . import measures
from .corpora import column_lists, corpus, terms_of

Row = tuple[str, str, str, str, str, float, int]
WORKLOADS: dict[str, Callable[[SparkSession, str], Iterable[Row]]] = {}
#: The axes of the sweeps. With 0 and 1 apart a context costs 3 to the k, so k ends at 8 there.
EVEN = tuple(range(0, 15, 2))
W6_GRID = [(k, w) for k in (0, 2, 4, 6, 8) for w in EVEN]
W7_GRID = [(k, w) for k in EVEN for w in EVEN] + [(k, w) for k in (12, 14, 16) for w in (20, 40, 60)]
W9_BOTH = {"merged": trits.hybrid(10, 12, 4), "apart": trits.Context(10, (12,), 4, False, False)}
W9_BITS = (*range(2, 24), "exact")
W16_GRID = [(2, 0), (4, 4), (6, 16), (8, 32)]
SCHEMA = "workload string, dataset string, method string, params string, part string, bits double, ints bigint"


def workload(f):
    WORKLOADS[f.__name__] = f
    return f


def run_workload(spark: SparkSession, name: str, sf_dir: str) -> DataFrame:
    """Measurements are few rows: one for each dataset, method, setting and part."""
    rows = [(name, *r[:4], round(float(r[4]), 1), int(r[5])) for r in WORKLOADS[name](spark, sf_dir)]
    return spark.createDataFrame(rows, SCHEMA).withColumn("bpi", F.round(F.col("bits") / F.greatest(F.col("ints"), F.lit(1)), 4))


def _each(f: Callable[..., Iterable[Row]], *settings: tuple) -> Iterable[Row]:
    """The rows of f for each setting, several collections side by side: parts of an order's work are a task alone."""
    for rows in together(lambda x: list(f(*x)), settings, 3):
        yield from rows


def _compared(dataset: str, lists: Lists, methods=measures.MAIN, params: str = ""):
    for r in measures.compare(lists, methods).collect():
        yield dataset, r.method, params, r.part, r.bits, lists.i


@workload
def w1_mailboxes(spark, sf_dir):
    """Conversations, split by role and whole, by bisection."""
    for name, where in (("user", F.col("role") == "user"), ("assistant", F.col("role") == "assistant"), ("all", None)):
        yield from _compared(name, corpus(spark, sf_dir, "conversations", "bisect", where))


@workload
def w2_office_mail(spark, sf_dir):
    """Documents by source, the four with most text, and whole, by bisection."""
    docs = read_table(spark, sf_dir, "documents")
    best = docs.groupBy("source").agg(F.sum("n_chars").alias("c")).orderBy(F.desc("c"), "source").limit(4).collect()
    own = lambda name, where: _compared(name, corpus(spark, sf_dir, "documents", "bisect", where))
    yield from _each(own, *((s.source, F.col("source") == s.source) for s in best), ("all", None))


@workload
def w3_books(spark, sf_dir):
    """The verse-like table, and documents by language, by bisection."""
    own = lambda name, table, where: _compared(name, corpus(spark, sf_dir, table, "bisect", where))
    yield from _each(own, ("benchmark", "benchmark", None), *((lang, "documents", F.col("lang") == lang) for lang in ("en", "fr", "de", "es")))


@workload
def w4_web(spark, sf_dir):
    """Pages by bisection, by url, and in random order."""
    yield from _each(lambda order: _compared("pages", corpus(spark, sf_dir, "pages", order), params=order), ("bisect",), ("url",), ("random",))


def _filtered(lists: Lists, share: float) -> tuple[Lists, int]:
    m = threshold_for_share(lists.gaps, share)
    gaps = filter_min_len(lists.gaps, m)
    w, i = gaps.where("before = 0").count(), gaps.agg(F.coalesce(F.sum(F.size("gaps")), F.lit(0))).first()[0]
    return Lists(gaps, lists.d, w, i), m


@workload
def w5_filtered(spark, sf_dir):
    """Long lists only, so many as hold 88.2% or 91.2% of the integers."""

    def long_ones(table):
        lists = corpus(spark, sf_dir, table, "bisect")
        for share in (0.882, 0.912):
            own, m = _filtered(lists, share)
            yield from _compared(table, own, params=f"share={share} min_len={m}")

    yield from _each(long_ones, ("pages",), ("documents",))


def _sweep(dataset, lists, contexts, bits, method="trit_static"):
    for r in coders.sweep_static(lists, contexts, bits).collect():
        yield dataset, method, r.model, "model", r.model_bits, lists.i
        yield dataset, method, r.model, "payload", r.payload_bits, lists.i


@workload
def w6_static_apart(spark, sf_dir):
    """k and w with 0 and 1 kept apart, counts stored exactly."""
    lists = corpus(spark, sf_dir, "documents", "source")
    yield from _sweep("documents", lists, {f"k={k} w={w}": trits.full_count(k, w) for k, w in W6_GRID}, "exact")


@workload
def w7_static_merged(spark, sf_dir):
    """k and w with 0 and 1 merged in contexts, 8-bit fractions."""
    lists = corpus(spark, sf_dir, "documents", "source")
    yield from _sweep("documents", lists, {f"k={k} w={w}": trits.hybrid(k, w, -(-k // 3)) for k, w in W7_GRID}, 8)


@workload
def w8_adaptive(spark, sf_dir):
    """k, w and the halving period of the adaptive coder."""
    lists = corpus(spark, sf_dir, "documents", "source")
    grid = {f"k={k} w={w} n=256": (trits.hybrid(k, w, min(2 * k, 8)), 256) for k in EVEN for w in EVEN}
    grid |= {f"k=7 w=7 n={n}": (trits.hybrid(7, 7, 8), n) for n in (64, 256, 1024, 4096, None)}
    for r in coders.sweep_adaptive(lists, grid).collect():
        yield "documents", "trit_adaptive", r.model, "payload", r.payload_bits, lists.i


@workload
def w9_widths(spark, sf_dir):
    """The width of stored fractions at k = 10, w = 12, k_init = 4, with and without merging."""
    lists = corpus(spark, sf_dir, "documents", "source")
    n = coders.collected(coders.context_counts(lists.gaps, W9_BOTH), W9_BOTH)
    for b in W9_BITS:
        for name, contexts, model_bits, payload in coders.priced(n, W9_BOTH, b):
            yield "documents", "trit_static", f"{name} bits={b}", "model", model_bits, lists.i
            yield "documents", "trit_static", f"{name} bits={b}", "payload", payload, lists.i


KERNELS = ["midpoint", "midpoint_block", "midpoint_block:pad", "elias_fano", "ef_block", "pef_approx", "pef_opt", "simple9", "simple16", "simple8b", "qmx", "packing", "packing_vector", "pfor_fast", "pfor_new", "pfor_opt", "split_blocks", "adaptive_frames", "group_varint", "g8iu", "bitmap_runs", "bitmap_chunks", "zlib", "bz2", "lzma"]


def _kernels(dataset, lists, names, params=""):
    short = baselines.optimal_ints(lists) if "pef_opt" in names else 0
    ints = {"pef_opt": short, baselines.OPT_LONG: lists.i - short}
    for r in baselines.kernel_bits(lists, names).collect():
        yield dataset, r.codec, params, "payload", r.bits, ints.get(r.codec, lists.i)


def _clustered(lists: Lists, own: DataFrame, r: int, forms: Iterable[tuple], pairs: DataFrame | None = None) -> list[list]:
    """The sizes of each form (codec, shrink, reference lists), some at a time; forms of one split share it."""
    splits = clusters.Splits(lists, own, r, pairs)
    return together(lambda f: clusters.clustered_bits(lists, own, r, *f, splits=splits).collect(), forms)


@workload
def w10_all_methods(spark, sf_dir):
    """All codecs, the two trit coders, and clustered forms, on documents, pages and a table of verse size."""

    def all_of(table):
        lists = corpus(spark, sf_dir, table, "bisect")
        yield from _kernels(table, lists, KERNELS)
        gap = baselines.gap_code_bits(lists).first().asDict()
        for name in measures.GAP_CODES:
            yield table, name, "", "payload", gap[f"{name}_bits"], lists.i
        yield table, "bernoulli", "", "payload", baselines.density_bits(lists).first().bernoulli_bits, lists.i
        yield from _compared(table, lists, ("packed_arith", "trit_static", "trit_adaptive", "bitmap_markov4"))
        own = clusters.cluster_terms(lists, 4, 16)
        forms = [(name, shrink, None) for shrink in (False, True) for name in ("midpoint", "pef_approx", "packed_arith", "trit_adaptive")]
        for (name, shrink, _), rows in zip(forms, _clustered(lists, own, max(8, lists.d // 8), forms), strict=True):
            for r in rows:
                yield table, f"clustered:{name}", f"shrink={shrink}", r.part, r.bits, lists.i

    yield from _each(all_of, ("documents",), ("pages",), ("benchmark",))


SKIPPING = ["midpoint", "midpoint_block", "midpoint_block:pad", "midpoint_block:plain", "midpoint_block:trimmed", "pef_approx", "pef_skip"]


@workload
def w11_filtered_skipping(spark, sf_dir):
    """Blocked and skipping forms on long lists only, with clustered and space-based forms and their skip data."""

    def long_ones(table, share, lists, m):
        params = f"share={share} min_len={m}"
        yield from _kernels(table, lists, SKIPPING, params)
        yield from _compared(table, lists, ("packed_arith", "trit_adaptive"), params)
        yield table, "packed_arith", params, "directory", baselines.directory_bits(lists), lists.i
        own = clusters.cluster_terms(lists, 8, 32)
        r = max(8, lists.d // 8)
        pairs = cut(to_ids(lists.gaps))
        space = clusters.space_reference_lists(pairs, own, r, lists.d)
        forms = [(name, True, reference) for name, reference in (("midpoint", None), ("pef_approx", None), ("pef_skip", None), ("pef_approx", space))]
        for (name, _, reference), rows in zip(forms, _clustered(lists, own, r, forms, pairs), strict=True):
            for x in rows:
                yield table, f"clustered:{name}" + (":space" if reference is not None else ""), f"{params} r={r}", x.part, x.bits, lists.i

    with ThreadPoolExecutor(2) as ahead:  # pages are coded while documents are still ordered
        ordered = [(table, ahead.submit(corpus, spark, sf_dir, table, "bisect")) for table in ("pages", "documents")]
        for table, whole in ordered:  # ordered once for both shares
            yield from _each(long_ones, *((table, share, *_filtered(whole.result(), share)) for share in (0.882, 0.912)))


@workload
def w12_skipping(spark, sf_dir):
    """Blocked and skipping forms on all lists of pages, by bisection and by url."""
    tok = terms_of(spark, sf_dir, "pages")
    for rows in together(lambda order: list(_kernels("pages", corpus(spark, sf_dir, "pages", order, tok=tok), SKIPPING, order)), ("bisect", "url")):
        yield from rows


@workload
def w14_batches(spark, sf_dir):
    """Density classes: the four-state bitmap coder whole and by class, and the best method of each class."""
    lists = corpus(spark, sf_dir, "pages", "bisect")
    batch = clusters.batch_of(F.col("n") / F.lit(float(max(1, lists.d))))
    counts = cut(baselines.markov4_counts(lists, batch))  # few rows; the lists are read once
    whole = baselines.markov4_sizes(counts, []).first()
    yield "pages", "bitmap_markov4", "whole", "payload", whole.payload_bits, lists.i
    own = baselines.markov4_sizes(counts, ["batch"]).agg(F.sum("payload_bits").alias("p")).first()
    yield "pages", "bitmap_markov4", "by class", "payload", own.p, lists.i
    for r in clusters.batch_bits(lists).collect():
        yield "pages", r.method, f"class={r.batch}", "payload", r.bits, r.ints


@workload
def w15_quatrits(spark, sf_dir):
    """An end symbol in place of list lengths."""
    from dataclasses import replace


    def both(table):
        lists = corpus(spark, sf_dir, table, "bisect")
        lengths = baselines.length_bits(lists).first().length_bits
        c = trits.hybrid(5, 6, 2)
        yield from _sweep(table, lists, {"trits": c, "quatrits": replace(c, kinds=4)}, 8)
        yield table, "trit_static", "trits", "lengths", lengths, lists.i
        a = trits.hybrid(7, 7, 8)
        for r in coders.sweep_adaptive(lists, {"trits": (a, 256), "quatrits": (replace(a, kinds=4), 256)}).collect():
            yield table, "trit_adaptive", r.model, "payload", r.payload_bits, lists.i
        yield table, "trit_adaptive", "trits", "lengths", lengths, lists.i

    yield from _each(both, ("pages",), ("conversations",))


@workload
def w16_bit_contexts(spark, sf_dir):
    """(k, w) contexts on bits against trits and the midpoint coder."""
    lists = corpus(spark, sf_dir, "pages", "bisect")
    for (k, w, adaptive), (payload, model) in baselines.bitmap_context_sizes(lists, W16_GRID, 16).items():
        name = "bitmap_adaptive" if adaptive else "bitmap_static"
        yield "pages", name, f"k={k} w={w}", "payload", payload, lists.i
        yield "pages", name, f"k={k} w={w}", "model", model, lists.i
    yield from _compared("pages", lists, ("midpoint", "packed_arith", "trit_static", "trit_adaptive"))


@workload
def w17_balanced(spark, sf_dir):
    """One stored number for 0 and 1 together: half the model, a longer payload."""
    lists = corpus(spark, sf_dir, "documents", "source")
    c = trits.hybrid(5, 6, 2)
    n = coders.collected(coders.context_counts(lists.gaps, {"m": c}), {"m": c})["m"]
    for balanced in (False, True):
        yield "documents", "trit_static", f"balanced={balanced}", "payload", trits.ideal_bits(n, trits.quantise(n, 8, balanced)), lists.i
        yield "documents", "trit_static", f"balanced={balanced}", "model", c.model_bits(8, 1 if balanced else 2), lists.i


@workload
def w18_boxes(spark, sf_dir):
    """Several windows of counts, and a window that covers the longest run, against one window."""
    lists = corpus(spark, sf_dir, "documents", "source")
    grid = {"w=7": trits.hybrid(6, 7, 2), "w=3+4": trits.boxes(6, (3, 4), 2), "w=2+2+3": trits.boxes(6, (2, 2, 3), 2), "cover": trits.covering(6, lists.d, 2)}
    yield from _sweep("documents", lists, grid, 8)


@workload
def w19_word_order(spark, sf_dir):
    """The order of words before adaptive coding."""
    lists = corpus(spark, sf_dir, "documents", "source")
    for order in ("length", "desc", "alpha", "none"):
        for r in coders.sweep_adaptive(lists, {order: (trits.hybrid(7, 7, 8), 256)}, order).collect():
            yield "documents", "trit_adaptive", f"order={order}", "payload", r.payload_bits, lists.i


@workload
def w20_parameter_fit(spark, sf_dir):
    """The best k of subsets of growing size, and the line through them: k = a ln(integers) + b (under ``bits``: a, b)."""
    found = []
    for table, where in (("benchmark", None), ("conversations", None), ("pages", None), ("documents", F.col("lang") == "es"), ("documents", None)):
        lists = corpus(spark, sf_dir, table, "id", where)
        grid = {str(k): (trits.hybrid(k, k, min(2 * k - 1, 8)), 1 << min(max(k, 8), 16)) for k in (2, 3, 5, 7, 9)}
        got = {int(r.model): r.payload_bits for r in coders.sweep_adaptive(lists, grid).collect()}
        best = min(got, key=got.get)
        found.append((math.log(lists.i), float(best)))
        yield table if where is None else f"{table}:es", "trit_adaptive", f"best k={best}", "payload", got[best], lists.i
    fit = spark.createDataFrame(found, "x double, y double").agg(F.regr_slope("y", "x").alias("a"), F.regr_intercept("y", "x").alias("b")).first()
    yield "fit", "trit_adaptive", "slope", "parameter", fit.a, 1
    yield "fit", "trit_adaptive", "intercept", "parameter", fit.b, 1


@workload
def w21_static_adaptive(spark, sf_dir):
    """Static against adaptive, by table, and the adaptive stream in more segments."""
    methods = ("trit_static", "trit_adaptive")

    def segments():
        lists = corpus(spark, sf_dir, "documents", "source")
        for target in (1 << 22, 1 << 19, 1 << 17):
            for r in coders.sweep_adaptive(lists, {"k=7": (trits.hybrid(7, 7, 8), 256)}, target=target).collect():
                yield "documents", "trit_adaptive", f"segments of {target} trits", "payload", r.payload_bits, lists.i

    own = lambda table: segments() if table is None else _compared(table, corpus(spark, sf_dir, table, "bisect"), methods)
    yield from _each(own, ("benchmark",), ("conversations",), ("pages",), (None,))


@workload
def w22_columns(spark, sf_dir):
    """Columns of relational tables as lists of rows."""
    line, events = read_table(spark, sf_dir, "lineitem"), read_table(spark, sf_dir, "events")
    yield from _compared("part -> orders", column_lists(line, F.col("l_partkey"), F.col("l_orderkey") + 1))
    yield from _compared("supplier -> orders", column_lists(line, F.col("l_suppkey"), F.col("l_orderkey") + 1))
    yield from _compared("user -> events", column_lists(events, F.col("user_id"), F.col("event_id") + 1))
    yield from _compared("type -> events", column_lists(events, F.col("event_type"), F.col("event_id") + 1))


@workload
def w23_duplicates(spark, sf_dir):
    """Exact copies kept, and removed."""
    for dedup in (False, True):
        yield from _compared("documents", corpus(spark, sf_dir, "documents", "source", dedup=dedup), ("midpoint", "trit_adaptive"), f"dedup={dedup}")
