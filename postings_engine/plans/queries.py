"""The engine's queries: one for each method, variant, baseline, measure and experiment."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import closed
from ..functions.text import dedup_docs, split_ligatures, tokens, trim_urls, with_stems
from ..operators import baselines, clusters, coders, lookup, ordering, postings, trits
from ..operators.ids import cut, together
from ..operators.postings import Lists
from ..sources.tables import read_table
from . import measures
from .corpora import column_lists, corpus, documents_of
from .workloads import WORKLOADS, run_workload

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
#: Parameters of the small context model that SQL can follow on the verse-like table.
SMALL = trits.hybrid(2, 3, 1)
WORDS = ["the", "and", "with"]
FAMILIES = {"none": trits.none(), "full2": trits.full(2), "full4": trits.full(4), "full_count": trits.full_count(3, 4), "hybrid": trits.hybrid(4, 5, 2), "boxes": trits.boxes(4, (2, 3), 2), "covering": trits.covering(4, 1000, 2)}


def query(f):
    QUERIES[f.__name__] = f
    return f


def _pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents_of(spark, sf_dir, "documents")
    return postings.postings(tokens(docs, "doc", "text"), ordering.order_by(docs, "doc"))


def _joined(column: str):
    return F.array_join(F.col(column).cast("array<string>"), " ").alias(column)


@query
def vocab_df(spark, sf_dir):
    return tokens(documents_of(spark, sf_dir, "documents"), "doc", "text").groupBy("term").agg(F.count(F.lit(1)).alias("n"))


@query
def vocab_ligatures(spark, sf_dir):
    return tokens(documents_of(spark, sf_dir, "documents"), "doc", split_ligatures(F.lower("text")), stopwords=["the"]).groupBy("term").agg(F.count(F.lit(1)).alias("n"))


@query
def vocab_stems(spark, sf_dir):
    """English documents' words by stem, those of the others as they are."""
    docs = documents_of(spark, sf_dir, "documents")
    tok = tokens(docs, "doc", "text").join(docs.select("doc", "lang"), "doc")
    return with_stems(tok, F.col("lang") == "en").groupBy("term").agg(F.count(F.lit(1)).alias("n"))


@query
def url_trimming(spark, sf_dir):
    return read_table(spark, sf_dir, "pages").select("page_id", trim_urls(F.col("url")).alias("url"))


@query
def distinct_documents(spark, sf_dir):
    return dedup_docs(read_table(spark, sf_dir, "documents")).select("doc_id")


@query
def collection_stats(spark, sf_dir):
    return postings.collection_stats(corpus(spark, sf_dir)).withColumn("density", F.round("density", 9))


@query
def postings_lists(spark, sf_dir):
    pairs = postings.to_ids(corpus(spark, sf_dir).gaps)
    return pairs.groupBy("term").agg(F.count(F.lit(1)).alias("n"), F.array_join(F.sort_array(F.collect_list("ord")).cast("array<string>"), " ").alias("ids"))


@query
def gap_lists(spark, sf_dir):
    return corpus(spark, sf_dir).gaps.select("term", "n", _joined("gaps"))


@query
def trit_strings(spark, sf_dir):
    return postings.trit_strings(corpus(spark, sf_dir, "benchmark").gaps).select("term", "trits")


@query
def quatrit_strings(spark, sf_dir):
    return postings.quatrit_strings(corpus(spark, sf_dir, "benchmark").gaps).select("term", "trits")


@query
def symbol_counts(spark, sf_dir):
    return postings.symbol_counts(corpus(spark, sf_dir))


@query
def bit_runs(spark, sf_dir):
    return postings.bit_runs(corpus(spark, sf_dir, "benchmark"))


@query
def gap_code_bits(spark, sf_dir):
    return baselines.gap_code_bits(corpus(spark, sf_dir))


@query
def gap_code_bits_sql(spark, sf_dir):
    """The same lengths through the registered SQL functions."""
    closed.register(spark)
    postings.long_gaps(corpus(spark, sf_dir, "benchmark").gaps).createOrReplaceTempView("long_gaps")
    return spark.sql("SELECT sum(gamma_bits(gap)) AS gamma_bits, sum(delta_bits(gap)) AS delta_bits, sum(zeta_bits(gap, 3)) AS zeta3_bits, sum(vbyte_bits(gap)) AS vbyte_bits, sum(nibble_bits(gap)) AS nibble_bits, sum(rice_bits(gap, 2)) AS rice2_bits, sum(golomb_bits(gap, 5)) AS golomb5_bits FROM long_gaps")


@query
def density_bits(spark, sf_dir):
    return baselines.density_bits(corpus(spark, sf_dir))


@query
def block_code_bits(spark, sf_dir):
    return baselines.block_code_bits(corpus(spark, sf_dir))


@query
def length_bits(spark, sf_dir):
    return baselines.length_bits(corpus(spark, sf_dir))


@query
def midpoint_bits(spark, sf_dir):
    return baselines.kernel_bits(corpus(spark, sf_dir, "benchmark"), ["midpoint"])


@query
def midpoint_options(spark, sf_dir):
    names = [f"midpoint_:{s}:{m}" for s in ("none", "center", "center+leaf_ends") for m in ("plain", "pow2")]
    return baselines.kernel_bits(corpus(spark, sf_dir, "benchmark"), names)


@query
def kernel_bits(spark, sf_dir):
    from .workloads import KERNELS, SKIPPING

    return baselines.kernel_bits(corpus(spark, sf_dir, "conversations"), list(dict.fromkeys(KERNELS + SKIPPING)))


@query
def bitmap_chunk_bits(spark, sf_dir):
    return baselines.kernel_bits(corpus(spark, sf_dir, "benchmark"), ["bitmap_chunks", "raw32"])


@query
def context_counts(spark, sf_dir):
    return coders.context_counts(corpus(spark, sf_dir, "benchmark").gaps, {"m": SMALL}).select("ctx", "n0", "n1", "n2")


@query
def static_ideal_bits(spark, sf_dir):
    out = coders.sweep_static(corpus(spark, sf_dir, "benchmark"), {"m": SMALL}, 8)
    return out.select("contexts", "model_bits", F.round("payload_bits", 3).alias("payload_bits"))


@query
def conditional_entropy(spark, sf_dir):
    c = coders.context_counts(corpus(spark, sf_dir, "benchmark").gaps, {"m": SMALL})
    return measures.conditional_entropy(c).select("trits", "bits")


@query
def adaptive_bits_order_free(spark, sf_dir):
    out = coders.sweep_adaptive(corpus(spark, sf_dir, "benchmark"), {"m": (SMALL, None)})
    return out.select(F.round("payload_bits", 3).alias("payload_bits"))


@query
def context_variants(spark, sf_dir):
    """Every context family by the payload and the model of the static coder."""
    families = FAMILIES
    out = coders.sweep_static(corpus(spark, sf_dir, "conversations"), families, 8)
    return out.withColumn("payload_bits", F.round("payload_bits", 1))


@query
def markov4_counts(spark, sf_dir):
    return baselines.markov4_counts(corpus(spark, sf_dir))


@query
def packed_arith_bits(spark, sf_dir):
    lists = corpus(spark, sf_dir, "documents")
    out = None
    for s, m in (("arith", "modelled"), ("raw6", "modelled"), ("arith", "raw")):
        one = baselines.packed_arith_bits(lists, s, m).select(F.lit(s).alias("selector"), F.lit(m).alias("mantissa"), "blocks", F.round("selector_bits", 1).alias("selector_bits"), F.round("payload_bits", 1).alias("payload_bits"), "model_bits", "selector_bits_per_block")
        out = one if out is None else out.unionByName(one)
    return out


@query
def packed_selectors(spark, sf_dir):
    return baselines.packed_classes(corpus(spark, sf_dir, "benchmark")).where("symbol = -1").select("selector", "n")


@query
def order_url(spark, sf_dir):
    return ordering.order_url(read_table(spark, sf_dir, "pages"))


@query
def order_terms(spark, sf_dir):
    return ordering.order_terms(baselines.per_list(corpus(spark, sf_dir)))


@query
def order_bisection(spark, sf_dir):
    return ordering.order_bisect(tokens(documents_of(spark, sf_dir, "conversations"), "doc", "text"))


@query
def order_gain(spark, sf_dir):
    """Mean log2 of gaps by bisection, and in random order."""
    return measures.clustering_gain(*together(lambda order: corpus(spark, sf_dir, "pages", order).gaps, ("bisect", "random")))


@query
def batch_sizes(spark, sf_dir):
    lists = corpus(spark, sf_dir)
    batch = clusters.batch_of(F.col("n") / F.lit(float(lists.d))).alias("batch")
    g = postings.long_gaps(lists.gaps)
    return g.groupBy(batch).agg(F.count(F.lit(1)).alias("ints"), F.sum(closed.gamma(F.col("gap"))).cast("long").alias("gamma_bits"))


def _letters(pairs: DataFrame) -> DataFrame:
    return pairs.select("term").distinct().select("term", F.pmod(F.ascii("term"), F.lit(4)).cast("int").alias("c"))


@query
def reference_lists(spark, sf_dir):
    pairs = _pairs(spark, sf_dir)
    return clusters.reference_lists(pairs, _letters(pairs), 50).select("c", "ord", F.col("rank").cast("long").alias("rank"))


@query
def reference_split(spark, sf_dir):
    pairs = cut(_pairs(spark, sf_dir))
    own = _letters(pairs)
    split = clusters.split_by_reference(pairs, own, clusters.reference_lists(pairs, own, 50))
    return split.groupBy("c", "part").agg(F.count(F.lit(1)).alias("n"), F.sum("x").alias("x"), F.max("x").alias("most"))


@query
def clustered_bits(spark, sf_dir):
    lists = corpus(spark, sf_dir, "pages")
    return clusters.clustered_bits(lists, clusters.cluster_terms(lists, 4, 32), max(4, lists.d // 8))


@query
def best_per_batch(spark, sf_dir):
    return clusters.best_per_batch(corpus(spark, sf_dir, "pages"))


@query
def cheapest_codec(spark, sf_dir):
    return clusters.cheapest(corpus(spark, sf_dir, "conversations"), ["gamma", "delta", "zeta2", "midpoint", "elias_fano", "packing"])


@query
def codec_rules(spark, sf_dir):
    return clusters.by_rules(corpus(spark, sf_dir, "conversations"), [(F.col("n") < 4, "delta"), (F.col("n") < 128, "midpoint")], "pfor_opt")


@query
def filter_share(spark, sf_dir):
    lists = corpus(spark, sf_dir)
    m = postings.threshold_for_share(lists.gaps, 0.882)
    kept = postings.filter_min_len(lists.gaps, m)
    return kept.agg(F.lit(m).cast("long").alias("min_len"), F.count(F.lit(1)).alias("words"), F.sum(F.size("gaps")).cast("long").alias("ints"))


@query
def bool_and(spark, sf_dir):
    return lookup.and_query(_pairs(spark, sf_dir), WORDS)


@query
def bool_or(spark, sf_dir):
    return lookup.or_query(_pairs(spark, sf_dir), WORDS)


@query
def bool_not(spark, sf_dir):
    return lookup.not_query(_pairs(spark, sf_dir), ["the"], ["with"])


@query
def topk_terms(spark, sf_dir):
    return lookup.top_terms(_pairs(spark, sf_dir), 20)


@query
def topk_docs(spark, sf_dir):
    return lookup.top_docs(_pairs(spark, sf_dir), ["the", "and", "with", "la", "der"], 20)


@query
def block_directory(spark, sf_dir):
    return lookup.blocks(corpus(spark, sf_dir).gaps)


@query
def block_lookup(spark, sf_dir):
    lists = corpus(spark, sf_dir)
    return lookup.in_blocks(lookup.blocks(lists.gaps), spark.range(1, max(2, lists.d), 100).withColumnRenamed("id", "ord"))


@query
def part_order_lists(spark, sf_dir):
    line = read_table(spark, sf_dir, "lineitem")
    return postings.whole_texts(column_lists(line, F.col("l_partkey"), F.col("l_orderkey") + 1).gaps)


@query
def event_type_lists(spark, sf_dir):
    e = read_table(spark, sf_dir, "events")
    lists = column_lists(e, F.col("event_type"), F.col("event_id") + 1).gaps
    return postings.whole_texts(lists).select("term", "n", F.md5("gaps").alias("gaps"))


@query
def json_value_lists(spark, sf_dir):
    e = read_table(spark, sf_dir, "events")
    lists = column_lists(e, F.get_json_object("props", "$.k"), F.col("event_id") + 1).gaps
    return postings.whole_texts(lists).select("term", "n", F.md5("gaps").alias("gaps"))


@query
def method_cube(spark, sf_dir):
    """Sizes by language and code, with all totals."""
    docs = documents_of(spark, sf_dir, "documents")
    pairs = cut(_pairs(spark, sf_dir).join(ordering.order_by(docs, "doc"), "ord").join(docs.select("doc", "lang"), "doc"))
    gaps = postings.to_gaps(pairs.select(F.concat_ws(":", "lang", "term").alias("term"), "ord"))
    rows = postings.long_gaps(gaps).withColumn("lang", F.substring_index("term", ":", 1))
    codes = F.create_map(F.lit("gamma"), closed.gamma(F.col("gap")), F.lit("delta"), closed.delta(F.col("gap")), F.lit("vbyte"), closed.vbyte(F.col("gap")))
    return rows.select("lang", F.explode(codes).alias("code", "bits")).cube("lang", "code").agg(F.sum("bits").alias("bits"))


def _roundtrip(lists: Lists, method: str, **how) -> DataFrame:
    done = cut(coders.encode(lists, method, **how))
    return coders.roundtrip_mismatches(lists.gaps, coders.decode(done))


@query
def trit_static_roundtrip(spark, sf_dir):
    return _roundtrip(corpus(spark, sf_dir, "conversations"), "trit_static")


@query
def trit_adaptive_roundtrip(spark, sf_dir):
    return _roundtrip(corpus(spark, sf_dir, "conversations"), "trit_adaptive", target=1 << 16)


@query
def quatrit_roundtrip(spark, sf_dir):
    from dataclasses import replace

    return _roundtrip(corpus(spark, sf_dir, "benchmark"), "trit_adaptive", ctx=replace(SMALL, kinds=4), forget=256)


@query
def midpoint_roundtrip(spark, sf_dir):
    lists = corpus(spark, sf_dir, "conversations")
    return coders.roundtrip_mismatches(lists.gaps, measures.list_gaps(measures.list_bytes(lists, "midpoint"), "midpoint", lists.d))


@query
def coder_overhead(spark, sf_dir):
    """Real against ideal bits of the adaptive coder, by segment."""
    s = coders.encode(corpus(spark, sf_dir, "conversations"), "trit_adaptive", target=1 << 16)
    return s.select("seg", "n_lists", "n_ints", "symbols", (8 * F.length("payload")).cast("long").alias("bits"), F.round("ideal_bits", 1).alias("ideal_bits"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main comparison on documents by bisection: bits per integer of each method, all parts."""
    return measures.totals(measures.compare(corpus(spark, sf_dir, "documents", "bisect"), ("delta", *measures.MAIN)))


QUERIES["main_comparison"] = flagship
for _name in WORKLOADS:
    QUERIES[_name] = lambda spark, sf_dir, name=_name: run_workload(spark, name, sf_dir)


from . import surround  # noqa: E402, F401  registers its queries
