"""Queries on what stands around the methods: joins along an order, windows, dates, samples, further measures, round trips."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from ..functions import closed
from ..functions.text import html_text, message_text, tokens
from ..operators import baselines, clusters, codecs, coders, modelled, postings, relational, trits
from ..operators.ids import cut, together
from ..sources.tables import read_table
from ..streaming import segments as streaming
from . import measures
from .corpora import column_lists, corpus, documents_of
from .queries import SMALL, _letters, _pairs, query

#: Codecs that the round-trip query leaves out: unary codes of wide gaps, and the quadratic partition of long lists.
SLOW = ("unary", "pef_opt")
LENGTH_CODES = ("delta", "gamma", "vbyte", "nibble", "zeta2", "zeta3", "zeta4")


@query
def page_terms(spark, sf_dir):
    """Markup to text by patterns."""
    pages = read_table(spark, sf_dir, "pages")
    return tokens(pages, "page_id", html_text(F.col("html"))).groupBy("term").agg(F.count(F.lit(1)).alias("n"))


@query
def message_terms(spark, sf_dir):
    """Header fields as text before the body."""
    turns = read_table(spark, sf_dir, "conversations")
    text = message_text(F.col("role"), F.col("turn").cast("string"), F.col("text"))
    return tokens(turns.withColumn("doc", F.col("conv_id") * 65536 + F.col("turn")), "doc", text).groupBy("term").agg(F.count(F.lit(1)).alias("n"))


@query
def dense_bitmaps(spark, sf_dir):
    return relational.dense_bitmaps(_pairs(spark, sf_dir), 100)


@query
def length_codes(spark, sf_dir):
    """List lengths by every code tried."""
    lists = corpus(spark, sf_dir)
    out = None
    for c in LENGTH_CODES:
        one = baselines.length_bits(lists, c).select(F.lit(c).alias("code"), "words", "length_bits")
        out = one if out is None else out.unionByName(one)
    return out


@query
def model_share(spark, sf_dir):
    """The parameters that the rules choose, and the static model's share of the integers."""
    rows = []
    for table in ("benchmark", "conversations", "documents"):
        i = corpus(spark, sf_dir, table).i
        k, w, k_init = trits.choose_static(i, most=coders.MAX_CONTEXTS)
        c = trits.hybrid(k, w, k_init)
        a = trits.choose_adaptive(i)
        rows.append((table, i, k, w, k_init, c.model_bits(8), round(c.model_bits(8) / i, 6), a[0], a[3], trits.state_bytes(trits.hybrid(*a[:3]))))
    return spark.createDataFrame(rows, "dataset string, ints bigint, k bigint, w bigint, k_init bigint, model_bits bigint, share double, adaptive_k bigint, adaptive_n bigint, state_bytes bigint")


@query
def size_split(spark, sf_dir):
    """Megabytes of lengths, model and payload, side by side."""
    return measures.by_part(measures.compare(corpus(spark, sf_dir, "conversations")))


@query
def overheads(spark, sf_dir):
    return measures.overheads(corpus(spark, sf_dir, "conversations"))


@query
def halving_clocks(spark, sf_dir):
    """Counts halved by context, by one clock for all, and never; all ones or a stored static model to start with."""
    lists = corpus(spark, sf_dir, "conversations")
    grid = {"m": (trits.hybrid(7, 7, 8), 256)}
    _, q = coders.static_model(lists.gaps, trits.hybrid(7, 7, 8))
    rows = []
    for clock, prior in (("context", None), ("global", None), ("context", (2, 2, 1)), ("context", "static")):
        own = coders.prior_of(q) if prior == "static" else prior
        bits = coders.sweep_adaptive(lists, grid, halving=clock, prior=own).first().payload_bits
        rows.append((clock, str(prior), round(bits, 1)))
    return spark.createDataFrame(rows, "halving string, prior string, payload_bits double")


@query
def codec_roundtrips(spark, sf_dir):
    """Every codec of single lists, coded and decoded, and its bytes against the priced bits."""
    names = [n for n in codecs.CODECS if n not in SLOW]
    return measures.verify(corpus(spark, sf_dir, "benchmark"), names).select("codec", "lists", "ints", "mismatches", "wrong_sizes")


@query
def model_roundtrips(spark, sf_dir):
    """The coders with a counted model, and variants of the trit coders, coded and decoded."""
    lists, wide = together(lambda table: corpus(spark, sf_dir, table), ("benchmark", "conversations"))

    def packed(mantissa: str, selector: str):
        m = modelled.packed_model(lists, mantissa)
        return modelled.packed_decode(cut(modelled.packed_encode(lists, m, mantissa, selector)), m, mantissa, selector)

    def bitmap(k: int, w: int):
        q = modelled.bitmap_model(lists, k, w)
        return modelled.bitmap_decode(cut(modelled.bitmap_encode(lists, q, k, w)), q, lists.d, k, w)

    def trit(how: dict):
        return coders.decode(cut(coders.encode(wide, **how)))

    runs = {f"packed_arith:{m}:{s}": (lists, packed, (m, s)) for m, s in (("modelled", "arith"), ("raw", "arith"), ("modelled", "raw6"))}
    runs |= {f"bitmap:k={k}:w={w}": (lists, bitmap, (k, w)) for k, w in ((2, 0), (3, 5))}
    for name, how in (("static lanes", {"method": "trit_static", "lanes_": 20}), ("adaptive lanes", {"lanes_": 20}), ("one lane", {"lanes_": 1}), ("global halving", {"halving": "global", "forget": 500, "lanes_": 8}), ("static prior", {"prior": "static", "lanes_": 8}), ("quatrit lanes", {"ctx": replace(SMALL, kinds=4), "forget": 256, "lanes_": 8})):
        runs[f"trits:{name}"] = (wide, trit, (how,))

    def mismatches(name: str) -> tuple[str, int]:
        coded, way, with_ = runs[name]
        return name, coders.roundtrip_mismatches(coded.gaps, way(*with_)).first().mismatches

    # the longest, which have few tasks, side by side and first
    return spark.createDataFrame(together(mismatches, reversed(runs), 6)[::-1], "coder string, mismatches bigint")


@query
def clustered_roundtrips(spark, sf_dir):
    """Split by reference lists, coded, decoded and merged again."""
    lists = corpus(spark, sf_dir, "benchmark")
    own = cut(_letters(postings.to_ids(lists.gaps)))
    return clusters.clustered_roundtrips(lists, own, 8, ("midpoint", "pef_approx", "midpoint_block:trimmed", "trit_static", "trit_adaptive"))


@query
def codec_times(spark, sf_dir):
    """Microseconds per integer, mean of ten runs, and their ratios to the midpoint coder's."""
    rows = []
    for table in ("conversations", "documents"):
        lists = corpus(spark, sf_dir, table)
        got = {m: measures.time_codec(lists, m, 10) for m in ("midpoint", "delta", "trit_static", "trit_adaptive")}
        base = got["midpoint"]
        rows += [(table, m, lists.i, 10, up, down, up / base[0], down / base[1]) for m, (up, down) in got.items()]
    return spark.createDataFrame(rows, "dataset string, method string, ints bigint, runs int, compress_us double, decompress_us double, compress_ratio double, decompress_ratio double")


@query
def trit_rows(spark, sf_dir):
    """Trits with places and contexts, by the table function."""
    gaps = corpus(spark, sf_dir, "benchmark").gaps
    return gaps.lateralJoin(relational.ExplodeTrits(F.col("gaps").outer(), F.lit(2), F.lit(3), F.lit(1))).select("term", "pos", "trit", "ctx")


@query
def sampled_terms(spark, sf_dir):
    """Words sampled by hash, for the choice of parameters."""
    gaps = relational.sample_by_hash(corpus(spark, sf_dir).gaps, "term", 100)
    return postings.long_gaps(gaps).agg(F.count_distinct("term").alias("words"), F.count(F.lit(1)).alias("ints"), F.sum(closed.bitlen(F.col("gap"))).alias("trits"))


@query
def length_statistics(spark, sf_dir):
    """Percentiles of list lengths, and whether the sketch of the number of words is near."""
    n = baselines.per_list(corpus(spark, sf_dir))
    near = F.abs(F.approx_count_distinct("term", 0.02) - F.count(F.lit(1))) <= 0.1 * F.count(F.lit(1))
    return n.agg(F.count(F.lit(1)).alias("words"), F.percentile("n", F.lit(0.5)).alias("median"), F.percentile("n", F.lit(0.99)).alias("p99"), F.max_by("term", F.struct("n", "term")).alias("longest"), F.mode("n", True).alias("mode"), near.alias("near"))


@query
def code_rollup(spark, sf_dir):
    """Sizes by language and list class, with subtotals."""
    docs = documents_of(spark, sf_dir, "documents")
    tok = tokens(docs, "doc", "text").join(docs.select("doc", "lang"), "doc")
    return tok.groupBy("lang", "term").agg(F.count(F.lit(1)).alias("n")).withColumn("size", closed.bitlen(F.col("n"))).rollup("lang", "size").agg(F.count(F.lit(1)).alias("lists"), F.sum("n").alias("ints"))


@query
def asof_events(spark, sf_dir):
    """Each purchase with the user's last view at or before it."""
    e = read_table(spark, sf_dir, "events")
    views = e.where("event_type = 'view'")
    bought = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    return relational.asof_join(bought, views, "user_id", "ts", "event_id", "view_id").select("event_id", "view_id")


@query
def interval_events(spark, sf_dir):
    """Events of a user in the 36 hours from each of the user's signups on."""
    e = read_table(spark, sf_dir, "events")
    spans = e.where("event_type = 'signup'").select("user_id", F.col("event_id").alias("signup"), F.col("ts").alias("start"), (F.col("ts") + F.expr("INTERVAL 36 HOURS")).alias("until"))
    hits = relational.interval_join(spans, e.select("user_id", "event_id", "ts"), "user_id", "start", "until", "ts")
    return hits.groupBy("signup").agg(F.count(F.lit(1)).alias("n"), F.max("event_id").alias("last"))


@query
def daily_lists(spark, sf_dir):
    """Day -> events."""
    e = read_table(spark, sf_dir, "events")
    lists = column_lists(e, F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd"), F.col("event_id") + 1).gaps
    return postings.whole_texts(lists).select("term", "n", F.md5("gaps").alias("gaps"))


@query
def windowed_counts(spark, sf_dir):
    """The streaming windows over the whole table."""
    w = streaming.windowed_counts(read_table(spark, sf_dir, "events"), "6 hours", "3 hours")
    return w.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n")


@query
def session_counts(spark, sf_dir):
    s = streaming.sessions(read_table(spark, sf_dir, "events"), "12 hours")
    return s.select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss.SSSSSS").alias("start"), "user_id", "n")


@query
def variant_values(spark, sf_dir):
    """A member of a VARIANT as an indexable value."""
    v = F.try_variant_get(F.try_parse_json("props"), "$.k", "bigint")
    return read_table(spark, sf_dir, "events").groupBy(v.alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query
def segment_headers(spark, sf_dir):
    """What stands in the headers of segments."""
    s = coders.encode(corpus(spark, sf_dir, "benchmark"), "trit_adaptive", target=1 << 11)
    h = F.col("header").cast("string")
    return s.agg(F.sum("n_ints").alias("ints"), F.sum("n_lists").alias("lists"), F.max(F.get_json_object(h, "$.forget")).alias("forget"), F.max(F.get_json_object(h, "$.ctx.k")).alias("k"))
