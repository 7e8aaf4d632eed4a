"""Boolean queries over lists, and top lists."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def lookup(pairs: DataFrame, terms: Iterable[str]) -> DataFrame:
    return pairs.where(F.col("term").isin(list(terms)))


def and_query(pairs: DataFrame, terms: Iterable[str]) -> DataFrame:
    """(ord) of documents with all words; pairs are distinct."""
    terms = list(dict.fromkeys(terms))
    return lookup(pairs, terms).groupBy("ord").agg(F.count(F.lit(1)).alias("k")).where(F.col("k") == len(terms)).select("ord")


def or_query(pairs: DataFrame, terms: Iterable[str]) -> DataFrame:
    return lookup(pairs, terms).select("ord").distinct()


def not_query(pairs: DataFrame, terms: Iterable[str], without: Iterable[str]) -> DataFrame:
    return or_query(pairs, terms).join(or_query(pairs, without), "ord", "left_anti")


def top_terms(pairs: DataFrame, k: int) -> DataFrame:
    return pairs.groupBy("term").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "term").limit(k)


def top_docs(pairs: DataFrame, terms: Iterable[str], k: int) -> DataFrame:
    """(ord, hits): documents with most of the words."""
    return lookup(pairs, terms).groupBy("ord").agg(F.count(F.lit(1)).alias("hits")).orderBy(F.desc("hits"), "ord").limit(k)


def segments_for(segments: DataFrame, terms: Iterable[str]) -> DataFrame:
    """The segments that may hold a word, by their least and greatest words: pushed down to the files."""
    keep = F.lit(False)
    for t in terms:
        keep = keep | ((F.col("term_lo") <= t) & (F.col("term_hi") >= t))
    return segments.where(keep)


def blocks(lists: DataFrame, size: int = 128) -> DataFrame:
    """(term, blk, first, max, n): a directory of the blocks of each list, for skipping."""
    rows = lists.select("term", "shard", F.posexplode("gaps").alias("i", "gap"), "before")
    at = F.col("before") + F.sum("gap").over(Window.partitionBy("term", "shard").orderBy("i"))
    return rows.withColumn("id", at).groupBy("term", "shard", F.floor(F.col("i") / size).cast("int").alias("blk")).agg(F.min("id").alias("first"), F.max("id").alias("max"), F.count(F.lit(1)).alias("n"))


def in_blocks(directory: DataFrame, ids: DataFrame, span: int = 4096) -> DataFrame:
    """(ord, term, shard, blk): which blocks may hold each id. Both sides meet by ranges of ``span`` ids, so neither is
    broadcast: a block is in as many ranges as it spans, at most its own length in ids over ``span``, and one more."""
    cells = F.sequence(F.floor(F.col("first") / span), F.floor(F.col("max") / span))
    rows = directory.withColumn("cell", F.explode(cells)).join(ids.withColumn("cell", F.floor(F.col("ord") / span)), "cell")
    return rows.where("ord between first and max").select("ord", "term", "shard", "blk")
