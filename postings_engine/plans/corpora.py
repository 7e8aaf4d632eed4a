"""The given tables as collections of documents, in any order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import dedup_docs, html_text, terms, tokens, trim_urls
from ..operators import ordering
from ..operators.ids import cut
from ..operators.postings import Lists, build, postings_from_column, to_gaps
from ..sources.tables import read_table


def documents_of(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """(doc, text, and the columns that orders need) of a text table; a turn of a conversation is a document."""
    df = read_table(spark, sf_dir, table)
    if table == "documents":
        return df.select(F.col("doc_id").alias("doc"), "text", "lang", "source")
    if table == "pages":
        return df.select(F.col("page_id").alias("doc"), trim_urls(html_text(F.col("html"))).alias("text"), "url")
    if table == "conversations":
        return df.select((F.col("conv_id") * 65536 + F.col("turn")).alias("doc"), "text", "role")
    return df.select(F.col("item_id").alias("doc"), "text")


def corpus(spark: SparkSession, sf_dir: str, table: str = "documents", order: str = "id", where: Column | None = None, dedup: bool = False, tok: DataFrame | None = None) -> Lists:
    """Lists of a table's documents. Orders: id, bisect, url, random, or 'source' (language, source, id). ``tok`` are the terms of
    all documents, from :func:`terms_of`, where several orders read them."""
    docs = documents_of(spark, sf_dir, table)
    if where is not None:
        docs = docs.where(where)
    if dedup:
        docs = dedup_docs(docs, "text", "doc")
    if tok is None:
        tok = kept_terms(docs) if order == "bisect" else tokens(docs, "doc", "text")  # each level reads them again
    if order == "bisect":
        found = ordering.order_bisect(tok)
        rest = docs.select("doc").join(found, "doc", "left_anti")  # documents without a word come last
        n = found.count()
        doc_map = found if rest.isEmpty() else found.unionByName(ordering.order_by(rest, "doc").withColumn("ord", F.col("ord") + n))
    elif order == "random":
        doc_map = ordering.order_random(docs, "doc")
    else:
        doc_map = ordering.order_by(docs, "doc", *{"id": (), "url": ("url",), "source": ("lang", "source")}[order])
    return build(tok, doc_map)


def terms_of(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """(doc, term) of a table's documents, made once."""
    return kept_terms(documents_of(spark, sf_dir, table))


def kept_terms(docs: DataFrame) -> DataFrame:
    """(doc, term), kept as a row for each document, which takes less disk than one for each term."""
    rows = docs.select(F.col("doc").cast("long").alias("doc"), F.array_distinct(terms(F.col("text"))).alias("terms"))
    return cut(rows).select("doc", F.explode("terms").alias("term"))


def column_lists(df: DataFrame, value: Column, row: Column) -> Lists:
    """Value -> rows, of a table's column; rows are numbers from 1."""
    gaps = cut(to_gaps(postings_from_column(df, value, row)))
    last = F.aggregate("gaps", F.col("before"), lambda s, g: s + g)
    d, w, i = gaps.agg(F.coalesce(F.max(last), F.lit(0)), F.coalesce(F.sum((F.col("before") == 0).cast("long")), F.lit(0)), F.coalesce(F.sum(F.size("gaps")), F.lit(0))).first()
    return Lists(gaps, d, w, i)
