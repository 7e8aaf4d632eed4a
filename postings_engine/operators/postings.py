"""Inverted lists, gaps, trits and what can be counted on them without a coder."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import closed
from ..functions.text import tokens
from .ids import cut
from .ordering import order_by

#: Ids of one shard of a list; no row ever holds more.
SHARD = 1 << 20
#: Maps of at most so many documents (16 bytes each) are broadcast; postings never are.
SMALL_MAP = 1 << 20


@dataclass(frozen=True)
class Lists:
    """``gaps``: (term, n, shard, before, gaps), a row for each shard of a list; n counts the whole list and ``before``
    is the last id of the shards before. ``d`` documents, ``w`` words, ``i`` integers."""

    gaps: DataFrame
    d: int
    w: int
    i: int


def postings(tok: DataFrame, doc_map: DataFrame, d: int | None = None) -> DataFrame:
    """(term, ord) of (doc, term) and (doc, ord). ``d``, if known, is the number of documents and says whether their map is
    broadcast. Left to itself the planner may take the postings for the smaller side: it knows texts before they are split."""
    side = F.broadcast(doc_map) if d is not None and d <= SMALL_MAP else doc_map.hint("merge")
    return tok.join(side, "doc").select("term", "ord")


def postings_from_column(df: DataFrame, value: Column, row: Column) -> DataFrame:
    """(term, ord) of any column: value -> numbers of the rows that hold it, each once; nulls are in no list."""
    return df.select(value.cast("string").alias("term"), row.cast("long").alias("ord")).where("term is not null and ord is not null").distinct()


def to_gaps(pairs: DataFrame, shard: int = SHARD) -> DataFrame:
    """(term, n, shard, before, gaps) of distinct (term, ord). A frequent word's list is spread over shards by range; only
    a shard's count and last id, never its ids, meet those of the word's other shards in a task."""
    own = F.floor((F.col("ord") - 1) / shard).cast("long").alias("shard")
    lists = pairs.groupBy("term", own).agg(F.sort_array(F.collect_list("ord")).alias("ids"))
    lists = lists.where("term is not null and shard is not null")  # the join's own filter, on both uses alike: one shuffle serves both
    ends = lists.select("term", "shard", F.element_at("ids", -1).alias("last"), F.size("ids").alias("m"))  # from the same shuffle
    word = Window.partitionBy("term")
    ends = ends.select("term", "shard", F.coalesce(F.lag("last").over(word.orderBy("shard")), F.lit(0).cast("long")).alias("before"), F.sum("m").over(word).cast("long").alias("n"))
    gaps = F.transform("ids", lambda x, i: x - F.when(i == 0, F.col("before")).otherwise(F.get("ids", i - 1)))
    return lists.join(ends, ["term", "shard"]).select("term", "n", "shard", "before", gaps.alias("gaps"))


def to_ids(gaps: DataFrame) -> DataFrame:
    """(term, ord) back from shards of gaps, running sums over Arrow arrays."""

    def run(batches):
        for b in batches:
            col = b.column(2)
            n = np.diff(col.offsets.to_numpy())
            total = np.cumsum(col.flatten().to_numpy(zero_copy_only=False))
            ends = np.cumsum(n)
            start = np.concatenate([[0], total])[ends - n]  # sums of the rows before
            ords = total + np.repeat(b.column(1).to_numpy(zero_copy_only=False) - start, n)
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(np.repeat(np.arange(len(n)), n))), pa.array(ords)], names=["term", "ord"])

    return gaps.select("term", "before", "gaps").mapInArrow(run, "term string, ord bigint")


def whole_texts(gaps: DataFrame) -> DataFrame:
    """(term, n, gaps): one row for each list, its gaps as text apart by blanks, shards joined in order. A row holds a whole
    list's text, which is what is asked for here; nothing that codes or counts goes this way."""
    own = gaps.select("term", "n", F.struct("shard", F.array_join(F.col("gaps").cast("array<string>"), " ").alias("text")).alias("s"))
    return own.groupBy("term", "n").agg(F.array_join(F.transform(F.sort_array(F.collect_list("s")), lambda s: s["text"]), " ").alias("gaps"))


def long_gaps(lists: DataFrame) -> DataFrame:
    """(term, n, shard, i, gap, before): one row for each integer."""
    return lists.select("term", "n", "shard", F.posexplode("gaps").alias("i", "gap"))


def build(tok: DataFrame, doc_map: DataFrame | None = None, keep: bool = True) -> Lists:
    """Lists of (doc, term), documents numbered by ``doc_map``, by id if none is given."""
    if doc_map is None:
        doc_map = order_by(tok.select("doc").distinct(), "doc")
    d = doc_map.count()
    gaps = to_gaps(postings(tok, doc_map, d))
    gaps = cut(gaps) if keep else gaps
    w, i = gaps.agg(F.coalesce(F.sum((F.col("before") == 0).cast("long")), F.lit(0)), F.coalesce(F.sum(F.size("gaps")), F.lit(0))).first()
    return Lists(gaps, d, w, i)


def lists_of_docs(docs: DataFrame, id_col: str = "doc_id", text: Column | str = "text", doc_map: DataFrame | None = None, **how) -> Lists:
    """All documents count in d, also those without a word."""
    return build(tokens(docs, id_col, text, **how), order_by(docs, id_col) if doc_map is None else doc_map)


def collection_stats(lists: Lists) -> DataFrame:
    own = lists.gaps.agg(F.sum(F.when(F.col("before") == 0, 1).otherwise(0)).cast("long").alias("w"), F.sum(F.size("gaps")).cast("long").alias("i"), F.max("n").alias("longest"))
    d = F.lit(lists.d).cast("long")
    return own.select(d.alias("d"), "w", "i", "longest", (F.col("i") / (F.col("w") * d)).alias("density"))


def filter_min_len(lists: DataFrame, least: int) -> DataFrame:
    return lists.where(F.col("n") >= least)


def threshold_for_share(lists: DataFrame, share: float) -> int:
    """The greatest m such that lists of length >= m hold at least ``share`` of all integers. One row for each length comes
    to the window, not one for each list."""
    by = lists.where("before = 0").groupBy("n").agg((F.col("n") * F.count(F.lit(1))).alias("i"))
    above = F.sum("i").over(Window.orderBy(F.desc("n")).rowsBetween(Window.unboundedPreceding, 0))
    total = F.sum("i").over(Window.partitionBy())
    hit = by.withColumns({"a": above, "t": total}).where(F.col("a") >= share * F.col("t"))
    return hit.agg(F.max("n")).first()[0] or 1


def check_ids(ids: list[int]) -> None:
    """Lists are strictly increasing and start at 1 or above."""
    if any(b <= a for a, b in zip([0, *ids], ids, strict=False)):
        raise ValueError("ids must be strictly increasing, from 1 on")


def checked(lists: DataFrame) -> DataFrame:
    """``lists``, failing on a gap below 1 (an id 0, a repeated or a descending one)."""
    return lists.withColumn("gaps", F.when(F.exists("gaps", lambda g: g < 1), F.raise_error(F.lit("ids must be strictly increasing, from 1 on")).cast("array<bigint>")).otherwise(F.col("gaps")))


def trit_strings(lists: DataFrame) -> DataFrame:
    """(term, shard, trits) as strings of 0, 1, 2."""
    return lists.select("term", "shard", F.array_join(F.transform("gaps", closed.trit_string), "").alias("trits"))


def quatrit_strings(lists: DataFrame) -> DataFrame:
    """As :func:`trit_strings`, with a 3 at the end of each list."""
    last = F.max("shard").over(Window.partitionBy("term"))
    return lists.withColumn("__last", last).select("term", "shard", F.concat(F.array_join(F.transform("gaps", closed.trit_string), ""), F.when(F.col("shard") == F.col("__last"), "3").otherwise("")).alias("trits"))


def symbol_counts(lists: Lists) -> DataFrame:
    """Integers, trits, bits of the matrix, and how often each trit occurs."""
    g = long_gaps(lists.gaps)
    ones = F.length(F.replace(F.bin("gap"), F.lit("0"), F.lit("")))
    return g.agg(F.count(F.lit(1)).alias("ints"), F.sum(closed.bitlen(F.col("gap"))).alias("trits"), F.sum(closed.bitlen(F.col("gap")) - ones).cast("long").alias("zeros"), F.sum(ones - 1).cast("long").alias("ones"), F.count(F.lit(1)).alias("twos")).withColumn("matrix_bits", F.lit(lists.d * lists.w).cast("long"))


def bit_runs(lists: Lists) -> DataFrame:
    """(term, zeros, ones, tail): zeros and ones of each row of the matrix, and the zeros after its last one."""
    last = F.aggregate("gaps", F.col("before"), lambda s, g: s + g)
    return lists.gaps.select("term", "n", last.alias("last")).groupBy("term").agg(F.max("n").alias("ones"), (F.lit(lists.d) - F.max("last")).alias("tail")).select("term", (F.lit(lists.d) - F.col("ones")).alias("zeros"), "ones", "tail")
