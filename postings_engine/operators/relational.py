"""Joins along an order, samples by hash, and table functions over lists."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf
from pyspark.sql.window import Window


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, value: str, name: str = "last", bucket: str = "day") -> DataFrame:
    """``left`` with the ``value`` that ``right`` had last at or before each row's ``ts``, by ``key``; null if there is none.
    Of values at one time the greatest counts.

    Both sides meet by key and time bucket, so a key with any number of rows is spread; what a bucket takes over from
    those before it is one value for each key and bucket.
    """
    b = F.date_trunc(bucket, F.col(ts))
    marks = right.groupBy(F.col(key).alias("__k"), F.col(ts).alias("__t")).agg(F.max(value).alias("__v")).withColumn("__b", F.date_trunc(bucket, F.col("__t")))
    rows = left.withColumns({"__k": F.col(key), "__t": F.col(ts), "__b": b, "__v": F.lit(None).cast(right.schema[value].dataType), "__own": F.lit(1)})
    both = rows.unionByName(marks.withColumn("__own", F.lit(0)), allowMissingColumns=True)
    inside = F.last("__v", ignorenulls=True).over(Window.partitionBy("__k", "__b").orderBy("__t", "__own").rowsBetween(Window.unboundedPreceding, 0))
    seen = both.groupBy("__k", "__b").agg(F.max_by("__v", F.when(F.col("__v").isNotNull(), F.col("__t"))).alias("__end"))
    before = F.last("__end", ignorenulls=True).over(Window.partitionBy("__k").orderBy("__b").rowsBetween(Window.unboundedPreceding, -1))  # over buckets
    carried = seen.select(F.col("__k").alias("__kk"), F.col("__b").alias("__bb"), before.alias("__before"))
    out = both.withColumn("__in", inside).where("__own = 1").join(carried, F.col("__k").eqNullSafe(F.col("__kk")) & (F.col("__b") == F.col("__bb")), "left")
    return out.select(*left.columns, F.coalesce("__in", "__before").alias(name))


def interval_join(spans: DataFrame, rows: DataFrame, key: str, start: str, end: str, ts: str, bucket_seconds: int = 86_400) -> DataFrame:
    """``rows`` joined with the ``spans`` of their key that hold their time (start <= ts < end): an equi-join by key and time
    bucket, each span in the buckets that it touches, then the exact test. Columns other than the key must not clash."""
    at = lambda c: F.floor(F.unix_micros(F.col(c).cast("timestamp")) / (bucket_seconds * 1_000_000))
    cells = spans.withColumn("__b", F.explode(F.sequence(at(start), at(end))))
    return cells.join(rows.withColumn("__b", at(ts)), [key, "__b"]).where((F.col(ts) >= F.col(start)) & (F.col(ts) < F.col(end))).drop("__b")


def sample_by_hash(df: DataFrame, column: str, per_mille: int) -> DataFrame:
    """Rows whose ``column`` falls among the first of 1000 classes of its md5: all rows of a value or none, in any engine."""
    h = F.conv(F.substring(F.md5(F.col(column)), 1, 8), 16, 10).cast("long")
    return df.where(F.pmod(h, F.lit(1000)) < per_mille)


def dense_bitmaps(pairs: DataFrame, least: int) -> DataFrame:
    """(term, bucket, n): the lists of ``least`` ids and more as bitmaps of 32768 bits, and the ones in each."""
    some = pairs.groupBy("term").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= least).select("term")
    maps = pairs.join(some, "term", "left_semi").groupBy("term", F.bitmap_bucket_number("ord").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("ord")).alias("bits"))
    return maps.select("term", "bucket", F.bitmap_count("bits").alias("n"))


@udtf(returnType="pos bigint, trit int, ctx bigint")
class ExplodeTrits:
    """explode_trits(gaps, k, w, k_init): the trits of a list with their places and contexts."""

    def eval(self, gaps, k: int, w: int, k_init: int):
        import numpy as np

        from postings_engine.operators import trits

        if gaps:
            s, _ = trits.trits_of(np.array(gaps, np.int64))
            ids = trits.hybrid(k, w, k_init).ids(s, np.arange(len(s)))
            yield from zip(range(len(s)), s.tolist(), ids.tolist(), strict=True)


@udtf(returnType="term string, ord bigint")
class DecodeSegment:
    """decode_segment(row as a struct of a segment's columns, model): the postings of one segment."""

    def eval(self, row, model):
        import numpy as np

        from postings_engine.operators.coders import decoded

        row = row.asDict() if hasattr(row, "asDict") else dict(row)
        gaps, n = decoded(row, bytes(model or b""))
        for term, before, own in zip(row["terms"], row["before"], np.split(gaps, np.cumsum(n)[:-1]), strict=True):
            for x in (before + np.cumsum(own)).tolist():
                yield term, x


def register(spark: SparkSession) -> None:
    spark.udtf.register("explode_trits", ExplodeTrits)
    spark.udtf.register("decode_segment", DecodeSegment)


def midpoint_total() -> Column:
    """A grouped aggregate: bits of the midpoint coder over lists (ids, u)."""
    import numpy as np
    from pyspark.sql.functions import pandas_udf

    from .codecs import midpoint_bits

    @pandas_udf("bigint")
    def f(ids: pd.Series, u: pd.Series) -> int:
        return int(sum(midpoint_bits(np.asarray(i), int(d)) for i, d in zip(ids, u, strict=True)))

    return f
