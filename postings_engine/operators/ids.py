"""Dense numbers and running totals over a global order, without ever sorting in one task."""

from __future__ import annotations

import os
import tempfile
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from typing import TypeVar

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder that the cluster names. Where none is named a local session, as in tests, takes a folder of its
    own; on a cluster that is an error."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
    named = named or os.path.join(tempfile.gettempdir(), "checkpoints", spark.sparkContext.applicationId)
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(named)
    return named


def cut(df: DataFrame) -> DataFrame:
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


A, B = TypeVar("A"), TypeVar("B")


def together(f: Callable[[A], B], items: Iterable[A], at_once: int = 4) -> list[B]:
    """[f(x) for x in items], some at a time: jobs of one take the cores that another's last or only task leaves idle."""
    with ThreadPoolExecutor(at_once) as pool:
        return list(pool.map(f, items))


def ranked(df: DataFrame, *order: Column, name: str = "ord") -> DataFrame:
    """``df`` with dense numbers 1.. in the order given: a range sort, its partitions' counts, and offsets.

    What comes to the driver is one count for each partition.
    """
    rows = cut(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__m", F.monotonically_increasing_id()))
    part = F.shiftright("__m", 33)
    counts = dict(rows.groupBy(part.alias("p")).count().collect())
    offsets, at = [], 0
    for p in sorted(counts):
        offsets.append((p, at))
        at += counts[p]
    known = df.sparkSession.createDataFrame(offsets, "__p bigint, __o bigint")  # one row for each partition
    out = rows.join(F.broadcast(known), part == F.col("__p"))
    return out.withColumn(name, F.col("__o") + F.col("__m").bitwiseAND((1 << 33) - 1) + 1).drop("__m", "__p", "__o")


def running(df: DataFrame, value: str, name: str, *order: Column) -> DataFrame:
    """``df`` with the sum of ``value`` over all rows before and with each, in a global order."""
    rows = cut(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__m", F.monotonically_increasing_id()))
    part = F.shiftright("__m", 33)
    sums = {r.p: r.s for r in rows.groupBy(part.alias("p")).agg(F.sum(value).alias("s")).collect()}
    offsets, at = [], 0
    for p in sorted(sums):
        offsets.append((p, at))
        at += sums[p]
    known = df.sparkSession.createDataFrame(offsets, "__p bigint, __o bigint")
    within = F.sum(value).over(Window.partitionBy("__p").orderBy("__m").rowsBetween(Window.unboundedPreceding, 0))
    return rows.join(F.broadcast(known), part == F.col("__p")).withColumn(name, F.col("__o") + within).drop("__m", "__p", "__o")
