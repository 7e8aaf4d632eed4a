"""Readers and writers: tables with explicit schemas, gap lists as text, indexes, and a Python data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

SCHEMAS = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "pages": "page_id bigint, url string, html string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "region": "r_regionkey bigint, r_name string",
}


def read_table(spark: SparkSession, directory: str, name: str, fmt: str = "parquet") -> DataFrame:
    """A table of a folder; text tables with their schema given, so that nothing is inferred."""
    reader = spark.read
    if fmt != "parquet" and name in SCHEMAS:
        reader = reader.schema(SCHEMAS[name])
    if fmt == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    return reader.format(fmt).load(f"{directory}/{name}.{fmt}")


def write_gap_text(lists: DataFrame, path: str) -> None:
    """One list shard on a line: word, tab, shard, tab, last id before, tab, gaps apart by blanks."""
    lists.select(F.concat_ws("\t", "term", F.col("shard").cast("string"), F.col("before").cast("string"), F.concat_ws(" ", F.col("gaps").cast("array<string>"))).alias("value")).write.mode("overwrite").text(path)


def read_gap_text(spark: SparkSession, path: str) -> DataFrame:
    c = F.split("value", "\t")
    rows = spark.read.text(path).select(c[0].alias("term"), c[1].cast("long").alias("shard"), c[2].cast("long").alias("before"), F.split(c[3], " ").cast("array<bigint>").alias("gaps"))
    n = rows.groupBy("term").agg(F.sum(F.size("gaps")).cast("long").alias("n"))
    return rows.join(n, "term").select("term", "n", "shard", "before", "gaps")


def write_index(segments: DataFrame, path: str, index_id: str, mode: str = "append") -> None:
    """Parquet by index and method, rows by first word, so that min/max statistics prune look-ups."""
    segments.withColumn("index_id", F.lit(index_id)).repartitionByRange("method", "term_lo").sortWithinPartitions("method", "term_lo").write.mode(mode).partitionBy("index_id", "method").parquet(path)


def read_index(spark: SparkSession, path: str, index_id: str | None = None, method: str | None = None) -> DataFrame:
    df = spark.read.parquet(path)
    for name, value in (("index_id", index_id), ("method", method)):
        df = df.where(F.col(name) == value) if value is not None else df
    return df


class SegmentPartition(InputPartition):
    def __init__(self, rows):
        self.rows = rows


class PostingsSource(DataSource):
    """``spark.read.format("postings").option("path", ...)``: the (term, ord) pairs of an index in the files of a folder
    that the driver and the executors both see. A partition is a file."""

    @classmethod
    def name(cls) -> str:
        return "postings"

    def schema(self) -> str:
        return "term string, ord bigint"

    def reader(self, schema: StructType) -> DataSourceReader:
        return PostingsReader(self.options)


class PostingsReader(DataSourceReader):
    def __init__(self, options):
        self.path = options["path"].removeprefix("file://")

    def partitions(self):
        import glob

        return [SegmentPartition(p) for p in sorted(glob.glob(f"{self.path}/**/*.parquet", recursive=True))]

    def read(self, partition):
        import numpy as np
        import pyarrow.parquet as pq

        from postings_engine.operators.coders import decoded

        for r in pq.ParquetFile(partition.rows).read().to_pylist():
            if r["model"]:
                raise ValueError("static segments need their model: read them with read_index and decode")
            gaps, n = decoded(r | {"method": "trit_adaptive"}, b"")
            lists = np.split(gaps, np.cumsum(n)[:-1])
            for term, before, gaps in zip(r["terms"], r["before"], lists, strict=True):
                for x in (before + np.cumsum(gaps)).tolist():
                    yield term, x
