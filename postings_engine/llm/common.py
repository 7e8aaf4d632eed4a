"""Shared plumbing of the text operators: Arrow scans, checkpoints, bit filters."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DataType, LongType, StructField, StructType

#: Rows and bytes of one Arrow batch handed to Python: bounds a worker's memory however long the texts are.
BATCH_ROWS, BATCH_BYTES = 500, "8m"
#: The white space that ends a word in most contracts, as a Java regular expression class.
SPACE = r"[\x20\x09-\x0D]"


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def small_batches(spark: SparkSession) -> None:
    """Runtime SQL settings only; they hold for the plans made afterwards. Batches that are smaller already stay so."""
    try:
        if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) in range(1, BATCH_ROWS):
            return
    except Exception:  # not a number: a session without that setting
        pass
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
    try:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)
    except Exception:  # a session without that setting still has the row bound
        pass


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder that the cluster names. Where none is named a local session, as in tests, takes a folder of its
    own; on a cluster that is an error."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
        named = os.path.join(tempfile.gettempdir(), "checkpoints", spark.sparkContext.applicationId)
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(named)
    return named


def cut(df: DataFrame) -> DataFrame:
    """df with its lineage cut by a reliable checkpoint in the shared folder."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def keyed(df: DataFrame, name: str = "__row") -> DataFrame:
    """``df`` with a number of its own for each row, as a table in the shared folder: the numbers stay what they are."""
    path = f"{checkpoint_dir(df.sparkSession)}/keyed-{uuid.uuid4().hex}"
    df.withColumn(name, F.monotonically_increasing_id()).write.parquet(path)
    return df.sparkSession.read.parquet(path)


def typed(df: DataFrame, name: str) -> DataType:
    return df.schema[name].dataType


def scan_texts(
    df: DataFrame,
    rows: Callable[[list], Iterable[list]],
    fields: list[StructField],
    id_col: str = "doc_id",
    text_col: str = "text",
    binary: bool = False,
) -> DataFrame:
    """One narrow pass over (id, text): ``rows`` turns a batch's texts (str, or bytes; None for null) into columns.

    Only the two named columns are read, so further columns of ``df`` never clash with the outputs.
    """
    small_batches(df.sparkSession)
    text = F.col(text_col).cast("string")
    data = df.select(F.col(id_col).alias("id"), (text.cast("binary") if binary else text).alias("x"))
    schema = StructType([StructField(id_col, typed(df, id_col)), *fields])
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            columns = rows(b.column(1).to_pylist())
            arrays = [b.column(0).cast(arrow.field(0).type)]
            arrays += [pa.array(c, type=f.type) for c, f in zip(columns, list(arrow)[1:], strict=True)]
            yield pa.RecordBatch.from_arrays(arrays, schema=arrow)

    return data.mapInArrow(run, schema)


def long_field(name: str) -> StructField:
    return StructField(name, LongType())


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on uint64 arrays (the splitmix constants are fixed values)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class BitFilter:
    """A Bloom filter whose bits are made by Spark and held as one NumPy array.

    Its size is known before it is built (``bits_per_key`` x keys) and checked against ``max_bytes``; over that bound
    ``build`` returns None and the caller takes its other way.
    """

    CHUNK = 1 << 16

    def __init__(self, bits: np.ndarray, hashes: int, seed: int):
        self.bits, self.hashes, self.seed = bits, hashes, seed

    @staticmethod
    def positions(keys: np.ndarray, m: int, hashes: int, seed: int) -> Iterator[np.ndarray]:
        a = mix64(keys.astype(np.uint64) ^ np.uint64((seed * 0x9E3779B97F4A7C15) & (2**64 - 1)))
        b = mix64(a + np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
        for _ in range(hashes):
            yield (a % np.uint64(m)).astype(np.int64)
            a = a + b

    @classmethod
    def build(cls, keys: DataFrame, n: int, seed: int = 1, bits_per_key: int = 12, hashes: int = 6, max_bytes: int = 32 << 20):
        """From the one BIGINT column of ``keys`` (about n rows). Partitions emit the chunks that they touch, OR-ed by chunk."""
        chunk = cls.CHUNK
        m = max(512, int(n) * bits_per_key)
        m += -m % 8
        if m // 8 > max_bytes:
            return None

        def parts(batches):
            found: dict[int, np.ndarray] = {}
            for b in batches:
                k = b.column(0).to_numpy(zero_copy_only=False).view(np.int64).astype(np.uint64)
                for p in cls.positions(k, m, hashes, seed):
                    for c in np.unique(p // chunk):
                        own = found.setdefault(int(c), np.zeros(chunk // 8, np.uint8))
                        inside = p[p // chunk == c] % chunk
                        np.bitwise_or.at(own, inside >> 3, (1 << (inside & 7)).astype(np.uint8))
            if found:
                yield pa.RecordBatch.from_pydict({"c": pa.array(list(found), pa.int64()), "bits": [v.tobytes() for v in found.values()]})

        def merged(t: pa.Table) -> pa.Table:
            out = np.zeros(chunk // 8, np.uint8)
            for x in t.column("bits").to_pylist():
                out |= np.frombuffer(x, np.uint8)
            return pa.table({"c": t.column("c").slice(0, 1), "bits": [out.tobytes()]})

        rows = keys.mapInArrow(parts, "c bigint, bits binary").groupBy("c").applyInArrow(merged, "c bigint, bits binary").collect()
        bits = np.zeros((m + chunk - 1) // chunk * chunk // 8, np.uint8)
        for c, x in rows:
            bits[c * chunk // 8 : (c + 1) * chunk // 8] = np.frombuffer(x, np.uint8)
        return cls(bits[: m // 8].copy(), hashes, seed)

    def has(self, keys: np.ndarray) -> np.ndarray:
        """Whether each key (int64) may be among those that were added; never False for one that was."""
        ok = np.ones(len(keys), bool)
        for p in self.positions(keys.view(np.int64).astype(np.uint64), len(self.bits) * 8, self.hashes, self.seed):
            ok &= (self.bits[p >> 3] >> (p & 7).astype(np.uint8)) & 1 == 1
        return ok
