"""Near-duplicate embeddings by Euclidean p-stable hashing with exact cosine checks.

Vectors are normalised; in each of several tables, ``k`` random projections quantised to steps of ``width`` give a
bucket. Two unit vectors of cosine c lie sqrt(2 - 2c) apart; at cosine 0.98 a projection agrees with probability 0.92
for width 2, a table of 12 with 0.37, and one of 16 tables with more than 0.999. Buckets hold numbers and 64 signs of
further projections, no vectors: pairs in a bucket whose signs differ in too many places can't be linked (a chance of
about 1e-5 at the threshold) and are no candidates. Candidates make groups; each group's vectors are sent once, and all
its pairs are checked by cosine in double precision, tile by tile.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, small_batches
from .components import connected

#: Rows of one tile; a group is compared tile by tile, so its size doesn't bound memory.
TILE = 4096
#: Rows of a tile that are multiplied at once.
STRIP = 512
#: Different vectors of one bucket up to which their signs are compared in pairs; of more, all are candidates.
BIG_BUCKET = 2048
#: Of 64 signs, so many may differ: at cosine 0.98 4.1 do on average, with a deviation of 2.
SIGNS = 13


@dataclass(frozen=True)
class Tables:
    count: int = 16
    k: int = 12
    width: float = 2.0
    seed: int = 5

    @classmethod
    def sized(cls, n: int, least: float = 0.98, width: float = 2.0) -> Tables:
        """For n vectors that may meet: so many projections that a table brings a vector about one chance neighbour, and
        so many tables that a pair at the threshold is missed by all with a chance of 0.001 at most."""

        def agree(c: float) -> float:
            t = width / c
            return math.erf(t / math.sqrt(2)) - 2 / (math.sqrt(2 * math.pi) * t) * (1 - math.exp(-t * t / 2))

        k = max(12, math.ceil(math.log(max(n, 2)) / -math.log(agree(math.sqrt(2)))))
        hit = agree(math.sqrt(max(2 - 2 * least, 1e-9))) ** k
        return cls(max(1, math.ceil(math.log(0.001) / math.log(1 - hit))), k, width)

    def signs(self, unit: np.ndarray) -> np.ndarray:
        """The signs of 64 more projections, as one uint64 for each row."""
        d = unit.shape[1]
        a = np.random.default_rng([self.seed, d, 64]).standard_normal((d, 64))
        return np.packbits(unit @ a > 0, axis=1).view(np.uint64).ravel()

    def codes(self, unit: np.ndarray) -> np.ndarray:
        """One int64 for each row and table."""
        d = unit.shape[1]
        rng = np.random.default_rng([self.seed, d])
        a, b = rng.standard_normal((d, self.count * self.k)), rng.random(self.count * self.k) * self.width
        q = np.floor((unit @ a + b) / self.width).astype(np.int64).reshape(len(unit), self.count, self.k)
        out = np.zeros(q.shape[:2], np.uint64)
        for j in range(self.k):
            out = (out ^ q[:, :, j].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
            out ^= out >> np.uint64(29)
        return out.view(np.int64)


def classes_of(df: DataFrame, id_col: str, vector_col: str, label_col: str) -> tuple[DataFrame, DataFrame]:
    """(rows, classes): rows (id, label, k1, k2) with null k1 where a row links with nothing; classes of equal vectors."""
    e = F.col(vector_col)
    sound = F.col(label_col).isNotNull() & e.isNotNull() & (F.size(e) > 0) & F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(e, lambda x: x != 0)
    key = lambda i: F.when(sound, F.xxhash64(e, F.lit(i)))
    rows = df.select(F.col(id_col).alias("id"), F.col(label_col).alias("label"), e.alias("e"), key(1).alias("k1"), key(2).alias("k2"))
    classes = rows.where("k1 is not null").groupBy("label", "k1", "k2").agg(F.min("id").alias("least"), F.count(F.lit(1)).alias("copies"), F.first("e").alias("e"))
    return rows.drop("e"), cut(classes.withColumn("node", F.monotonically_increasing_id()))


def _raw_type(classes: DataFrame):
    return np.float32 if classes.schema["e"].dataType.elementType.typeName() == "float" else np.float64


def _unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)  # neither overflow nor underflow of the squares
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def _bucketed(classes: DataFrame, tables: Tables) -> DataFrame:
    """(bucket, node, signs) for each class and table."""
    small_batches(classes.sparkSession)
    data = classes.select("node", F.xxhash64("label").alias("label"), F.col("e").cast("array<double>").alias("e"))

    def run(batches):
        for b in batches:
            lists = b.column(2)
            sizes = np.diff(lists.offsets.to_numpy())
            flat = lists.flatten().to_numpy(zero_copy_only=False)
            node, label = (b.column(i).to_numpy(zero_copy_only=False) for i in range(2))
            at = np.concatenate([[0], np.cumsum(sizes)])
            for d in np.unique(sizes):
                rows = np.flatnonzero(sizes == d)
                unit = _unit(flat[(at[rows][:, None] + np.arange(d))])
                codes = tables.codes(unit) ^ (label[rows] * np.int64(0x2545F4914F6CDD1D))[:, None] ^ (np.arange(tables.count) * 1000003 + int(d))[None, :]
                signs = tables.signs(unit).view(np.int64)
                yield pa.RecordBatch.from_pydict({"bucket": pa.array(codes.ravel()), "node": pa.array(np.repeat(node[rows], tables.count)), "signs": pa.array(np.repeat(signs, tables.count))})

    return data.mapInArrow(run, "bucket bigint, node bigint, signs bigint")


def candidates(rows: DataFrame) -> DataFrame:
    """(u, v) that span, in each bucket of (bucket, node, signs), the pairs whose signs don't rule them out."""
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def links(node, signs):
        if len(node) > BIG_BUCKET:
            return node[1:], np.full(len(node) - 1, node[0])
        near = np.bitwise_count(signs[:, None] ^ signs[None, :]) <= SIGNS
        root = np.arange(len(node))
        while True:
            m = np.where(near, root[None, :], len(node)).min(1)
            if (m == root).all():
                break
            root = m
        hit = np.flatnonzero(root != np.arange(len(node)))
        return node[hit], node[root[hit]]

    def run(batches):
        held = [np.empty(0, np.int64) for _ in range(3)]
        for b in [*batches, None]:
            if b is not None:
                held = [np.concatenate([x, b.column(i).to_numpy(zero_copy_only=False)]) for i, x in enumerate(held)]
            if not len(held[0]):
                continue
            bucket, node, signs = held
            start = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
            last = len(bucket) if b is None else int(start[-1])
            if last == 0 and len(bucket) > BIG_BUCKET:  # a big bucket goes on: its first row stays for the rest
                u, v = links(node, signs)
                held = [x[:1] for x in held]
                yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])
                continue
            start = start[start < last]
            size = np.diff(np.append(start, last))
            two = start[size == 2]
            two = two[np.bitwise_count((signs[two] ^ signs[two + 1]).view(np.uint64)) <= SIGNS]
            found = [(node[two + 1], node[two])]
            found += [links(node[i : i + m], signs[i : i + m].view(np.uint64)) for i, m in zip(start[size > 2], size[size > 2], strict=True)]
            u, v = (np.concatenate(x) for x in zip(*found, strict=True))
            held = [x[last:] for x in held]
            if len(u):
                yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])

    return rows.repartition(parts, "bucket").sortWithinPartitions("bucket", "node").mapInArrow(run, "u bigint, v bigint").where("u <> v")


def _compared(unit, other, least: float, same: bool):
    """Positions (i, j) of pairs of two tiles with a cosine of ``least`` and more, strip by strip."""
    for a in range(0, len(unit), STRIP):
        i, j = np.nonzero(unit[a : a + STRIP] @ other.T >= least)
        i += a
        ok = i < j if same else slice(None)
        yield i[ok], j[ok]


def links(classes: DataFrame, least: float = 0.98, tables: Tables | None = None) -> tuple[DataFrame, DataFrame]:
    """(counts, pairs): counts (node, n) of linked vectors in other classes, not yet summed; pairs (u, v) that span the links.

    A group of more than TILE candidates is cut into tiles, each pair of tiles is a task's unit of work: copies of a row
    grow with the group's number of tiles, memory doesn't.
    """
    if tables is None:
        tables = Tables.sized(classes.groupBy("label").agg(F.count(F.lit(1)).alias("m")).agg(F.coalesce(F.max("m"), F.lit(0))).first()[0], least)
    group = cut(connected(candidates(_bucketed(classes, tables))).withColumnRenamed("comp", "g"))
    size = group.groupBy("g").agg(F.count(F.lit(1)).alias("m"))
    raw_type = _raw_type(classes)
    rows = group.join(size, "g").join(classes, "node")
    rows = rows.withColumn("k", F.ceil(F.col("m") / TILE).cast("int")).withColumn("i", F.pmod(F.xxhash64("node"), F.col("k")).cast("int"))
    rows = rows.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("k") - 1))).withColumn("lo", F.least("i", "o")).withColumn("hi", F.greatest("i", "o"))
    parts = int(classes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.select(F.xxhash64("g", "lo", "hi").alias("g"), "i", "lo", "hi", F.xxhash64("label").alias("label"), "node", "copies", "e").repartition(parts, "g").sortWithinPartitions("g")

    def compared(rows):
        i, lo, hi, label, node, copies, vector = zip(*rows, strict=True)
        if len(node) < 2:
            return None
        i, label, node, copies = (np.array(v, np.int64) for v in (i, label, node, copies))
        if len({(a, len(v)) for a, v in zip(label.tolist(), vector, strict=True)}) > 1:
            return None  # labels or lengths differ: nothing but a clash of hashes
        unit = _unit(np.array(vector, raw_type).astype(np.float64))
        if lo[0] == hi[0]:
            x = y = np.arange(len(node))
        else:
            x, y = np.flatnonzero(i == lo[0]), np.flatnonzero(i == hi[0])
        n, root = np.zeros(len(node), np.int64), np.arange(len(node))

        def top(v):
            while (root[v] != v).any():
                v = root[v]
            return v

        for a, b in _compared(unit[x], unit[y], least, lo[0] == hi[0]):
            a, b = x[a], y[b]
            np.add.at(n, a, copies[b])
            np.add.at(n, b, copies[a])
            while len(a):  # the greater root hangs under the smaller one until no link joins two trees
                a, b = top(a), top(b)
                apart = a != b
                a, b = np.maximum(a, b)[apart], np.minimum(a, b)[apart]
                np.minimum.at(root, a, b)
        hit = np.flatnonzero(n)
        return node[hit], n[hit], node[top(hit)]

    def run(batches):
        key, held = None, []

        def out():
            if held and (got := compared(held)):
                yield pa.RecordBatch.from_arrays([pa.array(v) for v in got], names=["node", "n", "root"])

        for b in batches:
            vectors = b.column(7)
            at, flat = vectors.offsets.to_numpy(), vectors.values.to_numpy(zero_copy_only=False)
            own = [flat[x:y] for x, y in zip(at[:-1], at[1:], strict=True)]
            for g, *row in zip(*(b.column(i).to_pylist() for i in range(7)), own, strict=True):
                if g != key:
                    yield from out()
                    key, held = g, []
                held.append(row)
        yield from out()

    found = cut(dealt.mapInArrow(run, "node bigint, n bigint, root bigint"))
    return found.select("node", "n"), found.select(F.col("node").alias("u"), F.col("root").alias("v"))


def near_duplicates(df: DataFrame, least: float = 0.98, tables: Tables | None = None, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """(id, n_links, component_id, kept) of every row.

    Vectors of equal, not null labels and equal lengths link when their cosine in double precision reaches ``least``.
    Null, empty and zero vectors and those with null or non-finite components link with nothing, nor do rows without a
    label. ``tables`` follow the number of vectors of the commonest label. Repeated rows are vectors like any other and link with each other. An empty table gives an empty result.
    """
    rows, classes = classes_of(df, id_col, vector_col, label_col)
    counts, pairs = links(classes, least, tables)
    comps = connected(pairs)
    sums = counts.groupBy("node").agg(F.sum("n").alias("far"))
    own = cut(classes.drop("e").join(sums, "node", "left").join(comps, "node", "left"))
    named = own.where("comp is not null").groupBy("comp").agg(F.min("least").alias("named"))
    label = own.join(named, "comp", "left").select("label", "k1", "k2", (F.col("copies") - 1 + F.coalesce("far", F.lit(0))).alias("n"), F.coalesce("named", "least").alias("c"))
    out = rows.join(label, ["label", "k1", "k2"], "left")
    comp = F.coalesce("c", "id")
    return out.select(F.col("id").alias(id_col), F.coalesce("n", F.lit(0)).alias("n_links"), comp.alias("component_id"), F.coalesce(F.col("id") == comp, F.lit(True)).alias("kept"))
