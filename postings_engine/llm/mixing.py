"""Mixing sources to target weights by cube-method balanced sampling.

Every document's expected number of copies is its source's target over the source's size: a whole part, which is taken
as it is, and a fraction, an inclusion probability. The flight moves these fractions, three documents at a time, along
the null space of two constraints (documents and words), until at most two in a block of a source are left undecided;
and a few more stay on the ground; what blocks leave flies again. The last block's few are the landing problem, small
enough to look at all its outcomes.
"""

from __future__ import annotations

import math
import random
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import SPACE, cut, keyed

#: Rows that one flight handles; a source of any size is cut into blocks of about so many.
BLOCK_ROWS = 4096
#: Documents of a landing problem; all 2**LANDING outcomes are looked at.
LANDING = 14
#: Sources are listed on the driver; more than this many is an error (a mix of single documents isn't meant).
MAX_SOURCES = 100_000


def targets(sizes: dict, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0) -> dict:
    """source -> target. Sources by code point, null last, take ``weights`` in turn and share ``share`` of all sizes;
    what a source would get above ``most`` times its size is shared again by weight among the others."""
    order = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    left, free, out = share * sum(sizes.values()), list(order), {}
    while free:
        total = sum(weight[s] for s in free)
        full = [s for s in free if left * weight[s] / total > most * sizes[s]]
        if not full:
            return out | {s: left * weight[s] / total for s in free}
        for s in full:
            out[s] = float(most * sizes[s])
        left -= sum(out[s] for s in full)
        free = [s for s in free if s not in set(full)]
    return out


def flight(p: list[float], x: list[float], seed: int = 0) -> list[float]:
    """Fractions p, moved so that sum(p) and sum(p * x) stay; at most two of the result lie strictly between 0 and 1.

    Each step goes to one end of its line or the other by a draw that keeps the expectation; draws follow from ``seed``
    and the order of the rows, so reruns agree.
    """
    p = list(p)
    draw = random.Random(seed).random
    tiny = 1e-9
    held: list[int] = []
    for i in range(len(p)):
        if tiny < p[i] < 1 - tiny:
            held.append(i)
        else:
            p[i] = float(round(p[i]))
        while len(held) == 3 or len(held) == 2 and x[held[0]] == x[held[1]]:
            if len(held) == 2:
                u = (1.0, -1.0)
            else:
                a, b, c = (x[j] for j in held)
                u = (c - b, a - c, b - a)
                if not any(u):
                    u = (1.0, -1.0, 0.0)
            ahead = min((1 - p[j]) / d if d > 0 else -p[j] / d for j, d in zip(held, u, strict=True) if d)
            back = min(p[j] / d if d > 0 else -(1 - p[j]) / d for j, d in zip(held, u, strict=True) if d)
            step = ahead if draw() < back / (ahead + back) else -back
            for j, d in zip(held, u, strict=True):
                p[j] += step * d
            for j in held:
                if not tiny < p[j] < 1 - tiny:
                    p[j] = float(round(p[j]))
            held = [j for j in held if 0 < p[j] < 1]
    return p


def landing(p: list[float], x: list[float]) -> list[int]:
    """0 or 1 for each of the few fractions that are left: of all outcomes with the expected number of documents, rounded up
    or down, the one whose words come nearest to expectation."""
    p, x = np.asarray(p, float), np.asarray(x, float)
    bits = np.arange(1 << len(p))[:, None] >> np.arange(len(p)) & 1
    n, off = bits.sum(1), np.abs(bits @ x - p @ x)
    ok = np.flatnonzero(np.abs(n - p.sum()) < 1 + 1e-6)
    best = ok[np.lexsort((ok, np.abs(n - p.sum())[ok], off[ok]))[0]]
    return bits[best].tolist()


def _fly(rows: DataFrame, last: bool, seed: int) -> DataFrame:
    """One flight for each (rank, block); with ``last`` what it leaves undecided lands."""
    schema = rows.schema

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by([("h", "ascending"), ("size", "ascending"), ("nth", "ascending")])
        x = t.column("size").to_pylist()
        p = t.column("p").to_pylist()
        open_ = [i for i, v in enumerate(p) if 0 < v < 1]
        ground = open_[max(0, len(open_) - LANDING + 2) :]  # two more places for what the flight leaves
        up = sorted(set(range(len(p))) - set(ground))
        for i, v in zip(up, flight([p[i] for i in up], [x[i] for i in up], seed), strict=True):
            p[i] = v
        if last:
            open_ = [i for i, v in enumerate(p) if 0 < v < 1]
            for i, v in zip(open_, landing([p[i] for i in open_], [x[i] for i in open_]), strict=True):
                p[i] = float(v)
        return t.set_column(t.schema.get_field_index("p"), "p", pa.array(p, pa.float64()))

    return rows.groupBy("rank", "block").applyInArrow(run, schema)


def _numbered(rows: DataFrame) -> DataFrame:
    """``rows`` with ``nth``, which tells rows of equal (rank, id, size) apart: 0, 1, ... in each such group.

    Most groups are single rows and get 0 from a count. Of the others each partition numbers its own rows and starts
    after those of the partitions before, so that a group of any size is no task's alone.
    """
    key, same = ["rank", "id", "size"], lambda a, b, on: [a[k].eqNullSafe(b[f"__{k}"]) for k in on]
    named = lambda d, on: d.withColumnsRenamed({k: f"__{k}" for k in on})
    many = named(rows.groupBy(*key).agg(F.count(F.lit(1)).alias("m")).where("m > 1").drop("m"), key)
    marked = rows.join(many, same(rows, many, key), "left").withColumn("many", F.col("__rank").isNotNull()).select(*rows.columns, "many")
    marked = cut(marked.withColumn("part", F.shiftright("row", 33)))
    some = marked.where("many")
    ahead = F.sum("m").over(Window.partitionBy(*key).orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    on = [*key, "part"]
    parts = named(some.groupBy(*on).agg(F.count(F.lit(1)).alias("m")).withColumn("ahead", F.coalesce(ahead, F.lit(0).cast("long"))).drop("m"), on)
    own = F.row_number().over(Window.partitionBy(*on).orderBy("row")) - 1
    counted = some.withColumn("own", own).join(parts, same(some, parts, on)).withColumn("nth", F.col("ahead") + F.col("own")).select(*rows.columns, "nth")
    return marked.where("not many").select(*rows.columns, F.lit(0).cast("long").alias("nth")).unionByName(counted)


def mix(
    df: DataFrame,
    weights: tuple[float, ...] = (3, 1, 2),
    share: float = 1.5,
    most: float = 2.0,
    seed: int = 17,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    size=None,
) -> DataFrame:
    """(id, size, source_size, target, copies, taken) of every row: ``taken`` = copies * size words of the mix.

    Size: number of words of the whole text (null: 0), or the column ``size``. Sources of size 0 have target 0 and take
    nothing. A row has at most ceil(target / source_size) copies, so at most ``most``. Repeated rows are sampled each by
    itself; rows of equal source, id and size are interchangeable. The result depends on the rows' contents, not on how
    they are partitioned. A null source is a source of its own. An empty table gives an empty result.
    """
    return _mixed(df.withColumn("__row", F.monotonically_increasing_id()), weights, share, most, seed, id_col, text_col, source_col, size).drop("row").withColumnRenamed("id", id_col)


def _mixed(df: DataFrame, weights, share, most, seed, id_col, text_col, source_col, size) -> DataFrame:
    """As :func:`mix`, with the number ``row`` that ``df`` has in ``__row``."""
    spark = df.sparkSession
    words = F.regexp_count(F.coalesce(F.col(text_col).cast("string"), F.lit("")), F.lit(SPACE.replace("[", "[^") + "+")).cast("long")
    base = cut(df.select(F.col(id_col).alias("id"), F.col(source_col).cast("string").alias("source"), (words if size is None else size).alias("size"), F.col("__row").alias("row")))
    totals = base.groupBy("source").agg(F.sum("size").alias("size"), F.count(F.lit(1)).alias("n")).limit(MAX_SOURCES + 1).collect()
    if len(totals) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    goal = targets({s: z for s, z, _ in totals}, weights, share, most)
    plan = []
    for rank, (s, z, n) in enumerate(sorted(totals, key=lambda r: (r[0] is None, r[0]))):
        ratio = goal[s] / z if z else 0.0
        whole = math.floor(ratio + 1e-12)
        plan.append((s, rank, z, float(goal[s]), whole, max(0.0, ratio - whole), -(-n // BLOCK_ROWS)))
    shape = "source string, rank int, source_size bigint, target double, whole bigint, p double, blocks bigint"
    known = spark.createDataFrame(plan, shape)  # one row for each source, at most MAX_SOURCES
    rows = base.join(F.broadcast(known.withColumnRenamed("source", "s")), F.col("source").eqNullSafe(F.col("s"))).drop("s", "source")
    rows = _numbered(rows).withColumn("h", F.xxhash64(F.col("id"), F.col("size"), F.col("nth"), F.lit(seed)))
    rows = rows.withColumn("block", F.pmod(F.shiftrightunsigned("h", 8), F.greatest("blocks", F.lit(1))))
    done = None
    blocks = max((r[6] for r in plan), default=1)
    while True:
        rows = cut(_fly(rows, blocks <= 1, seed))
        settled = rows.where("p <= 0 or p >= 1")
        done = settled if done is None else done.unionByName(settled)
        if blocks <= 1:
            break
        # at most LANDING rows of each block are left: fewer blocks hold them
        blocks = min(blocks - 1, -(-blocks * LANDING // BLOCK_ROWS))
        rows = rows.where("p > 0 and p < 1").withColumn("block", F.pmod("block", F.lit(blocks)))
    copies = F.col("whole") + F.round("p").cast("long")
    return done.select("row", "id", "size", "source_size", "target", copies.alias("copies"), (F.col("size") * copies).alias("taken"))


def mixed_rows(
    df: DataFrame,
    weights: tuple[float, ...] = (3, 1, 2),
    share: float = 1.5,
    most: float = 2.0,
    seed: int = 17,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    size=None,
) -> DataFrame:
    """The mix itself: each row of ``df`` as often as :func:`mix` takes it, with its columns.

    Rows are told apart by a number of their own, never by their ids, which may be null or repeat. Rows without a copy
    are absent; an empty table gives an empty result.
    """
    rows = keyed(df)
    took = _mixed(rows, weights, share, most, seed, id_col, text_col, source_col, size).where("copies > 0").select(F.col("row").alias("__row"), F.col("copies").cast("int").alias("__copies"))
    return rows.join(took, "__row").withColumn("__k", F.explode(F.sequence(F.lit(1), "__copies"))).select(*df.columns)


def check_flight(p: Iterable[float], x: Iterable[float]) -> tuple[float, float, int]:
    """How far a flight moved sum(p) and sum(p * x), and how many fractions it left."""
    p, x = list(p), list(x)
    q = flight(p, x)
    return abs(sum(q) - sum(p)), abs(float(np.dot(q, x) - np.dot(p, x))), sum(0 < v < 1 for v in q)
