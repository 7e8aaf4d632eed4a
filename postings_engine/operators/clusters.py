"""Word clusters, reference lists, density batches and the mixing of codecs."""

from __future__ import annotations

from threading import Lock

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import baselines
from .ids import cut, together
from .postings import Lists, to_gaps, to_ids

# The edges of the density classes, 1 to 7, each open below and closed above.
EDGES = (0.0, 0.0002, 0.001, 0.01, 0.03, 0.1, 0.2, 1.0)
#: Parts of a cluster's documents that name their own candidates for its reference list, and ids of a range of one.
SLICES, RANGE = 64, 256


def batch_of(density: Column) -> Column:
    out = F.lit(len(EDGES) - 1)
    for k in range(len(EDGES) - 2, 0, -1):
        out = F.when(density <= EDGES[k], k).otherwise(out)
    return out.cast("int")


def cluster_by_hash(terms: DataFrame, c: int) -> DataFrame:
    """A control: (term, c) by hash."""
    return terms.select("term", F.pmod(F.xxhash64("term"), F.lit(c)).cast("int").alias("c"))


def cluster_terms(lists: Lists, c: int = 8, features: int = 64, seed: int = 1, iterations: int = 10) -> DataFrame:
    """(term, c) by k-means on where in the collection a list's ids lie: a histogram over ``features`` ranges of ids,
    normalised. Centroids are c x features numbers whatever the data."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    cell = F.floor((F.col("ord") - 1) * features / F.lit(max(1, lists.d))).cast("int")
    bins = to_ids(lists.gaps).groupBy("term", cell.alias("k")).agg(F.count(F.lit(1)).alias("m"))
    rows = bins.groupBy("term").agg(F.map_from_entries(F.collect_list(F.struct("k", "m"))).alias("m"), F.sqrt(F.sum(F.col("m") * F.col("m"))).alias("norm"))
    value = F.transform(F.sequence(F.lit(0), F.lit(features - 1)), lambda k: F.coalesce(F.try_element_at("m", k), F.lit(0)) / F.col("norm"))
    data = cut(rows.select("term", value.alias("f"))).select("term", array_to_vector("f").alias("features"))
    model = KMeans(k=c, seed=seed, maxIter=iterations).fit(data)
    return model.transform(data).select("term", F.col("prediction").alias("c"))


def _best(df: DataFrame, by: Column, r: int) -> DataFrame:
    """(c, ord, rank): in each cluster the r documents with the greatest ``by``, ties by id, ranked by id from 1. Each of
    SLICES parts of a cluster names its own r first, so that no task sees all documents of one."""
    rows = df.withColumn("by", by).withColumn("slice", F.pmod(F.xxhash64("ord"), F.lit(SLICES)))
    for key in (["c", "slice"], ["c"]):
        rows = rows.withColumn("k", F.row_number().over(Window.partitionBy(*key).orderBy(F.desc("by"), "ord"))).where(F.col("k") <= r)
    return rows.select("c", "ord", F.row_number().over(Window.partitionBy("c").orderBy("ord")).alias("rank"))


def reference_lists(pairs: DataFrame, clusters: DataFrame, r: int) -> DataFrame:
    """(c, ord, rank): in each cluster the r documents in most of its lists, ties by id, ranked by id from 1."""
    return _best(pairs.join(clusters, "term").groupBy("c", "ord").agg(F.count(F.lit(1)).alias("df")), F.col("df"), r)


def space_reference_lists(pairs: DataFrame, clusters: DataFrame, r: int, d: int) -> DataFrame:
    """As :func:`reference_lists`, choosing documents by the bits they may save: occurrences times the gap between the cost
    of an id among d and among r, less the cost of naming the document once."""
    df = pairs.join(clusters, "term").groupBy("c", "ord").agg(F.count(F.lit(1)).alias("df"))
    saved = F.col("df") * F.log2(F.lit(float(max(2, d)) / r)) - F.log2(F.lit(float(max(2, d))))
    return _best(df.withColumn("s", saved).where("s > 0"), F.col("s"), r)


def _with_below(rows: DataFrame, marks: DataFrame, x: str) -> DataFrame:
    """``rows`` (c, x, ...) with ``below``, how many of the cluster's ``marks`` (c, y) are less than x, and ``hit``, whether x
    is one: an as-of join without a sort of a cluster's rows.

    Numbers are cut into ranges of RANGE. For each cluster and range a row holds its marks and how many lie in the ranges
    before; rows meet it in a join by cluster and range.
    """
    cell = lambda c: F.floor(F.col(c) / RANGE).cast("long")
    held = marks.groupBy("c", cell("y").alias("cell")).agg(F.sort_array(F.collect_list("y")).alias("ids"))
    own = Window.partitionBy("c").orderBy("cell")  # over numbers of ranges only
    counts = held.select("c", "cell", F.size("ids").alias("m")).withColumns({"ahead": F.coalesce(F.sum("m").over(own.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0).cast("long")), "next": F.lead("cell").over(own)})
    top = rows.agg(F.coalesce(F.max(cell(x)), F.lit(0))).first()[0]
    # ranges without a mark share what the last one with some has
    until = F.greatest(F.col("cell"), F.coalesce(F.col("next") - 1, F.lit(top)))
    spread = counts.select("c", F.explode(F.sequence("cell", until)).alias("cell"), F.col("cell").alias("at"), "ahead", "m")
    here = F.col("cell") == F.col("at")
    known = spread.join(held.withColumnRenamed("cell", "at"), ["c", "at"]).select("c", "cell", F.when(here, F.col("ahead")).otherwise(F.col("ahead") + F.col("m")).alias("ahead"), F.when(here, F.col("ids")).otherwise(F.array().cast("array<bigint>")).alias("ids"))
    ids = F.coalesce("ids", F.array().cast("array<bigint>"))
    joined = rows.withColumn("cell", cell(x)).join(known, ["c", "cell"], "left")
    return joined.withColumns({"below": F.coalesce("ahead", F.lit(0).cast("long")) + F.size(F.filter(ids, lambda y: y < F.col(x))), "hit": F.array_contains(ids, F.col(x))}).drop("cell", "ahead", "ids")


def split_by_reference(pairs: DataFrame, clusters: DataFrame, reference: DataFrame, shrink: bool = True) -> DataFrame:
    """(term, c, part, x): 'hit' with the position in the cluster's reference list, or 'rest' with the id, less the number
    of reference ids below it if ``shrink``."""
    rows = _with_below(pairs.join(clusters, "term"), reference.select("c", F.col("ord").alias("y")), "ord")
    value = F.when(F.col("hit"), F.col("below") + 1).otherwise(F.col("ord") - (F.col("below") if shrink else 0))
    return rows.select("term", "c", F.when(F.col("hit"), "hit").otherwise("rest").alias("part"), value.cast("long").alias("x"))


def merge_by_reference(split: DataFrame, reference: DataFrame, shrink: bool = True) -> DataFrame:
    """(term, ord) back from :func:`split_by_reference`."""
    hits = split.where("part = 'hit'").join(reference.select("c", "ord", F.col("rank").cast("long").alias("x")), ["c", "x"]).select("term", "ord")
    rest = split.where("part = 'rest'")
    if not shrink:
        return hits.unionByName(rest.select("term", F.col("x").alias("ord")))
    # the i-th reference id lies below an id that has shrunk to x if it is less than x + i
    marks = reference.select("c", (F.col("ord") - F.col("rank")).cast("long").alias("y"))
    return hits.unionByName(_with_below(rest, marks, "x").select("term", (F.col("x") + F.col("below")).alias("ord")))


def pair_mismatches(got: DataFrame, want: DataFrame) -> DataFrame:
    """(mismatches): pairs (term, ord) that one side holds oftener than the other, each as often as it does."""
    both = got.select("term", "ord", F.lit(1).alias("s")).unionByName(want.select("term", "ord", F.lit(-1).alias("s")))
    return both.groupBy("term", "ord").agg(F.abs(F.sum("s")).alias("m")).agg(F.coalesce(F.sum("m"), F.lit(0)).cast("long").alias("mismatches"))


def clustered_roundtrip(lists: Lists, clusters: DataFrame, r: int, codec: str = "midpoint", shrink: bool = True) -> DataFrame:
    """(mismatches) of coding and decoding the clustered form of any codec of single lists, or of a trit coder."""
    return clustered_roundtrips(lists, clusters, r, (codec,), (shrink,)).select("mismatches")


def clustered_roundtrips(lists: Lists, clusters: DataFrame, r: int, codecs: tuple[str, ...], shrinks: tuple[bool, ...] = (False, True)) -> DataFrame:
    """(codec, shrink, mismatches): clusters and reference lists are found once, lists split once for each form."""
    from ..plans.measures import list_bytes, list_gaps
    from .coders import decode, encode

    pairs, clusters = cut(to_ids(lists.gaps)), cut(clusters)
    reference = cut(reference_lists(pairs, clusters, r))
    out = None
    for shrink in shrinks:
        split = cut(split_by_reference(pairs, clusters, reference, shrink))
        parts = []
        for part, universe in (("hit", r), ("rest", lists.d)):
            gaps = cut(to_gaps(split.where(F.col("part") == part).select("term", F.col("x").alias("ord"))))
            parts.append((part, Lists(gaps, universe, 0, gaps.agg(F.coalesce(F.sum(F.size("gaps")), F.lit(0))).first()[0])))
        for codec in codecs:
            back = None
            for part, own in parts:
                done = decode(cut(encode(own, codec))) if codec.startswith("trit_") else list_gaps(cut(list_bytes(own, codec)), codec, own.d)
                one = to_ids(done).withColumnRenamed("ord", "x").join(clusters, "term").select("term", "c", F.lit(part).alias("part"), "x")
                back = one if back is None else back.unionByName(one)
            merged = merge_by_reference(back, reference, shrink)
            one = pair_mismatches(merged, pairs).select(F.lit(codec).alias("codec"), F.lit(shrink).alias("shrink"), "mismatches")
            out = one if out is None else out.unionByName(one)
    return out


class Splits:
    """Lists split by the reference lists of their clusters: each split is made once, for all the codecs that take it, which
    may ask side by side."""

    def __init__(self, lists: Lists, clusters: DataFrame, r: int, pairs: DataFrame | None = None):
        self.lists, self.clusters, self.r, self.pairs = lists, clusters, r, pairs
        self.c: int | None = None
        self.references: dict = {}
        self.made: dict = {}
        self.lock = Lock()

    def of(self, shrink: bool, reference: DataFrame | None) -> tuple[list[tuple[str, Lists]], DataFrame]:
        """The parts of each split, hits and rest, and its reference lists."""
        with self.lock:
            if self.c is None:
                self.pairs = cut(to_ids(self.lists.gaps)) if self.pairs is None else self.pairs
                self.clusters = cut(self.clusters)
                self.c = self.clusters.agg(F.coalesce(F.max("c"), F.lit(0)) + 1).first()[0]
            by = id(reference)  # kept below, so that no other frame gets it
            if by not in self.references:
                self.references[by] = reference, cut(reference_lists(self.pairs, self.clusters, self.r) if reference is None else reference)
            known = self.references[by][1]
            if (by, shrink) not in self.made:
                split = cut(split_by_reference(self.pairs, self.clusters, known, shrink))

                def part(x) -> tuple[str, Lists]:
                    gaps = cut(to_gaps(split.where(F.col("part") == x[0]).select("term", F.col("x").alias("ord"))))
                    return x[0], Lists(gaps, x[1], 0, gaps.agg(F.coalesce(F.sum(F.size("gaps")), F.lit(0))).first()[0])

                self.made[by, shrink] = together(part, (("hit", self.r), ("rest", self.lists.d)))
            return self.made[by, shrink], known


def clustered_bits(lists: Lists, clusters: DataFrame, r: int, name: str = "midpoint", shrink: bool = True, reference: DataFrame | None = None, splits: Splits | None = None) -> DataFrame:
    """(part, bits) of the clustered form of a codec: hits, rest, their lengths, the reference lists, cluster numbers.
    ``splits``, of the same lists, clusters and r, keeps what several codecs take."""
    from .coders import encode

    splits = Splits(lists, clusters, r) if splits is None else splits
    parts, reference = splits.of(shrink, reference)
    clusters, c = splits.clusters, splits.c
    out = None
    for part, own in parts:
        if not own.i:
            continue
        if name.startswith("trit_"):
            bits = encode(own, name, payload=False).agg(F.ceil(F.sum("ideal_bits")).alias("bits"), F.coalesce(F.sum(8 * F.length("model")), F.lit(0)).alias("m")).select((F.col("bits") + F.col("m")).cast("long").alias("bits"))
        elif name == "packed_arith":
            bits = baselines.packed_arith_bits(own).select((F.ceil(F.col("selector_bits") + F.col("payload_bits")) + F.col("model_bits")).cast("long").alias("bits"))
        else:
            bits = baselines.kernel_bits(own, [name]).select("bits")
        lengths = baselines.length_bits(own).select(F.lit(f"{part}_lengths").alias("part"), F.col("length_bits").alias("bits"))
        both = bits.select(F.lit(part).alias("part"), "bits").unionByName(lengths)
        out = both if out is None else out.unionByName(both)
    ref = to_gaps(reference.select(F.col("c").cast("string").alias("term"), "ord"))
    coded = baselines.kernel_bits(Lists(ref, lists.d, c, 0), ["midpoint"]).select(F.lit("reference").alias("part"), "bits")
    names = clusters.agg(F.lit("clusters").alias("part"), (F.count(F.lit(1)) * max(0, (c - 1).bit_length())).alias("bits"))
    return (coded if out is None else out.unionByName(coded)).unionByName(names)


def batch_bits(lists: Lists, methods: tuple[str, ...] = ("midpoint", "trit_static", "trit_adaptive")) -> DataFrame:
    """(batch, method, ints, bits) for each density class."""
    from .coders import encode, static_bits

    rows = cut(lists.gaps.withColumn("batch", batch_of(F.col("n") / F.lit(float(max(1, lists.d))))))
    classes = rows.groupBy("batch").agg(F.sum(F.size("gaps")).alias("i")).orderBy("batch").collect()  # seven at most

    def one(x) -> DataFrame:
        r, m = x
        own = Lists(rows.where(F.col("batch") == r.batch).drop("batch"), lists.d, 0, r.i)
        if m == "trit_static":
            bits = rows.sparkSession.createDataFrame([(sum(static_bits(own)),)], "bits bigint")
        elif m.startswith("trit_"):
            bits = encode(own, m, payload=False).agg((F.ceil(F.sum("ideal_bits")) + F.coalesce(F.sum(8 * F.length("model")), F.lit(0))).cast("long").alias("bits"))
        else:
            bits = baselines.kernel_bits(own, [m]).select("bits")
        return bits.select(F.lit(r.batch).alias("batch"), F.lit(m).alias("method"), F.lit(r.i).cast("long").alias("ints"), "bits")

    out = None
    for x in together(one, [(r, m) for r in classes for m in methods]):
        out = x if out is None else out.unionByName(x)
    return out


def best_per_batch(lists: Lists, methods: tuple[str, ...] = ("midpoint", "trit_static", "trit_adaptive")) -> DataFrame:
    """(batch, ints, method, bits): the cheapest method of each class, with two bits that name it."""
    return batch_bits(lists, methods).groupBy("batch", "ints").agg(F.min_by("method", "bits").alias("method"), (F.min("bits") + 2).alias("bits"))


def cheapest(lists: Lists, names: list[str]) -> DataFrame:
    """(codec, lists, ints, bits): every list by its cheapest codec, with the bits that name it."""
    each = baselines.kernel_bits(lists, names, by_list=True).groupBy("term", "n", "codec").agg(F.sum("bits").alias("bits"))
    best = each.groupBy("term", "n").agg(F.min(F.struct("bits", "codec")).alias("b"))
    name = (len(names) - 1).bit_length()
    return best.groupBy(F.col("b.codec").alias("codec")).agg(F.count(F.lit(1)).alias("lists"), F.sum("n").alias("ints"), F.sum(F.col("b.bits") + name).alias("bits"))


def by_rules(lists: Lists, rules: list[tuple[Column, str]], default: str) -> DataFrame:
    """(codec, ints, bits): the first rule on n (or any column of the lists) that holds chooses the codec."""
    chosen = F.lit(default)
    for cond, name in reversed(rules):
        chosen = F.when(cond, name).otherwise(chosen)
    rows = lists.gaps.withColumn("codec", chosen)
    out = None
    for name in dict.fromkeys([*(n for _, n in rules), default]):
        own = Lists(rows.where(F.col("codec") == name).drop("codec"), lists.d, 0, 0)
        one = baselines.kernel_bits(own, [name]).join(own.gaps.agg(F.sum(F.size("gaps")).alias("ints")))
        out = one if out is None else out.unionByName(one)
    return out.select("codec", F.coalesce("ints", F.lit(0)).cast("long").alias("ints"), "bits")
