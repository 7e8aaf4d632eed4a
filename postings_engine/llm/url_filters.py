"""URL filters by Bloom filter cascades: exact membership of listed keys without joins.

A key is a host followed by the beginning of a path. Level 1 encodes the listed keys; level 2 those keys of the corpus
that level 1 takes for listed and that aren't; level 3 the listed keys that level 2 takes for such; and so on until a
level makes no mistake over the corpus's complete key universe. The first level that says no decides.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BitFilter, cut, small_batches, typed

#: The rules of the contract: (action, host and path), path included up to its last slash.
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
MAX_LEVELS = 40


def url_parts(url: Column) -> tuple[Column, Column]:
    """(host, path) of a url; both empty for null and where no ``://`` stands."""
    part = lambda k: F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)([^?#]*)", k), F.lit(""))
    return F.translate(part(1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), part(2)


@dataclass
class Cascade:
    levels: list[BitFilter]

    @classmethod
    def build(cls, listed: DataFrame, universe: DataFrame, max_bytes: int = 32 << 20) -> Cascade | None:
        """From the one BIGINT column (key hashes) of each. None if level 1 would pass ``max_bytes``: then join instead.

        Only level 1 is asked about the whole universe, in a scan that ships nothing but its mistakes.
        """
        listed = cut(listed.toDF("k").distinct())
        n = listed.count()
        levels: list[BitFilter] = []
        own, other = listed, None
        for level in range(MAX_LEVELS):
            f = BitFilter.build(own, n, seed=level + 1, max_bytes=max_bytes)
            if f is None:
                return None
            levels.append(f)
            against = universe.toDF("k") if level == 0 else other
            wrong = _passing(against, f).distinct()
            if level == 0:
                wrong = wrong.join(listed, "k", "left_anti")
            wrong = cut(wrong)
            n = wrong.count()
            if not n:
                return cls(levels)
            own, other = wrong, own
        raise RuntimeError("the cascade did not end")

    def has(self, keys: np.ndarray) -> np.ndarray:
        """Whether each key (int64, of the universe) is listed."""
        out = np.full(len(keys), len(self.levels) % 2 == 1)
        at = np.arange(len(keys))
        for i, f in enumerate(self.levels):
            inside = f.has(keys[at])
            out[at[~inside]] = i % 2 == 1
            at = at[inside]
        return out


def _passing(keys: DataFrame, f: BitFilter) -> DataFrame:
    def run(batches):
        for b in batches:
            k = b.column(0).to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([pa.array(k[f.has(k)])], names=["k"])

    return keys.select("k").mapInArrow(run, "k bigint")


def rule_table(spark: SparkSession, rules=RULES) -> DataFrame:
    return spark.createDataFrame([(a, r) for a, r in rules], "action string, rule string")


def judge_urls(df: DataFrame, rules: DataFrame, default: str = "allow", id_col: str = "page_id", url_col: str = "url", max_bytes: int = 32 << 20) -> DataFrame:
    """(id, host, path, rule, verdict) of every row.

    ``rules`` (action 'block' or 'allow', rule = host, then a path that starts with '/') may be of any length; only the
    different numbers of labels and lengths of paths among them, few, come to the driver. A rule fits its host and all
    subdomains if the url's path starts with its path; the longest wins, of two equally long the one with the longer
    host, of a rule listed under both actions the block. Urls that no rule fits get ``default``; a null url has an empty
    host and path. Repeated rows are judged each by itself.
    """
    small_batches(df.sparkSession)
    cutoff = F.locate("/", "rule")
    shaped = rules.where("rule is not null and locate('/', rule) > 0")
    shape = shaped.select(F.size(F.split(F.substring("rule", F.lit(1), cutoff - 1), r"\.")).alias("labels"), (F.char_length("rule") - cutoff + 1).alias("chars")).distinct().limit(10_001).collect()
    if len(shape) > 10_000:
        raise ValueError("rules of more than 10000 shapes")
    host, path = url_parts(F.col(url_col))
    urls = df.select(F.col(id_col).alias("id"), host.alias("host"), path.alias("path"))
    fit = [F.when(F.char_length("path") >= c, F.concat(F.substring_index("host", ".", -n), F.substring("path", 1, c))) for n, c in sorted({(r.labels, r.chars) for r in shape})]
    keys = F.array_compact(F.array(*fit)) if fit else F.array().cast("array<string>")
    keyed = urls.withColumn("keys", F.filter(keys, lambda k: F.col("host") != ""))
    universe = keyed.select(F.explode("keys").alias("x")).select(F.xxhash64("x").alias("k"))
    lists = {a: Cascade.build(shaped.where(F.col("action") == a).select(F.xxhash64("rule")), universe, max_bytes) for a in ("block", "allow")}
    if None in lists.values():
        return _by_join(keyed, shaped, default, id_col)
    hashed = keyed.withColumn("hashes", F.transform("keys", lambda k: F.xxhash64(k)))
    kind = typed(urls, "id").simpleString()

    def run(batches):
        for b in batches:
            keys, hashes = b.column(3), b.column(4)
            flat = hashes.flatten().to_numpy(zero_copy_only=False)
            block, allow = lists["block"].has(flat), lists["allow"].has(flat)
            rule, verdict, at = [], [], 0
            for own in keys.to_pylist():
                best = None
                for j, k in enumerate(own, at):
                    if block[j] or allow[j]:
                        best = max(best or ((0, 0), "", ""), ((len(k), k.index("/")), k, "block" if block[j] else "allow"))
                at += len(own)
                rule.append(best and best[1])
                verdict.append(best[2] if best else default)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(rule, pa.string()), pa.array(verdict, pa.string())], names=["id", "host", "path", "rule", "verdict"])

    return hashed.mapInArrow(run, f"id {kind}, host string, path string, rule string, verdict string").withColumnRenamed("id", id_col)


def _by_join(keyed: DataFrame, rules: DataFrame, default: str, id_col: str) -> DataFrame:
    """The same by joins, for lists too long for bit filters on every machine."""
    rows = cut(keyed.withColumn("row", F.monotonically_increasing_id()))
    listed = rules.groupBy("rule").agg(F.max("action").alias("action"))  # block after allow
    hits = rows.select("row", F.explode("keys").alias("rule")).join(listed, "rule")
    best = hits.groupBy("row").agg(F.max(F.struct(F.char_length("rule").alias("n"), F.locate("/", "rule").alias("h"), "rule", "action")).alias("b"))
    out = rows.join(best, "row", "left")
    return out.select(F.col("id").alias(id_col), "host", "path", F.col("b.rule").alias("rule"), F.coalesce("b.action", F.lit(default)).alias("verdict"))


ORACLE = """
WITH p AS (SELECT page_id, coalesce(url, '') AS u, instr(coalesce(url, ''), '://') AS s FROM pages),
r AS (SELECT page_id, CASE WHEN s > 0 THEN substr(u, s + 3) ELSE '' END AS x FROM p),
h AS (SELECT page_id, translate(regexp_extract(x, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(x, '^[^/?#]*([^?#]*)', 1) AS path FROM r),
c(action, rhost, rpath) AS (VALUES ('block', 'net', '/'), ('allow', 'example.net', '/en/'), ('block', 'example.com', '/de/'), ('allow', 'org', '/fr/')),
b AS (SELECT page_id, host, path, max_by(rhost || rpath, length(rhost || rpath)) AS rule, max_by(action, length(rhost || rpath)) AS action
  FROM h LEFT JOIN c ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath) GROUP BY page_id, host, path)
SELECT page_id, host, path, rule, coalesce(action, 'allow') AS verdict FROM b
"""
