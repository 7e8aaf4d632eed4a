"""Streams with state and late rows, markup by a parser, table functions, the aggregate of a function."""

from pyspark.sql import functions as F

from postings_engine.functions.text import html_text_strict
from postings_engine.operators import coders, postings, relational
from postings_engine.operators.codecs import midpoint_bits
from postings_engine.plans.corpora import corpus
from postings_engine.sources import tables
from postings_engine.streaming import segments as streaming


def test_running_counts_and_late_rows(spark, sf_dir, tmp_path):
    events = tables.read_table(spark, sf_dir, "events").orderBy("ts").limit(300).collect()
    src = str(tmp_path / "src")
    for part in (events[:150], events[150:], [r.asDict() | {"event_id": 10**6 + r.event_id} for r in events[:20]], events[-1:]):
        spark.createDataFrame(part, streaming.EVENTS).coalesce(1).write.mode("append").parquet(src)
    seen = []
    out = streaming.running_counts(streaming.event_stream(spark, src))
    q = out.writeStream.outputMode("update").foreachBatch(lambda df, n: seen.extend(df.collect())).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    final = {r.event_type: (r.n, r.last) for r in seen}
    want: dict = {}
    for r in events:
        n, last = want.get(r.event_type, (0, -1))
        want[r.event_type] = n + 1, max(last, r.event_id)
    assert final == want and streaming.late_rows(q) == 20


def test_markup_by_a_parser(spark):
    rows = [("<p>a<b>b</b>&eacute;&amp;<script>var x = '<i>';</script> c</p><style>p{}</style><!-- no -->d",), (None,), ("",)]
    got = [r.t for r in spark.createDataFrame(rows, "html string").select(html_text_strict()(F.col("html")).alias("t")).collect()]
    assert got[0].split() == ["a", "b", "é&", "c", "d"] and got[1:] == [None, ""]


def test_segments_by_a_table_function(spark, sf_dir):
    lists = corpus(spark, sf_dir, "benchmark")
    done = coders.encode(lists, "trit_adaptive", target=1 << 11).cache()
    row = F.struct(*("method", "n_lists", "header", "lengths", "payload", "terms", "before"))
    got = done.select(row.alias("row")).lateralJoin(relational.DecodeSegment(F.col("row").outer(), F.lit(None).cast("binary"))).select("term", "ord")
    want = postings.to_ids(lists.gaps)
    assert got.exceptAll(want).count() == 0 and got.count() == lists.i


def test_aggregate_of_a_function(spark):
    df = spark.createDataFrame([("a", [1, 5, 9], 20), ("a", [2], 20), ("b", [3, 4], 9)], "k string, ids array<bigint>, u bigint")
    got = {r.k: r.b for r in df.groupBy("k").agg(relational.midpoint_total()("ids", "u").alias("b")).collect()}
    assert got == {"a": midpoint_bits([1, 5, 9], 20) + midpoint_bits([2], 20), "b": midpoint_bits([3, 4], 9)}


def test_model_roundtrips_side_by_side(spark, sf_dir, monkeypatch):
    """All coders go through the same call, some at a time, and each is there once and without a mismatch."""
    from postings_engine.plans import surround

    seen, plain = [], surround.together

    def noted(f, items, *more):
        items = list(items)
        seen.append((len(items), *more))
        return plain(f, items, *more)

    monkeypatch.setattr(surround, "together", noted, raising=False)
    rows = surround.model_roundtrips(spark, sf_dir).collect()
    assert (11, 6) in seen
    assert len({r.coder for r in rows}) == len(rows) == 11 and not any(r.mismatches for r in rows)
