"""Queries against SQL, and the pieces that SQL doesn't reach."""

import json

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from postings_engine.operators import baselines, clusters, coders, lookup, ordering, postings
from postings_engine.operators.postings import Lists
from postings_engine.plans import corpora, measures
from postings_engine.plans.corpora import corpus
from postings_engine.plans.oracles import ORACLES
from postings_engine.plans.queries import QUERIES
from postings_engine.sources import tables
from postings_engine.streaming import segments as streaming

MINI = [("a", (12, 16)), ("b", (2, 7, 8, 10, 11, 13)), ("c", (2, 3, 4)), ("d", (11,)), ("e", (4, 5, 6, 9, 14, 16))]


def plain(v):
    return round(v, 6) if isinstance(v, float) else v


def rows_of(names, rows):
    at = sorted(range(len(names)), key=lambda i: names[i])
    return sorted(repr(tuple(plain(r[i]) for i in at)) for r in rows)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_against_sql(spark, duck, sf_dir, name):
    df = entry.queries()[name](spark, sf_dir)
    want = duck.execute(ORACLES[name])
    names = [d[0] for d in want.description]
    assert sorted(df.columns) == sorted(names)
    assert rows_of(df.columns, [tuple(r) for r in df.collect()]) == rows_of(names, want.fetchall())


@pytest.fixture(scope="module")
def mini(spark):
    pairs = spark.createDataFrame([(t, i) for t, ids in MINI for i in ids], "term string, ord bigint")
    return Lists(postings.to_gaps(pairs), 16, 5, 18)


def test_mini(mini):
    assert {r.term: r.gaps for r in mini.gaps.collect()}["b"] == [2, 5, 1, 2, 1, 2]
    assert baselines.length_bits(mini).first().length_bits == 19
    assert {r.state: (r.zeros, r.ones) for r in baselines.markov4_counts(mini).collect()} == {"00": (45, 9), "01": (6, 4), "10": (7, 3), "11": (4, 2)}
    got = mini.gaps.select(clusters.batch_of(F.col("n") / 16.0).alias("b"), "term").orderBy("term").collect()
    assert [r.b for r in got] == [6, 7, 6, 5, 7]
    g = baselines.gap_code_bits(mini).first()
    assert (g.gamma_bits, g.delta_bits, g.vbyte_bits, g.nibble_bits, g.unary_bits) == (58, 66, 144, 80, 60)


@pytest.mark.parametrize("span", [256, 3])
def test_split_by_reference(spark, mini, span, monkeypatch):
    monkeypatch.setattr(clusters, "RANGE", span)
    pairs = postings.to_ids(mini.gaps)
    own = pairs.select("term").distinct().withColumn("c", F.lit(0))
    ref = clusters.reference_lists(pairs, own, 4)
    assert [r.ord for r in ref.orderBy("ord").collect()] == [2, 4, 11, 16]
    want = {("a", "hit"): [4], ("a", "rest"): [9], ("b", "hit"): [1, 3], ("b", "rest"): [5, 6, 8, 10], ("c", "hit"): [1, 2], ("c", "rest"): [2], ("d", "hit"): [3], ("e", "hit"): [2, 4], ("e", "rest"): [3, 4, 7, 11]}
    got: dict = {}
    for r in clusters.split_by_reference(pairs, own, ref).collect():
        got.setdefault((r.term, r.part), []).append(r.x)
    assert {k: sorted(v) for k, v in got.items()} == want


def test_shards_are_lists_of_their_own(spark):
    pairs = spark.createDataFrame([("x", i) for i in range(1, 60, 3)] + [("y", 7)], "term string, ord bigint")
    gaps = postings.to_gaps(pairs, shard=8)
    lists = Lists(gaps, 60, 2, 21)
    assert gaps.count() > 2 and sorted(map(tuple, postings.to_ids(gaps).collect())) == sorted(map(tuple, pairs.collect()))
    for method in ("trit_static", "trit_adaptive"):
        done = coders.encode(lists, method, target=20).cache()
        assert done.count() > 1
        assert coders.roundtrip_mismatches(gaps, coders.decode(done)).first().mismatches == 0


@pytest.mark.parametrize("shard", [2, 8, 16])
def test_bit_contexts_count_every_shard(spark, shard):
    pairs = [("x", i) for i in range(1, 60, 3)] + [("x", 30), ("x", 32), ("x", 33), ("y", 7), ("z", 9), ("z", 50)]
    pairs = spark.createDataFrame(pairs, "term string, ord bigint")
    cut, whole = (Lists(postings.to_gaps(pairs, shard=s), 64, 3, 26) for s in (shard, 64))
    assert cut.gaps.where("n > size(gaps)").count() > 0
    for k, w in ((0, 0), (2, 0), (3, 4), (4, 12)):
        for adaptive in (False, True):
            a, b = (baselines.bitmap_context_bits(x, k, w, adaptive).first() for x in (cut, whole))
            assert a.payload_bits == pytest.approx(b.payload_bits, rel=1e-12) and a.model_bits == b.model_bits and a.payload_bits > 0, (k, w)


def test_optimal_partition_keeps_its_name(spark, monkeypatch):
    monkeypatch.setattr(baselines, "OPT_LONGEST", 10)
    pairs = [("long", i * i) for i in range(1, 21)] + [("short", i) for i in (3, 4, 5, 90)]
    lists = Lists(postings.to_gaps(spark.createDataFrame(pairs, "term string, ord bigint")), 400, 2, 24)
    bits = lambda t, name: baselines.kernel_bits(Lists(lists.gaps.where(f"term = '{t}'"), 400, 1, 0), [name]).collect()
    got = {r.codec: r.bits for r in baselines.kernel_bits(lists, ["pef_opt", "pef_approx"]).collect()}
    assert got["pef_opt_long_approx"] == bits("long", "pef_approx")[0].bits > 0
    assert [(r.codec, r.bits) for r in bits("short", "pef_opt")] == [("pef_opt", got["pef_opt"])]
    assert baselines.optimal_ints(lists) == 4
    each = baselines.kernel_bits(lists, ["pef_opt"], by_list=True).collect()
    assert sorted((r.term, r.codec) for r in each) == [("long", "pef_opt_long_approx"), ("short", "pef_opt")]


def test_empty_collection(spark):
    empty = spark.createDataFrame([], "doc bigint, term string")
    lists = postings.build(empty)
    assert (lists.d, lists.w, lists.i) == (0, 0, 0)
    assert coders.encode(lists, "trit_adaptive").count() == 0
    assert ordering.order_bisect(empty).count() == 0


def test_malformed_gaps_raise(spark):
    bad = spark.createDataFrame([("a", 2, 0, 0, [3, 0])], "term string, n bigint, shard bigint, before bigint, gaps array<bigint>")
    with pytest.raises(Exception, match="strictly increasing"):
        coders.encode(Lists(bad, 9, 1, 2), "trit_adaptive").collect()
    with pytest.raises(ValueError):
        postings.check_ids([3, 3])


def test_segments_cost_little(spark, sf_dir):
    from postings_engine.operators import trits

    lists = corpus(spark, sf_dir, "documents", "source")
    bits = [coders.sweep_adaptive(lists, {"k": (trits.hybrid(7, 7, 8), 256)}, target=t).first().payload_bits for t in (1 << 22, 1 << 17)]
    assert abs(bits[1] - bits[0]) <= 0.03 * bits[0]


def test_distributed_bisection_is_near_the_local_one(spark, sf_dir):
    docs = tables.read_table(spark, sf_dir, "conversations").select((F.col("conv_id") * 65536 + F.col("turn")).alias("doc"), "text")
    from postings_engine.functions.text import tokens

    tok = tokens(docs, "doc", "text").cache()
    size = lambda o: baselines.gap_code_bits(postings.build(tok, o)).first().delta_bits
    local, spread = size(ordering.order_bisect(tok)), size(ordering.order_bisect(tok, rounds=4, local_postings=3000))
    assert spread <= 1.05 * local < size(ordering.order_random(docs, "doc"))


def test_distributed_bisection_uses_common_words(spark):
    # two kinds of documents, 7 to 3 in either half by id; every word is in far more than a tenth of them
    kind = {i: int(i % 10 < (3 if i < 100 else 7)) for i in range(200)}
    rows = [(i, f"{kind[i]}_{j}") for i in range(200) for j in range(8) if (i // 10 + j) % 5]
    order = ordering.order_bisect(spark.createDataFrame(rows, "doc bigint, term string"), rounds=4, local_postings=800)
    first = [kind[r.doc] for r in order.orderBy("ord").collect()][:100]
    assert sum(first) in range(5) or sum(first) in range(96, 101)


def test_main_comparison_favours_adaptive(spark, sf_dir):
    got = {r.method: r.bpi for r in QUERIES["main_comparison"](spark, sf_dir).collect()}
    assert got["trit_adaptive"] < min(v for k, v in got.items() if k != "trit_adaptive")
    total = measures.totals(measures.compare(corpus(spark, sf_dir, "pages", "bisect"), ("midpoint", "trit_adaptive")))
    assert measures.gain(total).first().gain_pct > 0


def test_index_round_trip_and_pruning(spark, sf_dir, tmp_path):
    lists = corpus(spark, sf_dir, "benchmark")
    tables.write_index(coders.encode(lists, "trit_adaptive", target=1 << 11), str(tmp_path / "i"), "one")
    back = tables.read_index(spark, str(tmp_path / "i"), "one", "trit_adaptive")
    assert coders.roundtrip_mismatches(lists.gaps, coders.decode(back)).first().mismatches == 0
    found = lookup.segments_for(back, ["the"])
    plan = found._jdf.queryExecution().toString()
    assert "PartitionFilters" in plan and "term_lo" in plan
    spark.dataSource.register(tables.PostingsSource)
    pairs = spark.read.format("postings").option("path", str(tmp_path / "i")).load()
    assert pairs.exceptAll(postings.to_ids(lists.gaps)).count() == 0 and pairs.count() == lists.i
    tables.write_gap_text(lists.gaps, str(tmp_path / "t"))
    assert coders.roundtrip_mismatches(lists.gaps, tables.read_gap_text(spark, str(tmp_path / "t"))).first().mismatches == 0


def test_scans_read_only_what_they_need(spark, sf_dir):
    plan = QUERIES["vocab_df"](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    schema = plan.split("ReadSchema: ")[1].split("\n")[0]
    assert "text" in schema and "n_chars" not in schema and "lang" not in schema


def test_stream_of_segments(spark, sf_dir, tmp_path):
    events = tables.read_table(spark, sf_dir, "events").orderBy("ts")
    rows = events.collect()
    src = tmp_path / "src"
    for k in range(5):
        part = rows[k * len(rows) // 5 : (k + 1) * len(rows) // 5]
        spark.createDataFrame(part, streaming.EVENTS).coalesce(1).write.mode("append").parquet(str(src))
    late = [r.asDict() | {"event_id": 10**6 + r.event_id} for r in rows[:20]]
    q = streaming.write_segments(streaming.event_stream(spark, str(src)), str(tmp_path / "out"), str(tmp_path / "cp"))
    q.awaitTermination(120)
    spark.createDataFrame(late, streaming.EVENTS).coalesce(1).write.mode("append").parquet(str(src))
    q = streaming.write_segments(streaming.event_stream(spark, str(src)), str(tmp_path / "out"), str(tmp_path / "cp"))
    q.awaitTermination(120)
    got = streaming.read_segments(spark, str(tmp_path / "out"))
    want = events.select(F.col("event_type").alias("term"), (F.col("event_id") + 1).alias("ord"))
    assert got.exceptAll(want).count() == 0 == want.exceptAll(got).count()
    streaming.compact(spark, str(tmp_path / "out"), str(tmp_path / "one"))
    assert streaming.compacted(spark, str(tmp_path / "one")).exceptAll(want).count() == 0


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_header_is_readable(spark, sf_dir):
    s = coders.encode(corpus(spark, sf_dir, "benchmark"), "trit_static")
    assert json.loads(s.first().header)["bits"] == 8


@pytest.mark.parametrize("name", ["json_value_lists", "part_order_lists", "daily_lists", "event_type_lists"])
def test_a_list_of_several_shards_is_one_row(spark, duck, sf_dir, name, monkeypatch):
    whole = postings.to_gaps
    monkeypatch.setattr(corpora, "to_gaps", lambda pairs: whole(pairs, 50))
    df = entry.queries()[name](spark, sf_dir)
    want = duck.execute(ORACLES[name])
    assert rows_of(df.columns, [tuple(r) for r in df.collect()]) == rows_of([d[0] for d in want.description], want.fetchall())


@pytest.mark.parametrize("parts", [1, 5])
def test_bisection_goes_on_in_tasks_of_its_parts(spark, sf_dir, parts, monkeypatch):
    tok = corpora.tokens(corpora.documents_of(spark, sf_dir, "documents"), "doc", "text").cache()
    monkeypatch.setattr(ordering, "LOCAL_PARTS", parts)
    got = {r.doc: r.ord for r in ordering.order_bisect(tok).collect()}
    pairs = tok.toPandas()
    docs, terms = sorted(set(pairs["doc"])), pairs["term"].factorize()[0]
    place = {x: i for i, x in enumerate(docs)}
    order = ordering.bisect_block(pairs["doc"].map(place).to_numpy(), terms, len(docs))
    assert [docs[i] for i in order] == sorted(got, key=got.get)


def test_bisection_in_one_task_reads_its_pairs_once(spark):
    read = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    rows = [(i, f"{i % 3}_{j}") for i in range(60) for j in range(5)]
    tok = spark.createDataFrame(rows, "doc bigint, term string").mapInArrow(count, "doc bigint, term string")
    assert ordering.order_bisect(tok).count() == 60
    assert read.value == len(rows)


def test_columns_are_read_once(spark):
    read = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    kind = "v bigint, r bigint"
    rows = spark.createDataFrame([(i % 7, 1 + i * i % 500) for i in range(300)] + [(None, 3), (2, None)], kind).mapInArrow(count, kind)
    lists = corpora.column_lists(rows, F.col("v"), F.col("r"))
    want = {(i % 7, 1 + i * i % 500) for i in range(300)}
    assert (lists.d, lists.w, lists.i, read.value) == (max(r for _, r in want), 7, len(want), 302)
    assert {(int(r.term), r.ord) for r in postings.to_ids(lists.gaps).collect()} == want
    gaps = lists.gaps
    read.value = 0
    counted = postings.Lists(gaps.mapInArrow(count, gaps.schema), lists.d, lists.w, lists.i)
    baselines.packed_arith_bits(counted).collect()
    assert read.value == gaps.count()


def test_static_sizes_without_segments(spark, sf_dir):
    lists = corpus(spark, sf_dir, "conversations")
    want = {r.part: r.bits for r in coders.sizes(coders.encode(lists, "trit_static", payload=False)).collect()}
    got = {r.part: r.bits for r in measures.parts(lists, "trit_static").collect()}
    assert got["model"] == want["model"] and abs(got["payload"] - want["ideal"]) <= 1
    q, n = baselines.packed_symbols(np.array([1, 2, 65535, 65536, 1 << 40]), "modelled")[1:]
    assert baselines.raw_bits(q, "modelled").tolist() == n.tolist()


@pytest.mark.parametrize("mantissa", ["modelled", "raw"])
def test_packed_classes_against_a_plain_count(spark, mantissa):
    rng = np.random.default_rng(3)
    rows = [(f"t{i}", n := 1 + 97 * i % 400, 0, 0, (1 + rng.zipf(1.2, n) % (1 << 20)).tolist()) for i in range(20)]
    gaps = spark.createDataFrame(rows, "term string, n bigint, shard bigint, before bigint, gaps array<bigint>")
    want = {}
    for *_, g in rows:
        for a in range(0, len(g), 128):
            width, sym, raw = baselines.packed_symbols(np.array(g[a : a + 128]), mantissa)
            own = baselines.selector_of(width)
            for s, r in [*zip(sym.tolist(), raw.tolist(), strict=True), (-1, 0)]:
                n, b = want.get((own, s), (0, 0))
                want[own, s] = n + 1, b + r
    got = baselines.packed_classes(postings.Lists(gaps, 1 << 30, 20, 0), mantissa=mantissa).collect()
    assert {(r.selector, r.symbol): (r.n, r.raw) for r in got} == want


@pytest.mark.parametrize("bound", [6000, 1500])
def test_levels_by_arrays_give_the_order_of_one_task(spark, bound, monkeypatch):
    rng = np.random.default_rng(6)
    rows = [(7 * i, f"w{j}") for i in range(512) for j in np.unique(rng.zipf(1.3, 25) % (60 + i % 5 * 40))]
    tok = spark.createDataFrame(rows, "doc bigint, term string").cache()
    in_order = lambda df: [r.doc for r in df.orderBy("ord").collect()]
    monkeypatch.setattr(ordering, "GAIN_ROWS", 100)
    monkeypatch.setattr(ordering, "BLOCK_POSTINGS", 2000)
    assert len(rows) > bound
    with monkeypatch.context() as less:
        less.setattr(ordering, "_level", None)  # no joins
        assert in_order(ordering.order_bisect(tok, local_postings=bound)) == in_order(ordering.order_bisect(tok))
    monkeypatch.setattr(ordering, "ARRAY_DOCS", 0)
    assert sorted(in_order(ordering.order_bisect(tok, rounds=2, local_postings=6000))) == [7 * i for i in range(512)]
