"""Rows that share an id or have none, digests by brute force, licence notices by edit distance."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from postings_engine.llm import embedding_dedup, license_scan, mixing, ngram_join, secret_scan
from postings_engine.llm.common import read
from postings_engine.llm.queries import QUERIES

SCHEMA = "doc_id bigint, text string, source string, copies int, row string, __k int"


def frame(spark, rows):
    return spark.createDataFrame([(*r, 1, "x", 2) for r in rows], SCHEMA).repartition(3)


@pytest.mark.parametrize("block", [4096, 32])
def test_mixed_rows_of_repeated_ids(spark, block, monkeypatch):
    monkeypatch.setattr(mixing, "BLOCK_ROWS", block)
    rng = random.Random(5)
    rows = [(None, f"a{i} b c", "s") for i in range(20)] + [(1, f"t{i}", "s") for i in range(4)] + [(7, "same words here", "s")] * 30
    rows += [(i, "w " * rng.randrange(60), rng.choice(["s", "t", None])) for i in range(100, 300)]
    df = frame(spark, rows)
    took = mixing.mix(df).collect()
    assert len(took) == len(rows) and sorted(map(str, took)) == sorted(map(str, mixing.mix(df.repartition(5)).collect()))
    out = mixing.mixed_rows(df)
    assert out.columns == df.columns
    got = Counter((r.doc_id, r.text, r.source) for r in out.collect())
    assert sum(got.values()) == sum(r.copies for r in took)
    assert all(n <= 2 * Counter(rows)[k] for k, n in got.items()) and set(got) <= set(rows)
    words = Counter()
    for (_, text, source), n in got.items():
        words[source] += n * len(text.split())
    target = {source: r.target for r in took for source in ("s", "t", None) if r.source_size == sum(len(t.split()) for _, t, x in rows if x == source)}
    assert len(target) == 3 and all(abs(words[s] - t) <= 6 for s, t in target.items())


def test_mixed_rows_empty_and_wordless(spark):
    assert mixing.mixed_rows(frame(spark, [(1, "a", "s")]).limit(0)).count() == 0
    assert mixing.mixed_rows(frame(spark, [(1, None, "s"), (1, "", None), (None, " \t", "s")])).count() == 0


@pytest.mark.parametrize("block", [4096, 64])
def test_mix_comes_near_its_targets(spark, sf_dir, block, monkeypatch):
    monkeypatch.setattr(mixing, "BLOCK_ROWS", block)
    rows = QUERIES["op8_mixing"](spark, sf_dir).join(read(spark, sf_dir, "documents").select("doc_id", "source", "text"), "doc_id")
    got = rows.groupBy("source").agg(F.sum("taken").alias("t"), F.first("target").alias("goal"), F.first("source_size").alias("z"), F.sum("size").alias("s"), F.count("*").alias("n")).collect()
    for r in got:
        assert r.z == r.s and abs(r.t - r.goal) <= max(5, 0.25 * r.s / r.n), r
    assert rows.where("size <> coalesce(size(filter(split(text, '[\\\\x20\\\\x09-\\\\x0D]+'), x -> x <> '')), 0) or taken > 2 * size").count() == 0
    assert sum(r.goal for r in got) == pytest.approx(1.5 * sum(r.z for r in got))


def test_keep_one_of_repeated_ids(spark):
    near = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen " * 2
    rows = [(1, "a text of its own with some words", "s"), (1, "another text that shares only the id", "s"), (2, near, "s"), (2, near, "s"), (2, near.upper(), "s"), (3, near + "more", "s")]
    rows += [(None, "nobody named this one text here", "s")] * 3 + [(None, near, "s"), (None, "nor this one of six words", "t"), (4, None, "s"), (4, None, "s"), (4, "", "s")]
    df = frame(spark, rows)
    want = Counter([rows[0], rows[1], rows[6], rows[10], rows[11], rows[11], rows[13]])
    for k in (1, 4):
        out = ngram_join.keep_one(df.repartition(k))
        assert out.columns == df.columns
        got = Counter((r.doc_id, r.text, r.source) for r in out.collect())
        kept = [r for r in got if r[0] == 2]
        assert len(kept) == 1 and got[kept[0]] == 1 and kept[0][1].lower() == near
        assert Counter({r: n for r, n in got.items() if r[0] != 2}) == want
    assert ngram_join.keep_one(df.limit(0)).count() == 0


def test_stages_take_odd_and_empty_documents(spark, sf_dir):
    docs = read(spark, sf_dir, "documents")
    odd = spark.createDataFrame([(None, None, None, None, None), (None, "", "en", "s", 0), (5, "x", None, None, 1), (5, "y", None, None, 1)], docs.schema)
    for rows in (docs.limit(0), docs.limit(40).unionByName(odd).unionByName(docs.limit(3))):
        for name, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, rows, sf_dir)
            assert out.columns == docs.columns and (out.count() == 0 or not rows.isEmpty()), name
        assert corpus_pipeline.STAGES[-1][1](spark, rows, sf_dir).count() == rows.count()


# --- secrets: the query's counts and digest ---------------------------------------------------------------------------


def test_secret_digest_holds_the_base(spark, sf_dir):
    patterns = {
        "assign": re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I | re.A),
        "access": re.compile(r"AKIA[A-Z0-9]+"), "hex": re.compile(r"[0-9a-f]+"),
    }
    odd = ['Token = "abcdef"', "token=abc", "paſſword: abcdefg", "API_KEY:'x1y2z3'", "AKIA" + "A1" * 9, "f" * 24, None, "", "secret secret=12345678"]
    docs = read(spark, sf_dir, "documents").select("doc_id", "text").unionByName(spark.createDataFrame(list(enumerate(odd, 10**6)), "doc_id bigint, text string"))
    text = {r.doc_id: r.text or "" for r in docs.collect()}
    for r in secret_scan.secret_digest(docs).collect():
        found = []
        for k, (kind, p) in enumerate(patterns.items()):
            for m in p.finditer(text[r.doc_id]):
                if kind == "assign" and len(m.group(2)) >= 6 or kind == "access" and len(m.group()) >= 20 or kind == "hex" and len(m.group()) >= 24:
                    found.append((m.start(), k, kind, m.end()))
        line = ",".join(f"{kind}:{a}:{b}" for a, _, kind, b in sorted(found))
        assert r.base_sha256 == hashlib.sha256(line.encode()).hexdigest()
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(x[2] == kind for x in found) for kind in patterns)
        spans = r.spans.split(",") if r.spans else []
        assert set(line.split(",") if line else []) <= set(spans)
        assert [int(x.split(":")[1]) for x in spans] == sorted(int(x.split(":")[1]) for x in spans)


# --- licences ----------------------------------------------------------------------------------------------------------


def near_places(line: bytes, notice: bytes, edits: int) -> bool:
    """Whether some run of whole words of the line lies within the edits of the notice, by the table of edit distances."""
    starts = [0, *(i + 1 for i, c in enumerate(line) if c == 32)]
    ends = {*(i for i, c in enumerate(line) if c == 32), len(line)}
    for a in starts:
        row = np.arange(len(notice) + 1)
        for b in range(a, min(len(line), a + len(notice) + edits) + 1):
            if b > a:
                diag = row[:-1] + (np.frombuffer(notice, np.uint8) != line[b - 1])
                new = np.concatenate([[b - a], np.minimum(diag, row[1:] + 1)])
                row = np.minimum.accumulate(new - np.arange(len(new))) + np.arange(len(new))
            if b in ends and b > a and row[-1] <= edits:
                return True
    return False


def test_notices_against_edit_distance():
    rng, search = random.Random(11), license_scan.NoticeSearch()
    notices = [n for n in license_scan.NOTICES if n.edits]
    for _ in range(250):
        n = rng.choice(notices)
        t = list(n.text)
        for _ in range(rng.randrange(n.edits + 2)):
            at, how = rng.randrange(len(t)), rng.randrange(3)
            t[at : at + (how != 0)] = [rng.choice("aeilst x")] if how < 2 else []
        words = "".join(t).split()
        around = ["plain", "words", "the", "license", "of"]
        line = " ".join([*rng.choices(around, k=rng.randrange(4)), *words, *rng.choices(around, k=rng.randrange(4))]).encode()
        found = {(m[0]) for m in search(line)}
        want = {x.label for x in license_scan.NOTICES if near_places(line, x.text.encode(), x.edits)}
        assert found == want, line
        for label, a, b, cost in search(line):
            assert (a == 0 or line[a - 1] == 32) and (b == len(line) or line[b] == 32) and cost <= max(x.edits for x in license_scan.NOTICES if x.label == label)


def test_windows_find_what_the_whole_line_holds():
    rng, search = random.Random(3), license_scan.NoticeSearch()
    for _ in range(60):
        parts = []
        for _ in range(rng.randrange(1, 6)):
            n = rng.choice(license_scan.NOTICES)
            t = list(n.text)
            for _ in range(rng.randrange(n.edits + 1)):
                t[rng.randrange(len(t))] = rng.choice("abc")
            parts += ["".join(t), "filler " * rng.randrange(20)]
        line = " ".join(" ".join(parts).split()).encode()
        whole = [(n.label, m.start()) for n, _, _, verify, _ in search.found for m in verify.finditer(line)]
        assert len(whole) == len(search(line)) and Counter(x[0] for x in whole) == Counter(m[0] for m in search(line))


def test_words_beyond_ascii_are_other_words():
    scan = license_scan.LicenseScan()
    n, places, matches, score = scan("éunder the mit license".encode())
    assert not places and score < 1.0 and all(m[3] > 0 for m in matches)
    assert scan("漢字under the mit license".encode())[2:] == ([], 0.0)


def test_license_query_reports_spans(spark, sf_dir):
    rows = QUERIES["op7_license_scan"](spark, sf_dir).collect()
    some = [r for r in rows if r.spans]
    assert some
    for r in rows:
        spans = [x.rsplit(":", 3) for x in r.spans.split(",")] if r.spans else []
        assert {x[0] for x in spans} | set(filter(None, r.base_labels.split(","))) == set(filter(None, r.labels.split(",")))
        assert all(0 <= int(a) <= int(b) < r.n_words for _, a, b, _ in spans)


# --- embeddings --------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("big", [2048, 4])
def test_embeddings_of_the_table(spark, sf_dir, big, monkeypatch):
    monkeypatch.setattr(embedding_dedup, "BIG_BUCKET", big)
    monkeypatch.setattr(embedding_dedup, "STRIP", 3 if big == 4 else 512)
    rows = read(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label").collect()
    rng = np.random.default_rng(1)
    extra = [(10**6 + i, (np.array(rows[i % 5].embedding) + 0.01 * rng.standard_normal(len(rows[0].embedding)) / 8).tolist(), rows[i % 5].label) for i in range(60)]
    data = [tuple(r) for r in rows] + extra + [(None, rows[0].embedding, rows[0].label)]
    df = spark.createDataFrame(data, "vec_id bigint, embedding array<float>, label int").repartition(4)
    v = np.array([np.array(r[1], np.float32).astype(float) for r in data])
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    same = np.array([r[2] for r in data])
    link = (v @ v.T >= 0.98) & (same[:, None] == same[None, :])
    want = {r[0]: int(link[i].sum()) - 1 for i, r in enumerate(data)}
    got = {r.vec_id: r for r in embedding_dedup.near_duplicates(df).collect()}
    assert len(got) == len(data) and sum(r.n_links for r in got.values()) >= 0.99 * sum(want.values())
    assert all(got[k].n_links <= n for k, n in want.items()) and all(r.kept == (r.vec_id == r.component_id) for r in got.values() if r.vec_id is not None)
