"""Each operator against brute force or the library it must agree with, and on awkward input."""

import base64
import hashlib
import random
import re
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers as P
import pytest

import corpus_pipeline
from postings_engine.llm import bpe_codec, components, embedding_dedup, license_scan, mixing, ngram_join, quality_rules, secret_scan, token_counts, toxicity, url_filters
from postings_engine.llm.common import BitFilter, read
from postings_engine.llm.queries import ORACLE_SQL, QUERIES

JSON, RANKS = P.path("byte_bpe_50k.json"), P.path("byte_bpe_50k.tiktoken")
LONG = "lorem ipsum dolor " * 20000
TEXTS = [None, "", " \t\n", "a", "a b", "The the THE", "same text here today", "same text here today", "é漢字 😀 <|endoftext|> x", "x" * 3000, LONG, "\u000b\u0085\u00a0\u2003 İ ß", "it's 'll  \n\n  12²٣"]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in all columns, empty and long texts, repeated rows, clashing extra columns."""
    rows = [(i, t, None if i % 3 == 0 else f"s{i % 2}", 7, "x", True) for i, t in enumerate(TEXTS)]
    rows += [rows[6], (None, "text without an id", None, None, None, None)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, source string, n_tokens int, score string, kept boolean").repartition(3)


@pytest.fixture(scope="module")
def empty(odd):
    return odd.limit(0)


OPERATORS = {
    "join": lambda d: ngram_join.similar_groups(d), "secrets": secret_scan.secret_digest, "tokens": lambda d: token_counts.count_tokens(d, JSON), "bpe": lambda d: bpe_codec.roundtrip_digest(d, RANKS),
    "licenses": license_scan.scan_licenses, "mix": mixing.mix, "quality": quality_rules.judge, "toxicity": lambda d: toxicity.score(d, toxicity.Lexicon({"idiot": 5.0})),
}


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_awkward_input(name, odd, empty):
    rows = OPERATORS[name](odd).collect()
    assert Counter(r.doc_id for r in rows) == Counter([*range(len(TEXTS)), 6, None])
    assert OPERATORS[name](empty).count() == 0


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_against_sql(name, spark, sf_dir, duck):
    df = QUERIES[name](spark, sf_dir)
    want = duck.execute(ORACLE_SQL[name])
    names = [d[0] for d in want.description]
    assert sorted(names) == sorted(df.columns)
    assert sorted(map(repr, (tuple(r[n] for n in names) for r in df.collect()))) == sorted(map(repr, want.fetchall()))


# --- 1 ---------------------------------------------------------------------------------------------------------------


def brute_url(url):
    host = path = ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        host = re.match(r"[^/?#]*", rest).group()
        path = re.match(r"[^?#]*", rest[len(host) :], re.S).group()
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
    best = max((r for r in url_filters.RULES if (host == (h := r[1].split("/")[0]) or host.endswith("." + h)) and path.startswith(r[1][len(h) :])), key=lambda r: len(r[1]), default=None)
    return host, path, best and best[1], best[0] if best else "allow"


URLS = [None, "", "no scheme", "http://", "http://NET", "http://net/", "http://a.net/x?y", "http://anet/", "ftp://x.EXAMPLE.net/en/a#b", "https://example.net/en", "https://b.example.com/de/", "https://org/fr/q", "https://x.org/fr/://net/", "http://.net/", "x://y://net/", "http://net?/", "http://a\nb.net/\n?"]


@pytest.mark.parametrize("max_bytes", [32 << 20, 1])
def test_urls(spark, max_bytes):
    df = spark.createDataFrame([(i, u, "h", "r") for i, u in enumerate(URLS + URLS)], "page_id bigint, url string, host string, rule string")
    got = url_filters.judge_urls(df, url_filters.rule_table(spark), max_bytes=max_bytes).collect()
    assert Counter(tuple(r) for r in got) == Counter((i, *brute_url(u)) for i, u in enumerate(URLS + URLS))
    assert url_filters.judge_urls(df.limit(0), url_filters.rule_table(spark)).count() == 0
    assert {r.verdict for r in url_filters.judge_urls(df, url_filters.rule_table(spark, []).limit(0)).collect()} == {"allow"} if max_bytes > 1 else True


def test_cascade_is_exact(spark):
    universe, listed = spark.range(20000).selectExpr("xxhash64(id) AS k"), spark.range(0, 20000, 7).selectExpr("xxhash64(id) AS k")
    c = url_filters.Cascade.build(listed, universe)
    keys = np.array([r.k for r in universe.collect()])
    want = {r.k for r in listed.collect()}
    assert len(c.levels) > 1 and c.has(keys).tolist() == [k in want for k in keys.tolist()]


def test_bit_filter_bound(spark):
    assert BitFilter.build(spark.range(10).toDF("k"), 10**9, max_bytes=1 << 20) is None


# --- 2 ---------------------------------------------------------------------------------------------------------------


def brute_groups(rows, n, pct):
    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), t or ""))
        return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)} if w else set()

    sets = [shingles(t) for _, t in rows]
    root = list(range(len(sets)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, x in enumerate(sets):
        for j in range(i):
            both = len(x & sets[j])
            if x and 100 * both >= pct * (len(x) + len(sets[j]) - both):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    least = defaultdict(lambda: 1 << 60)
    for i, (k, _) in enumerate(rows):
        least[find(i)] = min(least[find(i)], k)
    return {k: (len(sets[i]), least[find(i)]) for i, (k, _) in enumerate(rows)}


def copies(seed=1, n=120):
    rng = random.Random(seed)
    base = [[f"w{rng.randrange(40)}" for _ in range(rng.choice((4, 12, 60, 61)))] for _ in range(4)]
    passage = [f"p{i}" for i in range(55)]
    rows = []
    for k in range(n):
        w = list(rng.choice(base))
        for _ in range(rng.randrange(6)):
            w[rng.randrange(len(w))] = f"v{rng.randrange(9)}"
        if k % 5 == 0:
            w = [f"x{k}_{i}" for i in range(60)] + passage
        rows.append((k * 3 + 1, " ".join(w) if k % 17 else w[0]))
    return rows


@pytest.mark.parametrize(("n", "pct"), [(3, 90), (5, 80), (1, 60), (2, 100)])
@pytest.mark.parametrize("grams", [4_000_000, 400])
def test_groups(spark, n, pct, grams, monkeypatch):
    monkeypatch.setattr(ngram_join, "GROUP_GRAMS", grams)
    monkeypatch.setattr(ngram_join, "BIG_GROUP", 8 if grams == 400 else 2048)
    rows = copies()
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3)
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.similar_groups(df, n, pct).collect()} == brute_groups(rows, n, pct)


def test_keep_one(spark):
    rows = copies(2) + [(None, "no id")]
    df = spark.createDataFrame([(*r, 5) for r in rows], "doc_id bigint, text string, component_id int")
    groups = brute_groups(rows[:-1], 5, 80)
    kept = ngram_join.keep_one(df)
    assert kept.columns == df.columns
    assert {r.doc_id for r in kept.collect()} == {k for k, v in groups.items() if v[0] == 0 or v[1] == k} | {None}


def test_components(spark):
    links = [(i, i + 1) for i in range(1, 40)] + [(100, 101), (103, 101)] + [(200, 200 + i) for i in range(1, 50)]
    got = {r.node: r.comp for r in components.connected(spark.createDataFrame(links, "u bigint, v bigint")).collect()}
    assert got == {i: 1 for i in range(1, 41)} | {100: 100, 101: 100, 103: 100} | {i: 200 for i in range(200, 250)}


# --- 3 ---------------------------------------------------------------------------------------------------------------


def test_secret_patterns():
    kinds = lambda t: [k for k, _, _ in secret_scan.base_spans(t)]
    assert kinds('password = "hunter2x"') == ["assign"] and kinds("passwd: abc") == [] and kinds("PASSWORD=token:abcdefgh") == []
    assert kinds("AKIA" + "A1" * 8) == ["access"] and kinds("AKIA" + "A" * 15) == [] and kinds("ab12" * 6) == ["hex"] and kinds("ab12" * 5) == []
    assert kinds("pa\u017fsword=abcdefgh") == []  # a long s is not an s


def test_entropy():
    scan = secret_scan.EntropyScan(secret_scan.EntropyRule())
    rng = random.Random(4)
    key = "".join(rng.choice("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789") for _ in range(40))
    assert [k for k, _, _ in scan(f"é {key} x")] and scan(f"é {key} x")[0][1] >= 2
    for t in ("the quick brown fox " * 5, "antidisestablishmentarianism", "https://example.org/a1B2c3D4e5F6g7H8i9J0k1L2", "550e8400-e29b-41d4-a716-446655440000", "a" * 50, "sha256: " + "0123456789abcdef" * 4):
        assert scan(t) == []
    counts = lambda w: -sum(c / len(w) * np.log2(c / len(w)) for c in Counter(w).values())
    s = "".join(rng.choice("0123456789abcdef") for _ in range(300))
    want = np.zeros(300, bool)
    for i in range(281):
        w = s[i : i + 20]
        if counts(w) >= 3.0 - 1e-9 and sum(c.isdigit() for c in w) >= 2 and any(c.isalpha() for c in w):
            want[i : i + 20] = True
    got = np.zeros(300, bool)
    for a, b in scan.windows(s, 3.0, False):
        got[a:b] = True
    assert (got == want).all()


@pytest.mark.parametrize(
    ("letters", "least"),
    [("abcdefghijklmnopqrstuvwxyz0123456789", 0.9), ("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 0.9), ("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", 0.8), ("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 0.95), ("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ", 0.6), ("abcdefghijklmnopqrstuvwxyz", 0.6)],
)
def test_entropy_of_random_keys(letters, least):
    scan, rng = secret_scan.EntropyScan(secret_scan.EntropyRule()), random.Random(7)
    for n in (20, 40):
        keys = ["".join(rng.choice(letters) for _ in range(n)) for _ in range(300)]
        assert sum(bool(scan(f'key: "{k}"')) for k in keys) >= least * 300, n


def test_entropy_leaves_words_and_rulers():
    scan = secret_scan.EntropyScan(secret_scan.EntropyRule())
    for t in ("+" + "-" * 40 + "+", "internationalisation", "some-long-kebab-case-name-here", "AbstractSingletonProxyFactoryBean", "chteheitbergeerberer", "report_2024_11_26_final_version", "THISISALLUPPERCASEWRITING"):
        assert scan(t) == [], t


def test_redaction(spark):
    df = spark.createDataFrame([(1, "token = 'abcdef0123456789abcdef0123' ok", 3), (2, None, None)], "doc_id bigint, text string, spans int")
    got = {r.doc_id: r.text for r in secret_scan.redact(df).collect()}
    assert got == {1: "[secret]' ok", 2: None}


# --- 4 ---------------------------------------------------------------------------------------------------------------


def test_toxicity_matching():
    m = toxicity.Matcher(toxicity.Lexicon({"idiot": 5.0, "trash": 4.0}))
    for t in ("You IDIOT!", "1d10t", "іdіоt", "idiot$$$", "ïdíot", "ｉｄｉｏｔ"):
        assert m.score(t) >= 0.5, t
    for t in ("", None, "idiotic", "trash can", "hello world"):
        assert m.score(t) < 0.5, t


def test_toxicity_held_out(spark, duck):
    rng = random.Random(3)
    bad = ["zorg", "blaff", "krunt"]
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(4))
    rows, labels = [], []
    for k in range(600):
        w = [word() for _ in range(rng.randrange(20, 200))]
        if k % 8 == 0:
            w[rng.randrange(len(w))] = rng.choice(bad)
        rows.append((k, " ".join(w)))
        labels.append((k, int(k % 8 == 0)))
    docs, labels = spark.createDataFrame(rows, "doc_id bigint, text string"), spark.createDataFrame(labels, "doc_id bigint, toxic int")
    lexicon = toxicity.learn(docs, labels.where("doc_id < 400"))
    assert set(lexicon.weights) == set(bad)
    got = {r.doc_id: r.predicted for r in toxicity.score(docs, lexicon).collect()}
    assert all(got[k] == int(k % 8 == 0) for k in range(600))
    assert toxicity.learn(docs, labels.limit(0)).weights == {}


def test_toxicity_copies_of_one_text_keep_the_lexicon(spark):
    rng = random.Random(5)
    bad = ["zorg", "blaff", "krunt"]
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(4))
    rows = []
    for k in range(400):
        w = [word() for _ in range(rng.randrange(20, 60))]
        if k % 8 == 0:
            w[rng.randrange(len(w))] = rng.choice(bad)
        rows.append((k, " ".join(w), int(k % 8 == 0)))
    hot = " ".join([word(), *(x for b in bad for x in (b, word()))])
    rows += [(1000 + k, hot, int(k > 0)) for k in range(600)]  # one of the copies has the other label
    df = spark.createDataFrame(rows, "doc_id bigint, text string, toxic int")
    docs, labels = df.select("doc_id", "text"), df.select("doc_id", "toxic")
    lexicon = toxicity.learn(docs.union(docs.where("doc_id = 8")), labels)
    assert set(lexicon.weights) == set(bad)
    got = {r.doc_id: r.predicted for r in toxicity.score(docs, lexicon).collect()}
    assert all(got[k] == y for k, _, y in rows if k < 1000) and all(got[k] == 1 for k, _, _ in rows if k >= 1000)
    assert toxicity.learn(docs, labels, max_labelled=401).weights == lexicon.weights


# --- 5 and 6 ---------------------------------------------------------------------------------------------------------


def strange_texts():
    rng = random.Random(3)
    alpha = ["'s", "'ll", "<|endoftext|>", "aaa", "the", " ", "  ", "\n", "1", "²", "٣", "é", "漢", "😀", "$$", "İ", "\U00016d40", "\x1c", "\u0085", "\u2003", "\u0378", "\ua7d2"]
    return ["".join(rng.choice(alpha) if rng.random() < 0.8 else chr(rng.choice([rng.randrange(32, 0x3000), rng.randrange(0x10000, 0x1FFFF)])) for _ in range(rng.randrange(60))) for _ in range(800)] + ["a" * 3000, "ab" * 900, " " * 500 + "x"] + [t for t in TEXTS if t]


def test_token_counts_agree_with_the_library():
    from tokenizers import Tokenizer

    lib, own = Tokenizer.from_file(JSON), token_counts.MergeCounter(JSON)
    for t in strange_texts():
        assert own.count(t) == len(lib.encode(t, add_special_tokens=False).ids), ascii(t)[:200]


def test_ids_agree_with_the_library(spark, odd):
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    lib, own = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={}), bpe_codec.MergeReplay(RANKS)
    for t in strange_texts():
        ids = own.encode(t)
        assert ids == lib.encode_ordinary(t), ascii(t)[:200]
        assert own.decode(ids).decode() == t
    back = bpe_codec.decode(bpe_codec.encode(odd, RANKS), RANKS).collect()
    assert Counter((r.doc_id, bytes(r.bytes).decode()) for r in back) == Counter((r.doc_id, r.text or "") for r in odd.collect())
    for r in bpe_codec.roundtrip_digest(odd.where("doc_id = 10"), RANKS).collect():
        assert r.ids_sha256 == hashlib.sha256(" ".join(map(str, lib.encode_ordinary(LONG))).encode()).hexdigest() and r.decoded_sha256 == hashlib.sha256(LONG.encode()).hexdigest()


# --- 7 ---------------------------------------------------------------------------------------------------------------


def test_licenses():
    scan = license_scan.LicenseScan()
    labels = lambda t: sorted({m[0] for m in scan(t.encode())[2]})
    assert labels("Released under the MIT license.") == ["mit"] == labels("released under the MlT licence!")
    assert labels("CC-BY-NC 4.0") == ["cc-by-nc"] and labels("CC BY ND") == [] and labels("Apache License, Versoin 2.0") == ["apache-2"]
    assert labels("plain words about a license") == []
    n, places, _, score = scan(b"CC by nc by NC cc-by/nc. " * 2)
    assert n == 16 and [p for p, _ in places] == [0, 5, 8, 13] and score == 1.0
    text = ("filler words of no use " * 50 + "under the mit license ") * 3
    words = re.findall(r"[0-9a-z]+", text)
    assert [p for p, _ in scan(text.encode())[1]] == [i for i in range(len(words)) if words[i : i + 4] == ["under", "the", "mit", "license"]]


def test_licenses_two_notices_in_one_window():
    search = license_scan.NoticeSearch()
    far, exact = "undar the mit licence", "under the mit license"
    for t in (f"{far} here and docs {exact}", f"docs {exact} here and {far}", f"{far} {far} and {exact}"):
        want = [(m.start(), m.end(), 0 if m.group() == exact else 2) for m in re.finditer(f"{far}|{exact}", t)]
        assert [m[1:] for m in search(t.encode()) if m[0] == "mit"] == want, t


# --- 8 ---------------------------------------------------------------------------------------------------------------


def test_flight():
    rng = random.Random(1)
    for _ in range(30):
        n = rng.randrange(1, 200)
        p, x = [rng.random()] * n, [rng.choice((0, 5, 5, rng.randrange(1000))) for _ in range(n)]
        docs, words, left = mixing.check_flight(p, x)
        assert docs < 1e-6 and words < 1e-3 and left <= 2


def test_targets():
    t = mixing.targets({"b": 10, "a": 100, None: 1000})
    assert t["a"] == 200 and t["b"] == 20 and abs(sum(t.values()) - 1.5 * 1110) < 1e-9
    assert mixing.targets({}) == {} and mixing.targets({"a": 0}) == {"a": 0.0}


@pytest.mark.parametrize("block", [4096, 16])
def test_mix(spark, block, monkeypatch):
    monkeypatch.setattr(mixing, "BLOCK_ROWS", block)
    rng = random.Random(7)
    rows = [(k, "w " * rng.randrange(200), rng.choice(["a", "b", "hot", "hot", "hot", None])) for k in range(900)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    got = mixing.mix(df).collect()
    again = mixing.mix(df.repartition(5)).collect()
    assert sorted(map(tuple, got)) == sorted(map(tuple, again)) and len(got) == 900
    source, took = {k: s for k, _, s in rows}, Counter()
    for r in got:
        took[source[r.doc_id]] += r.taken
        assert r.taken <= 2 * r.size and r.taken == r.copies * r.size
    for r in got:
        assert abs(took[source[r.doc_id]] - r.target) <= 200
    mixed = mixing.mixed_rows(df)
    assert mixed.columns == df.columns and mixed.count() == sum(r.copies for r in got)


# --- 9 ---------------------------------------------------------------------------------------------------------------


def test_quality_counts(odd):
    def brute(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        at = defaultdict(list)
        for i in range(len(w) - 7):
            at[tuple(w[i : i + 8])].append(i)
        under = {j for v in at.values() if len(v) > 1 for i in v for j in range(i, i + 8)}
        return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), len(lines) - len(set(lines)), len(under)

    for r in quality_rules.judge(odd).collect():
        text = TEXTS[r.doc_id] if r.doc_id is not None else "text without an id"
        n, chars, symbols, dup, repeat = brute(text)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (n, chars, symbols, dup, repeat)
        assert r.base_failed == (n < 20 or 100 * repeat > 30 * n) and not (r.kept and r.base_failed)


def test_quality_plan_has_no_python(odd):
    plan = quality_rules.judge(odd)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "MapInArrow" not in plan and "Pandas" not in plan
    assert quality_rules.keep(odd).columns == odd.columns


# --- 10 --------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("tile", [1024, 4])
def test_embeddings(spark, tile, monkeypatch):
    monkeypatch.setattr(embedding_dedup, "TILE", tile)
    rng = np.random.default_rng(2)
    base = rng.standard_normal((12, 16))
    x = [(base[rng.integers(12)] + 0.03 * rng.standard_normal(16)) * rng.choice([1e-3, 1, 50]) for _ in range(150)]
    x += [x[0]] * 5
    rows = [(i, v.astype(np.float32).tolist(), int(i % 2)) for i, v in enumerate(x)]
    odd = [(1000, None, 1), (1001, [], 1), (1002, [0.0] * 16, 1), (1003, [float("nan")] * 16, 1), (1004, [None] * 16, 1), (1005, rows[0][1], None), (1006, [1.0, 2.0], 1), (1007, [float("inf")] * 16, 0)]
    df = spark.createDataFrame([(*r, 1, 2) for r in rows + odd], "vec_id bigint, embedding array<float>, label int, n_links int, node int").repartition(3)
    v = np.array([r[1] for r in rows])
    v /= np.linalg.norm(v, axis=1, keepdims=True)
    link = (v @ v.T >= 0.98) & (np.arange(155)[:, None] % 2 == np.arange(155)[None] % 2)
    comp = np.arange(155)
    for _ in range(155):
        comp = np.where(link, comp[None, :], 1000).min(1)
    got = {r.vec_id: r for r in embedding_dedup.near_duplicates(df).collect()}
    assert len(got) == 163
    found = sum(got[i].n_links for i in range(155))
    assert found >= 0.99 * (link.sum() - 155) and all(got[i].n_links <= link[i].sum() - 1 for i in range(155))
    assert np.mean([got[i].component_id == comp[i] for i in range(155)]) > 0.99
    assert all(got[k].n_links == 0 and got[k].component_id == k and got[k].kept for k in range(1000, 1008))
    assert embedding_dedup.near_duplicates(df.limit(0)).count() == 0


# --- pipeline --------------------------------------------------------------------------------------------------------


def test_pipeline(spark, sf_dir, tmp_path):
    docs = read(spark, sf_dir, "documents")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "near_duplicates", "secrets", "mixture", "tokens"]
    stages = {}
    for name, f in corpus_pipeline.STAGES:  # each written and read again, as run() does

        def stage(*how, name=name, f=f):
            f(*how).write.parquet(str(tmp_path / name))
            return spark.read.parquet(str(tmp_path / name))

        stages[name] = stage
    good = stages["quality"](spark, docs, sf_dir)
    assert {r.doc_id for r in good.collect()} == {r.doc_id for r in quality_rules.judge(docs).where("kept").collect()}
    rows = [(r.doc_id, r.text) for r in good.collect()]
    one = stages["near_duplicates"](spark, good, sf_dir)
    assert {r.doc_id for r in one.collect()} == {k for k, v in brute_groups(rows, 5, 80).items() if v[1] == k}
    clean = stages["secrets"](spark, one, sf_dir)
    assert clean.count() == one.count() and not any(secret_scan.base_spans(r.text) for r in clean.collect())
    mixed = stages["mixture"](spark, clean, sf_dir)
    assert good.columns == one.columns == clean.columns == mixed.columns == docs.columns
    done = corpus_pipeline.run(spark, sf_dir).collect()
    assert Counter(r.doc_id for r in done) == Counter(r.doc_id for r in mixed.collect())
    text = {r.doc_id: r.text for r in clean.collect()}
    assert all(r.decoded_sha256 == hashlib.sha256(text[r.doc_id].encode()).hexdigest() for r in done)


@pytest.mark.parametrize("pct", [50, 80, 90])
def test_signatures_lose_no_link(pct):
    """Any two sets at the threshold share a signature, small and large ones, with all changes on either side."""
    make, rng = ngram_join.Signatures(pct), np.random.default_rng(7)
    for n in [*range(2, 120), 500, 1999, 4000]:
        for _ in range(3):
            both = -(-n * pct // 100)
            grams = rng.integers(0, 2**64, 2 * n, np.uint64)
            less, more = np.sort(grams[:both]), np.sort(grams[:n])
            k = next(k for k in range(n, 0, -1) if 100 * k < pct * (2 * n - k)) + 1  # least overlap of two sets of n
            other = np.sort(np.concatenate([grams[:k], grams[n : 2 * n - k]]))
            for x in (less, other):
                if len(x) and not np.array_equal(x, more):
                    assert set(make(x).tolist()) & set(make(more).tolist()), (n, len(x))
