"""Toxicity: a weighted lexicon matched by Aho-Corasick on folded text, normalised by length, with exception phrases."""

from __future__ import annotations

import math
import re
import unicodedata
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StructField

from .common import cut, scan_texts, small_batches

#: Labelled texts that learning looks at, at most, and words of them, the likeliest by odds, that are candidates, at most.
MAX_LABELLED, MAX_CANDIDATES = 20_000, 8_000
#: Different words that must stand before a lexicon word in toxic texts. Absolute: a share of the occurrences would tighten as they grow.
MIN_CONTEXTS = 5
# Signs and digits that stand for letters, and letters of other scripts that look like Latin ones.
SIGNS = dict(zip("0134578@$!|€£", "oieastbasiiel", strict=True))
LOOKALIKES = dict(
    zip(
        "абвгеёзіїјкмнорсԁѕтухѵԛԝһ" "αβγεηικνορστυχω" "ıłøđɑɡɩℓ",
        "abbreezIijkmhopcdstyxvqwh".lower() + "abyenikvopctuxw" + "ilodagil",
        strict=True,
    )
)
#: Phrases in which a lexicon word is harmless.
EXCEPTIONS = ("trash can", "trash cans", "trash bin", "trash bins", "clown fish", "sore loser rule", "pond scum")


WORD = re.compile(r"\w+")


class Fold(dict):
    """Code point -> folded character, one for one, so that places in a text stay."""

    def __init__(self, signs: bool = True):
        super().__init__()
        self.signs = SIGNS if signs else {}

    def __missing__(self, cp: int) -> str:
        c = chr(cp)
        low = c.lower()
        low = low if len(low) == 1 else c
        if low in self.signs:
            out = self.signs[low]
        elif low in LOOKALIKES:
            out = LOOKALIKES[low]
        else:
            plain = unicodedata.normalize("NFKD", low)
            base = "".join(x for x in plain if not unicodedata.combining(x)).lower()
            out = base if len(base) == 1 else low
            out = LOOKALIKES.get(out, out)
        if len(self) < 70_000:
            self[cp] = out
        return out


@dataclass(frozen=True)
class Lexicon:
    weights: dict[str, float]
    exceptions: tuple[str, ...] = EXCEPTIONS
    #: Of the logistic function over 1, log(1 + sum of weights), log(1 + weights per 100 characters).
    curve: tuple[float, float, float] = (-4.0, 4.0, 0.5)


class Matcher:
    def __init__(self, lexicon: Lexicon):
        self.lexicon, self.fold = lexicon, Fold()
        self.tree = ahocorasick.Automaton()
        for w, v in lexicon.weights.items():
            self.tree.add_word(w, (len(w), v, w))
        for p in lexicon.exceptions:
            p = p.translate(self.fold)
            if p not in lexicon.weights:
                self.tree.add_word(p, (len(p), 0.0, p))
        self.any = len(self.tree) > 0
        if self.any:
            self.tree.make_automaton()

    def hits(self, text: str) -> list[tuple[int, int, float, str]]:
        """(start, end, weight, word) of lexicon words at word borders of the text as it stands, outside exception phrases."""
        if not self.any or not text:
            return []
        n, found = len(text), []
        for last, (m, weight, w) in self.tree.iter(text.translate(self.fold)):
            a, b = last - m + 1, last + 1
            if (a == 0 or not text[a - 1].isalnum()) and (b == n or not text[b].isalnum()):
                found.append((a, b, weight, w))
        spared = [(a, b) for a, b, weight, _ in found if weight == 0.0]
        return [h for h in found if h[2] > 0 and not any(a <= h[0] and h[1] <= b for a, b in spared)]

    def features(self, text: str | None) -> tuple[float, float]:
        total = sum(h[2] for h in self.hits(text)) if text else 0.0
        return math.log1p(total), math.log1p(100 * total / max(1, len(text or "")))

    def score(self, text: str | None) -> float:
        a, b = self.features(text)
        x = self.lexicon.curve[0] + self.lexicon.curve[1] * a + self.lexicon.curve[2] * b
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, x))))


def words_of(text: str, fold: Fold) -> set[str]:
    """Folded words of at least three letters; letters and digits of the text as it stands make a word."""
    folded = text.translate(fold)
    out, a = set(), None
    if text.isascii():
        return {folded[m.start() : m.end()] for m in re.finditer(r"[A-Za-z0-9]{3,40}(?![A-Za-z0-9])", text)}
    for i, c in enumerate(text):
        if c.isalnum():
            a = i if a is None else a
        elif a is not None:
            if 3 <= i - a <= 40:
                out.add(folded[a:i])
            a = None
    if a is not None and 3 <= len(text) - a <= 40:
        out.add(folded[a:])
    return out


def learn(docs: DataFrame, labels: DataFrame, max_labelled: int = MAX_LABELLED, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Lexicon:
    """A lexicon from labelled texts, at most ``max_labelled`` different ones, those with the least hashes.

    Words are counted by class over texts; candidates are those far likelier in toxic texts, by odds and by a likelihood
    ratio that chance would not reach among so many words. Equal texts have one vote, that of most of their labels, so
    copies do not vote for the chance words of their text; a candidate must also stand in several contexts (words before
    it). Null labels and texts are left out; without both classes the lexicon is empty and every score low.
    """
    spark = docs.sparkSession
    small_batches(spark)
    chosen = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("id")).agg(F.max(label_col).alias("y"))
    data = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("x"), F.xxhash64(text_col).alias("h")).where("x is not null")
    votes = data.select("id", "h").join(chosen, "id").groupBy("h").agg(F.min("id").alias("id"), F.avg((F.col("y") > 0).cast("int")).alias("share"))
    votes = votes.orderBy("h").limit(max_labelled).select("id", "h", (F.col("share") >= 0.5).cast("int").alias("y"))
    rows = cut(data.join(F.broadcast(votes), ["id", "h"]).dropDuplicates(["h"]).select("id", "x", "y"))  # at most max_labelled texts

    def counts(batches):
        fold, n = Fold(), {}
        total = [0, 0]
        for b in batches:
            for text, y in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                y = int(y > 0)
                total[y] += 1
                for w in words_of(text, fold):
                    n.setdefault(w, [0, 0])[y] += 1
        yield pa.RecordBatch.from_pydict({"w": pa.array([*n, ""], pa.string()), "neg": pa.array([*(v[0] for v in n.values()), total[0]], pa.int64()), "pos": pa.array([*(v[1] for v in n.values()), total[1]], pa.int64())})

    table = rows.select("id", "x", "y").mapInArrow(counts, "w string, neg bigint, pos bigint").groupBy("w").agg(F.sum("neg").alias("neg"), F.sum("pos").alias("pos"))
    best = table.where("pos >= 3 or w = ''").orderBy(F.expr("w = ''").desc(), F.expr("(pos + 0.5) / (neg + 0.5)").desc(), "w").limit(MAX_CANDIDATES + 1).collect()
    if not best or best[0].w != "" or not best[0].pos or not best[0].neg:
        return Lexicon({})
    neg, pos = best[0].neg, best[0].pos
    weights = {}
    for r in best[1:]:
        share, ratio = pos / (pos + neg), r.pos / (r.pos + r.neg)
        g = 2 * (r.pos * math.log(ratio / share) + (r.neg * math.log((1 - ratio) / (1 - share)) if r.neg else 0.0))
        odds = math.log((r.pos + 0.5) / (pos + 1)) - math.log((r.neg + 0.5) / (neg + 1))
        if odds > 2.0 and g > 22.0:
            weights[r.w] = odds
    candidates = frozenset(weights)

    def before(batches):
        fold = Fold()
        for b in batches:
            w, c = [], []
            for text in b.column(0).to_pylist():
                last = ""
                for x in WORD.findall(text.translate(fold)):
                    if x in candidates:
                        w.append(x)
                        c.append(last)
                    last = x
            yield pa.RecordBatch.from_pydict({"w": pa.array(w, pa.string()), "c": pa.array(c, pa.string())})

    contexts = rows.where("y > 0").select("x").mapInArrow(before, "w string, c string").groupBy("w").agg(F.count_distinct("c").alias("c"))
    various = {r.w for r in contexts.collect() if r.c >= MIN_CONTEXTS}  # at most as many as candidates
    weights = {w: v for w, v in weights.items() if w in various}
    return fit_curve(rows, Lexicon(weights))


def fit_curve(rows: DataFrame, lexicon: Lexicon) -> Lexicon:
    """The logistic curve by Newton's method with a small ridge, over the same bounded rows (id, x, y)."""

    def features(batches):
        m = Matcher(lexicon)
        for b in batches:
            f = [m.features(t) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_pydict({"a": pa.array([v[0] for v in f], pa.float64()), "b": pa.array([v[1] for v in f], pa.float64()), "y": pa.array([float(y > 0) for y in b.column(1).to_pylist()], pa.float64())})

    got = np.array(sorted(tuple(r) for r in rows.select("x", "y").mapInArrow(features, "a double, b double, y double").collect()))
    if not len(got) or not lexicon.weights:
        return Lexicon(lexicon.weights, lexicon.exceptions)
    x, y = np.column_stack([np.ones(len(got)), got[:, :2]]), got[:, 2]
    c = np.zeros(3)
    ridge = np.diag([0.01, 1.0, 1.0])
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ c, -40, 40)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + ridge, x.T @ (y - p) - ridge @ c)
        c += np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-8:
            break
    return Lexicon(lexicon.weights, lexicon.exceptions, tuple(float(v) for v in c))


def score(docs: DataFrame, lexicon: Lexicon, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score, predicted) of every row; null and empty texts get the score of a text without hits."""

    def rows(texts):
        m = Matcher(lexicon)
        s = [m.score(t) for t in texts]
        return [s, [int(v >= 0.5) for v in s]]

    return scan_texts(docs, rows, [StructField("score", DoubleType()), StructField("predicted", IntegerType())], id_col, text_col)
