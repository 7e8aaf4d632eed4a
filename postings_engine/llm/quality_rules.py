"""Quality rules: a table of thresholds compiled into one Spark projection, without user functions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE

#: Words that running text of the four languages of the corpus holds (fixed values, all lower case).
STOP_WORDS = (
    "the of and to in that is was for with be by this it as are not at from have "
    "le la les de des du et un une en que qui dans pour pas sur avec est "
    "der die das und ist nicht ein eine mit von zu den dem auf für sich "
    "el los las una por con para del se no su como más"
).split()
SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class Rule:
    """``measure`` (a column of :func:`measures`) must lie between ``least`` and ``most``, each of which may be None."""

    measure: str
    least: float | None = None
    most: float | None = None


#: The method's own thresholds, lenient ones: clean prose of any length keeps well inside.
RULES = (
    Rule("mean_word_chars", 2.0, 14.0),
    Rule("symbol_ratio", None, 0.30),
    Rule("dup_line_ratio", None, 0.50),
    Rule("stop_word_ratio", 0.02, None),
)


def window_hashes(words: Column, width: int = 8) -> Column:
    """64-bit hashes of all windows of ``width`` words, in order; none if there are fewer words."""
    n = F.size(words)
    starts = F.when(n >= width, F.sequence(F.lit(1), n - (width - 1))).otherwise(F.array().cast("array<int>"))
    return F.transform(starts, lambda i: F.xxhash64(F.slice(words, i, F.lit(width))))


def covered(pairs: Column, words: Column, width: int = 8) -> Column:
    """From (hash, start) of all windows, sorted: the number of words under windows found twice or more, the first included.

    Windows with equal hashes are compared by their words. Documents without a repeated hash, nearly all, never get here.
    """
    same = lambda a, b: (a["h"] == b["h"]) & (F.slice(words, a["i"], F.lit(width)) == F.slice(words, b["i"], F.lit(width)))
    at = lambda k: F.get(pairs, k)
    twice = F.filter(pairs, lambda p, k: F.coalesce(same(p, at(k - 1)), F.lit(False)) | F.coalesce(same(p, at(k + 1)), F.lit(False)))
    order = F.array_sort(F.transform(twice, lambda p: p["i"]))
    step = F.struct(F.lit(0).alias("n"), F.lit(-width).alias("last"))
    return F.aggregate(order, step, lambda s, i: F.struct((s["n"] + F.least(F.lit(width), i - s["last"])).alias("n"), i.alias("last")), lambda s: s["n"])


def measures(df: DataFrame, text_col: str = "text") -> DataFrame:
    """``df`` plus its base counts and ratios, in columns named ``__q_...``; null text counts as empty.

    One chain of projections: no shuffle, no Python. They are columns of their own, not fields of a struct, since Spark
    would merge the projections of a struct and compute its costly fields once for each use.
    """
    c = F.col
    text = F.coalesce(c(text_col).cast("string"), F.lit(""))
    words = F.filter(F.split(c("__q_t"), f"{SPACE}+"), lambda w: w != "")
    lines = F.filter(F.split(c("__q_t"), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    blanks = "\x20\t\n\x0b\x0c\r"
    out = df.withColumn("__q_t", text).withColumns({"__q_w": words, "__q_l": lines})
    out = out.withColumn("__q_h", window_hashes(c("__q_w")))
    pairs = F.array_sort(F.transform("__q_h", lambda h, i: F.struct(h.alias("h"), (i + 1).alias("i"))))
    out = out.withColumn("__q_p", F.when(F.size(F.array_distinct("__q_h")) < F.size("__q_h"), pairs))
    counts = {
        "n_words": F.size("__q_w"),
        "word_chars": F.char_length(F.translate("__q_t", blanks, "")),
        "n_symbols": F.char_length("__q_t") - F.char_length(F.translate("__q_t", SYMBOLS, "")),
        "n_dup_lines": F.size("__q_l") - F.size(F.array_distinct("__q_l")),
        "n_lines": F.size("__q_l"),
        "n_repeat_words": F.when(c("__q_p").isNull(), F.lit(0)).otherwise(covered(c("__q_p"), c("__q_w"))),
        "n_stop_words": F.size(F.filter("__q_w", lambda w: F.lower(w).isin(*STOP_WORDS))),
    }
    out = out.withColumns({f"__q_{k}": v.cast("long") for k, v in counts.items()}).drop("__q_t", "__q_w", "__q_l", "__q_h", "__q_p")
    share = lambda a, b: c(f"__q_{a}") / F.greatest(c(f"__q_{b}"), F.lit(1))
    ratios = {"mean_word_chars": ("word_chars", "n_words"), "symbol_ratio": ("n_symbols", "word_chars"), "dup_line_ratio": ("n_dup_lines", "n_lines"), "stop_word_ratio": ("n_stop_words", "n_words")}
    return out.withColumns({f"__q_{k}": share(*v) for k, v in ratios.items()})


def verdict(rules: tuple[Rule, ...] = RULES) -> Column:
    """True where all rules hold."""
    ok = F.lit(True)
    for r in rules:
        c = F.col(f"__q_{r.measure}")
        ok = ok & (c >= r.least if r.least is not None else F.lit(True)) & (c <= r.most if r.most is not None else F.lit(True))
    return ok


def base_failed() -> Column:
    return (F.col("__q_n_words") < 20) | (100 * F.col("__q_n_repeat_words") > 30 * F.col("__q_n_words"))


def _computed_once(c: Column) -> Column:
    """c, in a projection through which Spark pushes no condition: below, it would repeat the costly columns many times."""
    return c & (F.monotonically_increasing_id() >= 0)


def judge(df: DataFrame, rules: tuple[Rule, ...] = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept) of every row.

    Null and empty texts have no words and fail. Repeated rows are judged each by itself.
    """
    base = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    q = measures(df.select(F.col(id_col), F.col(text_col)), text_col)
    return q.select(id_col, *(F.col(f"__q_{c}").alias(c) for c in base), base_failed().alias("base_failed"), _computed_once(~base_failed() & verdict(rules)).alias("kept"))


def keep(df: DataFrame, rules: tuple[Rule, ...] = RULES, text_col: str = "text") -> DataFrame:
    """The rows of ``df`` that are kept, with its columns."""
    return measures(df, text_col).withColumn("__q_kept", _computed_once(~base_failed() & verdict(rules))).where("__q_kept").select(*df.columns)


ORACLE = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, list_filter(regexp_split_to_array(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
m AS (SELECT *, len(w) AS n, list_transform(range(1, greatest(len(w) - 6, 1)), lambda i: array_to_string(w[i:i+7], ' ')) AS g FROM w),
u AS (SELECT doc_id, unnest(g) AS g, unnest(range(1, len(g) + 1)) AS i FROM m),
r AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM u),
s AS (SELECT doc_id, i, lag(i) OVER (PARTITION BY doc_id ORDER BY i) AS p FROM r WHERE c > 1),
k AS (SELECT doc_id, sum(least(8, i - coalesce(p, -8)))::BIGINT AS n_repeat_words FROM s GROUP BY doc_id),
q AS (SELECT m.doc_id, n::BIGINT AS n_words, len(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g'))::BIGINT AS word_chars, (len(t) - len(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
  (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, len(l) AS n_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words, len(list_filter(w, lambda x: list_contains(@stop, lower(x)))) AS n_stop
  FROM m LEFT JOIN k ON m.doc_id = k.doc_id),
b AS (SELECT *, (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AS base_failed FROM q)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (NOT base_failed AND word_chars / greatest(n_words, 1) BETWEEN 2.0 AND 14.0 AND n_symbols / greatest(word_chars, 1) <= 0.3
  AND n_dup_lines / greatest(n_lines, 1) <= 0.5 AND n_stop / greatest(n_words, 1) >= 0.02) AS kept FROM b
""".replace("@stop", "[" + ", ".join(f"'{w}'" for w in STOP_WORDS) + "]")
