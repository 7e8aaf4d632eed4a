"""Text to terms: case, accents, ligatures, markup, urls, tokens. All built-in expressions; the stemmer runs per distinct term."""

from __future__ import annotations

from collections.abc import Iterable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Latin letters with marks, and what is left without the marks, place by place.
ACCENTED = "àáâãäåçèéêëìíîïñòóôõöùúûüýÿāăąćĉċčďēĕėęěĝğġģĥĩīĭįĵķĺļľńņňōŏőŕŗřśŝşšţťũūŭůűųŵŷźżž"
PLAIN = "aaaaaaceeeeiiiinooooouuuuyyaaaccccdeeeeegggghiiiijklllnnnooorrrssssttuuuuuuwyzzz"
LIGATURES = (("œ", "oe"), ("æ", "ae"), ("ß", "ss"), ("ﬁ", "fi"), ("ﬂ", "fl"))


def fold_case(c: Column) -> Column:
    return F.lower(c)


def strip_accents(c: Column) -> Column:
    """Of lower-cased text."""
    return F.translate(c, ACCENTED, PLAIN)


def split_ligatures(c: Column) -> Column:
    for one, two in LIGATURES:
        c = F.replace(c, F.lit(one), F.lit(two))
    return c


def normalise(c: Column, ligatures: bool = False) -> Column:
    c = fold_case(c)
    return strip_accents(split_ligatures(c) if ligatures else c)


def terms(c: Column, ligatures: bool = False) -> Column:
    return F.regexp_extract_all(normalise(c, ligatures), F.lit("[a-z0-9]+"), F.lit(0))


def html_text(c: Column) -> Column:
    """Markup to text by patterns: scripts, styles, comments and tags give way to a blank, common entities are decoded."""
    c = F.regexp_replace(c, r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->", " ")
    c = F.regexp_replace(c, r"(?s)<[^>]*>", " ")
    for name, value in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        c = F.replace(c, F.lit(name), F.lit(value))
    return c


def html_text_strict():
    """A function of a column: text outside scripts and styles by the standard library's parser, which also decodes every
    entity. One Arrow batch at a time; :func:`html_text` stays in the JVM."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("string")
    def f(pages: pd.Series) -> pd.Series:
        from html.parser import HTMLParser

        class Text(HTMLParser):
            def __init__(self):
                super().__init__()
                self.out, self.hidden = [], 0

            def handle_starttag(self, tag, attrs):
                self.hidden += tag in ("script", "style")
                self.out.append(" ")

            def handle_endtag(self, tag):
                self.hidden -= tag in ("script", "style") and self.hidden > 0
                self.out.append(" ")

            def handle_data(self, data):
                if not self.hidden:
                    self.out.append(data)

        def text(page):
            if page is None:
                return None
            parser = Text()
            parser.feed(page)
            parser.close()
            return "".join(parser.out)

        return pages.map(text)

    return f


def trim_urls(c: Column) -> Column:
    """Cuts urls in a text after ``?`` and drops path pieces of more than 30 characters."""
    c = F.regexp_replace(c, r"(https?://[^\s?]*)\?\S*", "$1")
    return F.regexp_replace(c, r"(?<=[^/:\s]/)[^/\s]{31,}(?=/|\s|$)", "")


def message_text(*columns: Column) -> Column:
    return F.concat_ws("\n", *columns)


def tokens(df: DataFrame, id_col: str, text: Column | str, ligatures: bool = False, stopwords: Iterable[str] | None = None, distinct: bool = True) -> DataFrame:
    """(doc, term); with ``distinct`` each pair once, made so inside the document: no shuffle for it."""
    text = F.col(text) if isinstance(text, str) else text
    found = terms(text, ligatures)
    if stopwords is not None:
        found = F.array_except(found, F.array(*map(F.lit, stopwords)))
    return df.select(F.col(id_col).cast("long").alias("doc"), F.explode(F.array_distinct(found) if distinct else found).alias("term"))


def dedup_docs(df: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """One row for each text, the one with the least id."""
    least = df.groupBy(F.sha2(F.col(text_col), 256).alias("__h")).agg(F.min(id_col).alias(id_col)).drop("__h")
    return df.join(least, id_col, "left_semi")


def with_stems(tok: DataFrame, of: Column | None = None) -> DataFrame:
    """(doc, stem) of (doc, term): the stemmer sees each distinct term once. With ``of``, a condition on ``tok``, terms of
    other rows pass through as they are."""
    if of is not None:
        return with_stems(tok.where(of).select("doc", "term")).unionByName(tok.where(~F.coalesce(of, F.lit(False))).select("doc", "term")).distinct()
    from .stem import stem_udf

    known = tok.select("term").distinct().withColumn("stem", stem_udf()("term"))
    return tok.join(known, "term").select("doc", F.col("stem").alias("term")).distinct()
