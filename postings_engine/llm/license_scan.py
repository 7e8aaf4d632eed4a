"""License scans: exact word phrases, and fuzzy search for short notices.

A notice may differ in ``edits`` characters. Cut into ``edits + 1`` pieces, one of them must stand in the text unchanged
(pigeonhole); these exact seeds locate windows, and in them the regex library's bounded-error matching verifies the
edits and reports the span.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import regex
from pyspark.sql import DataFrame
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, StringType, StructField, StructType

from .common import long_field, scan_texts

#: Runs of ASCII letters, digits and everything beyond ASCII, in the UTF-8 bytes of a text whose A-Z are lower-cased.
WORDS = re.compile(rb"[0-9a-z\x80-\xff]+").findall
#: Phrases whose every place counts, with their labels (fixed by the contract).
PHRASES = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}


@dataclass(frozen=True)
class Notice:
    text: str
    label: str
    edits: int


NOTICES = (
    Notice("under the mit license", "mit", 2),
    Notice("permission is hereby granted free of charge to any person obtaining a copy", "mit", 6),
    Notice("apache license version 2", "apache-2", 2),
    Notice("licensed under the apache license", "apache-2", 3),
    Notice("gnu general public license", "gpl", 2),
    Notice("gnu lesser general public license", "lgpl", 2),
    Notice("mozilla public license", "mpl", 2),
    Notice("redistribution and use in source and binary forms", "bsd", 4),
    Notice("creative commons attribution noncommercial", "cc-by-nc", 3),
    Notice("cc by nc", "cc-by-nc", 0),  # a single edit makes another licence of it
)


class NoticeSearch:
    def __init__(self, notices: tuple[Notice, ...] = NOTICES):
        self.found = []
        for n in notices:
            raw, k = n.text.encode(), n.edits + 1
            cuts = [len(raw) * i // k for i in range(k + 1)]
            seeds = [(raw[a:b], a) for a, b in zip(cuts, cuts[1:], strict=False)]
            fuzzy = rb"(?<![^ ])(?:%s){e<=%d}(?![^ ])" % (regex.escape(n.text).encode(), n.edits)  # whole words of the line
            # one match after the other, then the best inside each: the best of a window at once would skip those before it
            verify = regex.compile(rb"(?e)" + fuzzy) if n.edits else regex.compile(rb"(?<![^ ])%s(?![^ ])" % regex.escape(n.text).encode())
            best = regex.compile(rb"(?b)" + fuzzy) if n.edits else verify
            self.found.append((n, raw, seeds, verify, best))

    def __call__(self, line: bytes) -> list[tuple[str, int, int, int]]:
        """(label, start, end, edits) in the line of words joined by single spaces; matches of one notice don't overlap."""
        out = []
        for n, raw, seeds, verify, best in self.found:
            reach = len(raw) + n.edits
            windows: list[list[int]] = []
            hits = []
            for seed, _ in seeds:
                at = line.find(seed)
                while at >= 0:
                    hits.append(at)
                    at = line.find(seed, at + 1)
            if not hits:
                continue
            for h in sorted(set(hits)):
                a, b = line.rfind(b" ", 0, max(0, h - reach)) + 1, line.find(b" ", h + reach + len(raw))
                b = len(line) if b < 0 else b
                if windows and a <= windows[-1][1]:
                    windows[-1][1] = b
                else:
                    windows.append([a, b])
            for a, b in windows:
                for m in verify.finditer(line, a, b):
                    if sum(m.fuzzy_counts):
                        m = best.search(line, m.start(), m.end()) or m
                    cost = sum(m.fuzzy_counts)
                    out.append((n.label, m.start(), m.end(), cost))
        return out


def phrase_places(words: list[bytes], phrases: dict[tuple[bytes, ...], str]) -> list[tuple[int, str]]:
    """(word index, label) of every place, overlapping ones too."""
    out = []
    for phrase, label in phrases.items():
        first, n = phrase[0], len(phrase)
        rarest = max(phrase, key=len)
        if rarest not in words:
            continue
        at = -1
        while True:
            try:
                at = words.index(first, at + 1)
            except ValueError:
                break
            if tuple(words[at : at + n]) == phrase:
                out.append((at, label))
    return sorted(out)


class LicenseScan:
    def __init__(self, phrases: dict[str, str] | None = None, notices: tuple[Notice, ...] = NOTICES):
        self.phrases = {tuple(p.encode().split()): label for p, label in (phrases or PHRASES).items()}
        self.search = NoticeSearch(notices)

    def __call__(self, raw: bytes | None) -> tuple:
        """(n_words, places, matches, score) of a text in UTF-8."""
        words = WORDS(raw.lower()) if raw else []
        if not words:
            return 0, [], [], 0.0
        line = b" ".join(words)
        places = phrase_places(words, self.phrases)
        matches = self.search(line)
        # 1 for an exact notice, less with the share of its characters that are edited
        score = 1.0 if places else max((1.0 - cost / max(1, end - start) for _, start, end, cost in matches), default=0.0)
        return len(words), places, matches, max(0.0, score)


def scan_licenses(df: DataFrame, phrases: dict[str, str] | None = None, notices: tuple[Notice, ...] = NOTICES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_words, n_base, first_word, last_word, base_labels, labels, score, matches) of every row.

    ``matches`` holds (label, first word, last word, edits) of each fuzzy match, word positions from 0, edits in bytes. Null and empty texts have
    no words and score 0; ``first_word`` and ``last_word`` are null without a base place. Repeated rows give repeated results.
    """
    match = StructType([StructField("label", StringType()), StructField("first", IntegerType()), StructField("last", IntegerType()), StructField("edits", IntegerType())])
    fields = [long_field("n_words"), long_field("n_base"), long_field("first_word"), long_field("last_word"), StructField("base_labels", StringType()), StructField("labels", StringType()), StructField("score", DoubleType()), StructField("matches", ArrayType(match))]

    def rows(texts):
        scan = LicenseScan(phrases, notices)
        out: list[list] = [[] for _ in fields]
        for raw in texts:
            n, places, matches, score = scan(raw)
            base = {label for _, label in places}
            line = b" ".join(WORDS(raw.lower())) if matches else b""
            values = (
                n, len(places), places[0][0] if places else None, places[-1][0] if places else None, ",".join(sorted(base)), ",".join(sorted(base | {m[0] for m in matches})), score,
                [{"label": label, "first": line.count(b" ", 0, a), "last": line.count(b" ", 0, b), "edits": cost} for label, a, b, cost in matches],
            )
            for column, v in zip(out, values, strict=True):
                column.append(v)
        return out

    return scan_texts(df, rows, fields, id_col, text_col, binary=True)
