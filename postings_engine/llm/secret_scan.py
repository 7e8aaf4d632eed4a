"""Secret scans: fixed patterns, and sliding-window Shannon entropy over candidate strings."""

from __future__ import annotations

import hashlib
import math
import re
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, StringType, StructField, StructType

from .common import long_field, scan_texts

#: Kinds of the fixed patterns, in the order in which spans with one start are listed; the entropy kinds follow.
BASE_KINDS = ("assign", "access", "hex")
KINDS = (*BASE_KINDS, "entropy_hex", "entropy_mixed", "entropy_alnum", "entropy_letters")
# The patterns of the contract.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")  # runs of 20 and more: a shorter run has no longer one inside
HEX = re.compile(r"[0-9a-f]{24,}")
KEYWORDS = ("password", "passwd", "secret", "token", "api")
CONSONANTS = frozenset("bcdfghjklmnpqrstvwxzBCDFGHJKLMNPQRSTVWXZ")
CANDIDATE = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{20,}")


@dataclass(frozen=True)
class EntropyRule:
    """Windows of ``window`` characters count from the class's threshold in bits on; at most log2(min(window, alphabet))."""

    window: int = 20
    hex_bits: float = 3.0
    mixed_bits: float = 3.9
    #: A window of the mixed class must hold at least so many digits, and letters of both cases or one of ``+/_=-``.
    digits: int = 2
    #: Random strings change between lower, upper and digit far more often than words with numbers do. From so many changes
    #: in a window on, lower thresholds count: with both cases and a digit, with one case and ``digits`` digits (base36,
    #: base32), with letters of both cases only.
    changes_mixed: int = 7
    changes_alnum: int = 3
    changes_letters: int = 7
    #: Letters of both cases with fewer changes than this also need the run of consonants, as names in camel case have up to 9.
    changes_sure: int = 10
    changed_bits: float = 3.3
    #: A window of letters of one case has no changes; it counts with a run of so many consonants, which words hardly have.
    consonants: int = 6
    #: What a candidate (whole, with the 12 characters before it) may be without being a secret.
    allow: tuple[str, ...] = field(
        default=(
            r"^[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}$",  # identifiers by RFC 9562
            r"^(.)\1+$",
            r"EXAMPLE",
            r"^[0-9]+([_/=+-]+[0-9]+)*$",  # numbers and dates
            r"^(0123456789|abcdefghij|ABCDEFGHIJ)",
        )
    )
    #: What may stand right before a candidate: addresses, data that names itself a digest.
    allow_before: tuple[str, ...] = (r"://\S*$", r"(?i)(sha-?\d+|md5|commit|etag|integrity)[\s:=\"'-]*$")


class EntropyScan:
    def __init__(self, rule: EntropyRule):
        self.rule = rule
        self.allow = [re.compile(p) for p in rule.allow]
        self.before = [re.compile(p) for p in rule.allow_before]
        self.clog = [0.0] + [c * math.log2(c) for c in range(1, rule.window + 2)]  # a window holds one more before its oldest leaves

    def windows(self, s: str, least: float, mixed: bool) -> list[tuple[int, int]]:
        """Spans of s that windows of enough entropy cover. Counts are kept while the window slides."""
        w, clog = self.rule.window, self.clog
        if len(s) < w:
            return []
        count: dict[str, int] = {}
        total = 0.0  # sum of c log c over the counts c
        digits = upper = lower = sign = 0
        spans: list[tuple[int, int]] = []
        for i, ch in enumerate(s):
            c = count.get(ch, 0)
            total += clog[c + 1] - clog[c]
            count[ch] = c + 1
            digits += "0" <= ch <= "9"
            upper += "A" <= ch <= "Z"
            lower += "a" <= ch <= "z"
            sign += ch in "+/_=-"
            if i >= w:
                old = s[i - w]
                c = count[old]
                total += clog[c - 1] - clog[c]
                count[old] = c - 1
                digits -= "0" <= old <= "9"
                upper -= "A" <= old <= "Z"
                lower -= "a" <= old <= "z"
                sign -= old in "+/_=-"
            if i >= w - 1 and math.log2(w) - total / w >= least - 1e-9 and digits >= self.rule.digits:
                if mixed and not (upper and lower or sign and (upper or lower)):
                    continue
                if not mixed and not (upper or lower):
                    continue
                a = i - w + 1
                if spans and a <= spans[-1][1]:
                    spans[-1] = (spans[-1][0], i + 1)
                else:
                    spans.append((a, i + 1))
        return spans

    def changes(self, s: str) -> list[tuple[str, int, int]]:
        """(kind, start, end) of spans of s covered by windows that change class often, or are letters without words' vowels."""
        r, w, clog = self.rule, self.rule.window, self.clog
        count: dict[str, int] = {}
        total = 0.0
        n = {"d": 0, "u": 0, "l": 0, "s": 0}
        cls = ["d" if "0" <= c <= "9" else "u" if "A" <= c <= "Z" else "l" if "a" <= c <= "z" else "s" for c in s]
        turn = [i > 0 and "s" not in (cls[i - 1], cls[i]) and cls[i - 1] != cls[i] for i in range(len(s))]
        turns = run = 0
        tight = -1  # first place of the latest run of enough consonants
        spans: dict[str, list[tuple[int, int]]] = {}
        for i, ch in enumerate(s):
            c = count.get(ch, 0)
            total += clog[c + 1] - clog[c]
            count[ch] = c + 1
            n[cls[i]] += 1
            turns += turn[i]
            run = run + 1 if ch in CONSONANTS else 0
            if run >= r.consonants:
                tight = i - r.consonants + 1
            a = i - w + 1
            if a > 0:
                old = s[a - 1]
                c = count[old]
                total += clog[c - 1] - clog[c]
                count[old] = c - 1
                n[cls[a - 1]] -= 1
            if a >= 0:
                turns -= turn[a]  # the change into a window's first character lies outside it
                if math.log2(w) - total / w < r.changed_bits - 1e-9:
                    continue
                if n["u"] and n["l"]:
                    kind = "entropy_mixed" if n["d"] else "entropy_letters"
                    good = turns >= r.changes_mixed if n["d"] else not n["s"] and turns >= r.changes_letters and (tight >= a or turns >= r.changes_sure)
                elif n["d"]:
                    kind, good = "entropy_alnum", n["d"] >= r.digits and n["s"] <= 1 and turns >= r.changes_alnum
                else:
                    kind, good = "entropy_letters", not n["s"] and tight >= a
                if good:
                    own = spans.setdefault(kind, [])
                    if own and a <= own[-1][1]:
                        own[-1] = (own[-1][0], i + 1)
                    else:
                        own.append((a, i + 1))
        return [(kind, a, b) for kind, own in spans.items() for a, b in own]

    def __call__(self, text: str) -> list[tuple[str, int, int]]:
        out = []
        for m in CANDIDATE.finditer(text):
            s = m.group()
            if any(p.search(s) for p in self.allow):
                continue
            before = text[max(0, m.start() - 200) : m.start()]
            if any(p.search(before) for p in self.before):
                continue
            hexes = not s.strip("0123456789abcdef") or not s.strip("0123456789ABCDEF")
            least = self.rule.hex_bits if hexes else self.rule.mixed_bits
            kind = "entropy_hex" if hexes else "entropy_mixed"
            found = [(kind, a, b) for a, b in self.windows(s, least, not hexes)]
            if not hexes:
                found = joined(found + self.changes(s))
            out += [(k, m.start() + a, m.start() + b) for k, a, b in found]
        return out


def joined(spans: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    """Spans of one kind that touch or overlap become one."""
    out: list[tuple[str, int, int]] = []
    for kind, a, b in sorted(spans):
        if out and out[-1][0] == kind and a <= out[-1][2]:
            out[-1] = (kind, out[-1][1], max(out[-1][2], b))
        else:
            out.append((kind, a, b))
    return out


def base_spans(text: str) -> list[tuple[str, int, int]]:
    out = []
    low = text.lower()
    if any(k in low for k in KEYWORDS):
        out += [("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m.group(2)) >= 6]
    if "AKIA" in text:
        out += [("access", *m.span()) for m in ACCESS.finditer(text)]
    out += [("hex", *m.span()) for m in HEX.finditer(text)]
    return out


def by_start(spans: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    return sorted(spans, key=lambda s: (s[1], KINDS.index(s[0]), s[2]))


def spans_of(text: str | None, scan: EntropyScan) -> list[tuple[str, int, int]]:
    """All spans of a text, base ones included, by start and kind."""
    if not text or max(map(len, text.split()), default=0) < 20 and not any(k in text.lower() for k in KEYWORDS):
        return []
    return by_start(base_spans(text) + scan(text))


def scan_secrets(df: DataFrame, rule: EntropyRule | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, spans ARRAY<STRUCT<kind, start, end>>) of every row; start and end count code points, end exclusive.

    Null and empty texts have no spans; repeated rows give repeated results; an empty table gives an empty one.
    """
    rule = rule or EntropyRule()

    def rows(texts):
        scan = EntropyScan(rule)
        return [[[{"kind": k, "start": a, "end": b} for k, a, b in spans_of(t, scan)] for t in texts]]

    span = StructType([StructField("kind", StringType()), StructField("start", IntegerType()), StructField("end", IntegerType())])
    return scan_texts(df, rows, [StructField("spans", ArrayType(span))], id_col, text_col)


def secret_digest(df: DataFrame, rule: EntropyRule | None = None, id_col: str = "doc_id") -> DataFrame:
    """(id, n_assign, n_access, n_hex, base_sha256, spans STRING) from :func:`scan_secrets`."""
    line = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    of = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE_KINDS))
    return scan_secrets(df, rule, id_col).select(id_col, *map(of, BASE_KINDS), F.sha2(line(base), 256).alias("base_sha256"), line(F.col("spans")).alias("spans"))


def redact(df: DataFrame, rule: EntropyRule | None = None, mark: str = "[secret]", text_col: str = "text") -> DataFrame:
    """``df`` with every span of its texts (overlapping ones together) replaced by ``mark``; null texts stay null.

    All columns are kept in order. The texts change inside one pass over Arrow batches, so no key is needed and repeated
    rows stay as they are.
    """
    import pyarrow as pa

    from .common import small_batches

    rule = rule or EntropyRule()
    small_batches(df.sparkSession)
    at = df.columns.index(text_col)

    def clean(text, scan):
        spans = spans_of(text, scan)
        if not spans:
            return text
        out, end = [], 0
        merged: list[list[int]] = []
        for _, a, b in spans:
            if merged and a <= merged[-1][1]:
                merged[-1][1] = max(merged[-1][1], b)
            else:
                merged.append([a, b])
        for a, b in merged:
            out += [text[end:a], mark]
            end = b
        return "".join([*out, text[end:]])

    def run(batches):
        for b in batches:
            scan = EntropyScan(rule)
            new = pa.array([clean(t, scan) for t in b.column(at).to_pylist()], type=b.schema.field(at).type)
            yield pa.RecordBatch.from_arrays([new if i == at else c for i, c in enumerate(b.columns)], schema=b.schema)

    return df.mapInArrow(run, df.schema)


def sha256_of(spans: list[tuple[str, int, int]]) -> str:
    return hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b in spans).encode()).hexdigest()


__all__ = ["EntropyRule", "EntropyScan", "base_spans", "by_start", "long_field", "redact", "scan_secrets", "secret_digest", "sha256_of", "spans_of"]
