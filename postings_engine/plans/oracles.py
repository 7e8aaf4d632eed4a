"""The same results by DuckDB SQL over the given tables, for every query that SQL can follow."""

from __future__ import annotations

from ..operators.clusters import EDGES
from .queries import WORDS


def bl(x: str) -> str:
    return f"length(bin(({x})::BIGINT))"


def delta(x: str) -> str:
    return f"({bl(x)} - 1 + 2 * {bl(bl(x))} - 1)"


def truncated(x: str, r: str) -> str:
    return f"({bl(r)} - CASE WHEN ({x}) < (1::BIGINT << {bl(r)}) - ({r}) THEN 1 ELSE 0 END)"


def zeta(x: str, k: int) -> str:
    h = f"(({bl(x)} - 1) // {k})"
    low, r = f"(1::BIGINT << ({h} * {k}))", f"((1::BIGINT << ({h} * {k} + {k})) - (1::BIGINT << ({h} * {k})))"
    return f"({h} + 1 + {truncated(f'{x} - {low}', r)})"


def elias_fano(n: str, u: str) -> str:
    low = f"(CASE WHEN {u} > {n} THEN {bl(f'{u} // {n}')} - 1 ELSE 0 END)"
    return f"({n} * {low} + {n} + ({u} >> {low}))"


def tok(table: str, key: str) -> str:
    return f"tok AS (SELECT DISTINCT {key} AS doc, unnest(regexp_extract_all(lower(strip_accents(text)), '[a-z0-9]+')) AS term FROM {table}), m AS (SELECT {key} AS doc, row_number() OVER (ORDER BY {key}) AS ord FROM {table}), d AS (SELECT count(*) AS d FROM {table})"


PAIRS = ", p AS (SELECT term, ord FROM tok JOIN m USING (doc))"
GAPS = PAIRS + ", g AS (SELECT term, ord, ord - lag(ord, 1, 0) OVER (PARTITION BY term ORDER BY ord) AS gap, count(*) OVER (PARTITION BY term) AS n, row_number() OVER (PARTITION BY term ORDER BY ord) - 1 AS i FROM p)"
DOCS = "WITH " + tok("documents", "doc_id")
BENCH = "WITH " + tok("benchmark", "item_id")
TRIT = "substr(bin(gap::BIGINT), 2) || '2'"
#: Symbols of the verse-like table with their contexts for k = 2, w = 3, k_init = 1.
CONTEXTS = (
    BENCH + GAPS + f", s AS (SELECT term, string_agg({TRIT}, '' ORDER BY i) AS s, any_value(n) AS n FROM g GROUP BY term), "
    "e AS (SELECT term, n, s, unnest(range(0, length(s))) AS i FROM s), "
    "z AS (SELECT term, n, i, substr(s, i + 1, 1)::INT AS x, CASE WHEN i >= 1 THEN (substr(s, i, 1) = '2')::INT ELSE 0 END AS z1, CASE WHEN i >= 2 THEN (substr(s, i - 1, 1) = '2')::INT ELSE 0 END AS z2, "
    "CASE WHEN i >= 5 THEN 3 - length(replace(substr(s, i - 4, 3), '2', '')) ELSE 0 END AS c FROM e), "
    "k AS (SELECT term, n, i, x, (CASE WHEN i >= 5 THEN 3 + 4 * c + z1 + 2 * z2 WHEN i >= 1 THEN 1 + z1 ELSE 0 END)::BIGINT AS ctx FROM z), "
    "c AS (SELECT ctx, count(*) FILTER (x = 0) AS n0, count(*) FILTER (x = 1) AS n1, count(*) FILTER (x = 2) AS n2 FROM k GROUP BY ctx) "
)
ENTROPY = "CASE WHEN {n} > 0 THEN {n} * log2((n0 + n1 + n2)::DOUBLE / {n}) ELSE 0 END"


def _values(rows) -> str:
    return ", ".join(f"({', '.join(map(str, r))})" for r in rows)


def _lists(table: str, value: str, row: str, md5: bool = False) -> str:
    gaps = "string_agg(gap::VARCHAR, ' ' ORDER BY ord)"
    gaps = f"md5({gaps})" if md5 else gaps
    return f"WITH p AS (SELECT DISTINCT ({value})::VARCHAR AS term, {row} AS ord FROM {table} WHERE {value} IS NOT NULL), g AS (SELECT term, ord, ord - lag(ord, 1, 0) OVER (PARTITION BY term ORDER BY ord) AS gap FROM p) SELECT term, count(*)::BIGINT AS n, {gaps} AS gaps FROM g GROUP BY term"


GOLOMB = "greatest(1, (69 * d + 50 * n) // (100 * n))"
WIDTH = f"(CASE WHEN gap > 1 THEN {bl('gap - 1')} ELSE 0 END)"
REFERENCE = DOCS + PAIRS + ", k AS (SELECT *, ascii(term) % 4 AS c FROM p), f AS (SELECT c, ord, count(*) AS df FROM k GROUP BY c, ord), t AS (SELECT c, ord, row_number() OVER (PARTITION BY c ORDER BY df DESC, ord) AS r FROM f), b AS (SELECT c, ord, row_number() OVER (PARTITION BY c ORDER BY ord) AS rank FROM t WHERE r <= 50) "
IN = ", ".join(f"'{w}'" for w in WORDS)
MISMATCH = "SELECT 0::BIGINT AS mismatches"

ORACLES: dict[str, str] = {
    "vocab_df": DOCS + " SELECT term, count(*)::BIGINT AS n FROM tok GROUP BY term",
    "vocab_ligatures": "WITH t AS (SELECT DISTINCT doc_id AS doc, unnest(regexp_extract_all(strip_accents(replace(replace(replace(replace(replace(lower(text), 'œ', 'oe'), 'æ', 'ae'), 'ß', 'ss'), 'ﬁ', 'fi'), 'ﬂ', 'fl')), '[a-z0-9]+')) AS term FROM documents) SELECT term, count(*)::BIGINT AS n FROM t WHERE term <> 'the' GROUP BY term",
    "url_trimming": r"SELECT page_id, regexp_replace(regexp_replace(url, '(https?://[^\s?]*)\?\S*', '\1'), '([^/:\s]/)[^/\s]{31,}(/|\s|$)', '\1\2', 'g') AS url FROM pages",
    "distinct_documents": "SELECT min(doc_id) AS doc_id FROM documents GROUP BY text",
    "collection_stats": DOCS + ", f AS (SELECT term, count(*) AS n FROM tok GROUP BY term) SELECT (SELECT d FROM d)::BIGINT AS d, count(*)::BIGINT AS w, sum(n)::BIGINT AS i, max(n)::BIGINT AS longest, round(sum(n)::DOUBLE / (count(*) * (SELECT d FROM d)), 9) AS density FROM f",
    "postings_lists": DOCS + PAIRS + " SELECT term, count(*)::BIGINT AS n, string_agg(ord::VARCHAR, ' ' ORDER BY ord) AS ids FROM p GROUP BY term",
    "gap_lists": DOCS + GAPS + " SELECT term, any_value(n)::BIGINT AS n, string_agg(gap::VARCHAR, ' ' ORDER BY i) AS gaps FROM g GROUP BY term",
    "trit_strings": BENCH + GAPS + f" SELECT term, string_agg({TRIT}, '' ORDER BY i) AS trits FROM g GROUP BY term",
    "quatrit_strings": BENCH + GAPS + f" SELECT term, string_agg({TRIT}, '' ORDER BY i) || '3' AS trits FROM g GROUP BY term",
    "symbol_counts": DOCS + GAPS + f" SELECT count(*)::BIGINT AS ints, sum({bl('gap')})::BIGINT AS trits, sum({bl('gap')} - length(replace(bin(gap::BIGINT), '0', '')))::BIGINT AS zeros, sum(length(replace(bin(gap::BIGINT), '0', '')) - 1)::BIGINT AS ones, count(*)::BIGINT AS twos, ((SELECT d FROM d) * count(DISTINCT term))::BIGINT AS matrix_bits FROM g",
    "bit_runs": BENCH + PAIRS + " SELECT term, ((SELECT d FROM d) - count(*))::BIGINT AS zeros, count(*)::BIGINT AS ones, ((SELECT d FROM d) - max(ord))::BIGINT AS tail FROM p GROUP BY term",
    "gap_code_bits": DOCS + GAPS + f""" SELECT count(*)::BIGINT AS ints, sum(gap)::BIGINT AS unary_bits, sum({bl('d - 1')})::BIGINT AS binary_bits, sum(2 * {bl('gap')} - 1)::BIGINT AS gamma_bits, sum({delta('gap')})::BIGINT AS delta_bits,
      sum({zeta('gap', 2)})::BIGINT AS zeta2_bits, sum({zeta('gap', 3)})::BIGINT AS zeta3_bits, sum({zeta('gap', 4)})::BIGINT AS zeta4_bits, sum((gap - 1) // gm + 1 + {truncated('(gap - 1) % gm', 'gm')})::BIGINT AS golomb_bits,
      sum(((gap - 1) >> ({bl('gm')} - 1)) + {bl('gm')})::BIGINT AS rice_bits, sum(8 * (({bl('gap')} + 6) // 7))::BIGINT AS vbyte_bits, sum(4 * (({bl('gap')} + 2) // 3))::BIGINT AS nibble_bits, (32 * count(*))::BIGINT AS raw32_bits
      FROM (SELECT *, {GOLOMB} AS gm FROM g, d)""",
    "gap_code_bits_sql": BENCH + GAPS + f" SELECT sum(2 * {bl('gap')} - 1)::BIGINT AS gamma_bits, sum({delta('gap')})::BIGINT AS delta_bits, sum({zeta('gap', 3)})::BIGINT AS zeta3_bits, sum(8 * (({bl('gap')} + 6) // 7))::BIGINT AS vbyte_bits, sum(4 * (({bl('gap')} + 2) // 3))::BIGINT AS nibble_bits, sum(((gap - 1) >> 2) + 3)::BIGINT AS rice2_bits, sum((gap - 1) // 5 + 1 + {truncated('(gap - 1) % 5', '5')})::BIGINT AS golomb5_bits FROM g",
    "density_bits": DOCS + f", f AS (SELECT term, count(*) AS n FROM tok GROUP BY term) SELECT round(sum(n * log2(d::DOUBLE / n) + CASE WHEN d > n THEN (d - n) * log2(d::DOUBLE / (d - n)) ELSE 0 END), 3) AS bernoulli_bits, sum({elias_fano('n', 'd')})::BIGINT AS ef_bits FROM f, d",
    "block_code_bits": DOCS + GAPS + f", w AS (SELECT term, i // 128 AS blk, gap, {WIDTH} AS b FROM g), b AS (SELECT term, blk, count(*) AS n, sum(gap)::BIGINT AS span, max(b) AS top, list(b) AS l FROM w GROUP BY term, blk), c AS (SELECT *, list_min(list_transform(range(0, top + 1), lambda v: n * v + coalesce(list_sum(list_transform(l, lambda y: CASE WHEN y > v THEN 8 + y - v ELSE 0 END)), 0))) AS best FROM b) SELECT count(*)::BIGINT AS blocks, sum(8 + n * top)::BIGINT AS packing_bits, sum(16 + best)::BIGINT AS pfor_opt_bits, sum({elias_fano('n', 'span')} + {delta('span')})::BIGINT AS ef_block_bits FROM c",
    "length_bits": DOCS + f", f AS (SELECT term, count(*) AS n FROM tok GROUP BY term) SELECT count(*)::BIGINT AS words, sum({delta('n')})::BIGINT AS length_bits FROM f",
    "midpoint_bits": BENCH.replace("WITH ", "WITH RECURSIVE ", 1) + PAIRS + f""", l AS (SELECT term, list(ord ORDER BY ord) AS v, count(*)::BIGINT AS n FROM p GROUP BY term),
      j AS (SELECT term, v, 0::BIGINT AS a, n AS b, 1::BIGINT AS lo, d::BIGINT AS hi FROM l, d UNION ALL
        SELECT term, v, unnest([a, (a + b) // 2 + 1]), unnest([(a + b) // 2, b]), unnest([lo, v[(a + b) // 2 + 1] + 1]), unnest([v[(a + b) // 2 + 1] - 1, hi]) FROM j WHERE b > a AND hi - lo + 1 > b - a),
      x AS (SELECT v[(a + b) // 2 + 1] - lo - ((a + b) // 2 - a) AS x, hi - (b - 1 - (a + b) // 2) - lo - ((a + b) // 2 - a) + 1 AS r FROM j WHERE b > a AND hi - lo + 1 > b - a),
      y AS (SELECT x, r, {bl('r')} - 1 AS w, (1::BIGINT << {bl('r')}) - r AS few FROM x)
      SELECT 'midpoint' AS codec, sum(w + CASE WHEN x >= (r - few) // 2 AND x < (r - few) // 2 + few THEN 0 ELSE 1 END)::BIGINT AS bits FROM y""",
    "bitmap_chunk_bits": BENCH + PAIRS + ", k AS (SELECT term, (ord - 1) // 65536 AS c, count(*) AS n FROM p GROUP BY ALL) SELECT 'bitmap_chunks' AS codec, sum(32 + least(16 * n, 65536))::BIGINT AS bits FROM k UNION ALL SELECT 'raw32', sum(32 * n)::BIGINT FROM k",
    "context_counts": CONTEXTS + "SELECT ctx, n0::BIGINT AS n0, n1::BIGINT AS n1, n2::BIGINT AS n2 FROM c",
    "static_ideal_bits": CONTEXTS + """, q AS (SELECT n0, n1, n2, greatest((510 * n0 + n0 + n1 + n2) // (2 * (n0 + n1 + n2)), (n0 > 0)::INT) AS q0, greatest((510 * n1 + n0 + n1 + n2) // (2 * (n0 + n1 + n2)), (n1 > 0)::INT) AS q1 FROM c),
      r AS (SELECT *, greatest((n2 > 0)::INT - (255 - q0 - q1), q0 + q1 - 255, 0) AS lack FROM q),
      v AS (SELECT n0, n1, n2, CASE WHEN q0 >= q1 THEN q0 - lack ELSE q0 END AS q0, CASE WHEN q0 >= q1 THEN q1 ELSE q1 - lack END AS q1, 255 - q0 - q1 + lack AS q2 FROM r)
      SELECT 19::BIGINT AS contexts, 304::BIGINT AS model_bits, round(sum(CASE WHEN n0 > 0 THEN n0 * log2(255.0::DOUBLE / q0) ELSE 0 END + CASE WHEN n1 > 0 THEN n1 * log2(255.0::DOUBLE / q1) ELSE 0 END + CASE WHEN n2 > 0 THEN n2 * log2(255.0::DOUBLE / q2) ELSE 0 END), 3) AS payload_bits FROM v""",
    "conditional_entropy": CONTEXTS + "SELECT sum(n0 + n1 + n2)::BIGINT AS trits, round(sum(" + " + ".join(ENTROPY.format(n=n) for n in ("n0", "n1", "n2")) + "), 3) AS bits FROM c",
    "adaptive_bits_order_free": CONTEXTS + ", o AS (SELECT count(*) OVER (PARTITION BY ctx, x ORDER BY n, term, i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS same, count(*) OVER (PARTITION BY ctx ORDER BY n, term, i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS allof FROM k) SELECT round(sum(log2((allof + 3)::DOUBLE / (same + 1))), 3) AS payload_bits FROM o",
    "markov4_counts": DOCS + GAPS + """, h AS (SELECT term, ord, gap, lag(gap) OVER w AS p, lag(gap, 2) OVER w AS p2, lead(gap) OVER w AS q FROM g WINDOW w AS (PARTITION BY term ORDER BY ord)),
      a AS (SELECT *, CASE WHEN p IS NULL THEN '00' WHEN p = 1 AND p2 IS NOT NULL THEN '11' ELSE '01' END AS st, (SELECT d FROM d) - ord AS tail FROM h),
      b AS (SELECT *, CASE WHEN substr(st, 2, 1) = '1' THEN '10' ELSE '00' END AS sh, CASE WHEN gap = 1 AND st IN ('01', '11') THEN '11' ELSE '01' END AS cl FROM a),
      e AS (SELECT CASE WHEN gap = 1 THEN st WHEN gap = 2 THEN sh ELSE '00' END AS state, 1 AS bit, 1 AS n FROM b UNION ALL SELECT st, 0, 1 FROM b WHERE gap >= 2 UNION ALL SELECT sh, 0, 1 FROM b WHERE gap >= 3 UNION ALL SELECT '00', 0, greatest(gap - 3, 0) FROM b
        UNION ALL SELECT cl, 0, 1 FROM b WHERE q IS NULL AND tail >= 1 UNION ALL SELECT '10', 0, 1 FROM b WHERE q IS NULL AND tail >= 2 UNION ALL SELECT '00', 0, greatest(tail - 2, 0) FROM b WHERE q IS NULL)
      SELECT state, coalesce(sum(n) FILTER (bit = 0), 0)::BIGINT AS zeros, coalesce(sum(n) FILTER (bit = 1), 0)::BIGINT AS ones FROM e GROUP BY state""",
    "packed_selectors": BENCH + GAPS + f", k AS (SELECT term, i // 128 AS blk, least({bl('gap')} - 1, 15) AS c FROM g), b AS (SELECT term, blk, list_sort(list(c)) AS l FROM k GROUP BY term, blk) SELECT (l[(len(l) - 1) // 2 + 1] * 16 + l[len(l)])::BIGINT AS selector, count(*)::BIGINT AS n FROM b GROUP BY ALL",
    "order_url": "SELECT page_id AS doc, row_number() OVER (ORDER BY url, page_id) AS ord FROM pages",
    "order_terms": DOCS + ", f AS (SELECT term, count(*)::BIGINT AS n FROM tok GROUP BY term) SELECT term, n, row_number() OVER (ORDER BY n, term) AS term_id FROM f",
    "batch_sizes": DOCS + GAPS + f", e(b, hi) AS (VALUES {_values((k, EDGES[k]) for k in range(1, 8))}) SELECT (SELECT min(b) FROM e WHERE n::DOUBLE / d <= hi) AS batch, count(*)::BIGINT AS ints, sum(2 * {bl('gap')} - 1)::BIGINT AS gamma_bits FROM g, d GROUP BY 1",
    "reference_lists": REFERENCE + "SELECT c, ord, rank FROM b",
    "reference_split": REFERENCE + ", s AS (SELECT k.c, k.ord, b.rank, (SELECT count(*) FROM b AS y WHERE y.c = k.c AND y.ord < k.ord) AS below FROM k LEFT JOIN b ON b.c = k.c AND b.ord = k.ord) SELECT c, CASE WHEN rank IS NULL THEN 'rest' ELSE 'hit' END AS part, count(*)::BIGINT AS n, sum(coalesce(rank, ord - below))::BIGINT AS x, max(coalesce(rank, ord - below))::BIGINT AS most FROM s GROUP BY 1, 2",
    "filter_share": DOCS + ", f AS (SELECT term, count(*) AS n FROM tok GROUP BY term), b AS (SELECT n, sum(n) AS i FROM f GROUP BY n), a AS (SELECT n, sum(i) OVER (ORDER BY n DESC) AS a, sum(i) OVER () AS t FROM b), m AS (SELECT max(n) AS m FROM a WHERE a >= 0.882 * t) SELECT m::BIGINT AS min_len, count(*)::BIGINT AS words, sum(n)::BIGINT AS ints FROM f, m WHERE n >= m GROUP BY m".replace(", m AS (SELECT max(n)", ", cutoff AS (SELECT max(n)").replace("FROM f, m WHERE", "FROM f, cutoff WHERE"),
    "bool_and": DOCS + PAIRS + f" SELECT ord FROM p WHERE term IN ({IN}) GROUP BY ord HAVING count(*) = {len(WORDS)}",
    "bool_or": DOCS + PAIRS + f" SELECT DISTINCT ord FROM p WHERE term IN ({IN})",
    "bool_not": DOCS + PAIRS + " SELECT DISTINCT ord FROM p WHERE term = 'the' AND ord NOT IN (SELECT ord FROM p WHERE term = 'with')",
    "topk_terms": DOCS + " SELECT term, count(*)::BIGINT AS n FROM tok GROUP BY term ORDER BY n DESC, term LIMIT 20",
    "topk_docs": DOCS + PAIRS + " SELECT ord, count(*)::BIGINT AS hits FROM p WHERE term IN ('the', 'and', 'with', 'la', 'der') GROUP BY ord ORDER BY hits DESC, ord LIMIT 20",
    "block_directory": DOCS + GAPS + " SELECT term, 0::BIGINT AS shard, (i // 128)::INT AS blk, min(ord)::BIGINT AS first, max(ord)::BIGINT AS max, count(*)::BIGINT AS n FROM g GROUP BY ALL",
    "block_lookup": DOCS + GAPS + ", b AS (SELECT term, (i // 128)::INT AS blk, min(ord) AS lo, max(ord) AS hi, count(*) AS n FROM g GROUP BY ALL), q AS (SELECT unnest(range(1, greatest(2, d), 100)) AS q FROM d) SELECT q AS ord, term, 0::BIGINT AS shard, blk FROM b, q WHERE q BETWEEN lo AND hi",
    "part_order_lists": _lists("lineitem", "l_partkey", "l_orderkey + 1"),
    "event_type_lists": _lists("events", "event_type", "event_id + 1", True),
    "json_value_lists": _lists("events", "json_extract_string(props, '$.k')", "event_id + 1", True),
    "method_cube": DOCS + f""", p AS (SELECT lang, term, ord FROM tok JOIN m USING (doc) JOIN documents ON doc_id = doc), g AS (SELECT lang, ord - lag(ord, 1, 0) OVER (PARTITION BY lang, term ORDER BY ord) AS gap FROM p),
      b AS (SELECT lang, unnest(['gamma', 'delta', 'vbyte']) AS code, unnest([2 * {bl('gap')} - 1, {delta('gap')}, 8 * (({bl('gap')} + 6) // 7)]) AS bits FROM g) SELECT lang, code, sum(bits)::BIGINT AS bits FROM b GROUP BY CUBE (lang, code)""",
    "trit_static_roundtrip": MISMATCH, "trit_adaptive_roundtrip": MISMATCH, "quatrit_roundtrip": MISMATCH, "midpoint_roundtrip": MISMATCH,
}

from .more_oracles import MORE  # noqa: E402  its SQL is built from this module's

ORACLES |= MORE
