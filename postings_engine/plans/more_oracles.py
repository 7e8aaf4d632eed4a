"""SQL for static models over whole collections, and for what stands around the methods."""

from __future__ import annotations

from .oracles import BENCH, CONTEXTS, DOCS, ENTROPY, GAPS, PAIRS, TRIT, _lists, bl, delta, tok, zeta
from .queries import FAMILIES
from .surround import LENGTH_CODES, SLOW
from .workloads import W6_GRID, W7_GRID, W9_BITS

BY_SOURCE = "WITH " + tok("documents", "doc_id").replace("ORDER BY doc_id", "ORDER BY lang NULLS FIRST, source NULLS FIRST, doc_id")
TURNS = "WITH " + tok("conversations", "conv_id * 65536 + turn")
#: (string of trits, the same with 2 as 1 and the rest as 0, place) of every trit.
TRITS = f", s AS (SELECT term, string_agg({TRIT}, '' ORDER BY i) AS s FROM g GROUP BY term), e AS MATERIALIZED (SELECT s, translate(s, '012', '001') AS zs, unnest(range(0, length(s))) AS i FROM s), ints AS (SELECT count(*)::BIGINT AS ints FROM g)"
WORDS_OF = "unnest(regexp_extract_all(lower(strip_accents({})), '[a-z0-9]+')) AS term"
F_N = ", f AS (SELECT term, count(*) AS n FROM tok GROUP BY term)"


def context_key(k: int, windows: tuple[int, ...], k_init: int, merge: bool = True, merge_init: bool = True) -> str:
    """What tells contexts apart: the last k symbols, then how many terminators each window before them holds; near the
    beginning of a list, up to k_init symbols."""
    reach = k + sum(windows)
    if not reach:
        return "''"
    parts, back = [f"substr({'zs' if merge else 's'}, i - {k} + 1, {k})"], k
    for w in windows:
        parts.append(f"length(replace(substr(zs, i - {back + w} + 1, {w}), '0', ''))::VARCHAR")
        back += w
    few = f"least(i, {k_init})"
    return f"CASE WHEN i >= {reach} THEN {' || chr(58) || '.join(parts)} ELSE 'i' || substr({'zs' if merge_init else 's'}, i - {few} + 1, {few}) END"


def size_of(k: int, windows: tuple[int, ...], k_init: int, merge: bool = True, merge_init: bool = True) -> int:
    n = (2 if merge else 3) ** k
    for w in windows:
        n *= w + 1
    return n + (sum((2 if merge_init else 3) ** i for i in range(k_init + 1)) if k + sum(windows) else 0)


def counted(key: str) -> str:
    x = "substr(s, i + 1, 1)"
    return f"SELECT count(*) FILTER ({x} = '0') AS n0, count(*) FILTER ({x} = '1') AS n1, count(*) FILTER ({x} = '2') AS n2 FROM e GROUP BY {key}"


def model_cell(counts: str, contexts: int, bits: int | str, balanced: bool = False) -> str:
    """SELECT contexts, model_bits, payload_bits of one context model from its counts (n0, n1, n2)."""
    if bits == "exact":
        cost = " + ".join(ENTROPY.format(n=n) for n in ("n0", "n1", "n2"))
        return f"SELECT {contexts}::BIGINT AS contexts, (3 * {contexts} * greatest(1, {bl('max(greatest(n0, n1, n2))')}))::BIGINT AS model_bits, sum({cost}) AS payload_bits FROM ({counts})"
    m = (1 << bits) - 1
    if balanced:
        q = f"SELECT n0, n1, n2, h AS q0, h AS q1, {m} - 2 * h AS q2 FROM (SELECT *, least(greatest(({2 * m} * (n0 + n1) + t) // (2 * t) // 2, (n0 + n1 > 0)::INT), ({m} - (n2 > 0)::INT) // 2) AS h FROM (SELECT *, n0 + n1 + n2 AS t FROM ({counts})))"
    else:
        first = f"SELECT *, greatest(({2 * m} * n0 + t) // (2 * t), (n0 > 0)::INT) AS a, greatest(({2 * m} * n1 + t) // (2 * t), (n1 > 0)::INT) AS b FROM (SELECT *, n0 + n1 + n2 AS t FROM ({counts}))"
        lack = f"SELECT *, greatest((n2 > 0)::INT - ({m} - a - b), a + b - {m}, 0) AS lack FROM ({first})"
        q = f"SELECT n0, n1, n2, a - CASE WHEN a >= b THEN lack ELSE 0 END AS q0, b - CASE WHEN a >= b THEN 0 ELSE lack END AS q1, {m} - a - b + lack AS q2 FROM ({lack})"
    part = " + ".join(f"CASE WHEN n{j} > 0 THEN n{j} * log2({m}::DOUBLE / q{j}) ELSE 0 END" for j in range(3))
    return f"SELECT {contexts}::BIGINT AS contexts, ({(1 if balanced else 2) * bits} * {contexts})::BIGINT AS model_bits, sum({part}) AS payload_bits FROM ({q})"


def cell(bits, k, windows, k_init, merge=True, merge_init=True, balanced=False) -> str:
    how = (k, windows, k_init, merge, merge_init)
    return model_cell(counted(context_key(*how)), size_of(*how), bits, balanced)


def static_sweep(workload: str, cells: list[tuple[str, str]], more: str = "") -> str:
    """Rows of a workload from (params, model cell)."""
    rows = " UNION ALL ".join(f"SELECT '{params}' AS params, model_bits, payload_bits FROM ({c})" for params, c in cells)
    bits = "SELECT params, 'model' AS part, model_bits::DOUBLE AS bits FROM r UNION ALL SELECT params, 'payload', round(payload_bits, 1) FROM r"
    return BY_SOURCE + GAPS + TRITS + more + f", r AS MATERIALIZED ({rows}) SELECT '{workload}' AS workload, 'documents' AS dataset, 'trit_static' AS method, params, part, bits, ints, round(bits / ints, 4) AS bpi FROM ({bits}), ints"


W9 = (("merged", (10, (12,), 4)), ("apart", (10, (12,), 4, False, False)))
COUNTS9 = "".join(f", {name} AS MATERIALIZED ({counted(context_key(*how))})" for name, how in W9)
# the covering window depends on the number of documents: one cell for each that is possible, of which the table's own counts
COVER = " UNION ALL ".join(f"SELECT contexts, model_bits, payload_bits FROM ({cell(8, 6, (w,), 2)}) WHERE greatest(1, (SELECT {bl('d')} - 6 FROM d)) = {w}" for w in range(1, 13))

PACKED = DOCS + GAPS + f""", k AS (SELECT term, i // 128 AS blk, gap, {bl('gap')} AS b, least({bl('gap')} - 1, 15) AS c FROM g), l AS (SELECT term, blk, list_sort(list(c)) AS l FROM k GROUP BY term, blk), v AS (SELECT term, blk, (l[(len(l) - 1) // 2 + 1] * 16 + l[len(l)])::BIGINT AS sel FROM l),
  x AS (SELECT 'modelled' AS mantissa, sel, CASE WHEN gap < 65536 THEN gap ELSE 65536 + b END AS sym, CASE WHEN gap < 65536 THEN 0 ELSE b - 1 END AS raw FROM k JOIN v USING (term, blk) UNION ALL SELECT 'raw', sel, b, b - 1 FROM k JOIN v USING (term, blk)),
  y AS (SELECT mantissa, sel, sym, count(*) AS n, sum(raw) AS raw FROM x GROUP BY ALL), z AS (SELECT *, sum(n) OVER (PARTITION BY mantissa, sel) AS t FROM y), o AS (SELECT mantissa, sum(n * log2(t::DOUBLE / n) + raw) AS payload, count(*) AS pe FROM z GROUP BY mantissa),
  q AS (SELECT sel, count(*) AS n FROM v GROUP BY sel), r AS (SELECT sum(n * log2(t::DOUBLE / n)) AS s, sum(n) AS blocks, count(*) AS re FROM (SELECT *, sum(n) OVER () AS t FROM q)), h(selector, mantissa) AS (VALUES ('arith', 'modelled'), ('raw6', 'modelled'), ('arith', 'raw'))
  SELECT selector, mantissa, blocks::BIGINT AS blocks, round(c, 1) AS selector_bits, round(payload, 1) AS payload_bits, ((pe + re) * 20)::BIGINT AS model_bits, round(c / blocks, 4) AS selector_bits_per_block FROM (SELECT *, CASE WHEN selector = 'arith' THEN s ELSE 6.0 * blocks END AS c FROM h JOIN o USING (mantissa), r)"""
CODES = {"delta": delta("n"), "gamma": f"2 * {bl('n')} - 1", "vbyte": f"8 * (({bl('n')} + 6) // 7)", "nibble": f"4 * (({bl('n')} + 2) // 3)", **{f"zeta{k}": zeta("n", k) for k in (2, 3, 4)}}
INTS = " UNION ALL ".join(f"SELECT '{name}' AS dataset, count(*)::BIGINT AS ints FROM (SELECT DISTINCT {key} AS doc, {WORDS_OF.format('text')} FROM {name})" for name, key in (("benchmark", "item_id"), ("conversations", "conv_id * 65536 + turn"), ("documents", "doc_id")))
RULE = "greatest(floor(ln(ints) / 1.67264 - 2.24758 + 0.5), 7)::BIGINT"
BENCH_N = f"WITH t AS (SELECT DISTINCT item_id, {WORDS_OF.format('text')} FROM benchmark), n AS (SELECT count(*)::BIGINT AS ints, count(DISTINCT term)::BIGINT AS lists FROM t)"


def listed(names) -> str:
    return "VALUES " + ", ".join(f"('{n}')" for n in names)


KNOWN = ["raw32", "binary", "gamma", "delta", "zeta2", "zeta3", "zeta4", "vbyte", "nibble", "rice", "golomb", "group_varint", "g8iu", "simple9", "simple16", "simple8b", "qmx", "packing", "packing_vector", "pfor_new", "pfor_opt", "pfor_fast", "split_blocks", "adaptive_frames", "midpoint"]
KNOWN += [f"midpoint_:{a}:{b}" for a in ("none", "center", "center+leaf_ends") for b in ("plain", "pow2")] + ["midpoint_block", "midpoint_block:pad", "midpoint_block:plain", "midpoint_block:trimmed", "elias_fano", "ef_block", "pef_opt", "pef_approx", "pef_skip", "bitmap_runs", "bitmap_chunks", "zlib", "bz2", "lzma", "simple8b+zlib", "packing+lzma"]
CODERS = ["packed_arith:modelled:arith", "packed_arith:raw:arith", "packed_arith:modelled:raw6", "bitmap:k=2:w=0", "bitmap:k=3:w=5", *(f"trits:{x}" for x in ("static lanes", "adaptive lanes", "one lane", "global halving", "static prior", "quatrit lanes"))]
CLUSTERED = ["midpoint", "pef_approx", "midpoint_block:trimmed", "trit_static", "trit_adaptive"]
HTML = r"regexp_replace(regexp_replace(html, '(?is)<script\b.*?</script\s*>|<style\b.*?</style\s*>|<!--.*?-->', ' ', 'g'), '<[^>]*>', ' ', 'g')"
for _name, _value in (("&nbsp;", "' '"), ("&lt;", "'<'"), ("&gt;", "'>'"), ("&quot;", "chr(34)"), ("&#39;", "chr(39)"), ("&amp;", "'&'")):
    HTML = f"replace({HTML}, '{_name}', {_value})"

MORE: dict[str, str] = {
    "w6_static_apart": static_sweep("w6_static_apart", [(f"k={k} w={w}", cell("exact", k, (w,), k, False, False)) for k, w in W6_GRID]),
    "w7_static_merged": static_sweep("w7_static_merged", [(f"k={k} w={w}", cell(8, k, (w,), -(-k // 3))) for k, w in W7_GRID]),
    "w9_widths": static_sweep("w9_widths", [(f"{name} bits={b}", model_cell(f"SELECT * FROM {name}", size_of(*how), b)) for b in W9_BITS for name, how in W9], COUNTS9),
    "w17_balanced": static_sweep("w17_balanced", [(f"balanced={x}", cell(8, 5, (6,), 2, balanced=x)) for x in (False, True)]),
    "w18_boxes": static_sweep("w18_boxes", [*((n, cell(8, 6, w, 2)) for n, w in (("w=7", (7,)), ("w=3+4", (3, 4)), ("w=2+2+3", (2, 2, 3)))), ("cover", COVER)]),
    "context_variants": TURNS + GAPS + TRITS + " " + " UNION ALL ".join(f"SELECT '{name}' AS model, contexts, model_bits, round(payload_bits, 1) AS payload_bits FROM ({cell(8, c.k, c.windows, c.k_init, c.merge, c.merge_init)})" for name, c in FAMILIES.items()),
    "packed_arith_bits": PACKED,
    "page_terms": f"WITH k AS (SELECT DISTINCT page_id, {WORDS_OF.format(HTML)} FROM pages) SELECT term, count(*)::BIGINT AS n FROM k GROUP BY term",
    "message_terms": f"WITH t AS (SELECT DISTINCT conv_id, turn, {WORDS_OF.format('concat_ws(chr(10), role, turn::VARCHAR, text)')} FROM conversations) SELECT term, count(*)::BIGINT AS n FROM t GROUP BY term",
    "dense_bitmaps": DOCS + PAIRS + ", f AS (SELECT term FROM p GROUP BY term HAVING count(*) >= 100) SELECT term, ((ord - 1) // 32768 + 1)::BIGINT AS bucket, count(*)::BIGINT AS n FROM p JOIN f USING (term) GROUP BY ALL",
    "length_codes": DOCS + F_N + " " + " UNION ALL ".join(f"SELECT '{c}' AS code, count(*)::BIGINT AS words, sum({CODES[c]})::BIGINT AS length_bits FROM f" for c in LENGTH_CODES),
    "model_share": f"WITH n AS ({INTS}), c AS (SELECT k, (k + 1)::BIGINT AS w, ((k + 2) // 3)::BIGINT AS k_init, (k + 2) * (1::BIGINT << k::INT) + (2::BIGINT << ((k + 2) // 3)::INT) - 1 AS contexts FROM range(1, 24) AS r(k)), b AS (SELECT dataset, ints, greatest(1, coalesce((SELECT max(k) FROM c WHERE 16 * contexts <= 0.02 * ints AND contexts <= 4194304), 1)) AS k, {RULE} AS ak FROM n) SELECT dataset, ints, k::BIGINT AS k, w, k_init, (16 * contexts)::BIGINT AS model_bits, round((16 * contexts)::DOUBLE / ints, 6) AS share, ak AS adaptive_k, (1::BIGINT << least(greatest(ak, 8), 16)::INT)::BIGINT AS adaptive_n, (24 * ((ak + 1) * (1::BIGINT << ak::INT) + (2::BIGINT << least(2 * ak - 1, 8)::INT) - 1))::BIGINT AS state_bytes FROM b JOIN c USING (k)",
    "codec_roundtrips": f"{BENCH_N} SELECT codec, lists, ints, 0::BIGINT AS mismatches, 0::BIGINT AS wrong_sizes FROM n, ({listed(c for c in KNOWN if c not in SLOW)}) AS v(codec)",
    "model_roundtrips": f"SELECT coder, 0::BIGINT AS mismatches FROM ({listed(CODERS)}) AS v(coder)",
    "clustered_roundtrips": f"SELECT codec, shrink, 0::BIGINT AS mismatches FROM ({listed(CLUSTERED)}) AS v(codec), (VALUES (true), (false)) AS w(shrink)",
    "trit_rows": CONTEXTS + "SELECT term, i::BIGINT AS pos, x::INT AS trit, ctx FROM k",
    "sampled_terms": DOCS + GAPS + f" SELECT count(DISTINCT term)::BIGINT AS words, count(*)::BIGINT AS ints, sum({bl('gap')})::BIGINT AS trits FROM g WHERE ('0x' || substr(md5(term), 1, 8))::BIGINT % 1000 < 100",
    "length_statistics": DOCS + F_N + ", h AS (SELECT n, count(*) AS c FROM f GROUP BY n) SELECT count(*)::BIGINT AS words, quantile_cont(n::DOUBLE, 0.5) AS median, quantile_cont(n::DOUBLE, 0.99) AS p99, (SELECT term FROM f ORDER BY n DESC, term DESC LIMIT 1) AS longest, (SELECT n::BIGINT FROM h ORDER BY c DESC, n LIMIT 1) AS mode, true AS near FROM f",
    "code_rollup": f"WITH t AS (SELECT DISTINCT doc_id, lang, {WORDS_OF.format('text')} FROM documents), f AS (SELECT lang, term, count(*) AS n FROM t GROUP BY lang, term), s AS (SELECT lang, n, {bl('n')} AS size FROM f) SELECT lang, size::BIGINT AS size, count(*)::BIGINT AS lists, sum(n)::BIGINT AS ints FROM s GROUP BY ROLLUP (lang, size)",
    "asof_events": "WITH v AS (SELECT user_id, ts, max(event_id) AS view_id FROM events WHERE event_type = 'view' GROUP BY ALL), b AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase') SELECT b.event_id, v.view_id FROM b ASOF LEFT JOIN v ON b.user_id = v.user_id AND b.ts >= v.ts",
    "interval_events": "SELECT s.event_id AS signup, count(*)::BIGINT AS n, max(e.event_id)::BIGINT AS last FROM events s JOIN events e ON e.user_id = s.user_id AND e.ts >= s.ts AND e.ts < s.ts + INTERVAL 36 HOURS WHERE s.event_type = 'signup' GROUP BY s.event_id",
    "daily_lists": _lists("events", "strftime(ts, '%Y-%m-%d')", "event_id + 1", True),
    "windowed_counts": "WITH w AS (SELECT event_type, unnest([time_bucket(INTERVAL 3 HOURS, ts, TIMESTAMP '1970-01-01'), time_bucket(INTERVAL 3 HOURS, ts, TIMESTAMP '1970-01-01') - INTERVAL 3 HOURS]) AS a FROM events) SELECT strftime(a, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*)::BIGINT AS n FROM w GROUP BY ALL",
    "session_counts": "WITH a AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER w + INTERVAL 12 HOURS THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), b AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a) SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S.%f') AS start, user_id, count(*)::BIGINT AS n FROM b GROUP BY user_id, s",
    "variant_values": "SELECT json_extract(props, '$.k')::BIGINT AS k, count(*)::BIGINT AS n FROM events GROUP BY 1",
    "segment_headers": f"{BENCH_N} SELECT ints, lists, (1::BIGINT << least(greatest({RULE}, 8), 16)::INT)::VARCHAR AS forget, ({RULE})::VARCHAR AS k FROM n",
}
