"""The static and the adaptive trit coder over segments: runs of whole list shards in coding order.

Lists are put in order of length (a range sort), a running total of their trits cuts that order into segments, and one
task codes a segment from start to end with a state of its own. A shard of a list (at most 2**20 ids) is coded as a
list: its context starts empty. What a segment needs to be read again stands in its row.
"""

from __future__ import annotations

import json
from dataclasses import asdict

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import closed
from . import arith, codecs, lanes, trits
from .ids import running
from .postings import Lists, checked
from .trits import Context

#: Trits of a segment: a minute of one Python worker; 22 bits' worth make one stream of the small tables.
SEGMENT_TRITS = 1 << 22
#: Contexts up to which a worker keeps its counts of a model until the end; of larger models it sends what each batch has.
DENSE_CONTEXTS = 1 << 16
#: Groups of settings of an adaptive sweep; the gaps are sent once to each.
SWEEP_GROUPS = 4
#: Counts that a static model's fractions make where they start an adaptive one.
PRIOR_COUNTS = 16
#: Contexts that a static model may have, so that counts and model always fit the driver and every worker.
MAX_CONTEXTS = 1 << 22
SEGMENT = (
    "seg bigint, method string, term_lo string, term_hi string, n_lists bigint, n_ints bigint, symbols bigint, header binary, lengths binary, model binary, "
    "payload binary, lengths_bits bigint, ideal_bits double, terms array<string>, ns array<bigint>, shards array<bigint>, before array<bigint>"
)


def segmented(lists: DataFrame, order: str = "length", target: int = SEGMENT_TRITS) -> DataFrame:
    """``lists`` with ``seg``, and the key ``__k`` that orders rows inside it. Orders: length, desc, alpha, none (by hash)."""
    first = {"length": F.col("n"), "desc": -F.col("n"), "alpha": F.lit(0).cast("long"), "none": F.xxhash64("term")}[order]
    rows = checked(lists).withColumn("__k", first).withColumn("__t", F.aggregate("gaps", F.lit(0).cast("long"), lambda s, g: s + closed.bitlen(g)))
    rows = running(rows, "__t", "__c", F.col("__k"), F.col("term"), F.col("shard"))
    return rows.withColumn("seg", F.floor((F.col("__c") - F.col("__t")) / target).cast("long")).drop("__t", "__c")


def _arrays(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """All gaps of the rows, one after another, and how many each row has."""
    col = t.column("gaps").combine_chunks()
    col = col.combine_chunks() if isinstance(col, pa.ChunkedArray) else col
    return col.flatten().to_numpy(zero_copy_only=False), np.diff(col.offsets.to_numpy())


def symbols(gaps: np.ndarray, sizes: np.ndarray, kinds: int) -> tuple[np.ndarray, np.ndarray]:
    """(symbols, places in their lists) of lists put one after another."""
    ends = None
    last = np.cumsum(sizes) - 1
    if kinds == 4:
        ends = np.zeros(len(gaps), bool)
        ends[last] = True
    s, width = trits.trits_of(gaps, ends)
    total = np.concatenate([[0], np.cumsum(width)])
    per_list = total[last + 1] - total[last + 1 - sizes]
    pos = np.arange(len(s)) - np.repeat(np.cumsum(per_list) - per_list, per_list)
    return s, pos


def context_counts(lists: DataFrame, contexts: dict[str, Context]) -> DataFrame:
    """(model, ctx, n0, n1, n2, n3) for each named context model: one pass for all of them, additive counts."""

    def sparse(name, ctx, n):
        wide = np.zeros((len(ctx), 4), np.int64)
        wide[:, : n.shape[1]] = n
        return pa.RecordBatch.from_pydict({"model": pa.array([name] * len(ctx), pa.string()), "ctx": pa.array(ctx, pa.int64()), **{f"n{j}": pa.array(wide[:, j].copy()) for j in range(4)}})

    def run(batches):
        total: dict[str, np.ndarray] = {}
        for b in batches:
            t = pa.Table.from_batches([b])
            if not t.num_rows:
                continue
            gaps, sizes = _arrays(t)
            cache: dict[int, tuple] = {}
            for name, c in contexts.items():
                if c.kinds not in cache:
                    cache[c.kinds] = symbols(gaps, sizes, c.kinds)
                s, pos = cache[c.kinds]
                ids = c.ids(s, pos)
                if c.size > DENSE_CONTEXTS:
                    yield sparse(name, *trits.sparse_counts(ids, s, c.kinds))
                    continue
                n = trits.counts(ids, s, c.size, c.kinds)
                total[name] = total[name] + n if name in total else n
        for name, n in total.items():
            used = np.flatnonzero(n.sum(1))
            yield sparse(name, used, n[used])

    for c in contexts.values():
        if c.size > MAX_CONTEXTS:
            raise ValueError(f"{c.size} contexts: more than {MAX_CONTEXTS}")
    rows = lists.select("gaps").mapInArrow(run, "model string, ctx bigint, n0 bigint, n1 bigint, n2 bigint, n3 bigint")
    return rows.groupBy("model", "ctx").agg(*(F.sum(f"n{j}").alias(f"n{j}") for j in range(4)))


def collected(counts: DataFrame, contexts: dict[str, Context]) -> dict[str, np.ndarray]:
    """Counts as arrays on the driver; at most MAX_CONTEXTS rows for each model."""
    out = {name: np.zeros((c.size, c.kinds), np.int64) for name, c in contexts.items()}
    t = counts.toArrow()
    coded = t.column("model").combine_chunks().dictionary_encode()
    coded = coded.combine_chunks() if isinstance(coded, pa.ChunkedArray) else coded
    place, names = coded.indices.to_numpy(), coded.dictionary.to_pylist()
    ctx = t.column("ctx").to_numpy()
    wide = np.stack([t.column(f"n{j}").to_numpy() for j in range(4)], 1) if t.num_rows else np.zeros((0, 4), np.int64)
    for name, c in contexts.items():
        if name in names:
            mine = np.flatnonzero(place == names.index(name))
            out[name][ctx[mine]] = wide[mine][:, : c.kinds]
    return out


def static_model(lists: DataFrame, ctx: Context, bits: int = 8, balanced: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """(counts, fractions) of a count pass."""
    n = collected(context_counts(lists, {"m": ctx}), {"m": ctx})["m"]
    return n, trits.quantise(n, bits, balanced)


def pack_model(q: np.ndarray, bits: int) -> bytes:
    flat = q[:, :-1].astype(np.int64).ravel()
    return np.packbits((flat[:, None] >> np.arange(bits - 1, -1, -1) & 1).astype(np.uint8)).tobytes()


def unpack_model(raw: bytes, size: int, kinds: int, bits: int) -> np.ndarray:
    n = size * (kinds - 1)
    b = np.unpackbits(np.frombuffer(raw, np.uint8), count=n * bits).reshape(n, bits).astype(np.int64)
    q = (b << np.arange(bits - 1, -1, -1)).sum(1).reshape(size, kinds - 1)
    last = np.where(q.sum(1) > 0, (1 << bits) - 1 - q.sum(1), 0)
    empty = q.sum(1) == 0  # only ends, or never seen: all to the last symbol
    return np.concatenate([q, np.where(empty, (1 << bits) - 1, last)[:, None]], 1)


def prior_of(q: np.ndarray) -> np.ndarray:
    """Starting counts of an adaptive model from a static one's fractions."""
    return np.maximum(1, PRIOR_COUNTS * q // np.maximum(q.sum(1, keepdims=True), 1))


def _delta_coded(values: np.ndarray) -> tuple[bytes, int]:
    one = np.array([len(values)])
    return codecs.bytes_of("delta", values, one, one)[0], int(codecs.CODECS["delta"].size(values, 0))


def encode(
    lists: Lists,
    method: str = "trit_adaptive",
    ctx: Context | None = None,
    bits: int = 8,
    forget: int | None = None,
    order: str = "length",
    target: int = SEGMENT_TRITS,
    prior: tuple[int, ...] | str | None = None,
    payload: bool = True,
    halving: str = "context",
    lanes_: int | None = None,
) -> DataFrame:
    """Segments of ``lists`` by 'trit_static' or 'trit_adaptive' (quatrits if the context codes 4 kinds of symbol).

    Without ``ctx`` the parameters follow the number of integers. ``prior``: starting counts of the adaptive coder, or
    'static' for those of a stored static model (an extension). ``halving``: 'context' or 'global'. ``payload`` False:
    sizes only, no coder runs. ``lanes_``: interleaved streams of a segment, by default as many as its symbols allow; with
    1, and where contexts or fractions are too wide for lanes, the sequential arithmetic coder writes.
    """
    if ctx is None:
        if method == "trit_static":
            k, w, k_init = trits.choose_static(lists.i, most=MAX_CONTEXTS)
        else:
            k, w, k_init, auto = trits.choose_adaptive(lists.i)
            forget = auto if forget is None else forget
        ctx = trits.hybrid(k, w, k_init)
    q = None
    if method == "trit_static" or prior == "static":
        _, q = static_model(lists.gaps, ctx, bits)
    elif method != "trit_adaptive":
        raise ValueError(method)
    shared = lists.gaps.sparkSession.sparkContext.broadcast(q)  # at most MAX_CONTEXTS rows
    schema = _segment_schema()
    if ctx.reach > lanes.REACH or bits > lanes.SCALE - 2:
        lanes_ = 1
    head = {"ctx": asdict(ctx), "bits": bits, "forget": forget, "prior": prior, "halving": halving}

    def code(t: pa.Table) -> pa.Table:
        t = t.sort_by([("__k", "ascending"), ("term", "ascending"), ("shard", "ascending")])
        gaps, sizes = _arrays(t)
        s, pos = symbols(gaps, sizes, ctx.kinds)
        ids = ctx.ids(s, pos)
        q, start = shared.value, prior
        if prior == "static":
            q, start = None, prior_of(shared.value)
        n = lanes_ or lanes.lanes_for(len(s), q is None)
        if q is not None:
            ideal = trits.ideal_bits(trits.counts(ids, s, ctx.size, ctx.kinds), q)
        else:
            ideal = trits.adaptive_bits(ids, s, ctx.size, ctx.kinds, forget, halving, start)
        if not payload:
            out = b""
        elif n > 1:
            out, _ = lanes.encode(ids, s, np.bincount(np.cumsum(pos == 0) - 1), ctx, q, n, forget, start, halving)
        else:
            out = arith.encode_static(ids, s, q) if q is not None else arith.encode_adaptive(ids, s, ctx.size, ctx.kinds, forget, start, halving)
        lengths, lbits = (b"", 0) if ctx.kinds == 4 else _delta_coded(sizes.astype(np.int64))
        terms = t.column("term")
        ends = pc.min_max(terms).as_py()
        seg = t.column("seg")[0].as_py()
        row = {
            "seg": seg, "method": method, "term_lo": ends["min"], "term_hi": ends["max"], "n_lists": len(terms), "n_ints": int(sizes.sum()), "symbols": len(s), "header": json.dumps(head | {"lanes": n}).encode(), "lengths": lengths,
            "model": pack_model(shared.value, bits) if seg == 0 and shared.value is not None else b"", "payload": out, "lengths_bits": lbits, "ideal_bits": ideal,
        }
        lists = dict(zip(("terms", "ns", "shards", "before"), map(_as_one, (terms, t.column("n"), t.column("shard"), t.column("before"))), strict=True))
        return pa.table([lists[f.name] if f.name in lists else pa.array([row[f.name]], f.type) for f in schema], schema=schema)

    rows = segmented(lists.gaps, order, target).select("seg", "__k", "term", "n", "shard", "before", "gaps")
    return rows.groupBy("seg").applyInArrow(code, SEGMENT)


def _as_one(column: pa.ChunkedArray) -> pa.ListArray:
    """A column as one row's array."""
    own = column.combine_chunks()
    own = pa.concat_arrays(own.chunks) if isinstance(own, pa.ChunkedArray) else own
    return pa.ListArray.from_arrays(pa.array([0, len(own)], pa.int32()), own)


def _segment_schema() -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    return to_arrow_schema(StructType.fromDDL(SEGMENT))


_models: dict[tuple, np.ndarray] = {}


def decoded(r: dict, model: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(gaps of all lists, how many each has) of one segment's row; a worker unpacks a model once."""
    h = json.loads(r["header"])
    h["ctx"]["windows"] = tuple(h["ctx"]["windows"])
    ctx, prior, q = Context(**h["ctx"]), h["prior"], None
    if r["method"] == "trit_static" or prior == "static":
        key = (hash(model), ctx, h["bits"])
        if key not in _models:
            _models.clear()
            _models[key] = unpack_model(model, ctx.size, ctx.kinds, h["bits"])
        q = _models[key]
        if prior == "static":
            q, prior = None, prior_of(q)
    one = np.array([r["n_lists"]])
    lengths = None if ctx.kinds == 4 else codecs.lists_from("delta", [r["lengths"]], one, one)
    if h.get("lanes", 1) > 1:
        return lanes.decode(r["payload"], lengths, r["n_lists"], ctx, q, h["forget"], prior, h["halving"])
    got = arith.decode_lists(r["payload"], None if lengths is None else lengths.tolist(), r["n_lists"], ctx, q, h["forget"], prior, h.get("halving", "context"))
    return np.concatenate([*got, np.empty(0, np.int64)]), np.array([len(x) for x in got], np.int64)


def model_of(segments: DataFrame) -> bytes:
    """The stored model, which stands in the first segment; empty without one."""
    first = segments.where("length(model) > 0").select("model").limit(1).collect()
    return bytes(first[0].model) if first else b""


def decode(segments: DataFrame, model: bytes | None = None) -> DataFrame:
    """(term, n, shard, before, gaps) back from segments. The model of the static coder stands in the first segment."""
    shared = segments.sparkSession.sparkContext.broadcast(model_of(segments) if model is None else model)

    def run(batches):
        for b in batches:
            whole = ("terms", "ns", "shards", "before")
            for j, r in enumerate(b.drop_columns(whole).to_pylist()):
                gaps, n = decoded(r, shared.value)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n)]).astype(np.int32)), pa.array(gaps))
                yield pa.RecordBatch.from_arrays([*(b.column(c)[j].values for c in whole), lists], names=["term", "n", "shard", "before", "gaps"])

    return segments.select("method", "n_lists", "header", "lengths", "payload", "terms", "ns", "shards", "before").mapInArrow(run, "term string, n bigint, shard bigint, before bigint, gaps array<bigint>")


def static_bits(lists: Lists, bits: int = 8) -> tuple[int, int]:
    """(model, payload rounded up) of the static coder with the parameters that the rule chooses. Its model is one for all
    segments, so the counts alone give the payload, and no segment is made."""
    n, q = static_model(lists.gaps, trits.hybrid(*trits.choose_static(lists.i, most=MAX_CONTEXTS)), bits)
    return 8 * len(pack_model(q, bits)) if lists.i else 0, int(np.ceil(trits.ideal_bits(n, q)))


def sizes(segments: DataFrame) -> DataFrame:
    """(method, part, bits) of segments: lengths, model, payload as coded, and what of it is rounding (padding)."""
    own = segments.groupBy("method").agg(F.sum("lengths_bits").alias("lengths"), F.coalesce(F.sum(8 * F.length("model")), F.lit(0)).cast("long").alias("model"), F.sum(8 * F.length("payload")).cast("long").alias("payload"), F.sum(8 * F.length("header")).cast("long").alias("header"), F.ceil(F.sum("ideal_bits")).alias("ideal"), F.sum("n_ints").alias("ints"))
    parts = F.explode(F.create_map(*(x for p in ("lengths", "model", "payload", "header", "ideal") for x in (F.lit(p), F.col(p))))).alias("part", "bits")
    return own.select("method", "ints", parts)


def roundtrip_mismatches(lists: DataFrame, decoded: DataFrame) -> DataFrame:
    """One row: how many list shards differ after coding and decoding, either way."""
    a, b = (d.select("term", "shard", "n", "before", F.xxhash64("gaps").alias("h")) for d in (lists, decoded))
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count(F.lit(1)).alias("mismatches"))


def sweep_static(lists: Lists, contexts: dict[str, Context], bits: int | str = 8) -> DataFrame:
    """(model, contexts, model_bits, payload_bits) for each context model, from one count pass; 'exact' counts are stored
    at the least width that holds them and predict exactly."""
    rows = priced(collected(context_counts(lists.gaps, contexts), contexts), contexts, bits)
    return lists.gaps.sparkSession.createDataFrame(rows, "model string, contexts bigint, model_bits bigint, payload_bits double")


def priced(counts: dict[str, np.ndarray], contexts: dict[str, Context], bits: int | str) -> list[tuple[str, int, int, float]]:
    """(model, contexts, model_bits, payload_bits) of counted models at one width of the stored fractions."""
    rows = []
    for name, c in contexts.items():
        n = counts[name]
        n = n[n.any(1)]  # a context that never occurs costs its place in the model only
        if bits == "exact":
            rows.append((name, c.size, c.kinds * max(1, int(n.max(initial=0)).bit_length()) * c.size, float(trits.ideal_bits(n))))
        else:
            rows.append((name, c.size, c.model_bits(bits), float(trits.ideal_bits(n, trits.quantise(n, bits)))))
    return rows


def sweep_adaptive(lists: Lists, contexts: dict[str, tuple[Context, int | None]], order: str = "length", target: int = SEGMENT_TRITS, halving: str = "context", prior=None) -> DataFrame:
    """(model, payload_bits) for each (context, forget); a task takes a segment and a share of the settings."""
    names = list(contexts)
    groups = min(SWEEP_GROUPS, len(names))
    rows = segmented(lists.gaps, order, target).select("seg", "__k", "term", "shard", "gaps")
    rows = rows.withColumn("c", F.explode(F.lit(list(range(groups)))))

    def code(t: pa.Table) -> pa.Table:
        t = t.sort_by([("__k", "ascending"), ("term", "ascending"), ("shard", "ascending")])
        own = names[t.column("c")[0].as_py() :: groups]
        gaps, sizes = _arrays(t)
        out, cache = [], {}
        for name in own:
            c, forget = contexts[name]
            if c.kinds not in cache:
                cache[c.kinds] = symbols(gaps, sizes, c.kinds)
            s, pos = cache[c.kinds]
            out.append(trits.adaptive_bits(c.ids(s, pos), s, c.size, c.kinds, forget, halving, prior))
        return pa.table({"model": pa.array(own), "bits": pa.array(out, pa.float64())})

    return rows.groupBy("seg", "c").applyInArrow(code, "model string, bits double").groupBy("model").agg(F.sum("bits").alias("payload_bits"))
