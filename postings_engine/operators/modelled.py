"""Coders whose model is counted over the whole collection first: packed classes, and contexts on bits.

Both code a batch of list shards into one arithmetic stream (its end costs a byte or two once, not for each list). The
model is a bounded table of counts, broadcast to the coder and to the decoder.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import baselines, trits
from .arith import Decoder, Encoder
from .coders import _arrays
from .postings import Lists

ROWS = "terms array<string>, ns array<bigint>, shards array<bigint>, before array<bigint>, sizes array<bigint>, payload binary, ideal_bits double"
BACK = "term string, n bigint, shard bigint, before bigint, gaps array<bigint>"
#: Gaps from here on are coded as a class and raw bits, so that an alphabet is never larger.
WIDE = 1 << 16


class Shares:
    """Counts by symbol as an arithmetic coder needs them."""

    def __init__(self, counts: dict[int, int]):
        self.symbols = sorted(counts)
        self.at = {s: i for i, s in enumerate(self.symbols)}
        self.edge = np.concatenate([[0], np.cumsum([counts[s] for s in self.symbols])]).tolist()
        self.total = self.edge[-1]

    def put(self, e: Encoder, s: int) -> None:
        i = self.at[s]
        e.put(self.edge[i], self.edge[i + 1] - self.edge[i], self.total)

    def get(self, d: Decoder) -> int:
        i = int(np.searchsorted(self.edge, d.get(self.total), "right")) - 1
        d.drop(self.edge[i], self.edge[i + 1] - self.edge[i])
        return self.symbols[i]

    def bits(self, s: int) -> float:
        i = self.at[s]
        return float(np.log2(self.total) - np.log2(self.edge[i + 1] - self.edge[i]))


def scaled(counts: dict[int, int], most: int = 1 << 24) -> Shares:
    """Counts, at least 1, whose total a coder can take."""
    total = sum(counts.values())
    return Shares(counts if total <= most else {s: max(1, n * most // total) for s, n in counts.items()})


def packed_model(lists: Lists, mantissa: str = "modelled", **how) -> tuple[Shares, dict[int, Shares]]:
    """(of selectors, of each selector's symbols); at most 136 selectors of at most WIDE symbols and a few classes."""
    own: dict[int, dict[int, int]] = {}
    for r in baselines.packed_classes(lists, mantissa=mantissa, **how).collect():
        own.setdefault(r.selector, {})[r.symbol] = r.n
    return scaled({k: v[-1] for k, v in own.items()} or {0: 1}), {k: scaled({s: n for s, n in v.items() if s >= 0}) for k, v in own.items()}


def _row(b: pa.RecordBatch, sizes: np.ndarray, payload: bytes, ideal: float) -> pa.RecordBatch:
    one = lambda x, kind: pa.array([x], pa.list_(kind))
    names = ["terms", "ns", "shards", "before", "sizes", "payload", "ideal_bits"]
    return pa.RecordBatch.from_arrays([one(b.column(0).to_pylist(), pa.string()), *(one(b.column(i).to_pylist(), pa.int64()) for i in (1, 2, 3)), one(sizes.tolist(), pa.int64()), pa.array([payload], pa.binary()), pa.array([ideal])], names=names)


def _lists(r: dict, lists: list[list[int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(r["terms"], pa.string()), *(pa.array(r[k], pa.int64()) for k in ("ns", "shards", "before")), pa.array(lists, pa.list_(pa.int64()))], names=["term", "n", "shard", "before", "gaps"])


def packed_encode(lists: Lists, model: tuple[Shares, dict[int, Shares]], mantissa: str = "modelled", selector: str = "arith", block: int = 128, classes: int = 16) -> DataFrame:
    """Streams of ``lists``; ``selector`` 'raw6' sends six raw bits for each block (at most 64 selectors in use)."""
    shared = lists.gaps.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        sel, sym = shared.value
        for b in batches:
            gaps, sizes = _arrays(pa.Table.from_batches([b]))
            if not len(gaps):
                continue
            width, s, raw = baselines.packed_symbols(gaps, mantissa)
            e, ideal, at = Encoder(), 0.0, 0
            for n in sizes.tolist():
                for i in range(at, at + n, block):
                    j = min(i + block, at + n)
                    k = baselines.selector_of(width[i:j], classes)
                    if selector == "raw6":
                        e.put(sel.at[k], 1, 64)
                        ideal += 6
                    else:
                        sel.put(e, k)
                        ideal += sel.bits(k)
                    own = sym[k]
                    for g, x, r in zip(gaps[i:j].tolist(), s[i:j].tolist(), raw[i:j].tolist(), strict=True):
                        own.put(e, x)
                        ideal += own.bits(x) + r
                        for lo in range(0, r, 16):
                            m = min(16, r - lo)
                            e.put(g >> lo & (1 << m) - 1, 1, 1 << m)
                at += n
            yield _row(b, sizes, e.finish(), ideal)

    return lists.gaps.select("term", "n", "shard", "before", "gaps").mapInArrow(run, ROWS)


def packed_decode(coded: DataFrame, model: tuple[Shares, dict[int, Shares]], mantissa: str = "modelled", selector: str = "arith", block: int = 128) -> DataFrame:
    shared = coded.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        sel, sym = shared.value
        for b in batches:
            for r in b.to_pylist():
                d, out = Decoder(r["payload"]), []
                for n in r["sizes"]:
                    gaps: list[int] = []
                    while len(gaps) < n:
                        if selector == "raw6":
                            k = d.get(64)
                            d.drop(k, 1)
                            k = sel.symbols[k]
                        else:
                            k = sel.get(d)
                        own = sym[k]
                        for _ in range(min(block, n - len(gaps))):
                            x = own.get(d)
                            if mantissa == "modelled" and x < WIDE:
                                gaps.append(x)
                                continue
                            w = x - (WIDE if mantissa == "modelled" else 0)
                            g = 1 << w - 1
                            for lo in range(0, w - 1, 16):
                                m = min(16, w - 1 - lo)
                                v = d.get(1 << m)
                                d.drop(v, 1)
                                g |= v << lo
                            gaps.append(g)
                    out.append(gaps)
                yield _lists(r, out)

    return coded.mapInArrow(run, BACK)


def bitmap_model(lists: Lists, k: int = 2, w: int = 0) -> np.ndarray:
    """Counts (context, bit) of the matrix, each at least 1 where the other bit occurs."""
    n = np.zeros((2**k * (w + 1), 2), np.int64)
    for r in baselines.bitmap_counts(lists, k, w).collect():
        n[r.ctx] = r.zeros, r.ones
    return trits.quantise(n, 16)


def bitmap_encode(lists: Lists, q: np.ndarray, k: int = 2, w: int = 0) -> DataFrame:
    """Streams of the matrix's bits, every zero coded: W x D steps, for small tables. Lists of one shard."""
    shared, d = lists.gaps.sparkSession.sparkContext.broadcast(q), lists.d

    def run(batches):
        m = (1 << 16) - 1
        for b in batches:
            gaps, sizes = _arrays(pa.Table.from_batches([b]))
            if not len(gaps):
                continue
            if (b.column(1).to_numpy() != sizes).any():
                raise ValueError("a list in several shards: only sizes are counted for those")
            e, ideal = Encoder(), 0.0
            for ids in np.split(gaps, np.cumsum(sizes)[:-1]):
                bits = np.zeros(d, np.int64)
                bits[np.cumsum(ids) - 1] = 1
                ctx = bit_contexts(bits, k, w)
                zero = shared.value[ctx, 0]
                share = np.where(bits == 1, m - zero, zero)
                ideal += float((np.log2(m) - np.log2(share)).sum())
                for bit, z, f in zip(bits.tolist(), zero.tolist(), share.tolist(), strict=True):
                    if f < m:
                        e.put(z if bit else 0, f, m)
            yield _row(b, sizes, e.finish(), ideal)

    return lists.gaps.select("term", "n", "shard", "before", "gaps").mapInArrow(run, ROWS)


def bit_contexts(bits: np.ndarray, k: int, w: int) -> np.ndarray:
    total = np.concatenate([np.zeros(k + w + 1, np.int64), np.cumsum(bits)])
    code = np.zeros(len(bits), np.int64)
    for j in range(k, 0, -1):
        code *= 2
        code[j:] += bits[: max(len(bits) - j, 0)]
    i = np.arange(len(bits)) + k + w
    return code + 2**k * (total[i - k] - total[i - k - w])


def bitmap_decode(coded: DataFrame, q: np.ndarray, d: int, k: int = 2, w: int = 0) -> DataFrame:
    shared = coded.sparkSession.sparkContext.broadcast(q)

    def run(batches):
        zero, m = shared.value[:, 0].tolist(), (1 << 16) - 1
        for b in batches:
            for r in b.to_pylist():
                dec, out = Decoder(r["payload"]), []
                for _ in r["sizes"]:
                    past, gaps, last = 0, [], -1
                    for i in range(d):
                        z = zero[(past & (1 << k) - 1) + 2**k * (past >> k & (1 << w) - 1).bit_count()]
                        bit = int(z == 0) if z in (0, m) else int(dec.get(m) >= z)
                        if 0 < z < m:
                            dec.drop(z if bit else 0, m - z if bit else z)
                        past = past << 1 | bit
                        past &= (1 << k + w) - 1
                        if bit:
                            gaps.append(i - last)
                            last = i
                    out.append(gaps)
                yield _lists(r, out)

    return coded.mapInArrow(run, BACK)
