"""Byte-level BPE encoding and decoding by merge replay over a block's distinct pieces.

All new pieces of a block stand in one array of symbols. An inverted index leads from the rank of an adjacent pair to
its positions in all words; ranks are taken in ascending order from a heap, each applied to all its positions at once,
and only the neighbours of what was merged are looked at again. Pieces are independent of each other, so a block's
replay gives each piece what a replay over the whole corpus would.
"""

from __future__ import annotations

import base64
import hashlib
import heapq

import public_tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, IntegerType, StringType, StructField

from .common import long_field, scan_texts
from .pieces import splitter

#: Pieces remembered by a worker, and the longest piece that is (bounds: about 230 MB); pieces replayed at once.
CACHE_PIECES, CACHE_CHARS, REPLAY_PIECES = 800_000, 64, 20_000
#: Pairs of symbols remembered by a worker.
CACHE_PAIRS = 400_000


class MergeReplay:
    def __init__(self, path: str, pattern: str = public_tokenizers.PATTERN):
        with open(path, "rb") as f:
            self.rank = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.token = {i: b for b, i in self.rank.items()}
        self.first = [self.rank[bytes([b])] for b in range(256)]
        self.pair: dict[int, int] = {}  # pair of symbols -> the symbol it makes, or -1
        self.pieces = splitter(pattern)
        self.ids: dict[str, str] = {}
        self.bytes: dict[str, bytes] = {}
        self.long: list[str] = []

    def makes(self, a: int, b: int) -> int:
        """The symbol of a pair, or -1."""
        made = self.rank.get(self.token[a] + self.token[b], -1)
        if len(self.pair) >= CACHE_PAIRS:
            self.pair.clear()
        self.pair[a << 32 | b] = made
        return made

    def replay(self, words: list[bytes]) -> list[list[int]]:
        """The ids of each word."""
        first, makes, pair = self.first, self.makes, self.pair.get
        sym, starts = [], []
        for raw in words:
            starts.append(len(sym))
            whole = self.rank.get(raw)  # a word of the vocabulary is its own id
            sym += [first[b] for b in raw] if whole is None else [whole]
            sym.append(-1)  # the words' border
        n = len(sym)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        index: dict[int, list[int]] = {}
        for i, (a, b) in enumerate(zip(sym, sym[1:], strict=False)):
            if a >= 0 and b >= 0:
                r = pair(a << 32 | b)
                if r is None:
                    r = makes(a, b)
                if r >= 0:
                    if r in index:
                        index[r].append(i)
                    else:
                        index[r] = [i]
        heap = list(index)
        heapq.heapify(heap)
        while heap:
            r = heapq.heappop(heap)
            places = index.pop(r, None)
            if places is None:
                continue
            places.sort()
            wait = -1  # up to this border the rank lets a lower one, that a merge has just made, pass
            later = []
            for i in places:
                a = sym[i]
                if a < 0:
                    continue
                j = after[i]
                b = sym[j]
                if b < 0:
                    continue
                q = pair(a << 32 | b)
                if (makes(a, b) if q is None else q) != r:
                    continue
                if i < wait:
                    later.append(i)
                    continue
                sym[i], sym[j] = r, -2
                k = after[i] = after[j]
                before[k] = i
                b = sym[k]
                if b >= 0:
                    q = pair(r << 32 | b)
                    if q is None:
                        q = makes(r, b)
                    if q >= 0:
                        if q in index:
                            index[q].append(i)
                        elif q == r:
                            later.append(i)
                        else:
                            index[q] = [i]
                            heapq.heappush(heap, q)
                        if q < r:
                            wait = sym.index(-1, i)
                h = before[i]
                if h >= 0 and (a := sym[h]) >= 0:
                    q = pair(a << 32 | r)
                    if q is None:
                        q = makes(a, r)
                    if q >= 0:
                        if q in index:
                            index[q].append(h)
                        elif q == r:
                            later.append(h)
                        else:
                            index[q] = [h]
                            heapq.heappush(heap, q)
                        if q < r:
                            wait = sym.index(-1, i)
            if later:
                index.setdefault(r, []).extend(later)
                heapq.heappush(heap, r)
        out = []
        for i in starts:
            ids = []
            while (x := sym[i]) >= 0:
                ids.append(x)
                i = after[i]
            out.append(ids)
        return out

    def block(self, texts: list[str]) -> tuple[list[list[str]], dict[str, str], dict[str, bytes]]:
        """(pieces of each text, piece -> ids in decimal, piece -> bytes that the ids stand for)."""
        split = [self.pieces(t) if t else [] for t in texts]
        own = set().union(*split)
        for p in self.long:  # of the block before
            del self.ids[p], self.bytes[p]
        if len(self.ids) > CACHE_PIECES:  # what this block needs stays
            self.ids = {p: v for p, v in self.ids.items() if p in own}
            self.bytes = {p: self.bytes[p] for p in self.ids}
        ids, raw, token = self.ids, self.bytes, self.token
        new = list(own - ids.keys())
        for at in range(0, len(new), REPLAY_PIECES):
            part = new[at : at + REPLAY_PIECES]
            for p, found in zip(part, self.replay([p.encode("utf-8") for p in part]), strict=True):
                ids[p] = " ".join(map(str, found))
                raw[p] = b"".join([token[i] for i in found])
        self.long = [p for p in new if len(p) > CACHE_CHARS]
        return split, ids, raw

    def encode(self, text: str) -> list[int]:
        split, ids, _ = self.block([text])
        return [int(i) for p in split[0] for i in ids[p].split()]

    def decode(self, ids) -> bytes:
        token = self.token
        return b"".join([token[i] for i in ids])


_replays: dict[str, MergeReplay] = {}


def replayer(path: str) -> MergeReplay:
    if path not in _replays:
        _replays[path] = MergeReplay(path)
    return _replays[path]


def encode(df: DataFrame, ranks: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids ARRAY<INT>) of every row; null text gives no ids, as the empty one does."""

    def rows(texts):
        split, ids, _ = replayer(ranks).block(texts)
        return [[[int(i) for p in pieces for i in ids[p].split()] for pieces in split]]

    return scan_texts(df, rows, [StructField("ids", ArrayType(IntegerType()))], id_col, text_col)


def decode(df: DataFrame, ranks: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, bytes BINARY) of every row of ids; null ids give no bytes. An id outside the vocabulary raises."""
    data = df.select(F.col(id_col), F.concat_ws(" ", F.col(ids_col).cast("array<string>")).alias("x"))

    def rows(lines):
        r = replayer(ranks)
        return [[r.decode(map(int, (x or "").split())) for x in lines]]

    return scan_texts(data, rows, [StructField("bytes", BinaryType())], id_col, "x")


def roundtrip_digest(df: DataFrame, ranks: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_tokens, ids_sha256, decoded_sha256) of every row, encoded and decoded again in one pass.

    Null text counts as empty (0 ids, the hash of nothing). Repeated rows give repeated results.
    """

    def rows(texts):
        split, ids, raw = replayer(ranks).block(texts)
        n, a, b = [], [], []
        for pieces in split:
            line = " ".join(map(ids.__getitem__, pieces))
            n.append(line.count(" ") + 1 if line else 0)
            a.append(hashlib.sha256(line.encode()).hexdigest())
            b.append(hashlib.sha256(b"".join(map(raw.__getitem__, pieces))).hexdigest())
        return [n, a, b]

    return scan_texts(df, rows, [long_field("n_tokens"), StructField("ids_sha256", StringType()), StructField("decoded_sha256", StringType())], id_col, text_col)
