"""Token counts by byte-pair merging with a heap over a linked list of symbols; identifiers are never emitted."""

from __future__ import annotations

import heapq
import json

import public_tokenizers
import regex
from pyspark.sql import DataFrame
from pyspark.sql.types import BooleanType, StructField

from .common import long_field, scan_texts
from .pieces import splitter

#: Pieces remembered by a worker, and the longest piece that is (bounds: about 150 MB).
CACHE_PIECES, CACHE_CHARS = 400_000, 64
#: How byte-level vocabularies write bytes: printable ones as themselves, the others from U+0100 on, in order.
PRINTABLE = [*range(33, 127), *range(161, 173), *range(174, 256)]


def byte_letters() -> dict[str, int]:
    rest = [b for b in range(256) if b not in set(PRINTABLE)]
    return {chr(b): b for b in PRINTABLE} | {chr(256 + i): b for i, b in enumerate(rest)}


class MergeCounter(dict):
    """piece -> number of tokens; a dict that fills itself and forgets everything once it is full."""

    def __init__(self, path: str):
        super().__init__()
        spec = json.load(open(path, encoding="utf-8"))
        model, pre = spec["model"], spec["pre_tokenizer"]
        plain = model["type"] == "BPE" and not any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "end_of_word_suffix", "ignore_merges", "byte_fallback"))
        if not plain or spec["normalizer"] or pre["type"] != "ByteLevel" or pre["add_prefix_space"] or not pre["use_regex"]:
            raise ValueError("only a plain byte-level BPE file can be counted")
        if any(t["lstrip"] or t["rstrip"] or t["single_word"] or t["normalized"] for t in spec["added_tokens"]):
            raise ValueError("added tokens with special matching are not handled")
        letters = byte_letters()
        ids = {bytes(letters[c] for c in w): i for w, i in model["vocab"].items()}
        self.first = [ids.get(bytes([b])) for b in range(256)]
        if None in self.first:
            raise ValueError("a byte has no symbol of its own")
        self.merge: dict[int, tuple[int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            a, b = (bytes(letters[c] for c in x) for x in (a, b))
            self.merge.setdefault(ids[a] << 32 | ids[b], (rank, ids[a + b]))
        self.pieces = splitter(public_tokenizers.PATTERN)
        added = sorted((t["content"] for t in spec["added_tokens"]), key=len, reverse=True)
        self.added = regex.compile("|".join(map(regex.escape, added))) if added else None

    def __missing__(self, piece: str) -> int:
        n = self.count_piece(piece.encode("utf-8", "surrogatepass"))
        if len(piece) <= CACHE_CHARS:
            if len(self) >= CACHE_PIECES:
                self.clear()
            self[piece] = n
        return n

    def count_piece(self, raw: bytes) -> int:
        """Initial symbols less merges."""
        sym = [self.first[b] for b in raw]
        n = left = len(sym)
        if n < 2:
            return n
        merge = self.merge
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(m[0], i, m[1], sym[i], sym[i + 1]) for i in range(n - 1) if (m := merge.get(sym[i] << 32 | sym[i + 1]))]
        heapq.heapify(heap)
        while heap:
            _, i, made, a, b = heapq.heappop(heap)
            j = after[i]
            if sym[i] != a or j >= n or sym[j] != b:
                continue  # one of the two is no longer what it was
            sym[i], sym[j] = made, -1
            left -= 1
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                if m := merge.get(made << 32 | sym[k]):
                    heapq.heappush(heap, (m[0], i, m[1], made, sym[k]))
            if (h := before[i]) >= 0 and (m := merge.get(sym[h] << 32 | made)):
                heapq.heappush(heap, (m[0], h, m[1], sym[h], made))
        return left

    def count(self, text: str) -> int:
        get, pieces = self.__getitem__, self.pieces
        if self.added is None or not self.added.search(text):
            return sum(map(get, pieces(text)))
        parts = self.added.split(text)
        return len(parts) - 1 + sum(sum(map(get, pieces(p))) for p in parts)


_counters: dict[str, MergeCounter] = {}


def counter(path: str) -> MergeCounter:
    if path not in _counters:
        _counters[path] = MergeCounter(path)
    return _counters[path]


def count_tokens(df: DataFrame, tokenizer: str, limit: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, n_tokens, over_limit) of every row, whole texts, as the file's own library counts them.

    ``tokenizer`` is the path of a byte-level BPE .json file, found at the same place on all machines. Strings of added
    tokens inside a text count as one token each. Null text counts as empty: 0 bytes, 0 tokens. Repeated rows give
    repeated results; an empty table gives an empty one.
    """

    def rows(texts):
        c = counter(tokenizer)
        n = [c.count(t) if t else 0 for t in texts]
        return [[len(t.encode()) if t else 0 for t in texts], n, [k > limit for k in n]]

    return scan_texts(df, rows, [long_field("n_bytes"), long_field("n_tokens"), StructField("over_limit", BooleanType())], id_col, text_col)
