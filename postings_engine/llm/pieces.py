"""Splitting texts into the pieces that byte-pair merging works on."""

from __future__ import annotations

import re
from collections.abc import Callable

import regex

# Letters and numbers that the regex module knows and that the tokenizer libraries, whose Unicode tables
# are older, still take for neither (found by probing both libraries with every code point).
NEWER = (
    "՘֋֌࢏౜೜₏₝-₟꟎꟏꟒꟔꟝꟢꟱꭬꭭"
    "\U000107bb-\U000107bf\U00010940-\U00010959\U00010ec5-\U00010ec7\U00010ed9-\U00010eee\U00011b0a\U00011db0-\U00011ddb"
    "\U00011de0-\U00011de9\U00011df1\U0001246f\U00012475-\U0001247f\U00012550-\U00012686\U00016ea0-\U00016eb8"
    "\U00016ebb-\U00016ed3\U00016ff2-\U00016ff6\U000187f8-\U000187ff\U00018cd6-\U00018cda\U00018d09-\U00018d20"
    "\U00018d80-\U00018df2\U00018e00-\U00019191\U000191a0-\U000191d2\U0001b123-\U0001b128\U0001b168\U0001d6a6"
    "\U0001df1f-\U0001df24\U0001df2b-\U0001df81\U0001df90-\U0001df96\U0001dfcd-\U0001dfff\U0001e6c0-\U0001e6de"
    "\U0001e6e0-\U0001e6e2\U0001e6e4\U0001e6e5\U0001e6e7-\U0001e6ed\U0001e6f0-\U0001e6f4\U0001e6fe\U0001e6ff"
    "\U0002b73a-\U0002b73f\U0002b81e\U0002cea2-\U0002cead\U000323b0-\U00033479\U0003d000-\U0003fc3f"
)
_newer = re.compile(f"[{NEWER}]")
#: An unassigned character, neither letter nor number anywhere, that stands in for one of these while a text is split.
STAND_IN = "͸"


def splitter(pattern: str) -> Callable[[str], list[str]]:
    """text -> its pieces, as the tokenizer libraries split it by this pattern."""
    find = regex.compile(pattern).findall

    def pieces(text: str) -> list[str]:
        if text.isascii() or not _newer.search(text):
            return find(text)
        out, at = [], 0
        for p in find(_newer.sub(STAND_IN, text)):  # every character of a text lies in some piece
            out.append(text[at : at + len(p)])
            at += len(p)
        return out

    return pieces
