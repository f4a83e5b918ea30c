"""Byte-pair merge tables read from a public tokenizer file, and the pair-compatibility test.

Tokens are kept as strings over a one-character-per-byte alphabet; where the
model marks word ends, the mark is one extra character ``END`` behind the last byte.

Two adjacent tokens are *compatible* when merging their joint text gives back
exactly these two tokens.  While the two sides evolve on their own, only the
pieces on the right edge of the left token and on the left edge of the right
one ever touch.  A piece lives until the merge that absorbs it, so the pair is
incompatible iff some touching pair of pieces has a merge rule of a rank that
comes before either piece is absorbed (an equal rank on the right means the
same rule further right, which is applied later).
"""

from __future__ import annotations

import json
from functools import lru_cache

END = "\x00"
FOREVER = 1 << 60


def byte_alphabet() -> list[str]:
    """The public printable stand-in for each byte value: printable Latin-1 stands for itself, the rest follow from 256 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    table, extra = [], 256
    for b in range(256):
        table.append(chr(b) if b in plain else chr(extra))
        extra += b not in plain
    return table


class MergeModel:
    """Vocabulary, ranked merges and a memoised compatibility test."""

    MEMO = 1 << 19

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        suffix = model.get("end_of_word_suffix") or ""
        mark = (lambda s: s[: -len(suffix)] + END if suffix and s.endswith(suffix) else s)
        self.word_end = bool(suffix)
        self.shown = {i: s for s, i in model["vocab"].items()}  # as the file spells it
        self.id_of = {mark(s): i for s, i in model["vocab"].items()}
        self.text_of = {i: s for s, i in self.id_of.items()}
        self.specials = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        for s, i in self.specials.items():
            self.shown.setdefault(i, s)
            self.id_of.pop(s, None)
            self.text_of.pop(i, None)
        self.rank: dict[tuple[int, int], int] = {}
        self.parts: dict[int, tuple[int, int, int]] = {}  # token -> left, right, rank
        for r, pair in enumerate(model["merges"]):
            a, b = (mark(x) for x in (pair.split(" ") if isinstance(pair, str) else pair))
            left, right, whole = self.id_of[a], self.id_of[b], self.id_of[a + b]
            self.rank.setdefault((left, right), r)
            self.parts.setdefault(whole, (left, right, r))
        self.units = [byte_alphabet()[b] for b in range(256)]
        self._memo: dict[int, bool] = {}
        self.tested = self._memo.get  # by ``a << 20 | b``: what ``compatible`` has found, or None

    def spell(self, word: str) -> str:
        """A word in the model's alphabet, with the end mark where the model has one."""
        u = self.units
        s = word if word.isascii() and word.isprintable() and " " not in word else "".join([u[b] for b in word.encode("utf-8", "replace")])
        return s + END if self.word_end else s

    def edge(self, token: int, side: int) -> list[tuple[int, int]]:
        """Pieces on one edge of a token (0: left, 1: right) with the rank of the merge that absorbs each."""
        out, death = [], FOREVER
        while True:
            out.append((token, death))
            if token not in self.parts:
                return out
            death, token = self.parts[token][2], self.parts[token][side]

    def compatible(self, a: int, b: int) -> bool:
        key = a << 20 | b
        known = self._memo.get(key)
        if known is None:
            if len(self._memo) >= self.MEMO:
                self._memo.clear()
            rank, known = self.rank, True
            right = self.edge(b, 0)
            for x, x_death in self.edge(a, 1):
                for y, y_death in right:
                    m = rank.get((x, y))
                    if m is not None and m < x_death and m <= y_death:
                        known = False
            self._memo[key] = known
        return known


@lru_cache(maxsize=1)
def load(path: str) -> MergeModel:
    return MergeModel(path)
