"""Letters, numbers and white space as the public tokenizer library classes them.

The library, the ``regex`` module and ``unicodedata`` each follow a Unicode
version of their own, so a code point may be a letter to one and unassigned to
another.  The library is asked once, for all code points, and the answer is kept
as ranges; texts without any code point on which the ``regex`` module differs
use its built-in classes, the others explicit sets.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from dataclasses import dataclass
from functools import cached_property, lru_cache

import regex

TOP, BLOCK = 0x110000, 0x800
GAP = 0xD800, 0xE000  # surrogates are no characters
LETTER, NUMBER, SPACE, OTHER = range(4)
#: The classes that the tokenizer files' patterns name, for the library and for the ``regex`` module.
ASKED = {LETTER: (r"\p{L}", r"\p{L}"), NUMBER: (r"\p{N}", r"\p{N}"), SPACE: (r"\s", r"\p{White_Space}")}


def _set(ranges) -> str:
    """Ranges as the inside of a character set."""
    return "".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in ranges)


def _ranges(flags) -> tuple[tuple[int, int], ...]:
    import numpy as np

    edges = np.flatnonzero(np.diff(np.concatenate([[False], flags, [False]]).astype(np.int8)))
    return tuple((int(a), int(b) - 1) for a, b in edges.reshape(-1, 2))


@dataclass(frozen=True)
class CharClasses:
    """Ascending inclusive ranges of code points, and those that the ``regex`` module classes otherwise."""

    letters: tuple[tuple[int, int], ...]
    numbers: tuple[tuple[int, int], ...]
    spaces: tuple[tuple[int, int], ...]
    unlike: tuple[tuple[int, int], ...]

    @cached_property
    def names(self) -> dict[str, str]:
        """Explicit sets by the placeholder that patterns use for them."""
        return {"{L}": _set(self.letters), "{N}": _set(self.numbers), "{S}": _set(self.spaces)}

    def compile(self, pattern: str, exact: bool):
        """A pattern with ``{L}``, ``{N}`` and ``{S}`` inside character sets, by explicit sets or by the ``regex`` module's classes."""
        names = self.names if exact else {"{L}": r"\p{L}", "{N}": r"\p{N}", "{S}": r"\p{White_Space}"}
        for name, inside in names.items():
            pattern = pattern.replace(name, inside)
        return regex.compile(pattern)

    @cached_property
    def strange(self):
        """Finds a code point on which the ``regex`` module differs; None where there is none at all."""
        return re.compile(f"[{_set(self.unlike)}]") if self.unlike else None

    def needs_exact(self, text: str) -> bool:
        return self.strange is not None and not text.isascii() and self.strange.search(text) is not None

    def of(self, ch: str) -> int:
        c = ord(ch)
        for kind, ranges in ((LETTER, self.letters), (NUMBER, self.numbers), (SPACE, self.spaces)):
            i = bisect_right(ranges, (c, TOP)) - 1
            if i >= 0 and c <= ranges[i][1]:
                return kind
        return OTHER


@lru_cache(maxsize=1)
def library_classes() -> CharClasses:
    """Ask the library (about two seconds, once a driver); the answer is small and travels with the task."""
    import numpy as np
    from tokenizers import Regex, pre_tokenizers

    theirs, ours = (np.zeros((len(ASKED), TOP), bool) for _ in range(2))
    for low in range(0, TOP, BLOCK):
        if not GAP[0] <= low < GAP[1]:
            chars = "".join(map(chr, range(low, low + BLOCK)))
            for kind, (asked, own) in ASKED.items():
                for _, (a, b) in pre_tokenizers.Split(Regex(f"{asked}+"), "removed", invert=True).pre_tokenize_str(chars):
                    theirs[kind, low + a : low + b] = True
                for m in regex.finditer(f"{own}+", chars):
                    ours[kind, low + m.start() : low + m.end()] = True
    found, differ = [_ranges(x) for x in theirs], (theirs != ours).any(axis=0)
    return CharClasses(found[LETTER], found[NUMBER], found[SPACE], _ranges(differ))
