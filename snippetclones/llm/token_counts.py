"""Operator 6 - token counts by a compiled finite-state tokenizer.

The byte-level tokenizer is compiled, lazily, into a deterministic transducer.
A state holds where the pre-tokenizer stands (a handful of modes), a pending
character where the next one decides (white space, an apostrophe that may open
a contraction), and a merge state: the longest suffix read so far that begins
a token, with the last token and the relative token count of each prefix that
a coming token may still attach to.  Every transition carries the number of
tokens it adds (it may be negative when a longer token replaces two).

Every text is cut into chunks (a short one is one chunk).  A chunk's *state map*
takes the state in which the chunk is entered to the state at its end and the
tokens added: the chunk is parsed once from a fresh start, and an actual entry is
stepped only as far as the two parses differ.  Maps compose associatively, so
totals come from a prefix scan (recursive doubling) over a text's chunks.  Time is
linear in the text, also where one class of characters never ends; the number of
compiled states is bounded within a text as well.

Edge cases: null text counts as empty; an empty text has 0 tokens; an empty table
gives no rows; repeated rows are counted independently; clashing columns are
replaced by the outputs.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import bpe_model
from .char_classes import CharClasses, library_classes
from .common import TwoGenerations, fresh_name, held, in_order, named

#: The public byte-level pre-tokenizer pattern.
PRETOKENS = r"'s|'t|'re|'ve|'m|'ll|'d| ?[{L}]+| ?[{N}]+| ?[^{S}{L}{N}]+|[{S}]+(?![^{S}])|[{S}]+"
ASCII_PRETOKENS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[a-zA-Z]+| ?[0-9]+| ?[^ \t-\ra-zA-Z0-9]+|[ \t-\r]+(?![^ \t-\r])|[ \t-\r]+")
CHUNK = 1 << 15
MEMO = 250_000
STATES = 300_000
SLICE = 4096  # bytes between two looks at the number of merge states
(START, LETTERS, NUMBERS, OTHERS, BLANK, SPACE, QUOTE, QUOTE_R, QUOTE_V, QUOTE_L) = range(10)
FRESH = (START, 0, "")


class MergeStates:
    """Merge states as small integers with lazily compiled byte transitions ``(state, byte) -> (state, tokens added)``."""

    def __init__(self, model: bpe_model.MergeModel):
        self.model, self.tokens = model, model.id_of
        self.begins = {t[:k] for t in model.id_of for k in range(1, len(t) + 1)}
        self.reset()

    def reset(self) -> None:
        self.index = {("", (-1,), (0,)): 0}
        self.states = [("", (-1,), (0,))]
        self.moves: dict[int, tuple[int, int]] = {}

    def number(self, key: tuple) -> int:
        at = self.index.get(key)
        if at is None:
            at = self.index[key] = len(self.states)
            self.states.append(key)
        return at

    def renew(self, state: int) -> int:
        """Forget all states but this one."""
        key = self.states[state]
        self.reset()
        return self.number(key)

    def step(self, state: int, byte: int) -> tuple[int, int]:
        key = state << 8 | byte
        found = self.moves.get(key)
        if found is None:
            found = self.moves[key] = self._compile(state, byte)
        return found

    def _compile(self, state: int, byte: int) -> tuple[int, int]:
        node, lasts, counts = self.states[state]
        node += self.model.units[byte]
        while node not in self.begins:
            node = node[1:]
        for k in range(min(len(node), len(lasts)), 0, -1):
            token = self.tokens.get(node[-k:])
            if token is not None and (lasts[-k] < 0 or self.model.compatible(lasts[-k], token)):
                break
        added = counts[-k] + 1
        keep = len(node) + 1
        key = node, (*lasts, token)[-keep:], (*(c - added for c in counts), 0)[-keep:]
        return self.number(key), added


class Chunk:
    """The state map of one chunk: from the state in which it is entered to the state at its end and the tokens added.

    Its text is parsed once as if a pre-token began with it.  Entered in any other state, it is stepped
    through up to the first place where a pre-token begins in both parses; from there they are the same.
    """

    def __init__(self, own: CountTransducer, text: str, final: bool):
        self.own, self.text, self.final, self.known_at = own, text, final, {}
        parts = own.parts(text)
        self.sure = parts if final else parts[:-3]  # what follows the chunk can change its last pre-tokens
        self.counts = own.known(self.sure)
        self.total, self.exit = sum(self.counts), None
        if not final:
            state, more = own.run(FRESH, "".join(parts[-3:]))
            self.total, self.exit = self.total + more, own.freeze(state)

    def __call__(self, entry: tuple) -> tuple[tuple | None, int]:
        if entry[0] == START:
            return self.exit, self.total
        found = self.known_at.get(entry)
        if found is None:
            found = self.known_at[entry] = self._enter(entry)
        return found

    def _enter(self, entry: tuple) -> tuple[tuple | None, int]:
        starts, at, left = {}, 0, self.total
        for p, n in zip(self.sure, self.counts, strict=True):
            starts[at] = left
            at, left = at + len(p), left - n
        if not self.final:
            starts[at] = left
        own, text, state, total, j = self.own, self.text, self.own.thaw(entry), 0, 0
        while j < len(text):
            state, d, j = own.glide(state, text, j)
            total += d
            if j == len(text):
                break
            after, d, fresh = own.step(state, text[j])
            if fresh and (left := starts.get(j - len(state[2]))) is not None:
                return self.exit, total + left
            state, total, j = after, total + d, j + 1
        return (None, total + own.finish(state)) if self.final else (own.freeze(state), total)


class Joined:
    """The map of neighbouring stretches, evaluated where it is needed; joining is associative."""

    def __init__(self, left, right):
        self.left, self.right, self.known_at = left, right, {}

    def __call__(self, entry: tuple) -> tuple[tuple | None, int]:
        found = self.known_at.get(entry)
        if found is None:
            between, n = self.left(entry)
            end, more = self.right(between)
            found = self.known_at[entry] = end, n + more
        return found


def scan(maps: list) -> list:
    """Inclusive prefix scan of state maps by recursive doubling."""
    reach = 1
    while reach < len(maps):
        maps = [m if i < reach else Joined(maps[i - reach], m) for i, m in enumerate(maps)]
        reach *= 2
    return maps


class CountTransducer:
    """Counts the tokens of a text; ``step`` reads a character, ``glide`` a stretch of one class, ``count`` takes whole texts."""

    def __init__(self, path: str, classes: CharClasses | None = None):
        self.model, self.chars = bpe_model.load(path), classes or library_classes()
        self.merge = MergeStates(self.model)
        marks = sorted(self.model.specials, key=len, reverse=True)
        self.marks = re.compile("|".join(map(re.escape, marks))) if marks else None
        self.memo = TwoGenerations(MEMO)
        self.classes: dict[str, int] = {}
        self.pretokens = self.chars.compile(PRETOKENS, False)
        self.exact = self.chars.compile(PRETOKENS, True) if self.chars.unlike else self.pretokens
        inside = {LETTERS: "{L}", NUMBERS: "{N}", OTHERS: "^{S}{L}{N}", BLANK: "{S}", SPACE: "{S}"}
        self.stretches = {exact: {mode: self.chars.compile(f"[{x}]+", exact) for mode, x in inside.items()} for exact in (False, True)}
        self.stretch = self.stretches[False]

    # --- transitions -------------------------------------------------------
    def feed(self, w: int, chars: str) -> tuple[int, int]:
        total, raw = 0, chars.encode("utf-8", "replace")
        for at in range(0, len(raw), SLICE):
            if len(self.merge.states) > STATES:  # bounded memory, also within one text
                w = self.merge.renew(w)
            step = self.merge.step
            for b in raw[at : at + SLICE]:
                w, d = step(w, b)
                total += d
        return w, total

    def freeze(self, state: tuple) -> tuple:
        """A state that outlives the numbering of merge states."""
        return state[0], self.merge.states[state[1]], state[2]

    def thaw(self, state: tuple) -> tuple:
        return state[0], self.merge.number(state[1]), state[2]

    def kind(self, ch: str) -> int:
        k = self.classes.get(ch)
        if k is None:
            k = self.classes[ch] = BLANK if ch == " " else (LETTERS, NUMBERS, SPACE, OTHERS)[self.chars.of(ch)]
        return k

    def begin(self, ch: str) -> tuple[tuple, int]:
        """The state after the first character of a fresh pre-token."""
        k = self.kind(ch)
        if k in (BLANK, SPACE):
            return (k, 0, ch), 0
        w, d = self.feed(0, ch)
        return (QUOTE if ch == "'" else k, w, ""), d

    def step(self, state: tuple, ch: str) -> tuple[tuple, int, bool]:
        """Next state, tokens added, and whether a pre-token begins here, before the pending character if there is one (so that the state no longer depends on the past)."""
        mode, w, pending = state
        k = self.kind(ch)
        if mode == START:
            return *self.begin(ch), True
        if mode in (LETTERS, NUMBERS, OTHERS):
            if k != mode:
                return *self.begin(ch), True
            w, d = self.feed(w, ch)
            return (mode, w, ""), d, False
        if mode in (BLANK, SPACE):
            if k in (BLANK, SPACE):
                w, d = self.feed(w, pending)
                return (k, w, ch), d, False
            if mode == BLANK:
                w, d = self.feed(0, pending + ch)
                return (k, w, ""), d, True
            _, d = self.feed(0, pending)
            after, more = self.begin(ch)
            return after, d + more, True
        if mode == QUOTE:
            if ch in "stmd":
                _, d = self.feed(w, ch)
                return FRESH, d, False
            if ch in "rvl":
                return ({"r": QUOTE_R, "v": QUOTE_V, "l": QUOTE_L}[ch], w, ch), 0, False
            if k == OTHERS:
                w, d = self.feed(w, ch)
                return (OTHERS, w, ""), d, False
            return *self.begin(ch), True
        if ch == ("l" if mode == QUOTE_L else "e"):
            _, d = self.feed(w, pending + ch)
            return FRESH, d, False
        w, d = self.feed(0, pending)
        after, more, _ = self.step((LETTERS, w, ""), ch)
        return after, d + more, True

    def glide(self, state: tuple, text: str, at: int) -> tuple[tuple, int, int]:
        """Read on while the character class stays: state, tokens added, place."""
        mode, w, pending = state
        same = self.stretch.get(mode)
        m = same.match(text, at) if same else None
        if not m:
            return state, 0, at
        run = pending + m[0]
        if mode in (BLANK, SPACE):
            w, d = self.feed(w, run[:-1])
            return (BLANK if run[-1] == " " else SPACE, w, run[-1]), d, m.end()
        w, d = self.feed(w, run)
        return (mode, w, ""), d, m.end()

    def run(self, state: tuple, text: str) -> tuple[tuple, int]:
        total, at = 0, 0
        while at < len(text):
            state, d, _ = self.step(state, text[at])
            state, more, at = self.glide(state, text, at + 1)
            total += d + more
        return state, total

    def finish(self, state: tuple) -> int:
        """Tokens still to add when the text ends in this state."""
        mode, w, pending = state
        return self.feed(w if mode in (BLANK, SPACE) else 0, pending)[1] if pending else 0

    # --- whole texts -------------------------------------------------------
    def parts(self, text: str) -> list[str]:
        if text.isascii():
            return ASCII_PRETOKENS.findall(text)
        return (self.exact if self.chars.needs_exact(text) else self.pretokens).findall(text)

    def known(self, pretokens: list[str]) -> list[int]:
        """Tokens of whole pre-tokens: memoised compositions of transitions from the start state."""
        out, memo = [], self.memo
        for p in pretokens:
            n = memo.young.get(p) or memo.get(p)
            if n is None:
                n = self.feed(0, p)[1]
                if len(p) <= 64:
                    memo.put(p, n)
            out.append(n)
        return out

    def count(self, text: str | None, chunk: int = CHUNK) -> int:
        """Chunk by chunk, whatever the length: a short text is one chunk."""
        if not text:
            return 0
        pieces = self.marks.split(text) if self.marks else [text]
        total = len(pieces) - 1
        for piece in filter(None, pieces):
            self.stretch = self.stretches[self.chars.needs_exact(piece)]
            maps = [Chunk(self, piece[i : i + chunk], i + chunk >= len(piece)) for i in range(0, len(piece), chunk)]
            total += scan(maps)[-1](FRESH)[1]
        return total


def transducer(path: str, classes: CharClasses) -> CountTransducer:
    return held("transducer", path, lambda: CountTransducer(path, classes))


def count_tokens(docs: DataFrame, path: str, limit: int = 512, text: str = "text") -> DataFrame:
    """``docs`` without its text, plus ``n_bytes``, ``n_tokens`` and ``over_limit`` (more than ``limit`` tokens). Narrow map, no shuffle."""
    new = ["n_bytes", "n_tokens", "over_limit"]
    kept = [c for c in docs.columns if c.lower() not in {text.lower(), *new}]
    source = docs.select(*map(named, kept), F.coalesce(F.octet_length(named(text).cast("string")), F.lit(0)).cast("long").alias("n_bytes"), named(text).cast("string").alias(fresh_name(docs, "text_")))
    classes = library_classes()  # ranges of code points
    schema = T.StructType([*(docs.schema[c] for c in kept), T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType())])

    def run(batches):
        own = transducer(path, classes)
        for batch in batches:
            *cols, texts = batch.columns
            counts = [own.count(t.as_py()) for t in texts]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(counts, pa.int64())], names=[*kept, "n_bytes", "n_tokens"])

    return in_order(source).mapInArrow(run, schema).withColumn("over_limit", F.col("n_tokens") > F.lit(limit))
