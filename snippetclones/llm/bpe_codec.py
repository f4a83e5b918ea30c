"""Operator 1 - BPE encoding and decoding by per-prefix dynamic programming.

For every prefix of a word exactly one token can be the last one of the
prefix's encoding.  A suffix-matching automaton over the vocabulary lists the
tokens that end at each position; the one whose predecessor (the stored last
token of the shorter prefix) passes the pair-compatibility test is stored, and
following the stored tokens back from the end gives the ids.  One pass, linear
in the text, and no merge queue.

Edge cases: null text is the empty text (no ids, empty decoding); empty texts
likewise; an empty table gives no rows; repeated rows are encoded independently;
other columns are kept except that an input column named like an output column
is replaced; time and memory are linear in a text's length.
"""

from __future__ import annotations

import re
import struct
import unicodedata

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import bpe_model
from .char_classes import CharClasses, library_classes
from .common import fresh_name, held, in_order, named

#: The word pattern that the tokenizer file states, letters first (an apostrophe is neither letter nor number).
WORDS = r"[{L}]+|[{N}]|'s|'t|'re|'ve|'m|'ll|'d|[^{S}{L}{N}]+"
ASCII_WORDS = re.compile(r"[a-z]+|[0-9]|'(?:[stmd]|re|ve|ll)|[^\sa-z0-9\x1c-\x1f]+|[\x1c-\x1f]+")  # of lower-cased text
_WHITE = "\t-\r\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: Runs of white space that aren't one blank already.
SPACES = re.compile(f"[{_WHITE}][ {_WHITE}]*| [ {_WHITE}]+")
#: Scripts whose composed and lower-case forms no Unicode version since 4.1 changes; other texts are normalised by the library.
SETTLED = re.compile("[\x00-\u036f\u0374-\u0377\u037a-\u037f\u0384-\u03ff\u0400-\u0527\u1e00-\u1eff\u2000-\u2064\u20a0-\u20b5\u2100-\u214e\u2190-\u23e7\u2500-\u26ff\u3000-\u30ff\u4e00-\u9fbb\uac00-\ud7a3]*")
MEMO_WORDS = 130_000
LONGEST_MEMO = 64


class WordMemo(dict):
    """What ``make`` gives for a word, looked up in one step; two generations of ``MEMO_WORDS`` words, longer words than ``LONGEST_MEMO`` are not kept."""

    def __init__(self, make):
        super().__init__()
        self.make, self.old = make, {}

    def __missing__(self, word):
        got = self.old.get(word) or self.make(word)
        if len(word) <= LONGEST_MEMO:
            if len(self) >= MEMO_WORDS:
                self.old = dict(self)
                self.clear()
            self[word] = got
        return got


class BpeCodec:
    """``encode`` text to ids and ``decode`` ids to text, as the public tokenizer file defines."""

    def __init__(self, path: str, classes: CharClasses | None = None):
        self.model, self.classes = bpe_model.load(path), classes or library_classes()
        self.pattern, self.normaliser = {}, None
        self.matcher = ahocorasick.Automaton()
        for token, i in self.model.id_of.items():
            self.matcher.add_word(token, (len(token), i))
        self.matcher.make_automaton()
        self.length = {i: len(s) for s, i in self.model.id_of.items()}
        marks = sorted(self.model.specials, key=len, reverse=True)
        self.marks = re.compile("(" + "|".join(map(re.escape, marks)) + ")") if marks else None
        self.memo = WordMemo(self._word)

    def word_ids(self, word: str) -> list[int]:
        """Ids of one word: the dynamic programme over its prefixes."""
        s, compatible, tested = self.model.spell(word), self.model.compatible, self.model.tested
        last: list[int] = [-1] * (len(s) + 1)
        for end, (k, token) in self.matcher.iter(s):
            if last[end + 1] >= 0:
                continue  # only one token can be the last one
            before = last[end + 1 - k]
            if k > end:
                last[end + 1] = token
            elif before >= 0:
                fits = tested(before << 20 | token)
                if compatible(before, token) if fits is None else fits:
                    last[end + 1] = token
        ids, at = [], len(s)
        while at:
            ids.append(last[at])
            at -= self.length[last[at]]
        return ids[::-1]

    def words(self, text: str) -> list[str]:
        """Normalised words of a text without special marks (composed form, lower case per character)."""
        if text.isascii() and not _SEPARATORS.search(text):
            return ASCII_WORDS.findall(text.lower())
        if SETTLED.fullmatch(text):
            text = SPACES.sub(" ", unicodedata.normalize("NFC", text)).replace("Σ", "σ").lower()
        else:
            text = self.normalised(text)
        exact = self.classes.needs_exact(text)
        if exact not in self.pattern:
            self.pattern[exact] = self.classes.compile(WORDS, exact)
        return self.pattern[exact].findall(text)

    def normalised(self, text: str) -> str:
        """The file's normaliser by the library, whose Unicode version may differ from this Python's."""
        if self.normaliser is None:
            from tokenizers import Regex, normalizers

            self.normaliser = normalizers.Sequence([normalizers.NFC(), normalizers.Replace(Regex(r"\s+"), " "), normalizers.Lowercase()])
        return self.normaliser.normalize_str(text)

    def _word(self, word: str) -> tuple[bytes, str]:
        ids = self.word_ids(word)
        return struct.pack(f"<{len(ids)}I", *ids), self.decode(ids)

    def pack(self, text: str | None) -> tuple[bytes, str]:
        """Ids as little-endian unsigned 32-bit integers, and their decoding."""
        if not text:
            return b"", ""
        memo, ids, shown = self.memo, [], []
        for k, part in enumerate(self.marks.split(text) if self.marks else [text]):
            if k % 2:
                ids.append(struct.pack("<I", self.model.specials[part]))
                shown.append(part)
            elif part:
                got = [memo[word] for word in self.words(part)]
                ids += [x for x, _ in got]
                shown += [x for _, x in got]
        return b"".join(ids), " ".join(shown)

    def encode(self, text: str | None) -> list[int]:
        raw = self.pack(text)[0]
        return list(struct.unpack(f"<{len(raw) // 4}I", raw))

    def decode(self, ids: list[int]) -> str:
        """The file names no decoder, so tokens are shown as spelt, blank-separated, special ones included."""
        shown = self.model.shown
        return " ".join([shown[i] for i in ids])


_SEPARATORS = re.compile(r"[\x1c-\x1f]")


def codec(path: str, classes: CharClasses) -> BpeCodec:
    return held("codec", path, lambda: BpeCodec(path, classes))


def encode_documents(docs: DataFrame, path: str, text: str = "text", ids: str = "ids_le", decoded: str = "decoded") -> DataFrame:
    """``docs`` without its text, plus ``ids_le`` (packed little-endian uint32) and ``decoded``.

    A narrow map: no shuffle, memory bounded by an Arrow batch and a word memo of fixed size.
    """
    kept = [c for c in docs.columns if c.lower() not in {text.lower(), ids, decoded}]
    source = docs.select(*map(named, kept), named(text).cast("string").alias(fresh_name(docs, "text_")))
    classes = library_classes()  # ranges of code points
    schema = T.StructType([*(docs.schema[c] for c in kept), T.StructField(ids, T.BinaryType()), T.StructField(decoded, T.StringType())])

    def run(batches):
        own = codec(path, classes)
        for batch in batches:
            for part in (batch.slice(i, 512) for i in range(0, batch.num_rows, 512)):
                texts = part.column(part.num_columns - 1)
                packed = [own.pack(t.as_py()) for t in texts]
                cols = [part.column(i) for i in range(part.num_columns - 1)]
                yield pa.RecordBatch.from_arrays([*cols, pa.array([p[0] for p in packed], pa.binary()), pa.array([p[1] for p in packed], pa.string())], names=[*kept, ids, decoded])

    return in_order(source).mapInArrow(run, schema)


def ids_array(ids: str = "ids_le"):
    """The packed ids as an array of ints, in the JVM."""
    return F.expr(
        f"transform(if(length({ids}) = 0, cast(array() as array<int>), sequence(1, cast(length({ids}) / 4 as int))), "
        f"k -> cast(conv(concat(hex(substring({ids}, 4 * k, 1)), hex(substring({ids}, 4 * k - 1, 1)), hex(substring({ids}, 4 * k - 2, 1)), hex(substring({ids}, 4 * k - 3, 1))), 16, 10) as int))"
    )
