"""Operator 4 - language identification by compression.

For each language a raw-content dictionary is gathered from a bounded sample
of labelled rows.  A text is compressed against each dictionary; the language
whose dictionary gives the fewest bytes wins, and the relative gap to the
runner-up is the score.  Narrow margins are rejected (``rejected`` is true).

Bounds of the fit: about ``ROWS`` sampled rows a language, of each text at most
``ROW_CHARS`` characters (a longer one gives a slice at a place set by its hash),
``DICT_BYTES`` a dictionary and ``ALL_BYTES`` all of them: every language is
learned, with smaller dictionaries where there are very many.  Prediction reads every whole text, in
pieces of ``PIECE`` bytes so that one long text can't outgrow the dictionary.

Edge cases: text null or without a letter gives ``und`` with score 0, rejected;
no labelled row at all gives ``und`` everywhere; ties go to the smaller name; an
empty table gives no rows; repeated rows are predicted alike; input columns named
like an output are replaced.
"""

from __future__ import annotations

import pyarrow as pa
import regex
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fresh_name, in_order, named

ROWS, ROW_CHARS, DICT_BYTES, ALL_BYTES, PIECE, LEVEL, MIN_MARGIN = 96, 8192, 1 << 17, 1 << 25, 4096, 3, 0.02
LETTER = regex.compile(r"\p{L}")


def fit(rows: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id") -> dict[str, bytes]:
    """Dictionaries by language from labelled ``rows``: a bounded sample chosen by hash, so reruns agree.

    One pass counts usable rows a language; a second keeps those whose hash falls below the share
    that is expected to give ``ROWS`` of them, so no language gathers in one task.
    """
    h = F.xxhash64(F.lit(11), named(key), named(text))
    start = F.pmod(h, F.greatest(F.length(named(text)) - ROW_CHARS + 1, F.lit(1))).cast("int") + 1  # a long text gives a slice
    usable = rows.where(named(lang).isNotNull() & named(text).rlike(r"\p{L}")).select(named(lang).cast("string").alias("lang"), F.substring(named(text), start, F.lit(ROW_CHARS)).alias("text"), h.alias("h"))
    counts = usable.groupBy("lang").count().collect()  # a row a language
    if not counts:
        return {}
    share = F.create_map(*[x for r in counts for x in (F.lit(r["lang"]), F.lit(min(1.0, ROWS / r["count"])))])
    unit = F.shiftrightunsigned("h", 11) / F.lit(float(1 << 53))
    picked = usable.where(unit < share[F.col("lang")]).orderBy("h", "lang").limit(2 * ROWS * len(counts)).collect()
    out: dict[str, list[bytes]] = {}
    for r in picked:
        out.setdefault(r["lang"], []).append(r["text"].encode("utf-8", "replace"))
    room = min(DICT_BYTES, max(1 << 10, ALL_BYTES // len(out)))
    return {name: b"\n".join(parts)[-room:] for name, parts in sorted(out.items())}


class Classifier:
    def __init__(self, dictionaries: dict[str, bytes]):
        self.names = sorted(dictionaries)
        kind = zstandard.DICT_TYPE_RAWCONTENT
        held = [zstandard.ZstdCompressionDict(dictionaries[n], dict_type=kind) for n in self.names]
        for d in held:
            d.precompute_compress(level=LEVEL)
        self.coders = [zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_checksum=False, write_content_size=False) for d in held]

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        if not text or not self.names or not LETTER.search(text):
            return "und", 0.0, True
        raw = text.encode("utf-8", "replace")
        pieces = [raw[i : i + PIECE] for i in range(0, len(raw), PIECE)]
        sizes = sorted((sum(len(c.compress(p)) for p in pieces), n) for c, n in zip(self.coders, self.names, strict=True))
        margin = 1.0 if len(sizes) == 1 else (sizes[1][0] - sizes[0][0]) / sizes[1][0]
        return sizes[0][1], float(margin), margin < MIN_MARGIN


def predict(docs: DataFrame, dictionaries: dict[str, bytes], text: str = "text") -> DataFrame:
    """``docs`` without its text plus ``lang_pred``, ``score`` (0 to 1) and ``rejected``. Only the text is read for a prediction."""
    new = ["lang_pred", "score", "rejected"]
    kept = [c for c in docs.columns if c.lower() not in {text.lower(), *new}]
    source = docs.select(*map(named, kept), named(text).cast("string").alias(fresh_name(docs, "text_")))
    schema = T.StructType([*(docs.schema[c] for c in kept), T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("rejected", T.BooleanType())])
    shared = docs.sparkSession.sparkContext.broadcast(dictionaries)  # about ALL_BYTES at most

    def run(batches):
        own = Classifier(shared.value)
        for batch in batches:
            *cols, texts = batch.columns
            got = [own.predict(t.as_py()) for t in texts]
            yield pa.RecordBatch.from_arrays([*cols, pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64()), pa.array([g[2] for g in got], pa.bool_())], names=[*kept, *new])

    return in_order(source).mapInArrow(run, schema)
