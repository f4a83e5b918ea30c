"""Operator 10 - personal data: patterns propose, checksums confirm, nearby words adjust the score.

Base kinds (e-mail, IPv4, payment card, phone) keep every span that passes the
stated test; the added kinds (``iban`` by mod-97, ``national_id`` by context)
are reported where their score reaches ``MIN_SCORE``.  Each search is linear in
the text: a search starts only where a match could begin.

Edge cases: null and empty texts have no spans; an empty table gives no rows; repeated rows are searched
independently; input columns named like an output are replaced.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fresh_name, in_order, named

#: The order of kinds, and the patterns of the contract.
KINDS = ("email", "ip", "card", "phone", "iban", "national_id")
LOCAL_PART = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
IP = re.compile(r"(?<![0-9])([0-9]++)\.([0-9]++)\.([0-9]++)\.([0-9]++)")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]){11,30}(?![A-Za-z0-9])")
NATIONAL = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
DIGIT = re.compile(r"[0-9]")
NOT_DIGIT = re.compile(r"[^0-9]+")
#: Context words that raise or lower a kind's score, and prior scores.
RAISE = {
    "email": ("mail", "contact", "write", "reach"),
    "ip": ("ip", "host", "server", "address", "login"),
    "card": ("card", "visa", "credit", "payment", "pay"),
    "phone": ("phone", "call", "tel", "mobile", "fax"),
    "iban": ("iban", "bank", "account", "transfer"),
    "national_id": ("ssn", "social", "security", "identity", "passport"),
}
LOWER = {"ip": ("version", "release"), "card": ("order", "isbn", "serial"), "phone": ("score", "ratio"), "national_id": ("part", "model", "order")}
PRIOR = {"email": 0.8, "ip": 0.6, "card": 0.7, "phone": 0.6, "iban": 0.8, "national_id": 0.3}
STEP, WINDOW, MIN_SCORE = 0.2, 48, 0.5
WORDS = re.compile(r"[a-z]+")


def luhn(digits: str) -> bool:
    """The public check-digit test: from the right, every second digit doubled with its digits summed."""
    doubled = (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)
    return sum(doubled[int(d)] if i % 2 else int(d) for i, d in enumerate(reversed(digits))) % 10 == 0


def mod97(code: str) -> bool:
    """ISO 7064 mod 97-10: the first four characters move to the end, letters become 10 to 35, remainder 1."""
    s = code.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def _emails(text: str):
    free, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in LOCAL_PART:
            start -= 1
        found = DOMAIN.match(text, at) if start < at else None
        if found:
            yield start, found.end()
            free = found.end()
        at = text.find("@", max(at + 1, free))


def _proposals(text: str):
    if "@" in text:
        yield from (("email", *s) for s in _emails(text))
    if not DIGIT.search(text):
        return
    for m in IP.finditer(text):
        if all(len(p := g.lstrip("0")) <= 3 and int(p or "0") <= 255 for g in m.groups()):
            yield "ip", *m.span()
    for m in CARD.finditer(text):
        digits = NOT_DIGIT.sub("", m[0])
        if 13 <= len(digits) <= 19 and luhn(digits):
            yield "card", *m.span()
    if "+" in text:
        for m in PHONE.finditer(text):
            if 9 <= len(NOT_DIGIT.sub("", m[0])) <= 15:
                yield "phone", *m.span()
    for m in IBAN.finditer(text):
        if mod97(m[0]):
            yield "iban", *m.span()
    for m in NATIONAL.finditer(text):
        if m[0][:3] not in ("000", "666") and m[0][0] != "9" and m[0][4:6] != "00" and m[0][7:] != "0000":
            yield "national_id", *m.span()


def score(kind: str, text: str, start: int, end: int) -> float:
    """Prior of the kind, moved by context words within ``WINDOW`` code points on either side."""
    near = set(WORDS.findall(f"{text[max(0, start - WINDOW) : start]} {text[end : end + WINDOW]}".lower()))
    moved = STEP * sum(w in near for w in RAISE[kind]) - STEP * sum(w in near for w in LOWER.get(kind, ()))
    return round(min(1.0, max(0.0, PRIOR[kind] + moved)), 3)


def find(text: str | None) -> list[dict]:
    """Spans of one text (code points, end exclusive), by kind as listed and then by start."""
    out = [{"kind": k, "start": a, "end": b, "score": score(k, text, a, b)} for k, a, b in _proposals(text or "")]
    return [s for s in out if s["kind"] in KINDS[:4] or s["score"] >= MIN_SCORE]


SPAN = T.StructType([T.StructField("kind", T.StringType()), T.StructField("start", T.LongType()), T.StructField("end", T.LongType()), T.StructField("score", T.DoubleType())])


def find_personal_data(docs: DataFrame, text: str = "text", out: str = "pii") -> DataFrame:
    """``docs`` without its text plus ``pii``: the array of scored spans. Narrow map, no shuffle."""
    kept = [c for c in docs.columns if c.lower() not in {text.lower(), out}]
    source = docs.select(*map(named, kept), named(text).cast("string").alias(fresh_name(docs, "text_")))
    schema = T.StructType([*(docs.schema[c] for c in kept), T.StructField(out, T.ArrayType(SPAN))])
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))

    def run(batches):
        for batch in batches:
            *cols, texts = batch.columns
            yield pa.RecordBatch.from_arrays([*cols, pa.array([find(t.as_py()) for t in texts], kind)], names=[*kept, out])

    return in_order(source).mapInArrow(run, schema)


def redact(text: str | None, spans: list[dict]) -> str | None:
    """Replace each span by its kind in angle brackets; of overlapping spans the first one wins."""
    if text is None:
        return None
    out, at = [], 0
    for s in sorted(spans, key=lambda s: (s["start"], -s["end"])):
        if s["start"] >= at:
            out += [text[at : s["start"]], f"<{s['kind']}>"]
            at = s["end"]
    return "".join(out) + text[at:]
