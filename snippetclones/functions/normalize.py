"""Column functions that normalise snippet text. All are built-in expressions, so they stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The white-space characters removed before fingerprinting, and the token separators.
WHITE = r"[ \t\n\r\f\x0B]+"
UNICODE_WHITE = r"[ \t\n\r\f\x0B\x85\xA0\p{Z}]+"
SEPARATORS = r"[^\p{L}\p{N}_]+"
SENTENCE = r"[.!?]+"


def strip_ws(code: Column, unicode_ws: bool = False) -> Column:
    """The snippet without any white space."""
    return F.regexp_replace(code, UNICODE_WHITE if unicode_ws else WHITE, "")


def fingerprint(code: Column, algo: str = "md5") -> Column:
    """Hash of the white-space-free snippet."""
    n = strip_ws(code)
    return {"md5": lambda: F.md5(n), "sha2": lambda: F.sha2(n, 256), "xxhash64": lambda: F.concat_ws(":", F.xxhash64(n), F.length(n))}[algo]()


def strip_comments(code: Column, inline: str | None = "#", block: tuple[str, str] | None = ('"""', '"""')) -> Column:
    """Block comments first, then inline comments to the end of the line."""
    if block:
        code = F.regexp_replace(code, f"(?s){block[0]}.*?{block[1]}", "")
    return F.regexp_replace(code, f"{inline}[^\n]*", "") if inline else code


def tokens(code: Column) -> Column:
    """The snippet's tokens in order, repeats included."""
    return F.filter(F.split(code, SEPARATORS), lambda t: t != "")


def abstract_tokens(code: Column, keywords: tuple[str, ...] = ()) -> Column:
    """Literals and identifiers replaced by class symbols; keywords stay."""
    keep = f"(?!(?:{'|'.join(keywords)})\\b)" if keywords else ""
    return F.regexp_replace(F.regexp_replace(code, r"\b[0-9]+\b", "0"), rf"\b{keep}\p{{L}}[\p{{L}}\p{{N}}_]*", "W")


def sentences(code: Column) -> Column:
    """Line count of a one-line cell: its sentences, one at least."""
    return F.greatest(F.lit(1), F.regexp_count(code, F.lit(SENTENCE))).cast("int")


def newline_loc(code: Column) -> Column:
    return F.size(F.split(code, "\n"))


def sloc(code: Column) -> Column:
    """Lines left non-blank when comments are gone."""
    return F.size(F.filter(F.split(strip_comments(code), "\n"), lambda x: F.trim(F.regexp_replace(x, r"[\t\r\f\x0B]", " ")) != ""))
