"""Operator 2 [native] - line dedup with a suffix array over line-ID sequences.

A document is its sequence of non-blank lines.  A *run* is a stretch of lines;
a line is deleted when it lies in a run of at least ``min_words`` words that
also occurs at an earlier place (documents by doc_id, null last, then line).

Ranks come from distributed prefix doubling: level 0 ranks the lines that occur
at least twice, level k+1 ranks pairs (rank of the 2**k lines here, rank of the
next 2**k) that occur at least twice, in the order of a range-partitioned sort,
so ranks order the suffixes by their first 2**k lines.  Unique stretches leave
at once, which keeps the active set small.  Suffixes whose common prefix reaches
a run's length are one LCP interval of the suffix array; it is named by two
overlapping ranks, its least place is the copy that stays, and the others go.

A line is covered by a repeated run of ``min_words`` words iff it is covered by
a repeated *shortest* run that starts at some line, or that ends at this line,
so only these two runs a line are looked up - of at most ``min_words`` lines,
as each line has a word, hence floor(log2(min_words)) doubling rounds.

Only DataFrame functions are used.  Edge cases: null text stays null; empty
texts and blank lines stay; rows that repeat a doc_id are separate documents in
the order of their numbers, which are written once with the rows; an empty table
gives no rows; line identity is the MD5 of the whole line; other columns are kept,
except that ones named like an output column are replaced.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, fresh_name, named, numbered

MIN_WORDS = 4
HAS_WORD = r"[^\x20\x09-\x0D]"


def line_rows(rows: DataFrame, rid: str, doc_id: str, text: str) -> DataFrame:
    """``(rid, doc, i, words, h)`` of every non-blank line; i counts the non-blank lines of a document."""
    lines = F.filter(F.split(named(text).cast("string"), "\n"), lambda x: x.rlike(HAS_WORD))
    each = F.transform(lines, lambda x: F.struct(F.unhex(F.md5(x)).alias("h"), F.regexp_count(x, F.lit(r"[^\x20\x09-\x0D]+")).alias("words")))
    return rows.select(F.col(rid).alias("rid"), named(doc_id).cast("long").alias("doc"), F.posexplode(each).alias("i", "e")).select("rid", "doc", "i", "e.words", "e.h")


def ranked(keys: DataFrame, by: list[str], name: str) -> DataFrame:
    """Order-preserving ranks of distinct keys: a range-partitioned sort, numbered by partition and place, then materialised."""
    return cut(keys.orderBy(*by).select(*by, F.monotonically_increasing_id().alias(name)))


def prefix_doubling(lines: DataFrame, levels: int) -> DataFrame:
    """Lines that occur twice or more, with ``r0 .. r<levels>``: the rank of the 2**k lines from here, null where unique."""
    twice = ranked(lines.groupBy("h").agg(F.count("*").alias("n")).where("n > 1"), ["h"], "r0")
    active = cut(lines.join(twice, "h").drop("h"))
    along = Window.partitionBy("rid").orderBy("i")
    for k in range(levels):
        here, span = f"r{k}", 1 << k
        joined = F.lead("i", span).over(along) == F.col("i") + span
        paired = active.withColumn("next", F.when(joined & F.col(here).isNotNull(), F.lead(here, span).over(along)))
        paired = cut(paired)
        names = ranked(paired.where("next is not null").groupBy(here, "next").agg(F.count("*").alias("n")).where("n > 1"), [here, "next"], f"r{k + 1}")
        active = cut(paired.join(names, [here, "next"], "left").drop("next"))
    return active


def _interval(length: int, first, second):
    """Name of the LCP interval of a run: its length and the two overlapping ranks that spell it (null where either is unique)."""
    return F.when(first.isNotNull() & second.isNotNull(), F.struct(F.lit(length).alias("length"), first.alias("x"), second.alias("y")))


def repeated_lines(lines: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """``(rid, i)`` of the lines to delete."""
    levels = max(0, min_words.bit_length() - 1)
    active = prefix_doubling(lines, levels)
    doc = Window.partitionBy("rid")
    active = active.withColumn("upto", F.sum("words").over(doc.orderBy("i").rowsBetween(Window.unboundedPreceding, 0))).withColumn("before", F.col("upto") - F.col("words"))
    ahead = doc.orderBy("before").rangeBetween(0, min_words - 1)
    behind = doc.orderBy("upto").rangeBetween(-(min_words - 1), 0)
    along = doc.orderBy("before")
    size_f, size_b = F.count("*").over(ahead), F.count("*").over(behind)
    whole_f = (F.max("i").over(ahead) - F.col("i") + 1 == size_f) & (F.sum("words").over(ahead) >= min_words)
    whole_b = (F.col("i") - F.min("i").over(behind) + 1 == size_b) & (F.sum("words").over(behind) >= min_words)
    runs = active.withColumn("lf", F.when(whole_f, size_f)).withColumn("lb", F.when(whole_b, size_b))
    pick = lambda col, per: reduce(lambda a, n: a.when(F.col(col) == n, per(n)), range(2, min_words + 1), F.when(F.col(col) == 1, per(1)))
    level = lambda n: n.bit_length() - 1
    forward = lambda n: _interval(n, F.col(f"r{level(n)}"), F.lead(f"r{level(n)}", n - (1 << level(n))).over(along))
    backward = lambda n: _interval(n, F.lag(f"r{level(n)}", n - 1).over(along), F.lag(f"r{level(n)}", (1 << level(n)) - 1).over(along))
    named = runs.withColumn("fwd", pick("lf", forward)).withColumn("bwd", pick("lb", backward))
    each = F.array(
        F.struct(F.col("fwd").alias("run"), F.col("i").alias("start"), F.lit(True).alias("ahead")),
        F.struct(F.col("bwd").alias("run"), (F.col("i") - F.col("lb") + 1).cast("int").alias("start"), F.lit(False).alias("ahead")),
    )
    found = named.select("rid", "doc", "i", F.explode(each).alias("e")).where("e.run is not null").select("rid", "doc", "i", F.col("e.run.length").cast("int").alias("length"), "e.run.x", "e.run.y", "e.start", "e.ahead")
    found = cut(found)
    name = ["length", "x", "y"]
    place = F.struct(F.col("doc").isNull().alias("no_doc"), "doc", "rid", "start")
    kept = found.groupBy(*name).agg(F.min(place).alias("kept"), F.count("*").alias("n")).where("n > 1").select(*name, "kept")
    later = found.join(kept, name).where((F.col("rid") != F.col("kept.rid")) | (F.col("start") != F.col("kept.start")))
    gone = F.when(F.col("ahead"), F.sequence(F.col("i"), F.col("i") + F.col("length") - 1)).otherwise(F.array("i"))
    return later.select("rid", gone.alias("gone"))


def dedup_lines(docs: DataFrame, min_words: int = MIN_WORDS, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with the later copies of repeated line runs deleted from the text, plus ``n_lines`` and ``n_removed``."""
    rows, rid = numbered(docs)
    own = next(c for c in docs.columns if c.lower() == text.lower())
    gone = repeated_lines(cut(line_rows(rows, rid, doc_id, own)), min_words)
    g, ls, full = (fresh_name(rows, x) for x in ("gone_", "lines_", "full_"))
    gone = gone.groupBy("rid").agg(F.array_distinct(F.flatten(F.collect_list("gone"))).alias(g)).withColumnRenamed("rid", rid)
    kept = [c for c in docs.columns if c.lower() not in {"n_lines", "n_removed"}]
    marked = rows.join(gone, rid, "left").withColumn(ls, F.split(named(own).cast("string"), "\n"))  # texts travel once
    places = F.filter(F.transform(F.col(ls), lambda x, p: F.when(x.rlike(HAS_WORD), p)), lambda p: p.isNotNull())
    marked = marked.withColumn(full, F.when(F.col(g).isNotNull(), places))
    drop = F.transform(g, lambda i: F.get(F.col(full), i))
    order = F.when(F.size(ls) > 0, F.sequence(F.lit(0), F.size(ls) - 1))
    left = F.array_join(F.transform(F.array_except(order, drop), lambda p: F.get(F.col(ls), p)), "\n")
    text_out = F.when(F.col(g).isNull(), named(own).cast("string")).otherwise(left)
    return marked.select(*[text_out.alias(c) if c == own else named(c) for c in kept], F.coalesce(F.size(ls), F.lit(0)).cast("long").alias("n_lines"), F.coalesce(F.size(g), F.lit(0)).cast("long").alias("n_removed"))


#: DuckDB SQL for the whole result: runs are compared as lists of lines.
ORACLE = """
WITH w AS (
  SELECT doc_id, pos, line, len(regexp_extract_all(line, '[^\\x20\\x09-\\x0D]+')) AS words
  FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(0, len(string_split(text, chr(10))))) AS pos FROM documents)),
l AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY pos) AS i, sum(words) OVER (PARTITION BY doc_id ORDER BY pos) AS upto FROM w WHERE words > 0),
r AS (
  SELECT doc_id, i, list(line) OVER f AS fwd, sum(words) OVER f AS fw, list(line) OVER b AS bwd, sum(words) OVER b AS bw
  FROM (SELECT *, upto - words AS before FROM l)
  WINDOW f AS (PARTITION BY doc_id ORDER BY before RANGE BETWEEN CURRENT ROW AND {last} FOLLOWING),
         b AS (PARTITION BY doc_id ORDER BY upto RANGE BETWEEN {last} PRECEDING AND CURRENT ROW)),
runs AS (
  SELECT doc_id, i AS start, i AS line_no, fwd AS run, true AS ahead FROM r WHERE fw >= {words}
  UNION ALL SELECT doc_id, i - len(bwd) + 1, i, bwd, false FROM r WHERE bw >= {words}),
firsts AS (SELECT run, min(struct_pack(d := doc_id, s := start)) AS kept FROM runs GROUP BY run),
dups AS (SELECT u.* FROM runs u JOIN firsts f USING (run) WHERE struct_pack(d := u.doc_id, s := u.start) <> f.kept),
gone AS (SELECT DISTINCT doc_id, unnest(CASE WHEN ahead THEN range(line_no, line_no + len(run)) ELSE [line_no] END) AS i FROM dups),
left_lines AS (
  SELECT w.doc_id, count(*) AS n_lines, count(g.i) AS n_removed, string_agg(w.line, chr(10) ORDER BY w.pos) FILTER (WHERE g.i IS NULL) AS text
  FROM w LEFT JOIN l ON l.doc_id = w.doc_id AND l.pos = w.pos LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.i = l.i GROUP BY w.doc_id)
SELECT d.doc_id, coalesce(x.n_lines, 0) AS n_lines, coalesce(x.n_removed, 0) AS n_removed, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(x.text, '') END AS text
FROM documents d LEFT JOIN left_lines x USING (doc_id)
""".format(words=MIN_WORDS, last=MIN_WORDS - 1)
