"""Operator 8 - mixing sources to target weights by subset-sum budget fitting.

Documents are counted by source and exact length.  A source's target is first
spent on whole passes over the source, then on equal shares of each length
count, and the budget that remains is fitted to the greatest reachable sum by a
bounded-knapsack dynamic programme over documents added and removed.  Documents are then picked by a
seeded hash within each length, in buckets of bounded size: whole buckets below
the cut, and one ranked bucket at the cut.

Only the histogram (distinct lengths d of a source obey d <= sqrt(2 * size))
reaches the per-source solver; documents are never gathered.

Edge cases: null or empty texts have size 0 and are never taken; null is a
source of its own, last; repeated rows are separate documents; a source of size
0 has target 0; an empty table gives no rows.
"""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import NOT_WORD, cut, fresh_name, named, numbered

WEIGHTS, SHARE, MOST, SEED, BUCKET, TRAIL_BITS = (3, 1, 2), 1.5, 2, 20240, 512, 1 << 31


def size_of(text: str = "text"):
    """Number of words: runs without ASCII white space; 0 for null."""
    t = F.coalesce(named(text).cast("string"), F.lit(""))
    return F.when(F.length(F.regexp_replace(t, NOT_WORD, "")) == 0, F.lit(0)).otherwise(F.regexp_count(t, F.lit(r"[^\x20\x09-\x0D]+"))).cast("long")


def targets(sources: DataFrame) -> DataFrame:
    """``(source, source_size)`` to ``(source, source_size, target)``.

    Water filling in one step: targets are min(level * weight, cap).  In ascending order of
    cap / weight, the sources before some point are at their cap; the level is what is left over
    the weights that are left, at the first point where it doesn't exceed the next cap / weight (levels fall from there on, so it is the greatest of these).
    """
    order = Window.orderBy(F.col("source").isNull(), F.col("source").cast("binary"))
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in WEIGHTS]), (F.pmod(F.row_number().over(order) - 1, F.lit(len(WEIGHTS))) + 1).cast("int"))
    cap = F.col("source_size") * F.lit(float(MOST))
    ranked = sources.withColumn("weight", weight).withColumn("cap", cap).withColumn("ratio", F.col("cap") / F.col("weight"))
    by_ratio = Window.orderBy("ratio", F.col("source").isNull(), "source")
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy()
    level = (F.lit(SHARE) * F.sum("source_size").over(whole) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    found = ranked.withColumn("level", level)
    best = F.max(F.when(F.col("level") <= F.col("ratio"), F.col("level"))).over(whole)
    return found.withColumn("best", best).select("source", "source_size", F.coalesce(F.least(F.col("best") * F.col("weight"), F.col("cap")), F.col("cap")).alias("target"))


def _exchange(lengths: list[int], counts: list[int], take: list[int], gap: int, copies: int, room: int) -> tuple[list[int], int]:
    """Close as much of ``gap`` as adding and removing at most ``copies`` documents of each length can, with sums that stray at most ``room``.

    A bounded-knapsack programme: reachable changes of the sum as bits of an integer, numbers of documents split into powers of two.
    """
    order = sorted((i for i in range(len(lengths)) if lengths[i]), key=lambda i: lengths[i])
    low = min(room, sum(lengths[i] * min(take[i], copies) for i in order))
    high = max(gap, min(room, sum(lengths[i] * min(counts[i] - take[i], copies) for i in order)))
    reach, mask, wish, steps = 1 << low, (1 << (low + high + 1)) - 1, low + gap, []
    for i in order:
        for sign, most in ((1, counts[i] - take[i]), (-1, take[i])):
            left, power = min(most, copies), 1
            while left > 0 and not reach >> wish & 1:
                n = min(power, left)
                left, power = left - n, power * 2
                if n * lengths[i] <= low + high:
                    steps.append((i, sign * n, reach))
                    reach |= (reach << n * lengths[i]) & mask if sign > 0 else reach >> n * lengths[i]
    at = (reach & ((1 << (wish + 1)) - 1)).bit_length() - 1
    best, out = at, list(take)
    for i, n, was in reversed(steps):
        if not was >> at & 1:
            out[i] += n
            at -= n * lengths[i]
    return out, wish - best


def fit_counts(lengths: list[int], counts: list[int], budget: int) -> list[int]:
    """How many documents of each length to take so that their lengths sum to the greatest reachable sum up to ``budget``.

    Equal shares first, then longest first whatever still fits, which leaves a gap below the longest length.
    The gap is closed by exchanging documents: first few of each length, then more.  A best choice is never more than
    2 * longest + 1 documents away from any other choice within the longest length of it (order the exchanges so that
    the sum stays within that length of zero; equal sums would enclose an exchange of nothing), so the search ends
    there with a proof, or earlier when the gap is closed.  Only where the proof's window outgrows ``TRAIL_BITS`` does
    it end without one, below the budget by less than the longest length.
    """
    total = sum(a * c for a, c in zip(lengths, counts, strict=True))
    goal = max(0, min(budget, total))
    step = math.gcd(*(a for a, c in zip(lengths, counts, strict=True) if c))
    if not total or not goal:
        return [0] * len(lengths)
    goal -= goal % step  # every sum is a multiple of the lengths' common divisor
    take = [c * goal // total for c in counts]
    gap = goal - sum(a * t for a, t in zip(lengths, take, strict=True))
    for i in sorted((i for i in range(len(lengths)) if lengths[i]), key=lambda i: -lengths[i]):
        more = min(counts[i] - take[i], gap // lengths[i])
        take[i] += more
        gap -= more * lengths[i]
    longest = max(a for a, c in zip(lengths, counts, strict=True) if c)
    proof = min(max(counts), 2 * longest + 1)
    most = min(total, proof * longest * len(lengths), (2 * longest + 1) * longest, TRAIL_BITS // (2 * len(lengths) * max(1, proof.bit_length())))
    copies, room = 1, min(most, 32 * longest)
    while gap:
        take, gap = _exchange(lengths, counts, take, gap, copies, room)
        if copies >= proof and room >= most:
            break
        copies, room = min(proof, copies * 4), min(most, room * 8)
    return take


def _solve(rows: pd.DataFrame) -> pd.DataFrame:
    """Per source: passes over all documents, and extra documents by length."""
    rows = rows.sort_values("size", kind="stable")
    total, goal = int(rows["source_size"].iloc[0]), int(round(float(rows["target"].iloc[0])))
    passes = min(goal // total, MOST) if total else 0
    extra = fit_counts(rows["size"].tolist(), rows["n"].tolist(), goal - passes * total if passes < MOST else 0)
    return rows.assign(passes=passes, extra=extra)


def mix(docs: DataFrame, source: str = "source", text: str = "text", doc_id: str = "doc_id") -> tuple[DataFrame, DataFrame, str]:
    """``(rid, doc_id, source, size, source_size, target, copies)``, the numbered input, and its number column. The input is evaluated once, whatever order its rows have."""
    rid = fresh_name(docs, "rid")
    rows = docs.withColumn(rid, F.monotonically_increasing_id())
    return _mix(rows, rid, source, text, doc_id), rows, rid


def _mix(rows: DataFrame, rid: str, source: str, text: str, doc_id: str) -> DataFrame:
    hashed = F.xxhash64(F.lit(SEED), named(doc_id), F.xxhash64(named(text)))
    base = cut(rows.select(F.col(rid).alias("rid"), named(doc_id).alias("doc_id"), named(source).cast("string").alias("source"), size_of(text).alias("size"), hashed.alias("h")))
    lengths = cut(base.groupBy("source", "size").agg(F.count("*").alias("n")))
    goals = cut(targets(lengths.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"))))
    solver_in = lengths.join(goals, lengths["source"].eqNullSafe(goals["source"])).select(lengths["source"], "size", "n", "source_size", "target")
    plan = cut(solver_in.groupBy("source").applyInPandas(_solve, "source string, size long, n long, source_size long, target double, passes int, extra long"))
    plan = plan.withColumn("buckets", F.greatest(F.lit(1), F.ceil(F.col("n") / BUCKET)).cast("long"))
    same = lambda a, b, *more: [a["source"].eqNullSafe(b["source"]), *[a[c] == b[c] for c in more]]
    unit = F.shiftrightunsigned("h", 11) / F.lit(float(1 << 53))
    dealt = base.join(plan, same(base, plan, "size")).select("rid", "doc_id", base["source"], base["size"], "source_size", "target", "h", "n", "passes", "extra", F.when((F.col("extra") > 0) & (F.col("extra") < F.col("n")), F.floor(unit * F.col("buckets"))).alias("bucket"))
    split = dealt.where(F.col("bucket").isNotNull())
    filled = split.groupBy("source", "size", "extra", "bucket").agg(F.count("*").alias("here"))
    upto = F.sum("here").over(Window.partitionBy("source", "size").orderBy("bucket"))
    edges = filled.withColumn("before", upto - F.col("here")).select(F.col("source").alias("s"), F.col("size").alias("z"), F.col("bucket").alias("k"), F.least(F.greatest(F.col("extra") - F.col("before"), F.lit(0)), F.col("here")).alias("some"), "here")
    ranked = split.join(edges, split["source"].eqNullSafe(F.col("s")) & (F.col("size") == F.col("z")) & (F.col("bucket") == F.col("k")))
    at_cut = ranked.where((F.col("some") > 0) & (F.col("some") < F.col("here")))
    place = F.row_number().over(Window.partitionBy("source", "size", "bucket").orderBy("h", "doc_id", "rid"))
    picked = at_cut.withColumn("place", place).where("place <= some").select("rid").union(ranked.where(F.col("some") == F.col("here")).select("rid")).withColumn("picked", F.lit(1))
    more = F.when(F.col("bucket").isNotNull(), F.coalesce("picked", F.lit(0))).otherwise((F.col("extra") > 0).cast("int"))
    copies = F.when(F.col("size") > 0, F.col("passes") + more).otherwise(F.lit(0))
    return dealt.join(picked, "rid", "left").select("rid", "doc_id", "source", "size", "source_size", "target", copies.alias("copies"))


def mixed_documents(docs: DataFrame, source: str = "source", text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """The mix itself: each document as often as it is taken. Columns are those of ``docs``."""
    rows, rid = numbered(docs)
    copies = fresh_name(rows, "copies")
    taken = _mix(rows, rid, source, text, doc_id).where("copies > 0").select(F.col("rid").alias(rid), F.col("copies").alias(copies))
    every = rows.join(taken, rid).withColumn(copies, F.explode(F.sequence(F.lit(1), F.col(copies))))
    return every.select(*map(named, docs.columns))
