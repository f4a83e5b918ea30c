"""Review of clone groups, deviated templates and the headline report. Near-miss pairs have no groups and are not accepted here."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import normalize as N
from . import cmw, connections, frequency


def top(groups: DataFrame, k: int, min_loc: int = 0, max_loc: int = 1 << 30) -> DataFrame:
    return groups.where((F.col("size") >= 2) & F.col("median_loc").between(min_loc, max_loc)).orderBy(F.desc("size"), "h").limit(k)


def pattern_only(groups: DataFrame, pattern: str) -> DataFrame:
    """Groups whose every line matches."""
    return groups.where(F.forall(F.split("sample", "\n"), lambda x: x.rlike(pattern)))


def licence(cells: DataFrame, phrases: dict[str, str]) -> DataFrame:
    """Cells by licence kind, in one pass."""
    one = cells.agg(F.array(*[F.struct(F.lit(k).alias("kind"), F.count_if(F.col("code").contains(p)).alias("cells")) for k, p in phrases.items()]).alias("a"))
    return one.select(F.explode("a").alias("x")).select("x.*")


def contains(groups: DataFrame, phrase: str) -> DataFrame:
    return groups.where(F.col("sample").contains(phrase))


def naming(groups: DataFrame, k: int, longest: int = 3) -> DataFrame:
    """Short identifiers of the k largest groups, weighted by group size."""
    t = top(groups, k).select("size", F.explode(F.filter(N.tokens(F.col("sample")), lambda x: F.length(x) <= longest)).alias("name"))
    return t.groupBy("name").agg(F.sum("size").alias("uses"))


def alias(cells: DataFrame, word: str) -> DataFrame:
    """Pairs around a binding word, as in "library as name"."""
    m = cells.select(F.explode(F.regexp_extract_all("code", F.lit(rf"[\p{{L}}]+ {word} [\p{{L}}]+"), F.lit(0))).alias("x"))
    part = rf"([\p{{L}}]+) {word} ([\p{{L}}]+)"
    return m.groupBy(F.regexp_extract("x", part, 1).alias("lib"), F.regexp_extract("x", part, 2).alias("alias")).agg(F.count("*").alias("uses"))


def single_token(groups: DataFrame) -> DataFrame:
    return groups.where(F.size(N.tokens(F.col("sample"))) == 1)


def accidental(groups: DataFrame) -> DataFrame:
    """Short and in many repositories: likely a clone by accident."""
    return groups.withColumn("score", F.col("n_repo") / (1.0 + F.length("sample")))


def majority(groups: DataFrame, notebooks: DataFrame) -> DataFrame:
    total = notebooks.agg(F.count("*").alias("b"))
    return groups.agg(F.max("n_nb").alias("top")).crossJoin(total).select((F.col("top") / F.col("b")).alias("top_share"), (F.col("top") / F.col("b") > 0.5).alias("majority"))  # one row each


def deviated(counts: DataFrame, templates: DataFrame, theta: float) -> DataFrame:
    """Notebooks of which a share ``theta`` or more lies in a template's groups: ``(nb_id, template)``."""
    of = counts.join(templates, F.col("nb_id") == F.col("template"), "left_semi").select(F.col("nb_id").alias("template"), "h")
    own = counts.groupBy("nb_id").agg(F.sum("n").alias("own"))
    shared = counts.join(of, "h").where("nb_id > template").groupBy("nb_id", "template").agg(F.sum("n").alias("shared"))
    return shared.join(own, "nb_id").where(F.col("shared") >= theta * F.col("own")).select("nb_id", "template")


def template_uses(templates: DataFrame, counts: DataFrame) -> DataFrame:
    """``(nb_id, cells, found, documents)`` of each template: its cells, those that the corpus holds, and the notebooks that hold any."""
    cells = templates.select("nb_id", "pos", "h")
    own = cells.groupBy("nb_id").agg(F.count("*").alias("cells"))
    found = cells.join(counts.select("h").distinct(), "h", "left_semi").groupBy("nb_id").agg(F.count("*").alias("found"))
    uses = cells.select("nb_id", "h").distinct().join(counts.select("h", F.col("nb_id").alias("other")), "h").select("nb_id", "other").distinct().groupBy("nb_id").agg(F.count("*").alias("documents"))
    return own.join(found, "nb_id", "left").join(uses, "nb_id", "left").na.fill(0, ["found", "documents"])


def headline(notebooks: DataFrame, cells: DataFrame) -> DataFrame:
    """One wide row with the headline numbers."""
    ne = cmw.non_empty(cells)
    f = frequency.per_notebook(notebooks, cmw.flags(ne)).agg(F.avg("freq").alias("mean_freq"), F.percentile("freq", 0.5).alias("median_freq"))
    e = connections.per_notebook(notebooks, cmw.counts(ne)).agg(F.avg("edge").alias("mean_edge"))
    return cells.agg(F.count("*").alias("cells")).crossJoin(cmw.totals(ne)).crossJoin(f).crossJoin(e)  # one row each
