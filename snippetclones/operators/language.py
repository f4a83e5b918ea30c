"""Language identification of notebooks from up to four places, folded into groups."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: The language groups and how values fold into them.
PREFIXES = {"PYTHON": ("python", "Python"), "SCALA": ("scala", "Scala")}
EQUALS = {"JULIA": ("julia", "Julia"), "R": ("r", "R")}


def places(parsed: DataFrame) -> DataFrame:
    """``(nb_id, f1, f2, f3, f4, mixed)``: the three metadata places and the cells' common language (null where cells disagree)."""
    langs = F.array_distinct(F.transform(F.filter("n.cells", lambda c: c["cell_type"] == "code"), lambda c: c["language"]))
    f4 = F.when(F.size(langs) == 1, langs[0])
    return parsed.where("readable").select("nb_id", F.col("n.metadata.language_info.name").alias("f1"), F.col("n.metadata.language").alias("f2"), F.col("n.metadata.kernelspec.language").alias("f3"), f4.alias("f4"), (F.size(langs) > 1).alias("mixed"))


def identify(found: DataFrame, fields: int = 4) -> DataFrame:
    """First filled place wins: ``(nb_id, lang_raw, field_used)``, 0 where none."""
    names = [f"f{i}" for i in range(1, fields + 1)]
    used = F.lit(0)
    for i in reversed(range(1, fields + 1)):
        used = F.when(F.col(f"f{i}").isNotNull(), F.lit(i)).otherwise(used)
    return found.select("nb_id", (F.coalesce(*names) if fields > 1 else F.col("f1")).alias("lang_raw"), used.alias("field_used"))


def to_group(lang):
    out = F.when(lang.isNull(), "UNDEFINED")
    for g, starts in PREFIXES.items():
        for s in starts:
            out = out.when(lang.startswith(s), g)
    for g, values in EQUALS.items():
        out = out.when(lang.isin(list(values)), g)
    return out.otherwise("OTHER")


def distribution(groups: DataFrame, group: str = "lang_group") -> DataFrame:
    g = groups.groupBy(group).agg(F.count("*").alias("notebooks"))
    return g.withColumn("pct", 100.0 * F.col("notebooks") / F.sum("notebooks").over(Window.partitionBy()))


def conflicts(found: DataFrame) -> DataFrame:
    """Notebooks whose filled places disagree, or whose cells name several languages."""
    values = F.array_distinct(F.filter(F.array("f1", "f2", "f3", "f4"), lambda x: x.isNotNull()))
    return found.where((F.size(values) > 1) | F.col("mixed")).select("nb_id", F.array_join(values, ",").alias("places"), "mixed")


def compare_methods(found: DataFrame) -> DataFrame:
    """Unidentified share of the one-, two- and four-place methods, in one pass."""
    filled = lambda k: F.avg(F.coalesce(*[F.col(f"f{i}") for i in range(1, k + 1)], F.lit(None)).isNull().cast("double"))
    one = found.agg(F.array(*[F.struct(F.lit(k).alias("fields"), filled(k).alias("unidentified")) for k in (1, 2, 4)]).alias("a"))
    return one.select(F.explode("a").alias("x")).select("x.*")
