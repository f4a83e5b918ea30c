"""Small helpers shared by the operators of this subpackage."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import re
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.components import release as release
from ..session import shared_dir, ship_package

#: The word definition shared by several contracts: maximal runs without ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
NOT_WORD = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship_package(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage: an eager reliable checkpoint in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def written(df: DataFrame, label: str) -> DataFrame:
    """Write to a fresh Parquet folder in the shared folder and read it back (compressed, columnar cut)."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/{re.sub('[^a-z0-9_]', '_', label)}_{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.parquet(path)


def named(column: str):
    """A column by its whole name, dots and backticks included."""
    return F.col("`" + column.replace("`", "``") + "`")


def in_order(df: DataFrame) -> DataFrame:
    """Columns named by their place: ``mapInArrow`` looks columns up by name, which fails for a dot."""
    return df.toDF(*(f"c{i}" for i in range(len(df.columns))))


def numbered(docs: DataFrame) -> tuple[DataFrame, str]:
    """``docs`` with a row number, written once, and the number's column: later reads see the same numbers whatever the input gives when evaluated again."""
    rid = fresh_name(docs, "rid")
    return written(docs.withColumn(rid, F.monotonically_increasing_id()), "numbered"), rid


def fresh_name(df: DataFrame, stem: str) -> str:
    """A column name that ``df`` doesn't have yet (input columns may clash with ours)."""
    name, taken = stem, {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


_HELD: dict = {}


def held(kind: str, key, make):
    """The one large object that a Python worker keeps between tasks.

    Workers are reused by whatever runs next; asking for another object lets the old one go and
    returns its memory, so that a chain of operators needs what its largest needs and not their sum.
    """
    if _HELD.get("name") != (kind, key):
        _HELD.clear()
        gc.collect()
        with contextlib.suppress(OSError, AttributeError):  # only glibc has it
            ctypes.CDLL(None).malloc_trim(0)
        _HELD.update(name=(kind, key), value=make())
    return _HELD["value"]


class TwoGenerations:
    """A bounded memo: lookups fall back to the previous generation, so frequent keys survive when a generation fills up."""

    def __init__(self, most: int):
        self.most, self.young, self.old = most, {}, {}

    def get(self, key):
        found = self.young.get(key)
        if found is None:
            found = self.old.get(key)
            if found is not None:
                self.put(key, found)
        return found

    def put(self, key, value) -> None:
        if len(self.young) >= self.most:
            self.young, self.old = {}, self.young
        self.young[key] = value
