"""A key that tells the rows of a table apart, whatever its identifiers are."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearcohort.plans.runtime import Workspace, small


def fresh(name: str, taken) -> str:
    """``name``, or with underscores before it, so that no column is called like it."""
    low = {c.lower() for c in taken}
    while name.lower() in low:
        name = "_" + name
    return name


def keyed_rows(docs: DataFrame, work: Workspace, key: str = "doc_id") -> tuple[DataFrame, str, bool]:
    """(rows, column, whether ``key`` is unique): ``docs`` with a long column that no two rows share.

    If ``key`` is never null and never repeats, it serves itself and nothing is written.
    Otherwise the rows are written once, numbered, so that a repeated scan can't number them anew.
    """
    own = F.col(f"`{key}`").cast("long")
    odd = docs.select(own.alias("k")).groupBy("k").agg(F.count("*").alias("n")).where("n > 1 or k is null")
    name = fresh("row_key", docs.columns)
    if odd.isEmpty():
        return docs.withColumn(name, own), name, True
    return work.save(docs.withColumn(name, F.monotonically_increasing_id()), "numbered"), name, False


def without(docs: DataFrame, gone: DataFrame, column: str, columns) -> DataFrame:
    """``columns`` of the rows of ``docs`` whose ``column`` is not in ``gone`` (one column, saved)."""
    gone = gone.toDF(column)
    return docs.join(small(gone, gone.count()), column, "left_anti").select(*[f"`{c}`" for c in columns])
