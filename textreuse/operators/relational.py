"""Joins and windows that Spark has no single operator for, each without a product of its sides."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, values: list[str]) -> DataFrame:
    """For each left row the values of the latest right row of the same key at or before its time.

    Both sides are unioned and carried forward in a window: one shuffle by key, no inequality join. On equal times the
    right row counts as before; of right rows with equal times the one of the largest values holds.
    """
    pack = F.struct(*values)
    l = left.withColumns({"_side": F.lit(1), "_v": F.lit(None).cast(right.select(pack.alias("x")).schema["x"].dataType)})  # noqa: E741
    r = right.select(by, at, *(F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in (by, at)), F.lit(0).alias("_side"), pack.alias("_v"))
    carried = Window.partitionBy(by).orderBy(at, "_side", "_v").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = l.unionByName(r).withColumn("_last", F.last("_v", ignorenulls=True).over(carried)).where("_side = 1")
    return rows.select(*left.columns, *(F.col(f"_last.{v}").alias(v) for v in values))


def interval_join(a: DataFrame, b: DataFrame, keys: list[str], a_span: tuple[str, str], b_span: tuple[str, str], width: int) -> DataFrame:
    """Rows of equal keys whose half-open spans overlap: both are binned, and a pair meets in the bin where the later one begins."""
    bins = lambda s: F.sequence(F.floor(F.col(s[0]) / width), F.floor((F.col(s[1]) - 1) / width))
    x, y = a.withColumn("_bin", F.explode(bins(a_span))), b.withColumn("_bin", F.explode(bins(b_span)))
    overlap = (F.col(a_span[0]) < F.col(b_span[1])) & (F.col(b_span[0]) < F.col(a_span[1]))
    first = F.floor(F.greatest(F.col(a_span[0]), F.col(b_span[0])) / width) == F.col("_bin")
    return x.join(y, [*keys, "_bin"]).where(overlap & first).drop("_bin")


def top_per_group(df: DataFrame, group: str, order: list[Column], k: int) -> DataFrame:
    """The first k rows of each group; Spark limits groups before it shuffles."""
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(group).orderBy(*order))).where(F.col("rank") <= k)
