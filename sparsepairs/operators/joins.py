"""Joins that Spark lacks, as compositions of equi-joins and windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def band_join(left: DataFrame, right: DataFrame, left_at: str, right_at: str, before: int, after: int, on: list[str] | None = None) -> DataFrame:
    """Rows with ``left_at`` in [right_at - before, right_at + after], both long, by equal cells.

    Cells are as wide as the band, so a right row looks into two of them at
    most and the join stays an equi-join, which spreads over the cells.
    """
    width = max(1, before + after + 1)
    cell = lambda c: F.floor(c / width).cast("long")
    low, high = F.col(right_at) - before, F.col(right_at) + after
    l2 = left.withColumn("__cell", cell(F.col(left_at)))
    r2 = right.withColumn("__cell", F.explode(F.sequence(cell(low), cell(high))))
    keys = [*(on or []), "__cell"]
    return l2.join(r2, keys).where(F.col(left_at).between(low, high)).drop("__cell")


def asof_join(left: DataFrame, right: DataFrame, by: str, left_at: str, right_at: str, value: str) -> DataFrame:
    """Left rows with the ``value`` of the last right row at or before them: one sort, no pairs."""
    a = left.select("*", F.col(left_at).alias("__at"), F.lit(1).alias("__side"), F.lit(None).alias("__v").cast(right.schema[value].dataType))
    b = right.select(F.col(by), F.col(right_at).alias("__at"), F.lit(0).alias("__side"), F.col(value).alias("__v"))
    both = a.unionByName(b, allowMissingColumns=True)
    run = Window.partitionBy(by).orderBy("__at", "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    out = both.withColumn(value, F.last("__v", ignorenulls=True).over(run)).where("__side = 1")
    return out.select(*left.columns, value)


def cyclic_join(left: DataFrame, right: DataFrame, x: str, y: str, width: int, domain: int, on: list[str]) -> DataFrame:
    """Rows with (x - y) modulo ``domain`` below ``width``, both powers of two, by equal cells."""
    shift, cells = width.bit_length() - 1, domain // width
    own = F.shiftright(y, shift)
    l2 = left.withColumn("__cell", F.shiftright(x, shift))
    r2 = right.withColumn("__cell", F.explode(F.array_distinct(F.array(own, F.pmod(own + 1, F.lit(cells))))))
    return l2.join(r2, [*on, "__cell"]).where((F.col(x) - F.col(y)).bitwiseAND(F.lit(domain - 1)) < width).drop("__cell")


def keep_first(df: DataFrame, keys: list[str], order: list[Column | str]) -> DataFrame:
    """One row for each key: the first by the order."""
    rank = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    return df.withColumn("__i", rank).where("__i = 1").drop("__i")
