"""Joins and rollups that the methods need and Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """Adds the last ``value`` of ``right`` at or before each row's time, by key: one shuffle and one pass, no range join."""
    l_, r_ = left.withColumn("_side", F.lit(1)).withColumn("_v", F.lit(None).cast(right.schema[value].dataType)), right.select(F.col(key), F.col(at), F.col(value).alias("_v")).withColumn("_side", F.lit(0))
    both = l_.unionByName(r_, allowMissingColumns=True)
    seen = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value, F.last("_v", ignorenulls=True).over(seen)).where("_side = 1").drop("_side", "_v")


def range_join(points: DataFrame, at: str, ranges: DataFrame, lo: str, hi: str, width: float) -> DataFrame:
    """Points in [lo, hi) by equi join on buckets of ``width``; each range goes to the buckets it touches."""
    p = points.withColumn("_b", F.floor(F.col(at) / width))
    r = ranges.withColumn("_b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return p.join(r, "_b").where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_b")


def _cells(item: Column, width: int, depth: int) -> Column:
    """The cell of an item in every row of a count-min sketch: eight hex digits of one digest for each row, so at most four rows."""
    digest = F.md5(item)
    return F.array(*[F.struct(F.lit(i).alias("row"), F.pmod(F.conv(F.substring(digest, 8 * i + 1, 8), 16, 10).cast("long"), F.lit(width)).alias("cell")) for i in range(depth)])


def count_min(df: DataFrame, item: Column, width: int = 4096, depth: int = 4) -> DataFrame:
    """(row, cell, n): a count-min sketch as a table of at most width * depth rows; sketches add up by (row, cell)."""
    t = df.select(item.alias("item")).where("item is not null").select(F.explode(_cells(F.col("item"), width, depth)).alias("c"))
    return t.groupBy("c.row", "c.cell").agg(F.count("*").alias("n"))


def count_min_estimates(items: DataFrame, item: str, sketch: DataFrame, width: int = 4096, depth: int = 4) -> DataFrame:
    """Adds estimate to distinct ``items``: never below the true count, above it by 2/width of all rows or more with chance 2^-depth."""
    t = items.select(item, F.explode(_cells(F.col(item), width, depth)).alias("c")).select(item, "c.row", "c.cell")
    t = t.join(F.broadcast(sketch), ["row", "cell"], "left").groupBy(item).agg(F.min(F.coalesce("n", F.lit(0))).alias("estimate"))  # width * depth rows at most
    return items.join(t, item)
