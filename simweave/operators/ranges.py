"""Joins that Spark has no operator for: ranges by bins, and the latest earlier row."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def range_join(points: DataFrame, value: str, ranges: DataFrame, low: str, high: str, bin_width: float) -> DataFrame:
    """Rows of points whose value is in [low, high) of a row of ranges: an equi-join on bins, then the exact test."""
    bins = ranges.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(low) / bin_width), F.floor(F.col(high) / bin_width))))
    found = points.withColumn("__bin", F.floor(F.col(value) / bin_width)).join(bins, "__bin").drop("__bin")
    return found.where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high)))


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, picked: list[str]) -> DataFrame:
    """Each left row with the right row of its key that is latest at or before it (picked columns, null if none).

    Both sides are one union, sorted once by key and time; no pair is made. Right rows at the same time count as earlier.
    """
    blank = [F.lit(None).cast(right.schema[c].dataType).alias(c) for c in picked]
    own = [c for c in left.columns if c not in (key, at)]
    a = left.select(F.col(key), F.col(at), F.lit(1).alias("__side"), *own, *blank)
    b = right.select(F.col(key), F.col(at), F.lit(0).alias("__side"), *(F.lit(None).cast(left.schema[c].dataType).alias(c) for c in own), *picked)
    order = Window.partitionBy(key).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b)
    for c in picked:
        both = both.withColumn(c, F.last(c, ignorenulls=True).over(order))
    return both.where("__side = 1").drop("__side")


def skew_report(df: DataFrame, *keys: str, top: int = 10) -> DataFrame:
    """The most frequent key values and their share of all rows."""
    counts = df.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"))
    total = counts.agg(F.sum("n").alias("total"))
    return counts.join(F.broadcast(total)).withColumn("share", F.col("n") / F.col("total")).orderBy(F.col("n").desc(), *keys).limit(top).drop("total")


