"""Joins that a plain equi-join does not express: as-of and within a gap."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, at: str, value: str) -> DataFrame:
    """left with the last `value` of right at or before its time, for equal `by`: a union and one window, no pairs."""
    a = left.withColumns({"__v": F.lit(None).cast(right.schema[value].dataType), "__side": F.lit(1)})
    b = right.select(F.col(by), F.col(at), F.col(value).alias("__v"), F.lit(0).alias("__side"))
    order = W.partitionBy(by).orderBy(at, "__side", "__v").rowsBetween(W.unboundedPreceding, W.currentRow)
    both = a.unionByName(b, allowMissingColumns=True)
    return both.withColumn(value, F.last("__v", ignorenulls=True).over(order)).where("__side = 1").drop("__v", "__side")


def gap_join(left: DataFrame, right: DataFrame, a: str, b: str, gap: int) -> DataFrame:
    """Pairs of rows with 0 <= right.b - left.a <= gap (numbers): equal or neighbouring buckets of width gap, then the test."""
    x = left.withColumn("__k", F.floor(F.col(a) / (gap + 1)))
    y = right.select("*", F.explode(F.array(F.floor(F.col(b) / (gap + 1)), F.floor(F.col(b) / (gap + 1)) - 1)).alias("__k"))
    return x.join(y, "__k").where((F.col(b) - F.col(a)).between(0, gap)).drop("__k")
