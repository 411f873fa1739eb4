"""What queries over graphs and their events need besides: joins to the last row before a time, dense numbers without a global sort."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: Sequence[str], time: str, values: Sequence[str], prefix: str = "last_") -> DataFrame:
    """left, and for each row the values (and time) of the last row of right, of the same `by`, at its time or before; null if there is none.

    Both sides go through one exchange by `by` and one sort; no pairs are made. Of rows of right at one time, the
    greatest values count.
    """
    names = left.columns
    a = left.select(*by, F.col(time).alias("_t"), F.lit(1).alias("_side"), F.struct(*names).alias("_row"), F.lit(None).alias("_v"))
    value = F.struct(F.col(time).alias(f"{prefix}{time}"), *(F.col(v).alias(f"{prefix}{v}") for v in values))
    b = right.select(*by, F.col(time).alias("_t"), F.lit(0).alias("_side"), F.lit(None).alias("_row"), value.alias("_v"))
    before = Window.partitionBy(*by).orderBy("_t", "_side", "_v").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn("_last", F.last("_v", True).over(before)).where("_side = 1").select("_row.*", "_last.*")


def numbered(df: DataFrame, by: Sequence[str], name: str = "number", parts: int = 64) -> DataFrame:
    """df with dense numbers from 0 in the order of `by` (without repeats), in two levels: within ranges, and from the ranges' counts, of which there are `parts` at most. No row goes through a global sort."""
    ranged = df.repartitionByRange(parts, *by).withColumn("_part", F.spark_partition_id())
    inside = Window.partitionBy("_part").orderBy(*by)
    placed = ranged.withColumn("_place", F.row_number().over(inside) - 1)
    counts = placed.groupBy("_part").agg(F.count("*").alias("_n"), F.min(F.struct(*by)).alias("_first"))
    starts = counts.withColumn("_start", F.coalesce(F.sum("_n").over(Window.orderBy("_first").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("_part", "_start")
    return placed.join(F.broadcast(starts), "_part").withColumn(name, F.col("_start") + F.col("_place")).drop("_part", "_place", "_start")
