"""The sorting primitives of the round model, without a task that sees all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spanweave.session import stored


def mr_sort(df: DataFrame, *keys: str) -> DataFrame:
    """Rows in order, with their rank: ranges, each sorted, offset by the sizes of the ranges before."""
    return _ranked(df, keys, F.lit(1), "rank")


def prefix_sum(df: DataFrame, key: str | list[str], value: str, out: str = "prefix") -> DataFrame:
    """Running sums over all rows in the order of ``key`` (which must order them fully)."""
    return _ranked(df, [key] if isinstance(key, str) else key, F.col(value), out)


def _ranked(df: DataFrame, keys, value, out: str) -> DataFrame:
    ranges = stored(df.withColumn("_v", value).repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_at", F.monotonically_increasing_id()), "ranges")
    part = F.shiftright("_at", 33)
    sums = ranges.groupBy(part.alias("_part")).agg(F.sum("_v").alias("_s"))
    # a row per range: bounded by the number of partitions
    before = sums.select("_part", F.coalesce(F.sum("_s").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    inside = F.sum("_v").over(Window.partitionBy("_part").orderBy("_at").rowsBetween(Window.unboundedPreceding, 0))
    return ranges.withColumn("_part", part).withColumn("_in", inside).join(F.broadcast(before), "_part").withColumn(out, F.col("_in") + F.col("_before")).drop("_v", "_at", "_part", "_in", "_before")


def segmented_prefix_sum(df: DataFrame, segment: str, key: str | list[str], value: str, out: str = "prefix") -> DataFrame:
    """Running sums within segments in the order of ``key``."""
    keys = [key] if isinstance(key, str) else key
    return df.withColumn(out, F.sum(value).over(Window.partitionBy(segment).orderBy(*keys).rowsBetween(Window.unboundedPreceding, 0)))
