"""Joins, windows and reports that the graph methods and their users need and Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def range_join(a: DataFrame, b: DataFrame, a_key: str, b_key: str, reach: int) -> DataFrame:
    """Pairs of rows with |a_key - b_key| <= reach (whole numbers): both sides in buckets as wide as the reach, b in three of them."""
    left = a.withColumn("_b", F.floor(F.col(a_key) / reach))
    right = b.withColumn("_b", F.explode(F.array(*[F.floor(F.col(b_key) / reach) + k for k in (-1, 0, 1)])))
    return left.join(right, "_b").filter(F.abs(F.col(a_key) - F.col(b_key)) <= reach).drop("_b")


def interval_join(points: DataFrame, spans: DataFrame, at: str, low: str, high: str, width: int) -> DataFrame:
    """Points with low <= at <= high (whole numbers): spans are listed under every bucket of ``width`` that they touch."""
    left = points.withColumn("_b", F.floor(F.col(at) / width))
    right = spans.withColumn("_b", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return left.join(right, "_b").filter(F.col(at).between(F.col(low), F.col(high))).drop("_b")


def as_of(a: DataFrame, b: DataFrame, key: str, at: str, value: str, out: str) -> DataFrame:
    """Each row of a with the latest ``value`` of b at or before it under the same key: one union and one window."""
    left = a.select("*", F.lit(None).cast(b.schema[value].dataType).alias(out), F.lit(1).alias("_side"))
    right = b.select(key, at, F.col(value).alias(out), F.lit(0).alias("_side"))
    both = left.unionByName(right, allowMissingColumns=True)
    win = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(out, F.last(out, ignorenulls=True).over(win)).filter("_side = 1").drop("_side")


def sessions(events: DataFrame, user: str, at: str, gap_seconds: int) -> DataFrame:
    """(user, session, started, ended, events): runs of events less than a gap apart."""
    win = Window.partitionBy(user).orderBy(at)
    t = F.unix_timestamp(at)
    new = F.when(t - F.lag(t).over(win) < gap_seconds, 0).otherwise(1)
    numbered = events.withColumn("_new", new).withColumn("session", F.sum("_new").over(win.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy(user, "session").agg(F.min(at).alias("started"), F.max(at).alias("ended"), F.count(F.lit(1)).alias("events"))


def top_per_group(df: DataFrame, group: str, order: list, k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(group).orderBy(*order))).filter(F.col("rank") <= k)


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Nodes whose center differs between two assignments, or that only one has."""
    x, y = a.select("node", F.col("center").alias("left_center")), b.select("node", F.col("center").alias("right_center"))
    return x.join(y, "node", "full_outer").filter(~F.col("left_center").eqNullSafe(F.col("right_center")))


def work_rollup(steps: DataFrame) -> DataFrame:
    """Steps, messages and updates by phase and stage with subtotals."""
    return steps.rollup("phase", "stage").agg(F.count(F.lit(1)).alias("steps"), F.sum("messages").alias("messages"), F.sum("updates").alias("updates"))


def comparison_table(results: DataFrame, measure: str) -> DataFrame:
    """One row per graph, one column per method."""
    return results.groupBy("graph").pivot("method").agg(F.first(measure))


def with_salt(df: DataFrame, hot: DataFrame, key: str, ways: int) -> DataFrame:
    """Adds ``_salt``: spread over ``ways`` for keys listed in ``hot`` (a table of few keys), else 0.

    A partial result per (key, _salt) is combined by key afterwards."""
    few = F.broadcast(hot.select(F.col(key).alias("_hot")))
    spread = F.pmod(F.xxhash64(*[c for c in df.columns if c != key]), F.lit(ways))
    salted = df.join(few, F.col(key) == F.col("_hot"), "left")
    return salted.withColumn("_salt", F.when(F.col("_hot").isNull(), F.lit(0)).otherwise(spread)).drop("_hot")
