"""Writers of results and of the loop's input layout."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_assignment(clusters: DataFrame, path: str) -> None:
    """Clusters as Parquet, a folder per stage."""
    clusters.write.mode("overwrite").partitionBy("stage").parquet(path)


def write_bucketed(edges: DataFrame, table: str, buckets: int, path: str | None = None) -> DataFrame:
    """Edges as a table in buckets of ``src``, one sorted file each; joins with a state of as many partitions read them in place.

    ``path``: where its files go (default: the warehouse)."""
    out = edges.repartition(buckets, "src").write.mode("overwrite").bucketBy(buckets, "src").sortBy("src")
    (out.option("path", path) if path else out).saveAsTable(table)
    return edges.sparkSession.table(table)


def append_metrics(rows: DataFrame, path: str, kind: str = "parquet") -> None:
    rows.write.mode("append").format(kind).save(path)


def to_csv(rows: DataFrame, path: str) -> None:
    rows.write.mode("overwrite").csv(path, header=True)


def time_only(rows: DataFrame) -> None:
    """Computes every row and keeps none."""
    rows.write.format("noop").mode("overwrite").save()
