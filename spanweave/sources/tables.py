"""Readers of the given tables and of edge lists, with fixed schemas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "src LONG, dst LONG, w LONG"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edge_csv(spark: SparkSession, path: str, sep: str = ",", schema: str = EDGE_SCHEMA, comment: str = "#") -> DataFrame:
    return spark.read.schema(schema).csv(path, sep=sep, comment=comment)


def read_edge_text(spark: SparkSession, path: str, comment: str = "#") -> DataFrame:
    """White-space separated ``u v [w]`` lines; a missing weight is 1."""
    cells = F.split(F.trim("value"), r"\s+")
    lines = spark.read.text(path).filter((F.trim("value") != "") & ~F.startswith(F.trim("value"), F.lit(comment)))
    return lines.select(F.get(cells, 0).cast("long").alias("src"), F.get(cells, 1).cast("long").alias("dst"), F.coalesce(F.get(cells, 2).cast("long"), F.lit(1)).alias("w"))


def read_edge_json(spark: SparkSession, path: str, schema: str = EDGE_SCHEMA) -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_edge_orc(spark: SparkSession, path: str, schema: str = EDGE_SCHEMA) -> DataFrame:
    return spark.read.schema(schema).orc(path)


def edges_from_catalog(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name).select("src", "dst", "w")


def edge_stream(spark: SparkSession, folder: str, schema: str) -> DataFrame:
    return spark.readStream.schema(schema).parquet(folder)
