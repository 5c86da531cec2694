"""Synthetic graphs of any size from ``spark.range`` or a table's keys and hashes, as canonical edges; also as a data source and table functions."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from spanweave.functions.hashing import SCALE, h32, h32_sql, joined
from spanweave.sources.fixtures import canonical, reweight, uniform_sql
from spanweave.sources.tables import read_table

#: Usual quadrant chances of the recursive power-law generator.
QUADRANTS = (0.57, 0.19, 0.19, 0.05)


def keys(spark: SparkSession, sf_dir: str, table: str, key: str) -> DataFrame:
    """A table's keys, which count from 0, as ``id``; spread over all cores, as a small file is read by one task and each key takes hashes or a call."""
    return read_table(spark, sf_dir, table).select(F.col(key).cast("long").alias("id")).repartition(spark.sparkContext.defaultParallelism)


def mesh(spark: SparkSession, side: int, weight: str = "uniform", cells: DataFrame | None = None) -> DataFrame:
    """side x side square mesh; weight: uniform, bimodal or unit. ``cells``: all ids below side^2 and maybe more (default: a range)."""
    cell = spark.range(side * side) if cells is None else cells.filter(F.col("id") < side * side)
    near = F.array_compact(F.array(F.when(F.col("id") % side < side - 1, F.col("id") + 1), F.when(F.col("id") < side * (side - 1), F.col("id") + side)))
    return reweight(cell.select(F.col("id").alias("src"), F.explode(near).alias("dst")), weight)


def mesh_bimodal(spark: SparkSession, side: int) -> DataFrame:
    return mesh(spark, side, "bimodal")


def power_law(spark: SparkSession, scale: int, edge_factor: int = 16, seed: int = 7, draws: DataFrame | None = None) -> DataFrame:
    """Recursive quadrants: 2^scale node ids, a draw per id of ``draws`` (default: edge_factor * 2^scale), uniform weights; loops and repeats are dropped."""
    a, b, c, _ = (int(q * SCALE) for q in QUADRANTS)
    # one hash a level: as nested columns each level would repeat those before it
    hashes = F.transform(F.sequence(F.lit(0), F.lit(scale - 1)), lambda level: h32(joined(seed, F.col("id"), level)))

    def deeper(at, x):
        down, right = x >= a + b, ((x >= a) & (x < a + b)) | (x >= a + b + c)
        return F.struct((at["src"] * 2 + down.cast("long")).alias("src"), (at["dst"] * 2 + right.cast("long")).alias("dst"))

    zero = F.lit(0).cast("long")
    draws = spark.range(edge_factor << scale) if draws is None else draws
    drawn = draws.select(F.aggregate(hashes, F.struct(zero.alias("src"), zero.alias("dst")), deeper).alias("e")).select("e.src", "e.dst", F.lit(1).cast("long").alias("w"))
    return reweight(canonical(drawn), "uniform")


def power_law_sql(scale: int, edge_factor: int = 16, seed: int = 7, draws: str | None = None) -> str:
    draws = draws or f"SELECT unnest(range({edge_factor << scale})) AS id"
    a, b, c, _ = (int(q * SCALE) for q in QUADRANTS)
    x = lambda level: h32_sql(f"'{seed}:' || id || ':{level}'")
    bit = lambda level, cond: f"CASE WHEN {cond.format(x=x(level))} THEN {1 << (scale - 1 - level)} ELSE 0 END"
    src = " + ".join(bit(k, f"{{x}} >= {a + b}") for k in range(scale))
    dst = " + ".join(bit(k, f"({{x}} BETWEEN {a} AND {a + b - 1}) OR {{x}} >= {a + b + c}") for k in range(scale))
    return f"""WITH e AS (SELECT ({src})::BIGINT AS a, ({dst})::BIGINT AS b FROM ({draws})),
p AS (SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM e WHERE a <> b) SELECT src, dst, {uniform_sql("src", "dst")}::BIGINT AS w FROM p"""


def path_product(spark: SparkSession, layers: int, base: DataFrame) -> DataFrame:
    """The product of a path of ``layers`` nodes with unit edges and a graph: node u in layer k is u * layers + k."""
    if layers < 1:
        raise ValueError("at least one layer")
    k = F.explode(F.sequence(F.lit(0), F.lit(layers - 1))).alias("k")
    inside = base.select("src", "dst", "w", k).select((F.col("src") * layers + F.col("k")).alias("src"), (F.col("dst") * layers + F.col("k")).alias("dst"), "w")
    if layers == 1:
        return inside
    nodes = base.select(F.col("src").alias("u")).union(base.select(F.col("dst").alias("u"))).distinct()
    step = F.explode(F.sequence(F.lit(0), F.lit(layers - 2))).alias("k")
    across = nodes.select("u", step).select((F.col("u") * layers + F.col("k")).alias("src"), (F.col("u") * layers + F.col("k") + 1).alias("dst"), F.lit(1).cast("long").alias("w"))
    return inside.unionByName(across.withColumn("w", F.col("w").cast(base.schema["w"].dataType)))


def hub_and_tail(spark: SparkSession, leaves: int, tail: int, ids: DataFrame | None = None) -> DataFrame:
    """A star of ``leaves`` around node 0 and a path of ``tail`` more nodes from it; unit weights. ``ids``: all below leaves + tail (default: a range)."""
    node = F.col("id") + 1
    return (spark.range(leaves + tail) if ids is None else ids).select(F.when(F.col("id") <= leaves, F.lit(0)).otherwise(F.col("id")).cast("long").alias("src"), node.alias("dst"), F.lit(1).cast("long").alias("w"))


def _uniform(u: int, v: int) -> int:
    return 1 + int(hashlib.md5(f"7:{min(u, v)}:{max(u, v)}".encode()).hexdigest()[:8], 16)


class GraphSource(DataSource):
    """``spark.read.format("diameter_graphs")``: option ``graph`` = mesh or star, ``size``, ``partitions``; rows src, dst, w."""

    @classmethod
    def name(cls) -> str:
        return "diameter_graphs"

    def schema(self) -> str:
        return "src bigint, dst bigint, w bigint"

    def reader(self, schema) -> DataSourceReader:
        return _GraphReader(self.options.get("graph", "mesh"), int(self.options.get("size", 16)), int(self.options.get("partitions", 4)))


class _Range(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class _GraphReader(DataSourceReader):
    def __init__(self, graph: str, size: int, partitions: int):
        if graph not in ("mesh", "star"):
            raise ValueError(f"unknown graph {graph!r}")
        self.graph, self.size, self.parts = graph, size, max(1, partitions)

    def partitions(self) -> list[_Range]:
        total = self.size**2 if self.graph == "mesh" else self.size
        step = -(-total // self.parts)
        return [_Range(a, min(total, a + step)) for a in range(0, total, step)] or [_Range(0, 0)]

    def read(self, partition: _Range) -> Iterator[tuple[int, int, int]]:
        for u in range(partition.start, partition.stop):
            if self.graph == "star":
                yield 0, u + 1, 1
                continue
            if u % self.size < self.size - 1:
                yield u, u + 1, _uniform(u, u + 1)
            if u + self.size < self.size**2:
                yield u, u + self.size, _uniform(u, u + self.size)


class GridNeighbours:
    """Table function: the right and the lower neighbour of a cell of a square grid."""

    def eval(self, id: int, side: int):
        if id % side < side - 1:
            yield (id + 1,)
        if id + side < side * side:
            yield (id + side,)


def register(spark: SparkSession) -> None:
    """The data source, and ``grid_neighbours(id, side)`` for SQL."""
    from pyspark.sql.functions import udtf

    spark.dataSource.register(GraphSource)
    spark.udtf.register("grid_neighbours", udtf(GridNeighbours, returnType="neighbour bigint"))
