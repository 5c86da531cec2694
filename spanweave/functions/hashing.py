"""Hashes that Spark and DuckDB compute alike; draws made with them are the same when a task is retried."""

from __future__ import annotations

from hashlib import md5

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

#: Uniform weights are integers 1..SCALE and stand for multiples of 1 / SCALE.
SCALE = 1 << 32


def h32(text: Column) -> Column:
    """The first 32 bits of the md5 of a string, as a long."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def joined(*parts) -> Column:
    return F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])


def uniform_weight(u: Column, v: Column, seed: int = 7) -> Column:
    """1..2^32, by the smaller and the larger end."""
    return F.lit(1) + h32(joined(seed, F.least(u, v), F.greatest(u, v)))


def drawn(node: Column, probability: float, seed: int, stage: int, mode: str = "md5") -> Column:
    """Whether a node is drawn; ``xxhash64`` is the cheaper mode for very large graphs."""
    if mode == "xxhash64":
        return F.pmod(F.xxhash64(node, F.lit(seed), F.lit(stage)), F.lit(SCALE)) < F.lit(probability * SCALE)
    return h32(joined(seed, stage, node)) < F.lit(probability * SCALE)


def drawn_here(nodes: np.ndarray, probability: float, seed: int, stage: int) -> np.ndarray:
    """The same draw, by md5, of nodes in an array."""
    return hashes_here(nodes, f"{seed}:{stage}") < probability * SCALE


def hashes_here(nodes: np.ndarray, prefix: str) -> np.ndarray:
    """``h32`` of the prefix, a colon and the node."""
    hashes = (int(md5(f"{prefix}:{node}".encode()).hexdigest()[:8], 16) for node in nodes.tolist())
    return np.fromiter(hashes, np.int64, len(nodes))


def h32_sql(text: str) -> str:
    """The DuckDB form of ``h32``."""
    return f"(('0x' || substr(md5({text}), 1, 8))::BIGINT)"


def register_sql(spark: SparkSession) -> None:
    """``h32(string)`` and ``uniform_weight(u, v)`` as SQL functions of the session."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION h32(s STRING) RETURNS BIGINT RETURN CAST(conv(substring(md5(s), 1, 8), 16, 10) AS BIGINT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION uniform_weight(u BIGINT, v BIGINT) RETURNS BIGINT RETURN 1 + h32(concat_ws(':', '7', least(u, v), greatest(u, v)))")
