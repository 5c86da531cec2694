"""Weighted graphs as DataFrames: validation, symmetrising, ids, degrees, subgraphs."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanweave.operators.components import connected_components
from spanweave.plans.arrays import Arrays, frame
from spanweave.session import Stored, delete_path, shared_dir, stored
from spanweave.sources.fixtures import canonical
from spanweave.sources.sinks import write_bucketed

#: A node is a hub if it has more edges than this and than ``HUB_SHARE`` of what an edge partition holds on average.
HUB_EDGES, HUB_SHARE = 200_000, 0.5
#: Up to so many undirected edges the queries run supersteps in arrays; beyond, and by default, as jobs.
ARRAY_EDGES = 50_000_000
#: A graph gets more buckets than the session has shuffle partitions where they would hold more directed edges than this: a
#: step keeps the rows of a bucket's nodes in a hash table, which can't spill.
BUCKET_EDGES = 1_000_000
#: Sums of whole weights stay below this, so that sums of distances fit 64 bits.
MOST = 2**61
WEIGHTS = ("byte", "short", "integer", "long", "float", "double")


@dataclass
class WeightedGraph:
    """Edges src, dst, w (light test and growth) and pw (weight on paths), both directions; ``nodes``: node; n nodes.

    ``near``: edges in ``partitions`` buckets of ``src``, read in place by a state with as many partitions.
    ``hub_edges``: those out of the few nodes of ``hubs`` (hub), spread evenly; null where there is no hub.
    ``small``: supersteps run in arrays on the driver, as the number of edges was checked; then there are no buckets and
    no hubs apart. ``array_parts``: by so many threads, each for a range of nodes."""

    near: DataFrame
    nodes: DataFrame
    n: int
    scale: float = 1.0
    partitions: int | None = None
    hubs: DataFrame | None = None
    hub_edges: DataFrame | None = None
    table: str | None = None
    small: bool = False
    array_parts: int = 1
    _arrays: Arrays | None = field(default=None, init=False, repr=False)

    @property
    def spark(self):
        return self.near.sparkSession

    @property
    def edges(self) -> DataFrame:
        return self.near if self.hub_edges is None else self.near.unionByName(self.hub_edges)

    @property
    def arrays(self) -> Arrays | None:
        """The graph in arrays if it is small, fetched once."""
        if self.small and self._arrays is None:
            self._arrays = Arrays.of(self.edges, self.nodes)
        return self._arrays

    def dealt(self, parts: int) -> WeightedGraph:
        """The same graph in arrays with so many parts."""
        out = replace(self, array_parts=parts)
        out._arrays = self.arrays
        return out

    def canonical(self) -> DataFrame:
        return self.edges.filter("src < dst")

    def mapped(self, change: Callable[[DataFrame], DataFrame]) -> WeightedGraph:
        """The same layout after a change of each edge part that leaves ``src`` alone."""
        return replace(self, near=change(self.near), hub_edges=None if self.hub_edges is None else change(self.hub_edges))

    def along(self, senders: DataFrame, keep: Column | str | None = None, key: str = "node") -> DataFrame:
        """``senders`` joined with their edges (of those that ``keep``): edges stay where they are.

        The buckets of ``src`` meet a state that is dealt alike, so nothing is exchanged. Hubs are few (their number is
        bounded by ``partitions / HUB_SHARE``): their rows are broadcast to their evenly spread edges."""
        part = lambda e: e if keep is None else e.where(keep)
        out = senders.hint("shuffle_hash").join(part(self.near), F.expr(f"{key} = src"))
        if self.hubs is None:
            return out
        few = senders.join(F.broadcast(self.hubs), F.expr(f"{key} = hub"), "left_semi")
        far = part(self.hub_edges).join(F.broadcast(few), F.expr(f"src = {key}"))
        return out.unionByName(far.select(*out.columns))

    def release(self) -> None:
        """Drops the bucketed table and its files."""
        if self.table:
            self.spark.sql(f"DROP TABLE IF EXISTS {self.table}")
            delete_path(self.spark, f"{shared_dir(self.spark)}/{self.table}")


def symmetrize(edges: DataFrame) -> DataFrame:
    """Both directions of every edge, least weight of duplicates, no loops."""
    return _both(canonical(edges))


def _both(one: DataFrame) -> DataFrame:
    return one.unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))


def _faults() -> tuple[Column, Column]:
    """Whether a row is bad, whether it is a loop."""
    w = F.col("w")
    unfit = w.isNull() | F.isnan(w.cast("double")) | (w <= 0) | (F.abs(w.cast("double")) == float("inf"))
    return F.col("src").isNull() | F.col("dst").isNull() | unfit, F.col("src") == F.col("dst")


def _pairs(edges: DataFrame) -> DataFrame:
    """For each pair src <= dst the least weight, the number of rows, of bad ones and of loops, and the largest weight."""
    bad, loop = _faults()
    return edges.groupBy(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(
        F.min("w").alias("w"), F.count(F.lit(1)).alias("n"), F.sum(bad.cast("long")).alias("bad"),
        F.sum(loop.cast("long")).alias("loops"), F.max(F.col("w").cast("double")).alias("most"),
    )


def _counts(pairs: DataFrame, *more: Column) -> DataFrame:
    total = lambda c: F.coalesce(F.sum(c), F.lit(0))
    return pairs.agg(
        total("n").alias("rows"), total("bad").alias("bad"), total("loops").alias("loops"),
        total(F.col("n") - 1).alias("duplicates"), F.max("most").alias("w_max"), *more,
    )


def validate(edges: DataFrame) -> DataFrame:
    """One row of counts: bad (null end, null, NaN, infinite or non-positive weight), loops, duplicates, rows; raises nothing."""
    return _counts(_pairs(edges))


def build(
    edges: DataFrame, nodes: DataFrame | None = None, *, scale: float = 1.0, partitions: int | None = None,
    growth_weight: str = "w", hub_edges: int | None = None, array_edges: int = 0,
) -> WeightedGraph:
    """Checks the weights, drops loops, keeps the least of parallel edges and writes both directions in buckets of ``src`` once.

    ``growth_weight``: ``w``, or ``unit`` to grow by hops while paths keep their weights. ``hub_edges``: from how many
    edges on a node is a hub (default: ``HUB_EDGES`` and ``HUB_SHARE`` of an average partition). ``array_edges``: up to how
    many undirected edges supersteps run in arrays."""
    spark = edges.sparkSession
    kind = edges.schema["w"].dataType.typeName()
    if array_edges and nodes is None and kind in WEIGHTS:
        # rows are few enough for the driver: parallel edges are found there, not by another exchange
        rows = Stored(edges.select("src", "dst", "w"), "rows")
        checked = _checked(rows)
        if checked["rows"] - checked["loops"] <= array_edges:
            return _in_arrays(rows.df, checked, kind, scale, partitions, growth_weight)
        edges = rows.df
    # the edges are computed once: what is checked is what is kept
    pairs = Stored(_pairs(edges), "edges")
    checked = _counts(pairs.df, F.count_if(F.col("a") != F.col("b")).alias("edges")).first()
    if checked["bad"]:
        pairs.drop()
        raise ValueError(f"{checked['bad']} of {checked['rows']} edges have a null end or a weight that is not positive and finite")
    if kind not in WEIGHTS:
        raise ValueError(f"weights must be whole or double, not {kind}")
    p = partitions or max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-2 * checked["rows"] // BUCKET_EDGES))
    w = F.col("w").cast("double" if kind in ("float", "double") else "long")
    one = pairs.df.filter("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst"), w.alias("w"))
    small = bool(array_edges) and checked["edges"] <= array_edges
    grow = F.lit(1).cast("long") if growth_weight == "unit" else F.col("w")
    both = _both(one).select("src", "dst", grow.alias("w"), F.col("w").alias("pw"))
    most = hub_edges if hub_edges is not None else max(HUB_EDGES, int(HUB_SHARE * 2 * checked["rows"] / p))
    hubs = far = table = None
    found = degrees(both).filter(F.col("degree") > most).select(F.col("node").alias("hub"))
    if checked["rows"] > most and not small:
        hubs = stored(found, "hubs")
        if hubs.isEmpty():
            hubs = None
        else:
            out = F.col("src") == F.col("hub")
            far = stored(both.join(F.broadcast(hubs), out, "left_semi").repartition(p, "dst"), "hub_edges")
            both = both.join(F.broadcast(hubs), out, "left_anti")
    near = both
    if not small:
        table = f"edges_{uuid.uuid4().hex}"
        near = write_bucketed(both, table, p, f"{shared_dir(spark)}/{table}")
    node = one.select(F.col("src").alias("node")).union(one.select("dst"))
    node = (node if nodes is None else node.unionByName(nodes.select("node"))).distinct()
    held = stored(node, "nodes")
    n = held.count()
    _check_sums(kind, n, checked["w_max"])
    return WeightedGraph(near, held, n, scale, p, hubs, far, table, small)


def _check_sums(kind: str, n: int, w_max) -> None:
    if kind not in ("float", "double") and n * float(w_max or 0) >= MOST:
        raise ValueError("sums of weights may overflow 64 bits: use double weights or a coarser scale")


def _checked(rows: Stored) -> dict:
    """Counts of stored rows, parallel ones among them, and the bounds of their columns; raises if there are bad ones."""
    bad, loop = _faults()
    ends = [f(F.col(c).cast("double")).alias(f"{k}_{c}") for c in ("src", "dst", "w") for k, f in (("low", F.min), ("high", F.max))]
    got = rows.df.agg(F.count(F.lit(1)).alias("rows"), F.count_if(bad).alias("bad"), F.count_if(loop).alias("loops"), *ends).first()
    if got["bad"]:
        rows.drop()
        raise ValueError(f"{got['bad']} of {got['rows']} edges have a null end or a weight that is not positive and finite")
    return got.asDict()


def _in_arrays(rows: DataFrame, checked: dict, kind: str, scale: float, partitions: int | None, growth_weight: str) -> WeightedGraph:
    """The graph of checked rows (src, dst, w) in arrays."""
    spark = rows.sparkSession
    w = F.col("w").cast("double" if kind in ("float", "double") else "long")
    one = rows.filter("src <> dst").select(F.least("src", "dst").cast("long").alias("src"), F.greatest("src", "dst").cast("long").alias("dst"), w.alias("w"))
    # what fits 32 bits travels so
    fits = lambda *cs: all(-(2**31) <= checked[f"low_{c}"] and checked[f"high_{c}"] < 2**31 for c in cs)
    some = checked["rows"] > 0
    ids = "int" if some and fits("src", "dst") else "long"
    weight = "int" if some and kind not in ("float", "double") and fits("w") else one.schema["w"].dataType.simpleString()
    arrays = Arrays.of(one.select(F.col("src").cast(ids).alias("src"), F.col("dst").cast(ids).alias("dst"), F.col("w").cast(weight).alias("w")), None, checked["rows"])
    if len(arrays.to) < 2 * (checked["rows"] - checked["loops"]):
        one = one.groupBy("src", "dst").agg(F.min("w").alias("w"))
    _check_sums(kind, len(arrays), checked["high_w"])
    grow = F.lit(1).cast("long") if growth_weight == "unit" else F.col("w")
    if growth_weight == "unit":
        arrays = replace(arrays, w=np.ones(len(arrays.w), np.int32))
    both = _both(one).select("src", "dst", grow.alias("w"), F.col("w").alias("pw"))
    held = frame(spark, {"node": pa.array(arrays.ids, pa.int64())}, "node long")
    p = partitions or max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-2 * checked["rows"] // BUCKET_EDGES))
    out = WeightedGraph(both, held, len(arrays), scale, p, small=True)
    out._arrays = arrays
    return out


def plain(edges: DataFrame, nodes: DataFrame, n: int) -> WeightedGraph:
    """Edges (src, dst, w, pw) as they are, without a layout."""
    return WeightedGraph(edges, nodes, n, partitions=int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def light(edges: DataFrame, delta) -> DataFrame:
    return edges.filter(F.col("w") <= F.lit(delta))


def heavy(edges: DataFrame, delta) -> DataFrame:
    return edges.filter(F.col("w") > F.lit(delta))


def weight_between(edges: DataFrame, low, high) -> DataFrame:
    return edges.filter(F.col("w").between(low, high))


def encode_ids(values: DataFrame, column: str) -> DataFrame:
    """(column, id): dense ids in sorted order, by range partitions and their sizes; the values must be distinct."""
    ordered = values.select(column).repartitionByRange(column).sortWithinPartitions(column)
    kept = stored(ordered.withColumn("at", F.monotonically_increasing_id()), "ids")
    part = F.shiftright("at", 33)
    sizes = kept.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n"))
    # a row per range: the window's single task is bounded by the number of partitions
    earlier = F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    before = sizes.select("part", F.coalesce(earlier, F.lit(0)).alias("before"))
    placed = kept.withColumn("part", part).join(F.broadcast(before), "part")
    return placed.select(column, (F.col("before") + F.col("at").bitwiseAND((1 << 33) - 1)).alias("id"))


def degrees(edges_both: DataFrame) -> DataFrame:
    return edges_both.groupBy(F.col("src").alias("node")).agg(F.count(F.lit(1)).alias("degree"))


def degree_histogram(edges_both: DataFrame) -> DataFrame:
    return degrees(edges_both).groupBy("degree").agg(F.count(F.lit(1)).alias("nodes"))


def degree_profile(edges_both: DataFrame) -> DataFrame:
    d = F.col("degree").cast("double")
    return degrees(edges_both).agg(
        F.avg(d).alias("mean"), F.stddev_pop(d).alias("deviation"), F.max("degree").alias("most"), F.skewness(d).alias("skewness")
    )


def subgraph(edges: DataFrame, keep: DataFrame) -> DataFrame:
    """Edges with both ends among ``keep`` (node)."""
    a = keep.select(F.col("node").alias("_a"))
    b = keep.select(F.col("node").alias("_b"))
    return edges.join(a, F.col("src") == F.col("_a"), "left_semi").join(b, F.col("dst") == F.col("_b"), "left_semi")


def components(edges: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """(node, component); nodes without edges are components of their own."""
    found = connected_components(edges, "src", "dst")
    if nodes is None:
        return found
    alone = nodes.join(found.select("node"), "node", "left_anti").select("node", F.col("node").alias("component"))
    return found.unionByName(alone)


def largest_component(edges: DataFrame) -> DataFrame:
    parts = stored(components(edges), "parts")
    top = parts.groupBy("component").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "component").limit(1).select("component")
    return subgraph(edges, parts.join(F.broadcast(top), "component").select("node"))


def two_hop(edges: DataFrame, delta) -> DataFrame:
    """Least two-edge ways of weight up to delta between different nodes."""
    one = edges.select("src", F.col("dst").alias("mid"), F.col("w").alias("w1"))
    two = edges.select(F.col("src").alias("mid"), "dst", F.col("w").alias("w2"))
    way = F.col("w1") + F.col("w2")
    ways = one.join(two, "mid").filter((F.col("src") != F.col("dst")) & (way <= delta))
    return ways.groupBy("src", "dst").agg(F.min(way).alias("w"))


def two_hop_rows(edges: DataFrame) -> int:
    """How many two-edge ways there are, without listing them: the sum over nodes of arrivals times departures."""
    ins = edges.groupBy(F.col("dst").alias("mid")).agg(F.count(F.lit(1)).alias("i"))
    outs = edges.groupBy(F.col("src").alias("mid")).agg(F.count(F.lit(1)).alias("o"))
    return ins.join(outs, "mid").agg(F.sum(F.col("i") * F.col("o")).alias("n")).first()["n"] or 0


def add_shortcuts(edges: DataFrame, delta, *, max_rows: int | None, rounds: int = 32) -> DataFrame:
    """Edges plus one for every pair at distance up to delta; their number can be quadratic.

    Raises before anything is joined if a round would list more than ``max_rows`` two-edge ways (null: no bound)."""
    now = Stored(edges.select("src", "dst", "w"), "shortcuts")
    for _ in range(rounds):
        ways = 0 if max_rows is None else two_hop_rows(light(now.df, delta))
        if max_rows is not None and ways > max_rows:
            now.drop()
            raise ValueError(f"{ways} two-edge ways, more than {max_rows}")
        both = now.df.unionByName(two_hop(light(now.df, delta), delta))
        grown = Stored(both.groupBy("src", "dst").agg(F.min("w").alias("w")), "shortcuts")
        before, after = (x.df.agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("s")).first() for x in (now, grown))
        now.drop()
        now = grown
        if before == after:
            break
    return now.df


def summary(g: WeightedGraph) -> DataFrame:
    """n, m, least, mean and largest weight, largest degree."""
    one = g.canonical().agg(
        F.count(F.lit(1)).alias("m"), F.min("pw").alias("w_min"), F.avg("pw").alias("w_mean"), F.max("pw").alias("w_max")
    )
    return one.crossJoin(degrees(g.edges).agg(F.max("degree").alias("degree_max"))).withColumn("n", F.lit(g.n))
