"""Other ways to the diameter: exact all pairs, min-plus squaring, hop-ball sketches."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanweave.functions.hashing import h32, joined
from spanweave.operators.decompose import weight_type
from spanweave.operators.graph import WeightedGraph, encode_ids
from spanweave.operators.quotient import eccentricities, quotient_diameter
from spanweave.plans.loop import Superstep, fixed_plan
from spanweave.session import Stored


def _weighted(g: WeightedGraph) -> DataFrame:
    return g.canonical().select("src", "dst", F.col("pw").alias("w"))


def exact_diameter(g: WeightedGraph):
    """The largest distance within a component, by one search from every node over a broadcast graph of checked size."""
    return eccentricities(_weighted(g), weight_type(g)).agg(F.max("ecc").alias("d")).first()["d"] or 0


def bounded_exact_diameter(g: WeightedGraph):
    """The same by few searches, from nodes that the triangle inequality leaves open."""
    return quotient_diameter(_weighted(g))[0]


def all_pairs(g: WeightedGraph, max_nodes: int = 2_000) -> DataFrame:
    """(src, dst, dist, hops) of all pairs by repeated min-plus products; ``hops``: the fewest edges of a least path.

    For small graphs."""
    if g.n > max_nodes:
        raise ValueError(f"{g.n} nodes give too many pairs; the bound is {max_nodes}")
    way = lambda d, h: F.struct(d.alias("d"), h.alias("h"))
    one = g.edges.select("src", "dst", way(F.col("pw"), F.lit(1)).alias("p"))
    none = way(F.lit(0).cast(weight_type(g)), F.lit(0)).alias("p")
    itself = g.nodes.select(F.col("node").alias("src"), F.col("node").alias("dst"), none)
    now = Stored(itself.unionByName(one), "pairs")
    while True:
        a = now.df.select(F.col("src"), F.col("dst").alias("mid"), F.col("p").alias("p1"))
        b = now.df.select(F.col("src").alias("mid"), F.col("dst"), F.col("p").alias("p2"))
        both = way(F.col("p1.d") + F.col("p2.d"), F.col("p1.h") + F.col("p2.h"))
        new = Stored(a.join(b, "mid").groupBy("src", "dst").agg(F.min(both).alias("p")), "pairs")
        sums = [F.count(F.lit(1)).alias("n"), F.sum("p.d").alias("d"), F.sum("p.h").alias("h")]
        total = [x.df.agg(*sums).first() for x in (now, new)]
        now.drop()
        now = new
        if total[0] == total[1]:
            return now.df.select("src", "dst", "p.d", "p.h").toDF("src", "dst", "dist", "hops")


def hop_bound(g: WeightedGraph, delta=None) -> int:
    """The fewest edges that connect every pair within ``delta`` by a least path (all pairs: within the diameter)."""
    pairs = all_pairs(g)
    if delta is not None:
        pairs = pairs.filter(F.col("dist") <= F.lit(delta))
    return pairs.agg(F.max("hops").alias("h")).first()["h"] or 0


#: Bits of a mask, and the correction of the mean position of the lowest unset bit (a published constant).
BITS, CORRECTION = 62, 0.77351


def _bit(place) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), place.cast("int"))


def _own_bits(g: WeightedGraph, registers: int) -> DataFrame:
    """A bit of its own for every node: dense numbers by ranges, 62 to a mask."""
    if g.n > BITS * registers:
        raise ValueError(f"{g.n} nodes need more than {registers} masks")
    k = F.col("id")
    mask = lambda i: F.when(F.floor(k / BITS) == i, _bit(F.pmod(k, F.lit(BITS)))).otherwise(F.lit(0).cast("long"))
    return encode_ids(g.nodes, "node").select("node", *[mask(i).alias(f"m{i}") for i in range(registers)])


def _hashed_bits(g: WeightedGraph, registers: int, seed: int) -> DataFrame:
    """In each mask one bit, by the trailing zeros of a hash (31 at most)."""

    def mask(i: int) -> Column:
        h = h32(joined(seed, i, F.col("node")))
        return _bit(F.least(F.lit(31), F.bit_count(h.bitwiseXOR(h - 1)) - 1))

    return g.nodes.select("node", *[mask(i).alias(f"m{i}") for i in range(registers)])


def sketch_eccentricity(
    g: WeightedGraph, registers: int = 16, seed: int = 7, exact: bool = False, max_hops: int = 100_000
) -> tuple[DataFrame, list[dict]]:
    """(node, hops): the last hop at which a node's sketch of its ball changed, and the neighbourhood function's estimate per hop.

    A sketch is ``registers`` bit masks; every node sets in each one bit with geometric chance. ``exact`` gives every node
    a bit of its own instead (graphs of up to 62 * registers nodes). Weights are not used: the method cannot take them."""
    loop = Superstep(g.spark)
    start = _own_bits(g, registers) if exact else _hashed_bits(g, registers, seed)
    masks = [f"m{i}" for i in range(registers)]
    # the mean position of the lowest unset bit over the registers estimates a ball's size
    lowest = [F.bit_count(F.col(m).bitwiseAND(F.bitwise_not(F.col(m) + 1))).cast("double") for m in masks]
    size = F.pow(F.lit(2.0), sum(lowest, F.lit(0.0)) / registers) / CORRECTION
    if exact:
        size = sum((F.bit_count(m) for m in masks), F.lit(0)).cast("double")
    figures: list[dict] = []
    with fixed_plan(g.spark, g.partitions):
        state = loop.start(start.withColumns({"hops": F.lit(0), "changed": F.lit(True)}), g.partitions)
        for hop in range(1, max_hops + 1):
            # only balls that grew in the last hop can make a neighbour's grow
            sent = g.along(state.filter("changed").select("node", *masks))
            offer = sent.groupBy("dst").agg(*[F.bit_or(m).alias(f"_{m}") for m in masks])
            new = state.join(offer.hint("shuffle_hash"), F.col("node") == F.col("dst"), "left")
            merged = {m: F.col(m).bitwiseOR(F.coalesce(F.col(f"_{m}"), F.lit(0).cast("long"))) for m in masks}
            grew = F.lit(False)
            for m in masks:
                grew = grew | (merged[m] != F.col(m))
            hops = F.when(grew, F.lit(hop)).otherwise(F.col("hops"))
            columns = [c.alias(m) for m, c in merged.items()]
            plan = new.select("node", *columns, hops.alias("hops"), grew.alias("changed"))
            state, got, seconds = loop.run(plan, {"updates": F.sum(F.col("changed").cast("long")), "pairs": F.sum(size)})
            loop.note("sketch", 0, 0, hop, got, seconds)
            if not got["updates"]:
                break
            figures.append({"hop": hop, "changed": got["updates"], "pairs": float(got["pairs"])})
    return state.select("node", "hops"), figures
