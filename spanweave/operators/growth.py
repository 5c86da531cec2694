"""Cluster growth: bounded relaxations, contraction in explicit and implicit form, and growth to a fixpoint.

State of a node: center (null: none yet), grow_dist (what the threshold bounds), path_weight (weight of
the real path from the center), settled_stage (null until its stage ends), offset (what a settled node starts
its offers from; null: it makes none), active (changed since it last made offers)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanweave.operators.graph import WeightedGraph
from spanweave.plans.loop import Superstep

WORKING = ("_offer", "_n", "_accepted")


def initial_state(nodes: DataFrame, weight_type: str = "long") -> DataFrame:
    none = F.lit(None)
    return nodes.select(
        "node", none.cast("long").alias("center"), none.cast(weight_type).alias("grow_dist"),
        none.cast(weight_type).alias("path_weight"), none.cast("int").alias("settled_stage"),
        none.cast(weight_type).alias("offset"), F.lit(False).alias("active"),
    )


def place_centers(state: DataFrame, chosen: Column) -> DataFrame:
    """Makes the chosen nodes among the uncovered ones centers of their own."""
    new = F.col("center").isNull() & chosen
    zero = F.lit(0)
    return state.withColumns({
        "center": F.when(new, F.col("node")).otherwise(F.col("center")),
        "grow_dist": F.when(new, zero).otherwise(F.col("grow_dist")),
        "path_weight": F.when(new, zero).otherwise(F.col("path_weight")),
        "active": F.col("active") | new,
    })


# A step is built anew in every round: its expressions are text, as each Column call costs a trip to the JVM.

BASE = "if(settled_stage is null, grow_dist, offset)"


def offers(state: DataFrame, g: WeightedGraph, delta, active_only: bool = True) -> DataFrame:
    """(dst, d, center, path): what covered nodes below the threshold offer along light edges."""
    most = number(delta)
    frontier = state.where(f"center is not null and {BASE} < {most}{' and active' if active_only else ''}")
    frontier = frontier.selectExpr("node", "center", "path_weight", f"{BASE} as _base")
    sent = g.along(frontier, f"w <= {most}").where(f"_base + w <= {most}")
    # a rescaled offset may be below zero under a step cap: distances start at zero
    return sent.selectExpr("dst", "greatest(_base + w, 0) as d", "center", "path_weight + pw as path")


def number(x) -> str:
    """A threshold as SQL text: whole numbers as such, others as doubles."""
    return f"{int(x)}L" if float(x) == int(x) and isinstance(x, int) else f"double('{float(x)!r}')"


def best_offers(sent: DataFrame, combine: str = "hash") -> DataFrame:
    """The least (d, center, path) for each node and how many offers it had; ``window`` ranks instead of aggregating."""
    if combine == "window":
        win = Window.partitionBy("dst")
        ranked = sent.withColumn("_r", F.row_number().over(win.orderBy("d", "center", "path")))
        ranked = ranked.withColumn("_n", F.count(F.lit(1)).over(win))
        return ranked.filter("_r = 1").select("dst", F.struct("d", "center", "path").alias("_offer"), "_n")
    return sent.groupBy("dst").agg(F.expr("min(struct(d, center, path)) as _offer"), F.expr("count(1) as _n"))


NEARER = "coalesce(settled_stage is null and _offer is not null and (grow_dist is null or _offer.d < grow_dist), false)"


def grow_step(
    state: DataFrame, g: WeightedGraph, delta, *, active_only: bool = True, combine: str = "hash"
) -> DataFrame:
    """The state after one synchronous step, with the working columns that the counters need."""
    best = best_offers(offers(state, g, delta, active_only), combine)
    joined = state.join(best.hint("shuffle_hash"), F.expr("node = dst"), "left").selectExpr("*", f"{NEARER} as _accepted")
    take = lambda new, old: f"if(_accepted, _offer.{new}, {old}) as {old}"
    return joined.selectExpr(
        "node", take("center", "center"), take("d", "grow_dist"), take("path", "path_weight"), "settled_stage", "offset",
        "_accepted as active", *WORKING,
    )


def counters() -> dict[str, Column]:
    """What a step reports, summed while it is written."""
    return {
        "messages": F.expr("sum(_n)"),
        "combined": F.expr("count(_offer)"),
        "updates": F.expr("count_if(_accepted)"),
        "covered": F.expr("count_if(center is not null and settled_stage is null)"),
        "uncovered": F.expr("count_if(center is null)"),
        "centers": F.expr("count_if(coalesce(center = node, false))"),
    }


def settle(state: DataFrame, stage: int, rescale=None) -> DataFrame:
    """Contraction in implicit form: covered nodes stop receiving, and offer as their center would along contracted edges.

    Without ``rescale`` such an edge has the weight of the original one, so offers start from 0; with it (twice the
    radius) the weight is d + w - rescale, and only the nodes of this stage still have such edges."""
    now = F.col("center").isNotNull() & F.col("settled_stage").isNull()
    if rescale is None:
        offset = F.when(F.col("center").isNotNull(), F.lit(0))
    else:
        offset = F.when(now, F.col("grow_dist") - F.lit(rescale))
    return state.withColumns({
        "offset": offset,
        "active": F.col("center").isNotNull() & (now | F.lit(rescale is None)),
        "settled_stage": F.when(now, F.lit(stage)).otherwise(F.col("settled_stage")),
    })


def reactivate(state: DataFrame) -> DataFrame:
    return state.withColumn("active", F.col("center").isNotNull())


def _with_centers(state: DataFrame, g: WeightedGraph, keep: Column | None = None) -> DataFrame:
    a = state.select("node", F.col("center").alias("cu"), F.col("grow_dist").alias("du"))
    b = state.select(F.col("node").alias("_b"), F.col("center").alias("cv"))
    return g.along(a, keep).join(b, F.col("dst") == F.col("_b"))


def contract(state: DataFrame, g: WeightedGraph) -> DataFrame:
    """Contraction in explicit form: edges between covered nodes go, those out of a cluster start at its center; least of parallel ones."""
    kept = _with_centers(state, g).filter("cu is null or cv is null")
    out = kept.select(F.coalesce("cu", "src").alias("src"), F.coalesce("cv", "dst").alias("dst"), "w")
    return out.groupBy("src", "dst").agg(F.min("w").alias("w"))


def contract_rescaled(state: DataFrame, g: WeightedGraph, reach) -> DataFrame:
    """As ``contract`` over edges up to ``reach`` (twice the radius); an edge out of a cluster weighs d + w - reach."""
    kept = _with_centers(state, g, F.col("w") <= F.lit(reach)).filter("cv is null")
    w = F.when(F.col("cu").isNull(), F.col("w")).otherwise(F.col("du") + F.col("w") - F.lit(reach))
    one = kept.select(F.coalesce("cu", "src").alias("src"), F.col("dst"), w.alias("w"))
    both = one.unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return both.groupBy("src", "dst").agg(F.min("w").alias("w"))


def grow_to_fixpoint(
    loop: Superstep, state: DataFrame, g: WeightedGraph, delta, *, cap: int | None = None, stage: int = 0,
    phase: str = "fixpoint", active_only: bool = True,
) -> DataFrame:
    """Steps until nothing changes, or ``cap`` steps."""
    done = 0
    while True:
        state, got, seconds = loop.run(grow_step(state, g, delta, active_only=active_only), counters(), WORKING)
        step = loop.note(phase, stage, 0, delta, got, seconds)
        done += 1
        if step.updates == 0 or (cap and done >= cap):
            return state


def has_boundary(state: DataFrame, g: WeightedGraph) -> bool:
    """Whether an edge leads from a covered to an uncovered node."""
    inside = state.filter("center is not null").select("node")
    outside = state.filter("center is null").select(F.col("node").alias("_b"))
    return not g.along(inside).join(outside, F.col("dst") == F.col("_b"), "left_semi").isEmpty()
