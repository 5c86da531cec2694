"""Diameter estimates: the quotient's diameter plus twice the radius, never below the diameter."""

from __future__ import annotations

import math
import time
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.operators import decompose, graph, sssp
from spanweave.operators.graph import WeightedGraph
from spanweave.operators.quotient import MAX_EDGES, MAX_NODES, LocalGraph, bounded_diameter, exact_diameter_of, local_graph, quotient, quotient_diameter
from spanweave.session import Stored, stored

#: Of the mode ``auto``: up to so many clusters the quotient's diameter is exact; beyond, an upper bound within this share or
#: after so many searches; above MAX_NODES an estimate.
EXACT_UP_TO, TOLERANCE, MOST_SEARCHES = 1_000, 0.02, 256
#: Components of more edges than this are estimated, smaller ones solved, each by one task.
SMALL_COMPONENT = 20_000
#: Components up to this are solved in arrays where all are to be exact; beyond, by searches in supersteps.
ARRAY_NODES, ARRAY_EDGES = 2_000_000, MAX_EDGES
#: Of a quotient too large for the driver, components up to so many edges are solved by a task each.
TASK_EDGES = 1_000_000


def choose_tau(n: int, *, eps: float | None = None, max_quotient_nodes: int | None = None) -> int:
    """tau = n^eps, or one whose expected clusters fill the quotient that is allowed.

    Stages usually cover far more than half, so two of them are reckoned with, and the leftovers: (8 + 2 gamma) tau log n."""
    if eps is not None:
        return max(1, math.ceil(n**eps))
    log_n = max(1.0, decompose.logarithm(n))
    room = max_quotient_nodes or MAX_NODES
    return max(1, min(n, int(room / ((8 + 2 * decompose.GAMMA) * log_n))))


def _radii(d: decompose.Decomposition) -> dict:
    """The radius of each cluster; as many rows as the quotient has nodes."""
    if d.grown is not None:
        return d.grown.radii()
    per = d.clusters.groupBy("center").agg(F.max("path_weight").alias("r")).toArrow()
    return dict(zip(per.column("center").to_pylist(), per.column("r").to_pylist()))


def _exact_max(edges: DataFrame):
    g = graph.build(edges)
    found = diameter_by_component(g, small=TASK_EDGES, exact=True).agg(F.max("diameter")).first()[0]
    g.release()
    return found or 0


def large_quotient_diameter(q: DataFrame, d: decompose.Decomposition, per_cluster: bool) -> tuple:
    """``quotient_diameter`` of a quotient of any size, exact: components apart, a task each or one after the other.

    A cluster's radius is the weight of a leaf at its center."""
    phi = _exact_max(q)
    if not per_cluster:
        return phi, None
    r = d.clusters.groupBy("center").agg(F.max("path_weight").alias("w"))
    leaves = r.filter("w > 0").select((2 * F.col("center")).alias("src"), (2 * F.col("center") + 1).alias("dst"), "w")
    doubled = q.select((2 * F.col("src")).alias("src"), (2 * F.col("dst")).alias("dst"), "w")
    return phi, max(2 * d.radius, _exact_max(doubled.unionByName(leaves)))


def estimate_diameter(
    g: WeightedGraph, tau: int = 1, *, method: str = "staged", quotient_mode: str = "bounds", seed: int = 7,
    bound: str = "radius", depth: int = 0, base: decompose.Decomposition | None = None, **options,
) -> tuple[dict, decompose.Decomposition]:
    """One row of figures and the decomposition behind it.

    ``method``: staged, rescaled or hop. ``bound``: the estimate is the quotient's diameter plus twice the ``radius``, or
    with ``per_cluster`` the most that r(A) + dist(A, B) + r(B) or 2 r(A) comes to: never more, and conservative too.
    ``base``: a decomposition to estimate from. ``quotient_mode``: ``bounds`` and ``exact`` take the quotient's exact
    diameter at any size; ``auto`` only up to ``EXACT_UP_TO`` clusters, and an upper bound of it beyond."""
    began = time.time()
    if base is not None:
        d = base
    elif method == "hop":
        d = decompose.hop_decompose(decompose.by_hops(g), tau, seed=seed)
    else:
        run = {"staged": decompose.staged_decompose, "rescaled": decompose.rescaled_decompose}[method]
        d = run(g, tau, seed=seed, **options)
    grown = time.time()
    mode, kept = quotient_mode, None
    if d.grown is not None and g.arrays is not None and mode in ("bounds", "exact", "sweep2"):
        # on the driver already, and no larger than the graph in arrays
        q, edges, fits = LocalGraph(*d.between.values()), len(d.between["src"]), True
    else:
        kept = Stored(quotient(g, d), "quotient")
        q, edges = kept.df, kept.df.count()
        fits = d.count <= MAX_NODES and edges <= MAX_EDGES
    if mode == "auto":
        mode = "bounds" if fits else "recursive"
    exact = quotient_mode != "auto" or d.count <= EXACT_UP_TO
    limits = {} if exact else {"tolerance": TOLERANCE, "most_searches": MOST_SEARCHES}
    radii = _radii(d) if bound == "per_cluster" and fits else None
    tight = None
    if mode == "recursive" and d.count < g.n and depth < 8:
        inner_graph = graph.build(q)
        inner, _ = estimate_diameter(
            inner_graph, max(1, tau // 4), seed=seed + 1, depth=depth + 1, quotient_mode="bounds" if fits else "auto"
        )
        inner_graph.release()
        phi = inner["estimate"]
    elif quotient_mode == "bounds" and not fits:
        phi, tight = large_quotient_diameter(q, d, bound == "per_cluster")
    else:
        phi, tight = quotient_diameter(q, "bounds" if mode == "recursive" else mode, radius=radii, **limits)
    if kept:
        kept.drop()
    done = time.time()
    row = {
        "method": method, "estimate": phi + 2 * d.radius if tight is None else tight, "quotient_diameter": phi,
        "radius": d.radius, "clusters": d.count, "quotient_edges": edges, "delta_end": d.delta_end, "stages": d.stages,
        "guesses": d.guesses, "growing_steps": d.loop.growing_steps, "rounds": d.rounds, "work": d.loop.work,
        "seconds": done - began, "quotient_seconds": done - grown,
    }
    return row, d


def fast_estimate(
    g: WeightedGraph, *, max_quotient_nodes: int = MAX_NODES, seed: int = 7, tau: int | None = None, **options
) -> tuple[dict, decompose.Decomposition]:
    """The staged decomposition from the mean weight, with a tau that fills the allowed quotient; halved while it does not fit."""
    tau = tau or choose_tau(g.n, max_quotient_nodes=max_quotient_nodes)
    while True:
        d = decompose.staged_decompose(g, tau, seed=seed)
        if d.count <= max_quotient_nodes or tau == 1:
            row, _ = estimate_diameter(g, tau, seed=seed, base=d, **options)
            return row | {"seconds": sum(s.seconds for s in d.loop.steps) + row["seconds"], "tau": tau}, d
        tau = max(1, tau // 2)


WALL = ("seconds", "quotient_seconds")


def result_frame(spark, rows: list[dict], whole: bool = True, wall: bool = False) -> DataFrame:
    """Rows of figures; those of wall time only if asked for, as no two runs agree in them."""
    w = "long" if whole else "double"
    amounts = ("estimate", "quotient_diameter", "radius", "delta_end", "lower", "exact", "upper")
    names = [k for k in rows[0] if k != "decomposition" and (wall or k not in WALL)]

    def kind(k: str) -> str:
        v = rows[0][k]
        return w if k in amounts else "string" if isinstance(v, str) else "double" if isinstance(v, float) else "long"

    as_ = {"long": int, "double": float, "string": str}
    kinds = {k: kind(k) for k in names}
    data = [tuple(None if r[k] is None else as_[kinds[k]](r[k]) for k in names) for r in rows]
    return spark.createDataFrame(data, ", ".join(f"{k} {t}" for k, t in kinds.items()))


def _solve(small: DataFrame, kind: str) -> DataFrame:
    """(component, diameter) of components of bounded size, given as (component, src, dst, w): each lies in one task."""
    number = pa.float64() if kind == "double" else pa.int64()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, found = [], []
            for comp, edges in zip(batch.column("component").to_pylist(), batch.column("edges")):
                e = edges.values
                found.append(bounded_diameter(LocalGraph(*(e.field(c).to_numpy() for c in ("src", "dst", "w"))))[0])
                names.append(comp)
            yield pa.record_batch([pa.array(names, pa.int64()), pa.array(found, number)], names=["component", "diameter"])

    # components are dealt whole to tasks; a group each would be slow for very many small ones
    gathered = small.groupBy("component").agg(F.collect_list(F.struct("src", "dst", "w")).alias("edges"))
    return gathered.mapInArrow(run, f"component long, diameter {kind}")


def diameter_by_supersteps(g: WeightedGraph):
    """The exact diameter of one component of any size: searches in supersteps until the triangle inequality leaves no node open."""
    bounds = Stored(g.nodes.select("node", F.lit(0).alias("low"), F.lit(None).cast(decompose.weight_type(g)).alias("high")), "bounds")
    best, done, width = 0, 0, sssp.widths(g)["mean16"]
    source = g.nodes.agg(F.min("node")).first()[0]
    while source is not None:
        paths = sssp.bucketed_sssp(g, source, width)
        dist = paths.dist.select(F.col("node").alias("_n"), "dist")
        ecc = dist.agg(F.max("dist")).first()[0]
        best, done = max(best, ecc), done + 1
        far, d = F.lit(ecc), F.col("dist")
        high = F.when(F.col("node") == source, far).otherwise(F.least("high", d + far))
        known = bounds.df.join(dist, F.col("node") == F.col("_n"))
        learnt = Stored(known.select("node", F.greatest("low", d, far - d).alias("low"), high.alias("high")), "bounds")
        bounds.drop()
        paths.loop.release()
        bounds = learnt
        # in turns the node of the largest upper bound and the most central one
        order = [F.desc("high"), "node"] if done % 2 else ["low", "node"]
        row = bounds.df.filter(F.col("high") > F.lit(best)).orderBy(*order).first()
        source = row and row["node"]
    bounds.drop()
    return best


def _exact_of(edges: DataFrame, max_nodes: int, max_edges: int):
    """The exact diameter of one component, given as src, dst, w."""
    size = edges.count()
    nodes = size + 1 if size < max_nodes else edges.select("src").union(edges.select("dst")).distinct().count()
    if size <= max_edges and nodes <= max_nodes:
        return exact_diameter_of(local_graph(edges, max_nodes, max_edges), edges.sparkSession)
    own = graph.build(edges)
    found = diameter_by_supersteps(own)
    own.release()
    return found


def diameter_by_component(
    g: WeightedGraph, *, small: int = SMALL_COMPONENT, tau: int | None = None, seed: int = 7, exact: bool = False,
    array_nodes: int = ARRAY_NODES, array_edges: int = ARRAY_EDGES,
) -> DataFrame:
    """(component, diameter, nodes, exact): components of up to ``small`` edges are solved in tasks, larger ones estimated.

    The larger ones (their number is at most edges / small) are estimated one after the other by the fast estimator, so
    that neither stages nor thresholds of one depend on the others; ``exact`` is false and the diameter an upper bound there.
    With ``exact`` they are solved too: in arrays up to ``array_nodes`` and ``array_edges``, beyond that in supersteps."""
    kind = decompose.weight_type(g)
    parts = stored(graph.components(g.canonical(), g.nodes), "parts")
    rows = g.canonical().join(parts, F.col("src") == F.col("node")).select("component", "src", "dst", F.col("pw").alias("w"))
    sizes = parts.groupBy("component").agg(F.count(F.lit(1)).alias("nodes"))
    counts = stored(rows.groupBy("component").agg(F.count(F.lit(1)).alias("edges")), "counts")
    large = counts.filter(F.col("edges") > small)
    solved = _solve(rows.join(large, "component", "left_anti"), kind)
    for row in large.orderBy("component").toLocalIterator():
        edges = rows.filter(F.col("component") == row["component"]).select("src", "dst", "w")
        if exact:
            found = _exact_of(edges, array_nodes, array_edges)
        else:
            own = graph.build(edges)
            found = fast_estimate(own, seed=seed, tau=tau, quotient_mode="auto")[0]["estimate"]
            own.release()
        one = g.spark.createDataFrame([(row["component"], found)], f"component long, diameter {kind}")
        solved = solved.unionByName(one)
    beyond = large.filter(F.lit(not exact)).select(F.col("component").alias("_large"))
    known = sizes.join(solved, "component", "left").join(beyond, F.col("component") == F.col("_large"), "left")
    diameter = F.coalesce("diameter", F.lit(0)).alias("diameter")
    return known.select("component", diameter, "nodes", F.col("_large").isNull().alias("exact"))


def estimate_components(g: WeightedGraph, **options) -> dict:
    """An upper bound of the largest distance within a component, for graphs of any number of components."""
    per = diameter_by_component(g, **options)
    row = per.agg(
        F.max("diameter").alias("estimate"), F.count(F.lit(1)).alias("components"), F.sum((~F.col("exact")).cast("long")).alias("estimated")
    ).first()
    return {"estimate": row["estimate"] or 0, "components": row["components"], "estimated": row["estimated"] or 0}
