"""Shortest paths from one or several sources in supersteps, and the diameter bounds they give."""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.functions.hashing import h32, hashes_here, joined
from spanweave.operators.decompose import DRAWN_HERE, weight_type
from spanweave.operators.graph import WeightedGraph
from spanweave.operators.growth import number
from spanweave.plans.arrays import Search, whole_sum
from spanweave.plans.loop import Superstep, fixed_plan


@dataclass
class Paths:
    """``dist``: node, dist, parent, hops (null where unreachable); the figures of the run."""

    held: DataFrame | Callable[[], DataFrame]
    loop: Superstep
    seconds: float
    search: Search | None = None

    @cached_property
    def dist(self) -> DataFrame:
        return self.held if isinstance(self.held, DataFrame) else self.held()

    @property
    def ecc(self):
        """The largest distance."""
        return self.dist.agg(F.max("dist").alias("d")).first()["d"] if self.search is None else self.search.ecc()

    @property
    def rounds(self) -> int:
        return self.loop.growing_steps


def pick_source(g: WeightedGraph, seed: int = 7) -> int:
    """A node drawn by hash."""
    if g.arrays is not None and 0 < g.n <= DRAWN_HERE:
        ids = g.arrays.ids
        return ids[np.argmin(hashes_here(ids, f"source:{seed}"))].item()
    return g.nodes.orderBy(h32(joined("source", seed, F.col("node"))), "node").first()["node"]


def _relax(state: DataFrame, mine: str, g: WeightedGraph, keep: str | None, marks: dict[str, str]) -> DataFrame:
    """One synchronous relaxation from the nodes that ``mine`` names, along the edges that ``keep``.

    ``marks``: the pending flags afterwards, over the old ones, ``_accepted`` and ``_mine``. Expressions are text, as each
    Column call costs a trip to the JVM in every round."""
    sent = g.along(state.where(mine).select("node", "dist", "hops"), keep)
    offer = F.expr("min(struct(dist + pw as d, hops + 1 as h, src as p)) as _offer")
    best = sent.groupBy("dst").agg(offer, F.expr("count(1) as _n"))
    both = state.join(best.hint("shuffle_hash"), F.expr("node = dst"), "left")
    better = "coalesce(_offer is not null and (dist is null or _offer.d < dist), false) as _accepted"
    both = both.selectExpr("*", f"coalesce({mine}, false) as _mine", better)
    take = lambda new, old: f"if(_accepted, _offer.{new}, {old}) as {old}"
    flags = [f"{flag} as {name}" for name, flag in marks.items()]
    return both.selectExpr("node", take("d", "dist"), take("p", "parent"), take("h", "hops"), *flags, *WORKING)


WORKING = ("_offer", "_n", "_accepted")


def bucketed_sssp(g: WeightedGraph, source: int, delta=None) -> Paths:
    """Distances by buckets of width ``delta``: light edges until the bucket is stable, then heavy ones once.

    ``delta=None``: one bucket."""
    began, loop = time.time(), Superstep(g.spark)
    kind = weight_type(g)
    if g.arrays is not None:
        search = Search(g.arrays, source, delta)

        def step(now: int, heavy: bool) -> tuple[dict, float]:
            at = time.time()
            return search.step(now, heavy), time.time() - at

        _by_buckets(loop, step, delta)
        return Paths(lambda: search.result(g.spark, kind), loop, time.time() - began, search)
    zero = F.lit(0).cast(kind)
    start = F.col("node") == source
    state = g.nodes.select(
        "node", F.when(start, zero).alias("dist"), F.lit(None).cast("long").alias("parent"),
        F.when(start, F.lit(0)).alias("hops"), start.alias("light"), start.alias("heavy"),
    )
    width = None if delta is None else number(delta)
    light, heavy = (None, None) if delta is None else (f"pw <= {width}", f"pw > {width}")
    bucket = "0L" if delta is None else f"cast(floor(dist / {width}) as long)"
    waits = {
        "messages": "sum(_n)", "combined": "count(_offer)", "updates": "count_if(_accepted)", "uncovered": "count_if(dist is null)",
        "next_light": f"min(if(light, {bucket}, null))", "next_any": f"min(if(light or heavy, {bucket}, null))",
    }
    waits = {k: F.expr(c) for k, c in waits.items()}
    # an improved node waits for both kinds of edges; who sent its light edges no longer waits for those
    after_light = {"light": "_accepted or (light and not _mine)", "heavy": "_accepted or heavy" if heavy else "false"}
    after_heavy = {"light": "_accepted or light", "heavy": "_accepted or (heavy and not _mine)"}
    def job(now: int, by_heavy: bool) -> tuple[dict, float]:
        nonlocal state
        here = f"dist is not null and {bucket} = {now}"
        plan = _relax(state, f"heavy and {here}", g, heavy, after_heavy) if by_heavy else _relax(state, f"light and {here}", g, light, after_light)
        state, got, seconds = loop.run(plan, waits, WORKING)
        return got, seconds

    with fixed_plan(g.spark, g.partitions):
        state = loop.start(state, g.partitions)
        _by_buckets(loop, job, delta)
    return Paths(state.select("node", "dist", "parent", "hops"), loop, time.time() - began)


def _by_buckets(loop: Superstep, step: Callable[[int, bool], tuple[dict, float]], delta) -> None:
    """Which phase of which bucket comes next; ``step(bucket, heavy)`` runs one and tells what waits then."""
    now = 0
    while True:
        # light phases while something of this bucket waits
        got, seconds = step(now, False)
        loop.note("light", now, 0, delta or 0, got, seconds)
        if got["next_light"] == now:
            continue
        if delta is not None:
            got, seconds = step(now, True)
            loop.note("heavy", now, 0, delta, got, seconds)
        if got["next_any"] is None:
            return
        now = got["next_any"]


def bellman_ford(g: WeightedGraph, source: int) -> Paths:
    return bucketed_sssp(g, source, None)


def tune_bucket_width(g: WeightedGraph, source: int, widths: dict[str, object]) -> list[dict]:
    """One row of figures per width, fewest rounds (then least work) first."""
    rows = []
    for name, delta in widths.items():
        p = bucketed_sssp(g, source, delta)
        ecc = p.ecc
        p.loop.release()
        figures = {"rounds": p.rounds, "work": p.loop.work, "seconds": p.seconds, "ecc": ecc}
        rows.append({"width": name, "delta": float(delta or 0)} | figures)
    return sorted(rows, key=lambda r: (r["rounds"], r["work"], r["width"]))


def widths(g: WeightedGraph) -> dict[str, object]:
    """The grid: least, mean, four and sixteen times the mean weight, no bound."""
    if g.arrays is not None and len(g.arrays.pw) and g.arrays.pw.dtype.kind == "i":
        row = {"a": g.arrays.pw.min().item(), "b": whole_sum(g.arrays.pw), "n": len(g.arrays.pw)}
    else:
        row = g.edges.agg(F.min("pw").alias("a"), F.sum("pw").alias("b"), F.count(F.lit(1)).alias("n")).first()
    mean = row["b"] / row["n"] if isinstance(row["a"], float) else -(-int(row["b"]) // row["n"])
    return {"least": row["a"], "mean": mean, "mean4": 4 * mean, "mean16": 16 * mean, "none": None}


def sssp_diameter_bound(g: WeightedGraph, source: int, delta=None) -> tuple:
    """(eccentricity, twice that): below and above the diameter of the source's component."""
    far = bucketed_sssp(g, source, delta).dist.agg(F.max("dist").alias("d")).first()["d"]
    return far, 2 * far


#: Sources that one state carries, a column of distances each.
MOST_SOURCES = 64


def multi_source(g: WeightedGraph, sources: list[int]) -> DataFrame:
    """(source, node, dist) of several sources at once, for what each reaches: one row per node with a column per source."""
    if not 1 <= len(sources) <= MOST_SOURCES:
        raise ValueError(f"1 to {MOST_SOURCES} sources, not {len(sources)}")
    loop = Superstep(g.spark)
    kind = weight_type(g)
    names = [f"d{i}" for i in range(len(sources))]
    at = F.col("node")
    start = [F.when(at == s, F.lit(0)).cast(kind).alias(d) for s, d in zip(sources, names)]
    with fixed_plan(g.spark, g.partitions):
        state = loop.start(g.nodes.select("node", *start, at.isin(sources).alias("active")), g.partitions)
        while True:
            sent = g.along(state.filter("active").select("node", *names))
            offer = sent.groupBy("dst").agg(*[F.min(F.col(d) + F.col("pw")).alias(f"_{d}") for d in names])
            both = state.join(offer.hint("shuffle_hash"), F.col("node") == F.col("dst"), "left")
            better = F.lit(False)
            for d in names:
                new = F.col(f"_{d}")
                better = better | F.coalesce(new.isNotNull() & (F.col(d).isNull() | (new < F.col(d))), F.lit(False))
            plan = both.select("node", *[F.least(d, f"_{d}").alias(d) for d in names], better.alias("active"))
            state, got, seconds = loop.run(plan, {"updates": F.sum(F.col("active").cast("long"))})
            loop.note("sources", 0, 0, 0, got, seconds)
            if not got["updates"]:
                break
    cell = lambda s, d: F.struct(F.lit(s).cast("long").alias("source"), F.col(d).alias("dist"))
    each = F.explode(F.array(*[cell(s, d) for s, d in zip(sources, names)]))
    return state.select("node", each.alias("x")).filter("x.dist is not null").select("x.source", "node", "x.dist")


def multi_sssp_bound(g: WeightedGraph, k: int, strategy: str = "random", seed: int = 7) -> tuple:
    """(largest eccentricity, least double eccentricity) of k sources: random, of largest degree, or each farthest from the others."""
    if strategy == "farthest":
        sources = [pick_source(g, seed)]
        while len(sources) < k:
            near = multi_source(g, sources).groupBy("node").agg(F.min("dist").alias("d"))
            sources.append(near.orderBy(F.desc("d"), "node").first()["node"])
    elif strategy == "degree":
        most = g.edges.groupBy("src").count().orderBy(F.desc("count"), "src")
        sources = [r["src"] for r in most.limit(k).collect()]
    else:
        drawn = g.nodes.orderBy(h32(joined("source", seed, F.col("node"))), "node")
        sources = [r["node"] for r in drawn.limit(k).collect()]
    each = multi_source(g, sources).groupBy("source").agg(F.max("dist").alias("e"))
    row = each.agg(F.max("e").alias("lower"), (2 * F.min("e")).alias("upper")).first()
    return row["lower"], row["upper"]


def farthest_sweeps(g: WeightedGraph, source: int, rounds: int = 4) -> list[dict]:
    """Each search starts at the farthest node of the one before (of equals the least id): a lower bound that grows."""
    rows, best = [], 0
    for i in range(rounds):
        top = bellman_ford(g, source).dist.filter("dist is not null").orderBy(F.desc("dist"), "node").first()
        best = max(best, top["dist"])
        rows.append({"sweep": i, "source": source, "farthest": top["node"], "ecc": top["dist"], "lower": best})
        source = top["node"]
    return rows


def light_distance(g: WeightedGraph, source: int, bound) -> DataFrame:
    """Distances along edges up to ``bound`` only; null where there is no such path."""
    return bellman_ford(g.mapped(lambda e: e.filter(F.col("pw") <= F.lit(bound))), source).dist.select("node", "dist")
