"""Decompositions of a weighted graph into clusters of small radius."""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import cached_property

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanweave.functions.hashing import drawn, drawn_here, h32, joined
from spanweave.operators import growth
from spanweave.operators.graph import WeightedGraph
from spanweave.plans.arrays import Growth, whole_sum
from spanweave.plans.loop import Superstep, fixed_plan

GAMMA = 4 * math.log(2)
#: Up to so many uncovered nodes a run in arrays hashes on the driver; more of them in a job.
DRAWN_HERE = 200_000


@dataclass
class Decomposition:
    """``clusters``: node, center, path_weight, stage; the figures of the run. ``grown``: the clusters in arrays, if they grew there."""

    held: DataFrame | Callable[[], DataFrame]
    radius: float
    count: int
    delta_end: float
    stages: int
    guesses: int
    loop: Superstep
    contractions: int
    grown: Growth | None = None

    @cached_property
    def clusters(self) -> DataFrame:
        return self.held if isinstance(self.held, DataFrame) else self.held()

    @cached_property
    def between(self) -> dict[str, np.ndarray]:
        """The quotient's edges of clusters that grew in arrays."""
        return self.grown.between()

    @property
    def rounds(self) -> int:
        """Growing steps, contractions, and two for the quotient."""
        return self.loop.growing_steps + self.contractions + 2


def start_threshold(g: WeightedGraph, rule):
    """min, mean (rounded up for whole weights) or a number."""
    if not isinstance(rule, str):
        return rule
    if g.arrays is not None and len(g.arrays.w) and g.arrays.w.dtype.kind == "i":
        w = g.arrays.w
        row = {"least": w.min().item(), "total": whole_sum(w), "n": len(w)}
    else:
        row = g.edges.agg(F.min("w").alias("least"), F.sum("w").alias("total"), F.count(F.lit(1)).alias("n")).first()
    if row["least"] is None:
        return 1
    if rule == "min":
        return row["least"]
    if rule == "mean":
        return row["total"] / row["n"] if isinstance(row["least"], float) else -(-int(row["total"]) // row["n"])
    raise ValueError(f"unknown start threshold {rule!r}")


def logarithm(n: int) -> float:
    return math.log2(n) if n > 1 else 0.0


def weight_type(g: WeightedGraph) -> str:
    return g.near.schema["pw"].dataType.simpleString()


class _Jobs:
    """Growth as one job a step."""

    def __init__(self, g: WeightedGraph, loop: Superstep):
        self.g, self.loop = g, loop
        self.state = loop.start(growth.initial_state(g.nodes, weight_type(g)), g.partitions)

    def place(self, chosen: Column) -> None:
        self.state = growth.place_centers(self.state, chosen)

    def draw(self, *how) -> None:
        self.place(drawn(F.col("node"), *how))

    def step(self, delta, active_only: bool = True) -> tuple[dict, float]:
        plan = growth.grow_step(self.state, self.g, delta, active_only=active_only)
        self.state, got, seconds = self.loop.run(plan, growth.counters(), growth.WORKING)
        return got, seconds

    def settle(self, stage: int, rescale=None) -> None:
        self.state = growth.settle(self.state, stage, rescale)

    def reactivate(self) -> None:
        self.state = growth.reactivate(self.state)

    def has_boundary(self) -> bool:
        return growth.has_boundary(self.state, self.g)

    def clusters(self, stage: int) -> DataFrame:
        return self.state.select(
            "node", F.coalesce("center", "node").alias("center"), F.coalesce("path_weight", F.lit(0)).alias("path_weight"),
            F.coalesce("settled_stage", F.lit(stage)).alias("stage"),
        )


class _InArrays:
    """The same steps in arrays; centers are drawn by the same hashes."""

    def __init__(self, g: WeightedGraph):
        self.g, self.state = g, Growth(g.arrays, g.array_parts)
        self.settle, self.reactivate, self.has_boundary = self.state.settle, self.state.reactivate, self.state.has_boundary

    def place(self, chosen: Column) -> None:
        rows = self.g.nodes.filter(chosen).select("node").toArrow()
        self.state.place_centers(self.g.arrays.place(rows.column(0).to_numpy()))

    def draw(self, probability: float, seed: int, stage: int, mode: str = "md5") -> None:
        left = np.flatnonzero(self.state.center < 0)
        if mode == "md5" and len(left) <= DRAWN_HERE:
            self.state.place_centers(left[drawn_here(self.g.arrays.ids[left], probability, seed, stage)])
        else:
            self.place(drawn(F.col("node"), probability, seed, stage, mode))

    def step(self, delta, active_only: bool = True) -> tuple[dict, float]:
        began = time.time()
        return self.state.step(delta, active_only), time.time() - began

    def clusters(self, stage: int) -> DataFrame:
        return self.state.clusters(self.g.spark, stage, weight_type(self.g))


def _run(g: WeightedGraph, loop: Superstep) -> _Jobs | _InArrays:
    return _Jobs(g, loop) if g.arrays is None else _InArrays(g)


def _finish(run: _Jobs | _InArrays, stage: int, loop: Superstep, delta, guesses: int, contractions: int) -> Decomposition:
    if isinstance(run, _InArrays):
        state = run.state
        return Decomposition(lambda: run.clusters(stage), state.radius(), state.heads(), delta, stage, guesses, loop, contractions, state)
    clusters = run.clusters(stage).checkpoint(eager=True)
    loop.release()
    own = F.sum((F.col("node") == F.col("center")).cast("long"))
    row = clusters.agg(F.max("path_weight").alias("r"), own.alias("k")).first()
    return Decomposition(clusters, row["r"] or 0, row["k"] or 0, delta, stage, guesses, loop, contractions)


def staged_decompose(
    g: WeightedGraph, tau: int = 1, *, seed: int = 7, delta0="mean", gamma: float = GAMMA,
    step_cap: int | str | None = None, count: str = "uncovered", active_only: bool = True, draw: str = "md5",
) -> Decomposition:
    """Batches of random centers grow together under one threshold, which doubles until each stage covers half of what is left.

    ``step_cap``: growing steps per guess at most (``auto``: n / tau). ``count``: what the inner stop counts, the newly
    covered among the ``uncovered``, or the covered among ``all_nodes`` of the contracted graph (the clusters of
    earlier stages, one node each, count as covered there)."""
    if not 1 <= tau <= max(1, g.n):
        raise ValueError(f"tau must lie between 1 and the number of nodes, not {tau}")
    cap = max(1, g.n // tau) if step_cap == "auto" else step_cap
    log_n = logarithm(g.n)
    loop = Superstep(g.spark)
    delta = start_threshold(g, delta0)
    uncovered, clusters = g.n, 0
    stage = guesses = 0
    with fixed_plan(g.spark, g.partitions):
        run = _run(g, loop)
        while uncovered and uncovered >= 8 * tau * log_n:
            left, before = uncovered, clusters
            probability = min(1.0, gamma * tau * log_n / left)
            run.draw(probability, seed, stage, draw)
            guesses, taken = guesses + 1, 0
            while True:
                got, seconds = run.step(delta, active_only)
                if not got["centers"]:  # nothing drawn and no cluster yet: the least hash is the center
                    first = g.nodes.orderBy(h32(joined(seed, stage, F.col("node"))), "node").first()["node"]
                    run.place(F.col("node") == first)
                    continue
                taken += 1
                step = loop.note("staged", stage, guesses, delta, got, seconds)
                uncovered, clusters = step.uncovered, got["centers"]
                if 2 * step.covered >= left:
                    break
                stops = count == "all_nodes" and 2 * (before + step.covered) >= before + left
                if stops or step.updates == 0 or (cap and taken >= cap):
                    if step.updates == 0 and not run.has_boundary():
                        break
                    delta, guesses, taken = delta * 2, guesses + 1, 0
                    run.reactivate()
            run.settle(stage)
            stage += 1
        return _finish(run, stage, loop, delta, guesses, stage)


def rescaled_decompose(
    g: WeightedGraph, tau: int = 1, *, seed: int = 7, step_cap: int | str | None = None,
    base: Decomposition | None = None, radius=None, delta0="mean",
) -> Decomposition:
    """Centers drawn with doubling probability; each iteration grows all clusters by twice the radius of a staged run."""
    base_steps = base
    if radius is None:
        base_steps = base or staged_decompose(g, tau, seed=seed, delta0=delta0)
        radius = base_steps.radius
        if not radius:
            return base_steps
    reach, n = 2 * radius, g.n
    log_n = logarithm(n)
    cap = max(1, math.ceil(n / tau * log_n)) if step_cap == "auto" else step_cap
    loop = Superstep(g.spark)
    if base_steps:
        loop.steps.extend(base_steps.loop.steps)
    iterations = max(1, math.ceil(log_n))
    with fixed_plan(g.spark, g.partitions):
        run = _run(g, loop)
        done = 0
        for i in range(1, iterations + 1):
            probability = 1.0 if i == iterations else min(1.0, 2**i / n)
            run.draw(probability, seed + 1, i)
            taken = 0
            while True:
                got, seconds = run.step(reach)
                step, taken = loop.note("rescaled", i, 0, reach, got, seconds), taken + 1
                if step.updates == 0 or (cap and taken >= cap):
                    break
            run.settle(i, rescale=reach)
            done = i
            if loop.steps[-1].uncovered == 0:
                break
        contractions = done + (base_steps.contractions if base_steps else 0)
        return _finish(run, done, loop, reach, done, contractions)


def by_hops(g: WeightedGraph) -> WeightedGraph:
    """The same graph growing by hops: every edge counts 1, paths keep their weights."""
    hops = g.mapped(lambda e: e.withColumn("w", F.lit(1).cast("long")))
    if g.arrays is not None:
        hops._arrays = replace(g.arrays, w=np.ones(len(g.arrays.w), np.int32))
    return hops


def hop_decompose(hops: WeightedGraph, tau: int = 1, *, seed: int = 7) -> Decomposition:
    """The unweighted predecessor: all frontiers advance one hop a step until half is covered (``hops``: see ``by_hops``)."""
    return staged_decompose(hops, tau, seed=seed, delta0=max(1, hops.n))
