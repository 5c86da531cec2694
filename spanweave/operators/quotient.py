"""The quotient graph of a clustering, graphs small enough for one process, and their diameters."""

from __future__ import annotations

import os
from collections.abc import Callable, Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanweave.operators.decompose import Decomposition
from spanweave.operators.graph import WeightedGraph
from spanweave.plans.arrays import Arrays, frame

#: Collected to the driver only below these counts, which the caller's tau is chosen to meet.
MAX_NODES, MAX_EDGES = 100_000, 5_000_000
#: Searches that one call holds together: cells of its distance table.
CELLS = 1 << 19
#: Distances that one wave of parallel searches brings to the driver.
WAVE_CELLS = 1 << 23
#: Up to so many directed edges the searches of a diameter run on the driver; beyond, in parallel tasks.
HERE = 60_000
#: Landmarks whose distances bound those of pairs: first so many, doubled while that pays, up to so many and so many cells;
#: pairs are compared only below so many sums.
LANDMARKS, MOST_LANDMARKS, LANDMARK_CELLS, PAIR_SUMS = 16, 128, 1 << 26, 1 << 32
#: Buckets of a search that are told apart; farther nodes wait together.
BUCKETS = 64
#: Sums of a block of pairs held together.
PAIR_CELLS = 1 << 22

Search = Callable[[list[np.ndarray]], np.ndarray]


def quotient(g: WeightedGraph, d: Decomposition) -> DataFrame:
    """src < dst, w: for clusters with an edge between them, the least weight of edge and both ends' paths."""
    if d.grown is not None and g.arrays is not None:
        return frame(g.spark, {k: pa.array(v) for k, v in d.between.items()}, f"src long, dst long, w {g.near.schema['pw'].dataType.simpleString()}")
    a = d.clusters.select("node", F.col("center").alias("ca"), F.col("path_weight").alias("pa"))
    b = d.clusters.select(F.col("node").alias("_b"), F.col("center").alias("cb"), F.col("path_weight").alias("pb"))
    joined = g.along(a, F.col("src") < F.col("dst")).join(b, F.col("dst") == F.col("_b")).filter("ca <> cb")
    ends = [F.least("ca", "cb").alias("src"), F.greatest("ca", "cb").alias("dst")]
    return joined.groupBy(*ends).agg(F.min(F.col("pw") + F.col("pa") + F.col("pb")).alias("w"))


def bucket_width(w: np.ndarray):
    """Four usual weights: a few heavy ones do not widen it."""
    if not len(w):
        return 1
    half = np.partition(w, len(w) // 2)[len(w) // 2].item()
    return 4 * half


def distinct(parts: list[np.ndarray], size: int) -> np.ndarray:
    """The numbers below ``size`` that occur, in rising order."""
    some = parts[0] if len(parts) == 1 else np.concatenate(parts)
    if len(some) * 16 < size:
        some = np.sort(some)
        return some[np.append(True, some[1:] != some[:-1])[: len(some)]]
    seen = np.zeros(size, bool)
    seen[some] = True
    return np.flatnonzero(seen)


class LocalGraph:
    """An undirected graph in arrays: the neighbours of node i are ``to[start[i]:start[i + 1]]``."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, w: np.ndarray, nodes: np.ndarray | None = None):
        self.ids = np.unique(np.concatenate([src, dst] + ([] if nodes is None else [nodes])).astype(np.int64))
        a, b = np.searchsorted(self.ids, src), np.searchsorted(self.ids, dst)
        here, self.to, self.w = np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([w, w])
        order = np.argsort(here, kind="stable")
        self.to, self.w = self.to[order], self.w[order]
        self.start = np.searchsorted(here[order], np.arange(len(self.ids) + 1))
        self.kind = self.w.dtype  # of distances
        self.far = np.inf if self.kind.kind == "f" else np.int64(2**62)
        # searches advance by this much at a time, so that few nodes are settled twice
        self.width = bucket_width(self.w)

    def __len__(self) -> int:
        return len(self.ids)

    @classmethod
    def of(cls, g: Arrays) -> LocalGraph:
        """A graph that is in arrays already, by its weights on paths."""
        out = cls(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, g.kind), g.ids)
        out.to, out.w, out.start = g.to, g.pw, g.start
        out.width = bucket_width(g.pw)
        return out

    def place(self, ids) -> np.ndarray:
        return np.searchsorted(self.ids, np.asarray(ids))

    def search(self, sets: list[np.ndarray], hops: bool = False) -> np.ndarray:
        """A row of distances per set of sources (places); ``far`` where none of them leads."""
        n = len(self)
        weight = np.ones(len(self.w), self.kind) if hops else self.w
        dist = np.full(len(sets) * n, self.far, self.kind)
        wait = np.concatenate([k * n + np.asarray(s) for k, s in enumerate(sets)])
        dist[wait] = 0
        width = 1 if hops else self.width
        # waiting nodes by bucket, up to the bucket ``end``, and those beyond; who has come nearer since waits twice
        buckets, later, end = {}, [wait], 0

        def deal(nodes: np.ndarray) -> None:
            at = dist[nodes] // width
            later.append(nodes[at >= end])
            nodes, at = nodes[at < end], at[at < end]
            order = np.argsort(at)
            nodes, at = nodes[order], at[order]
            cuts = np.append(np.flatnonzero(np.append(True, at[1:] != at[:-1])[: len(at)]), len(at))
            for low, high in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
                buckets.setdefault(at[low].item(), []).append(nodes[low:high])

        while True:
            if not buckets:
                wait, later = distinct(later, len(dist)), []
                wait = wait[dist[wait] // width >= end]
                if not len(wait):
                    break
                end = (dist[wait] // width).min().item() + BUCKETS
                deal(wait)
            k = min(buckets)
            now = distinct(buckets.pop(k), len(dist))
            d = dist[now]
            here = d // width == k
            now, d = now[here], d[here]
            node = now % n
            degree = self.start[node + 1] - self.start[node]
            at = np.repeat(self.start[node] - (np.cumsum(degree) - degree), degree) + np.arange(degree.sum())
            goal = np.repeat(now - node, degree) + self.to[at]
            found = np.repeat(d, degree) + weight[at]
            better = found < dist[goal]
            goal, found = goal[better], found[better]
            np.minimum.at(dist, goal, found)
            deal(distinct([goal], len(dist)))
        return dist.reshape(len(sets), n)

    def batches(self, places: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(sources, their distances), a bounded number together."""
        few = max(1, CELLS // max(1, len(self)))
        for k in range(0, len(places), few):
            some = places[k : k + few]
            yield some, self.search([np.array([s]) for s in some])

    def components(self) -> np.ndarray:
        """A number 0, 1, ... per node, equal for connected ones."""
        label = np.arange(len(self))
        here = np.repeat(label, np.diff(self.start))
        while len(here):
            new = label.copy()
            np.minimum.at(new, here, label[self.to])
            while not np.array_equal(new, new[new]):
                new = new[new]
            if np.array_equal(new, label):
                break
            label = new
        return np.unique(label, return_inverse=True)[1]

    def eccentricities(self) -> np.ndarray:
        """The largest finite distance of each node."""
        out = np.zeros(len(self), self.kind)
        for some, dist in self.batches(np.arange(len(self))):
            out[some] = np.where(dist < self.far, dist, 0).max(1)
        return out


def local_graph(edges: DataFrame, max_nodes: int = MAX_NODES, max_edges: int = MAX_EDGES) -> LocalGraph:
    """Edges src, dst, w on the driver; raises if there are more than allowed, before they are all fetched."""
    rows = edges.select("src", "dst", "w").limit(max_edges + 1).toArrow()
    if rows.num_rows > max_edges:
        raise ValueError(f"more than {max_edges} edges: choose a smaller tau or the recursive mode")
    g = LocalGraph(*(rows.column(c).to_numpy() for c in ("src", "dst", "w")))
    if len(g) > max_nodes:
        raise ValueError(f"{len(g)} nodes, more than {max_nodes}: choose a smaller tau or the recursive mode")
    return g


def eccentricities(edges: DataFrame, weight_type: str = "long", **limits) -> DataFrame:
    """(node, ecc) of every node with an edge: the graph is broadcast once its size is checked, searches run in parallel tasks."""
    spark = edges.sparkSession
    g = local_graph(edges, **limits)
    shared = spark.sparkContext.broadcast(g)
    tasks = min(max(1, len(g)), 4 * spark.sparkContext.defaultParallelism)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        local = shared.value
        kind = pa.float64() if weight_type == "double" else pa.int64()
        for batch in batches:
            for some, dist in local.batches(batch.column(0).to_numpy()):
                ecc = np.where(dist < local.far, dist, 0).max(1)
                yield pa.record_batch([pa.array(local.ids[some]), pa.array(ecc, kind)], names=["node", "ecc"])

    return spark.range(len(g)).repartition(tasks).mapInArrow(run, f"node long, ecc {weight_type}")


def searches(spark: SparkSession, g: LocalGraph) -> tuple[Search, int]:
    """How to run several searches and how many at a time: here for a small graph, else in parallel tasks over a broadcast."""
    if len(g.to) <= HERE:
        return g.search, 8
    shared, ways = spark.sparkContext.broadcast(g), spark.sparkContext.defaultParallelism

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k, s in zip(batch.column("k").to_pylist(), batch.column("s").to_pylist()):
                row = shared.value.search([np.frombuffer(s, np.int64)])[0]
                yield pa.record_batch([pa.array([k], pa.int32()), pa.array([row.tobytes()], pa.binary())], names=["k", "d"])

    def search(sets: list[np.ndarray]) -> np.ndarray:
        rows = [(k, np.asarray(s, np.int64).tobytes()) for k, s in enumerate(sets)]
        tasks = spark.createDataFrame(rows, "k int, s binary").repartition(min(len(sets), ways), "k")
        # a wave's distances: at most WAVE_CELLS numbers
        got = tasks.mapInArrow(run, "k int, d binary").toArrow()
        out = np.empty((len(sets), len(g)), g.kind)
        for k, d in zip(got.column("k").to_pylist(), got.column("d").to_pylist()):
            out[k] = np.frombuffer(d, g.kind)
        return out

    return search, int(max(ways, min(16 * ways, WAVE_CELLS // max(1, len(g)))))


def searches_here(g: LocalGraph) -> tuple[Search, int]:
    """The same for a graph that came from arrays on the driver: by threads there."""
    if len(g.to) <= HERE:
        return g.search, 8
    ways = os.cpu_count() or 1

    def search(sets: list[np.ndarray]) -> np.ndarray:
        with ThreadPoolExecutor(ways) as pool:
            return np.concatenate(list(pool.map(lambda s: g.search([s]), sets)))

    return search, ways


def _rank(groups: np.ndarray) -> np.ndarray:
    """0, 1, ... within each run of equal numbers."""
    at = np.arange(len(groups))
    return at - np.maximum.accumulate(np.where(np.append(True, np.diff(groups) != 0), at, 0))


class Bounds:
    """What searches tell about eccentricities, where each node has a leaf ``extra`` far out (0: the node itself)."""

    def __init__(self, g: LocalGraph, part: np.ndarray, extra: np.ndarray | None):
        self.part, self.parts, self.far = part, int(part.max()) + 1, g.far
        self.extra = np.zeros(len(g), g.kind) if extra is None else np.asarray(extra).astype(g.kind)
        self.low, self.high = np.zeros(len(g), g.kind), np.full(len(g), g.far)
        self.best = g.kind.type(0)

    def learn(self, sources: np.ndarray, dist: np.ndarray) -> None:
        """One search, from at most one source per component: any leaf is within its way to the source and that one's reach."""
        of = np.full(self.parts, -1)
        of[self.part[sources]] = sources
        hit = np.flatnonzero(of[self.part] >= 0)
        d, out, part = dist[hit], self.extra[hit], self.part[hit]
        most = np.zeros(self.parts, dist.dtype)
        np.maximum.at(most, part, d + out)
        self.low[hit] = np.maximum(self.low[hit], np.maximum(d + out, most[part] - d))
        self.high[hit] = np.minimum(self.high[hit], d + out + most[part])
        # from the source's own leaf to all others: exact
        other = np.where(hit == of[part], 0, d + out)
        reach = np.zeros(self.parts, dist.dtype)
        np.maximum.at(reach, part, other)
        exact = np.where(reach[self.part[sources]] > 0, reach[self.part[sources]] + self.extra[sources], 0)
        self.high[sources] = np.minimum(self.high[sources], exact)
        self.best = max(self.best, exact.max())

    def meet(self, open_: np.ndarray, marks: np.ndarray) -> bool:
        """Closes open nodes by pairs: two leaves are at most as far apart as by way of a landmark (a row of ``marks``).

        A way longer than the best known one has two open ends, so only open nodes meet each other. False: too many of them."""
        open_ = open_[np.argsort(self.part[open_], kind="stable")]
        cuts = np.append(np.flatnonzero(_rank(self.part[open_]) == 0), len(open_))
        if (np.diff(cuts).astype(float) ** 2).sum() * len(marks) > PAIR_SUMS:
            return False
        for low, high in zip(cuts[:-1], cuts[1:]):
            some = open_[low:high]
            d = marks[:, some]
            d = d[d[:, 0] < self.far]  # landmarks of this component
            if not len(d):
                continue
            rows = max(1, PAIR_CELLS // len(some))
            for at in range(0, len(some), rows):
                mine = some[at : at + rows]
                ways = d[0, at : at + rows, None] + d[0]
                for row in d[1:]:
                    np.minimum(ways, row[at : at + rows, None] + row, out=ways)
                ways += self.extra[mine][:, None] + self.extra[some]
                ways[np.arange(len(mine)), at + np.arange(len(mine))] = 0
                self.high[mine] = np.minimum(self.high[mine], np.maximum(ways.max(1), self.best))
        return True

    @property
    def above(self):
        return max(self.best, self.high.max()).item()


def bounded_diameter(
    g: LocalGraph, *, radius: np.ndarray | None = None, tolerance: float = 0.0, most_searches: int | None = None,
    search: Search | None = None, wave: int = 8,
) -> tuple:
    """(below, above, plain) of the diameter over all components: lower and upper bound, and the upper bound without radii.

    Both are equal unless ``tolerance`` (a share) or ``most_searches`` ends the work before. Searches start at nodes whose
    eccentricity the triangle inequality leaves open, a wave of them at a time, those of one search in different
    components. ``radius``: the way between u and v counts radius(u) + radius(v) more."""
    n = len(g)
    if not n:
        return 0, 0, 0
    search = search or g.search
    part = g.components()
    main, plain = Bounds(g, part, radius), Bounds(g, part, None)
    first = np.lexsort((-np.diff(g.start), part))
    sets, done = [first[_rank(part[first]) == 0]], 0
    marks, most_marks = np.zeros((0, n), g.kind), min(MOST_LANDMARKS, LANDMARK_CELLS // n)
    of_marks, marking, met, pays = _rank(part[first]), False, n, True
    while True:
        found = search(sets)
        for sources, dist in zip(sets, found):
            main.learn(sources, dist)
            if radius is not None:
                plain.learn(sources, dist)
        done += len(sets)
        if marking:
            marks = np.concatenate([marks, found])
        if len(marks):
            open_ = np.flatnonzero(main.high > main.best)
            if len(open_) and (marking or 2 * len(open_) < met):
                # more landmarks only while they close more than searches from open nodes would
                pays = main.meet(open_, marks) and len(open_) - np.count_nonzero(main.high > main.best) > 2 * len(sets)
                met = len(open_)
        open_ = np.flatnonzero(main.high > (main.best * (1 + tolerance) if tolerance else main.best))
        if not len(open_) or (most_searches and done >= most_searches):
            return main.best.item(), main.above, (main if radius is None else plain).above
        # landmarks are the nodes of most edges, none before two waves
        few = max(LANDMARKS, len(marks))
        ranks = range(len(marks), len(marks) + few)
        marking = not tolerance and not most_searches and done > 2 and len(open_) > 2 * few and len(marks) + few <= most_marks and pays
        if marking and (of_marks == ranks[-1]).any():
            sets = [first[of_marks == k] for k in ranks]
            continue
        marking = False
        # the nodes of the largest upper bounds close themselves, central ones lower those of many
        far, mid = (open_[np.lexsort((key[open_], part[open_]))] for key in (-main.high, main.low))
        ranks = _rank(part[far])  # the same for both orders: equal counts per component
        few = min(wave, max(8, done))  # early searches teach the most: waves grow with what is known
        sets = [order[ranks == k] for k in range(max(1, few // 2)) for order in (far, mid) if (ranks == k).any()]


def fold_leaves(g: LocalGraph) -> tuple[LocalGraph, np.ndarray, object]:
    """(what is left, how far out its nodes' hanging trees reach, the longest way within such a tree): leaves are cut until there are none.

    The diameter is the larger of that way and the diameter of what is left with the reaches at both ends; a tree leaves one node."""
    n = len(g)
    here = np.repeat(np.arange(n), np.diff(g.start))
    once = here < g.to
    a, b, w = here[once], g.to[once], g.w[once]
    degree, edge = np.diff(g.start), np.zeros(n, np.int64)  # edge: the exclusive or of the numbers of a node's edges still there
    number = np.arange(len(a))
    np.bitwise_xor.at(edge, a, number)
    np.bitwise_xor.at(edge, b, number)
    reach, gone, best = np.zeros(n, g.kind), np.zeros(n, bool), g.kind.type(0)
    leaf = np.flatnonzero(degree == 1)
    while len(leaf):
        e = edge[leaf]
        up = a[e] + b[e] - leaf
        keep = (degree[up] > 1) | (leaf > up)  # of two last nodes the smaller one stays
        leaf, up, e = leaf[keep], up[keep], e[keep]
        far = reach[leaf] + w[e]
        order = np.lexsort((-far, up))
        top, rank = up[order], _rank(up[order])
        first, second = far[order][rank == 0], far[order][rank == 1]
        own = top[rank == 0]
        best = max(best, (first + reach[own]).max())
        if len(second):
            both = np.isin(own, top[rank == 1], assume_unique=True)
            best = max(best, (first[both] + second).max())
        reach[own] = np.maximum(reach[own], first)
        gone[leaf], degree[leaf] = True, 0
        np.subtract.at(degree, up, 1)
        np.bitwise_xor.at(edge, up, e)
        leaf = own[degree[own] == 1]
    stays = ~(gone[a] | gone[b])
    core = LocalGraph(g.ids[a[stays]], g.ids[b[stays]], w[stays], g.ids[~gone])
    return core, reach[~gone], best


def exact_diameter_of(g: LocalGraph, spark: SparkSession | None = None):
    """The largest distance within a component: hanging trees are folded, what is left is searched (with a session: in parallel tasks, if it is large)."""
    core, reach, best = fold_leaves(g)
    search, wave = (core.search, 8) if spark is None else searches(spark, core)
    return max(best.item() if hasattr(best, "item") else best, bounded_diameter(core, radius=reach, search=search, wave=wave)[0])


def sweep_bound(g: LocalGraph, sweeps: int = 4, radius: np.ndarray | None = None):
    """An upper bound: for each component twice the least eccentricity that a few farthest-node searches find."""
    n, part = len(g), g.components()
    if not n:
        return 0
    extra = np.zeros(n, g.kind) if radius is None else radius.astype(g.kind)
    parts = int(part.max()) + 1
    bound = np.full(parts, g.far)
    sources = np.unique(part, return_index=True)[1]
    for _ in range(sweeps):
        d = g.search([sources])[0] + extra
        far = np.lexsort((np.arange(n), -d, part))
        sources = far[_rank(part[far]) == 0]
        bound = np.minimum(bound, 2 * d[sources])
    return bound.max().item()


def local_sweeps(g: LocalGraph, source: int = 0, sweeps: int = 4):
    """The largest eccentricity that farthest-node searches from one place find: a lower bound of its component's diameter."""
    best = 0
    for _ in range(sweeps):
        d = g.search([np.array([source])])[0]
        d = np.where(d < g.far, d, -1)
        source = int(d.argmax())
        best = max(best, d[source].item())
    return best


def quotient_diameter(
    edges: DataFrame | LocalGraph, mode: str = "bounds", *, tolerance: float = 0.0, most_searches: int | None = None, radius: dict | None = None
) -> tuple:
    """(the diameter, the same with clusters' radii at both ends) of a quotient of checked size; the second null without radii.

    ``exact``: one search per node in parallel tasks; ``bounds``: few searches, exact unless ``tolerance`` or
    ``most_searches`` ends them (then an upper bound); ``sweep2``: twice an eccentricity."""
    g = local_graph(edges) if isinstance(edges, DataFrame) else edges
    at = None if radius is None else np.array([radius.get(i, 0) for i in g.ids.tolist()], g.kind if len(g) else np.int64)
    alone = 0 if radius is None else max([2 * r for r in radius.values()], default=0)
    if mode == "sweep2":
        return sweep_bound(g), None if radius is None else max(alone, sweep_bound(g, radius=at))
    search, wave = searches(edges.sparkSession, g) if isinstance(edges, DataFrame) else searches_here(g)
    limits = {"tolerance": tolerance, "most_searches": most_searches, "search": search, "wave": wave}
    if mode == "exact":
        if isinstance(edges, LocalGraph):
            phi = g.eccentricities().max(initial=0).item()
        else:
            kind = "double" if g.kind.kind == "f" else "long"
            phi = eccentricities(edges, kind).agg(F.max("ecc").alias("d")).first()["d"] or 0
        return phi, None if radius is None else max(alone, bounded_diameter(g, radius=at, **limits)[1])
    _, above, plain = bounded_diameter(g, radius=at, **limits)
    return plain, None if radius is None else max(alone, above)
