import math

import pytest
from pyspark.sql import functions as F

from spanweave.operators import decompose, graph, growth, sssp
from spanweave.operators.quotient import quotient
from spanweave.plans.loop import Superstep, fixed_plan
from spanweave.sources import generators
from tests import reference


def run(spark, g, centers, delta, steps=None, **options):
    loop = Superstep(spark)
    with fixed_plan(spark, g.partitions):
        state = growth.place_centers(growth.initial_state(g.nodes), F.col("node").isin(centers))
        if steps is None:
            return growth.grow_to_fixpoint(loop, state, g, delta, **options), loop
        for i in range(steps):
            state, got, s = loop.run(growth.grow_step(state, g, delta, **options), growth.counters(), growth.WORKING)
            loop.note("t", 0, 0, delta, got, s)
    return state, loop


def table(state):
    return {r["node"]: (r["center"], r["grow_dist"]) for r in state.collect()}


GROW = [(1, 2, 2), (2, 3, 2), (3, 4, 9), (4, 5, 1), (5, 6, 1)]


def test_growth_example(spark, edges):
    g = graph.build(edges(GROW))
    state, _ = run(spark, g, [1, 5], 4, steps=2)
    assert table(state) == {1: (1, 0), 2: (1, 2), 3: (1, 4), 4: (5, 1), 5: (5, 0), 6: (5, 1)}
    clusters = state.select("node", "center", "path_weight", F.lit(0).alias("stage"))
    d = decompose.Decomposition(clusters, 4, 2, 4, 1, 1, None, 1)
    assert [tuple(r) for r in quotient(g, d).collect()] == [(1, 5, 14)]


def test_counters_by_hand(spark, edges):
    _, loop = run(spark, graph.build(edges(GROW)), [1, 5], 4, steps=1)
    assert (loop.steps[0].messages, loop.steps[0].updates, loop.steps[0].covered, loop.steps[0].uncovered) == (3, 3, 5, 1)


def test_equal_distance_goes_to_the_smaller_center(spark, edges):
    state, _ = run(spark, graph.build(edges([(1, 3, 2), (2, 3, 2)])), [1, 2], 2)
    assert table(state)[3] == (1, 2)


def test_late_equal_offer_is_refused(spark, edges):
    state, _ = run(spark, graph.build(edges([(1, 4, 3), (0, 3, 1), (3, 4, 2)])), [0, 1], 3)
    assert table(state)[4] == (1, 3)


def test_node_at_the_threshold_offers_nothing(spark, edges):
    state, _ = run(spark, graph.build(edges([(1, 2, 4), (2, 3, 1)])), [1], 4)
    assert table(state)[3] == (None, None)


@pytest.mark.parametrize("options", [{"active_only": False}, {"combine": "window"}])
def test_forms_of_a_step_agree(spark, options):
    g = graph.build(generators.mesh(spark, 8))
    plain, _ = run(spark, g, [0, 27, 60], 5_000_000_000, steps=3)
    other, _ = run(spark, g, [0, 27, 60], 5_000_000_000, steps=3, **options)
    assert table(plain) == table(other)


def test_path_weight_survives_contraction(spark, edges):
    g = graph.build(edges([(0, 1, 5), (1, 2, 5), (2, 3, 5)]))
    loop = Superstep(spark)
    with fixed_plan(spark):
        state = growth.place_centers(growth.initial_state(g.nodes), F.col("node") == 0)
        for stage in range(3):
            state, _, _ = loop.run(growth.grow_step(state, g, 5), growth.counters(), growth.WORKING)
            state = growth.settle(state, stage)
    got = {r["node"]: (r["grow_dist"], r["path_weight"]) for r in state.collect()}
    assert got == {0: (0, 0), 1: (5, 5), 2: (5, 10), 3: (5, 15)}


def test_rescaled_contraction(spark, edges):
    g = graph.build(edges([(0, 1, 3), (1, 2, 3), (2, 3, 3)]))
    loop, seen = Superstep(spark), []
    with fixed_plan(spark):
        state = growth.place_centers(growth.initial_state(g.nodes), F.col("node") == 0)
        for i in range(1, 4):
            state = growth.grow_to_fixpoint(loop, state, g, 4)
            seen.append(sorted((r["node"], r["grow_dist"], r["path_weight"]) for r in state.filter("settled_stage is null and center is not null").collect()))
            state = growth.settle(state, i, rescale=4)
    assert seen == [[(0, 0, 0), (1, 3, 3)], [(2, 2, 6)], [(3, 1, 9)]]


def test_explicit_contraction(spark, edges):
    g = graph.build(edges([(0, 1, 3), (1, 2, 3), (2, 3, 3)]))
    state, _ = run(spark, g, [0], 4)
    assert sorted(map(tuple, growth.contract(state, g).collect())) == [(0, 2, 3), (2, 0, 3), (2, 3, 3), (3, 2, 3)]
    assert sorted(map(tuple, growth.contract_rescaled(state, g, 4).collect())) == [(0, 2, 2), (2, 0, 2), (2, 3, 3), (3, 2, 3)]


@pytest.mark.parametrize(("seed", "tau", "side"), [(7, 1, 14), (8, 2, 15)])
def test_staged_decomposition_matches_sequential(spark, seed, tau, side):
    """Two seeds, two tau, an even and an odd number of nodes."""
    edges = generators.mesh(spark, side)
    rows = [tuple(r) for r in edges.collect()]
    g = graph.build(edges)
    mean = math.ceil(sum(w for _, _, w in rows) / len(rows))
    center, path = reference.staged(rows, tau, seed, mean)
    d = decompose.staged_decompose(g, tau, seed=seed)
    assert {r["node"]: (r["center"], r["path_weight"]) for r in d.clusters.collect()} == {v: (center[v], path[v]) for v in center}


@pytest.mark.parametrize("seed", [7, 9])
def test_rescaled_decomposition_matches_sequential(spark, seed):
    edges = generators.mesh(spark, 13)
    g = graph.build(edges)
    radius = decompose.staged_decompose(g, 1, seed=seed).radius
    center, path, when = reference.rescaled([tuple(r) for r in edges.collect()], radius, seed)
    d = decompose.rescaled_decompose(g, 1, seed=seed, radius=radius)
    assert {r["node"]: (r["center"], r["path_weight"], r["stage"]) for r in d.clusters.collect()} == {v: (center[v], path[v], when[v]) for v in center}
    log_n = decompose.logarithm(g.n)
    assert d.count <= 8 * log_n**4 and d.radius <= 2 * radius * math.ceil(log_n)


def plan_text(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("hub_edges", [None, 3])
def test_a_step_exchanges_only_offers(spark, hub_edges):
    """The edges as built, no broadcast by size: one exchange of any kind, of offers; hubs add broadcasts of marked rows only."""
    g = graph.build(generators.mesh(spark, 8), hub_edges=hub_edges)
    loop = Superstep(spark)
    with fixed_plan(spark, g.partitions):
        state = loop.start(growth.place_centers(growth.initial_state(g.nodes), F.col("node") == 0), g.partitions)
        state, _, _ = loop.run(growth.grow_step(state, g, 10), growth.counters(), growth.WORKING)
        text = plan_text(growth.grow_step(state, g, 10))
    exchanges = text.count("Exchange") - text.count("BroadcastExchange")
    assert exchanges == text.count("Exchange hashpartitioning(dst") == 1
    assert "Cartesian" not in text and "NestedLoop" not in text and "SortMergeJoin" not in text
    assert ("BroadcastExchange" in text) == (hub_edges is not None)
    assert "PushedFilters: [IsNotNull(w), LessThanOrEqual(w,10)" in text


def test_a_relaxation_exchanges_only_offers(spark):
    g = graph.build(generators.mesh(spark, 8))
    loop = Superstep(spark)
    with fixed_plan(spark, g.partitions):
        start = F.col("node") == 0
        state = g.nodes.select(
            "node", F.when(start, F.lit(0).cast("long")).alias("dist"), F.lit(None).cast("long").alias("parent"), F.lit(0).alias("hops")
        )
        state = loop.start(state, g.partitions)
        text = plan_text(sssp._relax(state, "dist is not null", g, None, {}))
    assert text.count("Exchange") == text.count("Exchange hashpartitioning(dst") == 1


def test_hubs_give_the_same_clusters_and_distances(spark):
    edges = generators.hub_and_tail(spark, 40, 10)
    flat, split = graph.build(edges), graph.build(edges, hub_edges=5)
    assert split.hubs.collect()[0]["hub"] == 0 and split.hub_edges.count() == 41 and split.edges.count() == flat.edges.count()
    one, two = (sorted(map(tuple, decompose.staged_decompose(g, 1).clusters.collect())) for g in (flat, split))
    assert one == two
    assert sorted(map(tuple, sssp.bellman_ford(flat, 50).dist.collect())) == sorted(map(tuple, sssp.bellman_ford(split, 50).dist.collect()))


def test_old_checkpoints_are_dropped(spark):
    """While a loop runs two states stay on disk; at its end the clusters alone."""
    import os

    from spanweave.session import shared_dir

    shared_dir(spark)
    folder = spark.sparkContext._jsc.sc().getCheckpointDir().get().removeprefix("file:")
    count = lambda: sum(n.startswith("rdd-") for n in os.listdir(folder))
    g = graph.build(generators.mesh(spark, 8))
    before = count()
    loop = Superstep(spark)
    with fixed_plan(spark, g.partitions):
        state = loop.start(growth.place_centers(growth.initial_state(g.nodes), F.col("node") == 0), g.partitions)
        for _ in range(6):
            state, _, _ = loop.run(growth.grow_step(state, g, 2**40), growth.counters(), growth.WORKING)
    assert count() == before + 2
    loop.release()
    decompose.staged_decompose(g, 1)
    assert count() == before + 1


def test_shortcuts_without_a_bound(spark, edges):
    """Without a bound every pair within the distance gets its edge; a bound of two-edge ways was demanded before."""
    both = graph.symmetrize(edges([(0, i, 1) for i in range(1, 6)]))
    assert graph.add_shortcuts(both, 2, max_rows=None).count() == 30
    with pytest.raises(ValueError):
        graph.add_shortcuts(both, 2, max_rows=10)
