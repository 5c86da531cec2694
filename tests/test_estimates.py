import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from spanweave.operators import baselines, decompose, estimate, graph, measures, quotient, sssp
from spanweave.operators.components import connected_components
from spanweave.operators.quotient import LocalGraph, bounded_diameter, exact_diameter_of, sweep_bound
from spanweave.sources import fixtures, generators
from tests import reference


@pytest.fixture(scope="module")
def small(spark):
    edges = generators.mesh(spark, 14)
    return graph.build(edges), reference.neighbours([tuple(r) for r in edges.collect()])


def test_known_diameter_of_the_part_mesh(spark, data):
    assert baselines.exact_diameter(graph.build(fixtures.part_mesh(spark, data))) == 33_303_823_696


@pytest.mark.parametrize("method", ["staged", "rescaled", "hop"])
def test_estimates_are_conservative(small, method):
    g, adj = small
    row, d = estimate.estimate_diameter(g, 1, method=method)
    assert reference.diameter(adj) <= row["estimate"] <= reference.diameter(adj) * 3
    check = measures.check_partition(d, g).first()
    assert check["missing"] == check["outside"] == 0 and check["nodes"] == check["distinct_nodes"] == g.n


def test_arrival(small):
    g, _ = small
    base = decompose.staged_decompose(g, 1)
    assert measures.check_arrival(decompose.rescaled_decompose(g, 1, base=base), g, 2 * base.radius).isEmpty()


def test_few_nodes_are_singletons_and_exact(spark, edges):
    g = graph.build(edges([(1, 2, 2), (2, 3, 2), (3, 4, 9)]))
    row, d = estimate.estimate_diameter(g, 1)
    assert (row["radius"], row["clusters"], row["estimate"]) == (0, 4, 13)


def test_disconnected_graph_ends(spark, edges):
    pairs = [(i, i + 1, 1 + i % 5) for i in range(0, 400, 2)]
    g = graph.build(edges(pairs), edges([(999, 999, 1)]).select(F.col("src").alias("node")))
    row, _ = estimate.estimate_diameter(g, 1)
    assert row["estimate"] >= 5
    assert estimate.diameter_by_component(g).agg(F.max("diameter")).first()[0] == 5


def test_bad_weights_are_refused(spark, edges):
    for w in (0, -1, None):
        with pytest.raises(ValueError):
            graph.build(edges([(1, 2, 3), (2, 3, w)]))
    with pytest.raises(ValueError):
        graph.build(edges([(1, 2, float("nan"))], "double"))
    g = graph.build(edges([(1, 1, 5), (1, 2, 4), (2, 1, 3)]))
    assert sorted(map(tuple, g.edges.select("src", "dst", "w").collect())) == [(1, 2, 3), (2, 1, 3)]
    with pytest.raises(ValueError):
        decompose.staged_decompose(g, 5)


def test_start_threshold_on_two_kinds_of_weight(spark, data):
    from spanweave.workloads import start_thresholds

    low, high = start_thresholds(spark, "bimodal", fixtures.part_mesh(spark, data, "bimodal"), {"min": "min", "heavy": 2_000_000})
    assert low[3] <= high[3] and low[2] < high[2]


def test_step_cap_keeps_the_bound(spark):
    g = graph.build(generators.hub_and_tail(spark, 60, 60))
    row, d = estimate.estimate_diameter(g, 1, step_cap=2)
    assert row["estimate"] >= 61


@pytest.mark.parametrize("delta", [None, 2**31, 2**34])
def test_bucketed_distances(small, delta):
    g, adj = small
    p = sssp.bucketed_sssp(g, 0, delta)
    assert {r["node"]: r["dist"] for r in p.dist.collect()} == reference.search(adj, 0)


def test_quotient_modes(small):
    g, _ = small
    got = {m: estimate.estimate_diameter(g, 1, quotient_mode=m)[0]["estimate"] for m in ("exact", "bounds", "sweep2")}
    assert got["exact"] == got["bounds"] <= got["sweep2"]


def test_estimator_needs_fewer_rounds_than_bucketed_search(spark, data):
    g = graph.build(fixtures.part_mesh(spark, data))
    row, _ = estimate.fast_estimate(g, tau=1)
    paths = sssp.bellman_ford(g, sssp.pick_source(g))
    assert row["rounds"] < paths.rounds and row["work"] < paths.loop.work


def test_components_of_a_path_a_star_and_a_loop(spark, edges):
    rows = [(i, i + 1, 1) for i in range(50)] + [(100, 100 + i, 1) for i in range(1, 30)] + [(200, 200, 1)]
    got = {r["node"]: r["component"] for r in connected_components(edges(rows), "src", "dst").collect()}
    assert got == {**{i: 0 for i in range(51)}, **{100 + i: 100 for i in range(30)}}


def test_components_take_logarithmic_rounds_on_an_ordered_path(spark):
    path = spark.range(4000).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    rounds = []
    got = connected_components(path, "src", "dst", rounds)
    assert got.agg(F.max("component"), F.count("*")).first() == (0, 4001)
    assert len(rounds) <= 14


def local(rows):
    return LocalGraph(*(np.array(c) for c in zip(*rows)))


def test_k_center_and_doubling(spark):
    g = local([tuple(r) for r in generators.mesh(spark, 3, "unit").collect()])
    assert measures.brute_k_center(g, 1) == 2 and 2 <= measures.greedy_k_center(g, 1) <= 4
    g = local([tuple(r) for r in generators.mesh(spark, 12, "unit").collect()])
    assert 1 <= measures.doubling_estimate(g, 3, (1, 2)) <= 4


def test_choose_tau():
    assert estimate.choose_tau(10**6, eps=0.5) == 1000
    assert estimate.choose_tau(10**9) >= estimate.choose_tau(10**9, max_quotient_nodes=10_000) >= 1


@given(st.lists(st.tuples(st.integers(0, 14), st.integers(0, 14), st.integers(1, 9)).filter(lambda e: e[0] != e[1]), min_size=1, max_size=30), st.booleans())
@settings(max_examples=60, deadline=None)
def test_local_searches_against_a_heap(rows, real):
    """Distances, eccentricities, both diameters (plain, and with a leaf at each node) of any graph, connected or not."""
    adj = reference.neighbours(rows)
    g = local([(a, b, w / 4 if real else w) for a, b, w in rows])
    far = {u: reference.search(adj, u) for u in adj}
    unit = 4 if real else 1
    for i, u in enumerate(g.ids.tolist()):
        d = g.search([np.array([i])])[0]
        assert {v: x * unit for v, x in zip(g.ids.tolist(), d) if x < g.far} == far[u]
    assert [e * unit for e in g.eccentricities()] == [max(far[u].values()) for u in g.ids.tolist()]
    exact = max(max(x.values()) for x in far.values())
    below, above, _ = bounded_diameter(g, wave=4)
    assert below * unit == above * unit == exact <= sweep_bound(g) * unit
    radius = np.array([u % 5 for u in g.ids.tolist()])
    leaves = max((x + u % 5 + v % 5 for u in far for v, x in far[u].items() if u != v), default=0)
    assert bounded_diameter(g, radius=radius / unit if real else radius)[1] * unit == leaves
    assert bounded_diameter(g, tolerance=0.5)[1] * unit >= exact <= bounded_diameter(g, most_searches=1)[1] * unit
    assert bounded_diameter(g, radius=radius)[2] * unit >= exact
    assert exact_diameter_of(g) * unit == exact


def test_parallel_searches_equal_local_ones(spark, small, monkeypatch):
    from spanweave.operators import quotient as q

    g, adj = small
    monkeypatch.setattr(q, "HERE", 0)
    assert q.quotient_diameter(g.canonical().select("src", "dst", F.col("pw").alias("w")))[0] == reference.diameter(adj)


def test_components_of_all_sizes_are_estimated_apart(spark, edges):
    """Many one-edge components and a large one: stages do not grow with their number, and the bound holds."""
    pairs = [(10_000 + 2 * i, 10_001 + 2 * i, 1 + i % 5) for i in range(1000)]
    mesh = [tuple(r) for r in generators.mesh(spark, 12).collect()]
    g = graph.build(edges(pairs + mesh))
    per = {r["component"]: r for r in estimate.diameter_by_component(g, small=100, tau=1).collect()}
    exact = reference.diameter(reference.neighbours(mesh))
    assert len(per) == 1001 and not per[0]["exact"] and exact <= per[0]["diameter"] <= 3 * exact
    assert all(per[10_000 + 2 * i]["diameter"] == 1 + i % 5 for i in range(1000))
    got = estimate.estimate_components(g, small=100, tau=1)
    assert (got["estimate"], got["components"], got["estimated"]) == (per[0]["diameter"], 1001, 1)


@pytest.mark.parametrize("limits", [{}, {"array_edges": 4}])
def test_large_components_are_exact_on_request(spark, edges, limits):
    """In arrays, and in supersteps beyond their limits: no estimate stands where the exact diameter is asked for."""
    mesh = [tuple(r) for r in generators.mesh(spark, 3).collect()]
    tree = [(1000 + (i - 1) // 3, 1000 + i, 1 + i * 7 % 11) for i in range(1, 8)]
    g = graph.build(edges(mesh + tree + [(5000, 5001, 3)]))
    per = {r["component"]: r for r in estimate.diameter_by_component(g, small=4, exact=True, **limits).collect()}
    want = {0: reference.diameter(reference.neighbours(mesh)), 1000: reference.diameter(reference.neighbours(tree)), 5000: 3}
    assert {c: r["diameter"] for c, r in per.items()} == want and all(r["exact"] for r in per.values())


def test_real_weights(spark, data):
    """Vectors' distances as weights: estimate, search and exact diameter on doubles."""
    e = fixtures.embedding_knn(spark, data, k=4)
    g = graph.build(e)
    adj = reference.neighbours([tuple(r) for r in e.collect()])
    source = min(adj)
    dist = {r["node"]: r["dist"] for r in sssp.bucketed_sssp(g, source, 2.5).dist.filter("dist is not null").collect()}
    assert dist == pytest.approx(reference.search(adj, source))
    row, _ = estimate.estimate_diameter(g, 1)
    assert reference.diameter(adj) <= row["estimate"] * (1 + 1e-9)


def test_the_sum_per_cluster_is_tighter(small):
    g, adj = small
    d = decompose.staged_decompose(g, 1)
    wide, fine = (estimate.estimate_diameter(g, base=d, bound=b)[0]["estimate"] for b in ("radius", "per_cluster"))
    assert reference.diameter(adj) <= fine <= wide


def test_a_quotient_too_large_for_the_driver_is_solved(spark, small, monkeypatch):
    g, _ = small
    two = graph.build(g.canonical().select("src", "dst", F.col("pw").alias("w")).unionByName(g.canonical().select(F.col("src") + 10_000, F.col("dst") + 10_000, "pw").toDF("src", "dst", "w")))
    d = decompose.staged_decompose(two, 1)
    options = {"base": d, "quotient_mode": "bounds"}
    want = [estimate.estimate_diameter(two, bound=b, **options)[0]["estimate"] for b in ("radius", "per_cluster")]
    monkeypatch.setattr(quotient.local_graph, "__defaults__", (100_000, 10))
    monkeypatch.setattr(estimate, "MAX_EDGES", 10)
    assert [estimate.estimate_diameter(two, bound=b, **options)[0]["estimate"] for b in ("radius", "per_cluster")] == want


def test_large_graphs_get_more_buckets(spark, edges, monkeypatch):
    monkeypatch.setattr(graph, "BUCKET_EDGES", 10)
    g = graph.build(edges([(i, i + 1, 1) for i in range(60)]))
    assert g.partitions == 12 and estimate.estimate_diameter(g)[0]["estimate"] >= 60


@pytest.mark.parametrize("method", ["staged", "rescaled"])
def test_estimates_do_not_depend_on_the_number_of_clusters(spark, monkeypatch, method):
    g = graph.build(generators.mesh(spark, 16), array_edges=1000)
    wants = [estimate.estimate_diameter(g, 2, method=method, quotient_mode=m)[0]["estimate"] for m in ("exact", "bounds")]
    monkeypatch.setattr(estimate, "EXACT_UP_TO", 1)
    monkeypatch.setattr(estimate, "TOLERANCE", 1.0)
    monkeypatch.setattr(estimate, "MOST_SEARCHES", 1)
    assert [estimate.estimate_diameter(g, 2, method=method)[0]["estimate"]] * 2 == wants
