"""Supersteps in arrays against the same supersteps as jobs: results, and every step's counters."""

from dataclasses import astuple

import numpy as np
import pytest

from spanweave import workloads
from spanweave.functions.hashing import drawn_here
from spanweave.operators import decompose, estimate, graph, measures, quotient, sssp
from spanweave.plans import arrays
from spanweave.sources import generators
from tests import reference


@pytest.fixture(scope="module")
def two(spark):
    """A mesh and two components that no search from it reaches, as jobs and in arrays."""
    rows = [tuple(r) for r in generators.mesh(spark, 5).collect()] + [(100, 101, 7), (101, 102, 7), (200, 201, 9)]
    edges = spark.createDataFrame(rows, "src long, dst long, w long")
    return graph.build(edges), graph.build(edges, array_edges=1000)


def steps(loop):
    return [astuple(s)[:-1] for s in loop.steps]


@pytest.mark.parametrize("delta", [None, 2**32])
def test_searches_agree(two, delta):
    jobs, arrays = (sssp.bucketed_sssp(g, 0, delta) for g in two)
    assert two[0].arrays is None and two[1].arrays is not None
    assert sorted(map(tuple, jobs.dist.collect())) == sorted(map(tuple, arrays.dist.collect()))
    assert [s[:9] for s in steps(jobs.loop)] == [s[:9] for s in steps(arrays.loop)] and jobs.dist.schema == arrays.dist.schema


@pytest.mark.parametrize("run", [
    lambda g: decompose.staged_decompose(g, 1, delta0="min", step_cap=2), lambda g: decompose.rescaled_decompose(g, 1, step_cap=2),
    lambda g: decompose.hop_decompose(decompose.by_hops(g), 1),
])
def test_decompositions_agree(two, run):
    jobs, arrays = (run(g) for g in two)
    assert sorted(map(tuple, jobs.clusters.collect())) == sorted(map(tuple, arrays.clusters.collect()))
    assert steps(jobs.loop) == steps(arrays.loop)
    assert (jobs.radius, jobs.count, jobs.delta_end, jobs.stages, jobs.guesses) == (arrays.radius, arrays.count, arrays.delta_end, arrays.stages, arrays.guesses)


def test_a_graph_beyond_the_bound_runs_as_jobs(spark):
    assert graph.build(generators.mesh(spark, 5), array_edges=39).arrays is None


@pytest.mark.parametrize("most_send", [0, 10**6])
@pytest.mark.parametrize("parts", [2, 4])
def test_parts_do_not_change_a_step(two, parts, most_send, monkeypatch):
    """Both ways to find what a part sends, and any number of parts."""
    monkeypatch.setattr(arrays, "MOST_SEND", most_send)
    for run in (lambda g: decompose.staged_decompose(g, 1, delta0="min"), lambda g: decompose.rescaled_decompose(g, 1)):
        jobs, dealt = run(two[0]), run(two[1].dealt(parts))
        assert len(dealt.grown.ranges) == parts and steps(jobs.loop) == steps(dealt.loop)
        assert sorted(map(tuple, jobs.clusters.collect())) == sorted(map(tuple, dealt.clusters.collect()))


def test_figures_of_a_small_graph_take_no_job_over_clusters(two, monkeypatch):
    """Radius, number of clusters and quotient come from the arrays of the growth."""
    hops = [decompose.hop_decompose(decompose.by_hops(g), 1) for g in two]
    for jobs, own in (hops, [decompose.staged_decompose(g, 1) for g in two]):
        assert sorted(map(tuple, quotient.quotient(two[0], jobs).collect())) == sorted(map(tuple, quotient.quotient(two[1], own).collect()))
    want = estimate.estimate_diameter(two[0], 1, quotient_mode="bounds")[0]

    def fail(*_):
        raise AssertionError("clusters were asked for as rows")

    monkeypatch.setattr(decompose._InArrays, "clusters", fail)
    got = estimate.estimate_diameter(two[1], 1, quotient_mode="bounds")[0]
    assert {k: v for k, v in got.items() if "seconds" not in k} == {k: v for k, v in want.items() if "seconds" not in k}


def test_draws_on_the_driver_equal_those_of_jobs(two, monkeypatch):
    from spanweave.functions.hashing import drawn

    nodes = two[1].nodes.filter(drawn(two[1].nodes["node"], 0.4, 7, 3)).toArrow().column(0).to_numpy()
    ids = two[1].arrays.ids
    assert sorted(nodes) == ids[drawn_here(ids, 0.4, 7, 3)].tolist()
    here = decompose.staged_decompose(two[1], 1)
    monkeypatch.setattr(decompose, "DRAWN_HERE", 0)
    assert steps(decompose.staged_decompose(two[1], 1).loop) == steps(here.loop)


def test_start_thresholds_and_local_graph_from_arrays(two, spark):
    for rule in ("min", "mean"):
        assert decompose.start_threshold(two[0], rule) == decompose.start_threshold(two[1], rule)
    one, other = (measures.in_arrays(g) for g in two)
    assert one.ids.tolist() == other.ids.tolist() and one.search([[0]]).tolist() == other.search([[0]]).tolist()
    # weights whose sum does not fit 64 bits
    far = graph.build(spark.createDataFrame([(i, j, 2**57) for i in range(12) for j in range(i)], "src long, dst long, w long"), array_edges=100)
    assert decompose.start_threshold(far, "mean") == 2**57


def test_scale_out_runs_in_parts_of_arrays(spark, data, monkeypatch):
    """Growth in parts; a graph beyond the bound runs as jobs in as many buckets, with the same rows."""
    monkeypatch.setattr(workloads.fixtures, "part_mesh", lambda spark, sf_dir: generators.mesh(spark, 5))
    seen, run = [], decompose._run

    def noted(g, loop):
        seen.append((g.arrays is None, g.partitions if g.arrays is None else g.array_parts))
        return run(g, loop)

    monkeypatch.setattr(decompose, "_run", noted)
    rows = workloads.bench_scale_out(spark, data).collect()
    assert seen == [(False, 1), (False, 2), (False, 4)] and len({r[1:] for r in rows}) == 1
    monkeypatch.setattr(graph, "ARRAY_EDGES", 10)
    assert workloads.bench_scale_out(spark, data).collect() == rows and seen[3:] == [(True, 1), (True, 2), (True, 4)]


def test_far_pairs_close_by_landmarks():
    rng, hubs = np.random.default_rng(1), 300
    core = [(i, int(j), int(rng.integers(1, 50))) for i in range(1, hubs) for j in rng.integers(0, i, 8)]
    fringe = [(hubs + k, int(c), int(rng.integers(40, 80))) for k in range(1500) for c in rng.choice(hubs, 2, replace=False)]
    g = quotient.LocalGraph(*(np.array(c) for c in zip(*core + fringe)))
    done = []

    def search(sets):
        done.extend(sets)
        return g.search(sets)

    dist = g.search([np.array([i]) for i in range(len(g))])
    assert quotient.bounded_diameter(g, search=search) == (dist.max(),) * 3 and len(done) < 50
    extra = rng.integers(0, 9, len(g))
    ways = dist + extra[:, None] + extra
    np.fill_diagonal(ways, 0)
    assert quotient.bounded_diameter(g, radius=extra)[:2] == (ways.max(),) * 2


def test_a_few_heavy_edges_do_not_widen_the_buckets_of_a_search():
    i = np.arange(2000)
    g = quotient.LocalGraph(np.append(i, i[:1000:50]), np.append(i + 1, i[:1000:50] + 900), np.append(np.ones(2000, np.int64), np.full(20, 700)))
    assert g.width == 4
    adj = reference.neighbours([(int(u), int(v), int(w)) for u, w, v in zip(np.repeat(g.ids, np.diff(g.start)), g.w, g.ids[g.to])])
    assert dict(enumerate(g.search([np.array([0])])[0].tolist())) == reference.search(adj, 0)


def test_a_large_quotient_that_grew_in_arrays_is_solved_there(spark, monkeypatch):
    g = graph.build(generators.mesh(spark, 12), array_edges=1000)
    d = decompose.staged_decompose(g, 1)
    want = [estimate.estimate_diameter(g, base=d, quotient_mode="bounds", bound=b)[0]["estimate"] for b in ("radius", "per_cluster")]
    monkeypatch.setattr(estimate, "MAX_EDGES", 1)
    monkeypatch.setattr(estimate, "large_quotient_diameter", None)
    assert [estimate.estimate_diameter(g, base=d, quotient_mode="bounds", bound=b)[0]["estimate"] for b in ("radius", "per_cluster")] == want


def test_arrays_hold_the_least_of_parallel_edges_in_32_bits(spark, edges):
    rows = [(i, (7 * i + 1) % 50, 1 + i % 9) for i in range(50)] + [((7 * i + 1) % 50, i, 5) for i in range(50)] + [(3, 3, 1)]
    one, two = graph.build(edges(rows)), graph.build(edges(rows), array_edges=1000)
    assert two.n == one.n and two.arrays.to.dtype == two.arrays.w.dtype == np.int32
    for e in ("edges", "nodes"):
        assert sorted(map(tuple, getattr(one, e).collect())) == sorted(map(tuple, getattr(two, e).collect()))
    a = two.arrays
    assert sorted(zip(a.ids[a.src].tolist(), a.ids[a.to].tolist(), a.pw.tolist())) == sorted((r["src"], r["dst"], r["pw"]) for r in one.edges.collect())
    with pytest.raises(ValueError):
        graph.build(edges([(0, 1, 0)]), array_edges=1000)


def test_widths_of_a_graph_in_arrays_need_no_frames(spark, monkeypatch):
    g = graph.build(generators.mesh(spark, 8), array_edges=1000)
    widths = sssp.widths(g)
    monkeypatch.setattr(arrays, "frame", None)
    got = {r["width"]: r["ecc"] for r in sssp.tune_bucket_width(g, 0, widths)}
    assert len(got) == 5 and len(set(got.values())) == 1
