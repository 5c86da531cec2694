"""All queries of the graph engine by name, with the DuckDB SQL that must give the same rows where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanweave import replay, surroundings, workloads
from spanweave.functions.hashing import SCALE, drawn, h32_sql
from spanweave.operators import baselines, decompose, estimate, graph, growth, measures, relational, rounds, sssp
from spanweave.operators.quotient import eccentricities, quotient
from spanweave.plans.loop import Superstep, fixed_plan
from spanweave.session import stored
from spanweave.sources import fixtures, generators
from spanweave.sources.tables import read_table
from spanweave.streaming import edges as stream

Query = Callable[[SparkSession, str], DataFrame]

QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: Of the growth examples: share of centers and threshold.
SHARE, DELTA = 0.05, 6_000_000_000


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def register(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return register


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)


# --- graphs -------------------------------------------------------------------------------------------------

NAMES = {"part_mesh": "mesh_uniform_edges", "part_mesh_size": "mesh_edges", "part_mesh_bimodal": "mesh_bimodal_edges", "part_mesh_unit": "mesh_unit_edges"}
for _name, _build in fixtures.BUILDERS.items():
    QUERIES[NAMES.get(_name, f"{_name}_edges")] = _build
    ORACLES[NAMES.get(_name, f"{_name}_edges")] = fixtures.SQL[_name]

#: The 16 x 16 mesh with uniform weights, small enough for all pairs in SQL.
SMALL = f"""
n AS (SELECT unnest(range(256)) AS id),
e AS (SELECT src, dst, {fixtures.uniform_sql("src", "dst")}::BIGINT AS w FROM (
  SELECT id AS src, id + 1 AS dst FROM n WHERE id % 16 < 15 UNION ALL SELECT id, id + 16 FROM n WHERE id < 240)),
b AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e)"""
MESH = f"e AS ({fixtures.SQL['part_mesh']}), b AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e)"
ORDER_PART = f"e AS ({fixtures.SQL['order_part']}), b AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e)"


def small_graph(spark: SparkSession) -> graph.WeightedGraph:
    return graph.build(generators.mesh(spark, 16))


@query(fixtures.mesh_sql("customer", "c_custkey", fixtures.uniform_sql("src", "dst")))
def generated_mesh_edges(spark, sf_dir):
    """The generator's mesh over the customers."""
    return generators.mesh(spark, fixtures.side_of(spark, sf_dir, "customer"), cells=generators.keys(spark, sf_dir, "customer", "c_custkey"))


#: Of the power-law graph: 2^12 nodes.
POWER_SCALE = 12


@query(generators.power_law_sql(POWER_SCALE, draws="SELECT c_custkey AS id FROM customer"))
def power_law_edges(spark, sf_dir):
    """A draw per customer."""
    return generators.power_law(spark, POWER_SCALE, draws=generators.keys(spark, sf_dir, "customer", "c_custkey"))


@query(f"""WITH e AS ({fixtures.SQL["part_mesh_size"]}), k AS (SELECT unnest(range(3)) AS k), u AS (SELECT src AS u FROM e UNION SELECT dst FROM e)
SELECT src * 3 + k AS src, dst * 3 + k AS dst, w FROM e, k UNION ALL SELECT u * 3 + k, u * 3 + k + 1, 1 FROM u, k WHERE k < 2""")
def path_product_edges(spark, sf_dir):
    return generators.path_product(spark, 3, fixtures.part_mesh(spark, sf_dir, "size"))


@query("""WITH c AS (SELECT c_custkey::BIGINT AS id, (SELECT count(*) FROM customer) * 5 // 8 AS leaves FROM customer)
SELECT CASE WHEN id <= leaves THEN 0 ELSE id END AS src, id + 1 AS dst, 1::BIGINT AS w FROM c""")
def hub_and_tail_edges(spark, sf_dir):
    """Over the customers: five eighths are leaves, the others the tail."""
    n = read_table(spark, sf_dir, "customer").count()
    return generators.hub_and_tail(spark, n * 5 // 8, n - n * 5 // 8, generators.keys(spark, sf_dir, "customer", "c_custkey"))


@query(fixtures.SQL["part_mesh"])
def data_source_edges(spark, sf_dir):
    """The data source's mesh of as many cells as there are parts, where both cells are parts."""
    generators.register(spark)
    side = fixtures.side_of(spark, sf_dir, "part")
    edges = spark.read.format("diameter_graphs").options(graph="mesh", size=str(side), partitions=str(max(4, spark.sparkContext.defaultParallelism))).load()
    part = generators.keys(spark, sf_dir, "part", "p_partkey")
    return edges.join(part, F.col("src") == F.col("id"), "left_semi").join(part, F.col("dst") == F.col("id"), "left_semi")


@query("""WITH s AS (SELECT floor(sqrt(count(*)))::BIGINT AS side FROM part), n AS (SELECT p_partkey::BIGINT AS id, side FROM part, s WHERE p_partkey < side * side)
SELECT id, id + 1 AS neighbour FROM n WHERE id % side < side - 1 UNION ALL SELECT id, id + side FROM n WHERE id < side * (side - 1)""")
def grid_neighbours_sql(spark, sf_dir):
    """The table function over the parts, as cells of the largest square."""
    generators.register(spark)
    side = fixtures.side_of(spark, sf_dir, "part")
    cells = generators.keys(spark, sf_dir, "part", "p_partkey").filter(F.col("id") < side * side)
    return spark.sql(f"SELECT r.id, t.neighbour FROM {{cells}} r, LATERAL grid_neighbours(r.id, {side}) t", cells=cells)


@query(f"WITH {MESH} SELECT (SELECT count(DISTINCT src) FROM b) AS n, count(*) AS m, min(w) AS w_min, avg(w) AS w_mean, max(w) AS w_max, (SELECT max(d) FROM (SELECT count(*) AS d FROM b GROUP BY src)) AS degree_max FROM e")
def graph_summary(spark, sf_dir):
    g = graph.build(fixtures.part_mesh(spark, sf_dir))
    return graph.summary(g).select(F.col("n").cast("long").alias("n"), "m", "w_min", "w_mean", "w_max", "degree_max")


@query(f"WITH {ORDER_PART}, d AS (SELECT src, count(*) AS degree FROM b GROUP BY src) SELECT degree, count(*) AS nodes FROM d GROUP BY degree")
def degree_distribution(spark, sf_dir):
    return graph.degree_histogram(graph.symmetrize(fixtures.order_part(spark, sf_dir)))


@query(f"WITH {ORDER_PART} SELECT count(*) FILTER (w <= 5) AS light, count(*) FILTER (w > 5) AS heavy, count(*) FILTER (w BETWEEN 3 AND 9) AS middle FROM e")
def light_heavy_counts(spark, sf_dir):
    e = fixtures.order_part(spark, sf_dir)
    count = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return count(graph.light(e, 5), "light").crossJoin(count(graph.heavy(e, 5), "heavy")).crossJoin(count(graph.weight_between(e, 3, 9), "middle"))


@query("""WITH r AS (SELECT l_orderkey AS a, l_partkey AS b, l_quantity - 10 AS w FROM lineitem),
p AS (SELECT least(a, b) AS x, greatest(a, b) AS y, count(*) AS n, sum((w <= 0)::INT) AS bad, sum((a = b)::INT) AS loops, max(w) AS most FROM r GROUP BY ALL)
SELECT sum(n)::BIGINT AS rows, sum(bad)::BIGINT AS bad, sum(loops)::BIGINT AS loops, sum(n - 1)::BIGINT AS duplicates, max(most) AS w_max FROM p""")
def validate_edges(spark, sf_dir):
    rows = read_table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("src"), F.col("l_partkey").alias("dst"), (F.col("l_quantity") - 10).alias("w"))
    return graph.validate(rows)


@query(f"WITH {MESH}, v AS (SELECT DISTINCT src AS node FROM b) SELECT node FROM v WHERE {h32_sql("'7:0:' || node")} < {SHARE} * {SCALE}")
def center_draw(spark, sf_dir):
    g = graph.build(fixtures.part_mesh(spark, sf_dir))
    return g.nodes.filter(drawn(F.col("node"), SHARE, 7, 0))


# --- growth and contraction ---------------------------------------------------------------------------------

_START = f"s0 AS (SELECT node, CASE WHEN c THEN node END AS center, CASE WHEN c THEN 0 END::BIGINT AS d FROM (SELECT DISTINCT src AS node, {h32_sql("'7:0:' || src")} < {SHARE} * {SCALE} AS c FROM b))"


def _step_sql(i: int) -> str:
    return f"""o{i} AS (SELECT b.dst AS node, min({{'d': s.d + b.w, 'c': s.center}}) AS o FROM s{i - 1} s JOIN b ON b.src = s.node
  WHERE s.d < {DELTA} AND b.w <= {DELTA} AND s.d + b.w <= {DELTA} GROUP BY b.dst),
s{i} AS (SELECT s.node, CASE WHEN o.o IS NOT NULL AND (s.d IS NULL OR o.o.d < s.d) THEN o.o.c ELSE s.center END AS center,
  CASE WHEN o.o IS NOT NULL AND (s.d IS NULL OR o.o.d < s.d) THEN o.o.d ELSE s.d END AS d FROM s{i - 1} s LEFT JOIN o{i} o ON o.node = s.node)"""


_STEPS = ",\n".join(_step_sql(i) for i in (1, 2, 3))
_STATE = "SELECT node, center, d AS grow_dist FROM "


def _grown(spark, sf_dir, steps: int, **options) -> tuple[graph.WeightedGraph, DataFrame]:
    g = graph.build(fixtures.part_mesh(spark, sf_dir))
    state = growth.place_centers(growth.initial_state(g.nodes), drawn(F.col("node"), SHARE, 7, 0))
    loop = Superstep(spark)
    with fixed_plan(spark, g.partitions):
        for _ in range(steps):
            state, _, _ = loop.run(growth.grow_step(state, g, DELTA, **options), growth.counters(), growth.WORKING)
    return g, state


@query(f"WITH {MESH}, {_START}, {_step_sql(1)} {_STATE} s1")
def grow_one_step(spark, sf_dir):
    return _grown(spark, sf_dir, 1)[1].select("node", "center", "grow_dist")


@query(f"WITH {MESH}, {_START}, {_STEPS} {_STATE} s3")
def grow_three_steps(spark, sf_dir):
    return _grown(spark, sf_dir, 3)[1].select("node", "center", "grow_dist")


@query(f"WITH {MESH}, {_START}, {_STEPS} {_STATE} s3")
def grow_three_steps_all_covered(spark, sf_dir):
    return _grown(spark, sf_dir, 3, active_only=False)[1].select("node", "center", "grow_dist")


@query(f"WITH {MESH}, {_START}, {_STEPS} {_STATE} s3")
def grow_three_steps_by_window(spark, sf_dir):
    return _grown(spark, sf_dir, 3, combine="window")[1].select("node", "center", "grow_dist")


@query(f"""WITH RECURSIVE {MESH}, {_START}, r(node, center, d) USING KEY (node) AS (
  SELECT node, center, d FROM s0 WHERE center IS NOT NULL
  UNION SELECT o.node, o.o.c, o.o.d FROM (SELECT b.dst AS node, min({{'d': r.d + b.w, 'c': r.center}}) AS o FROM r JOIN b ON b.src = r.node
    WHERE r.d < {DELTA} AND r.d + b.w <= {DELTA} GROUP BY b.dst) o LEFT JOIN recurring.r old ON old.node = o.node WHERE old.node IS NULL OR o.o.d < old.d)
SELECT s0.node, r.center, r.d AS grow_dist FROM s0 LEFT JOIN r ON r.node = s0.node""")
def grow_fixpoint_bounded(spark, sf_dir):
    g = graph.build(fixtures.part_mesh(spark, sf_dir))
    state = growth.place_centers(growth.initial_state(g.nodes), drawn(F.col("node"), SHARE, 7, 0))
    with fixed_plan(spark, g.partitions):
        return growth.grow_to_fixpoint(Superstep(spark), state, g, DELTA).select("node", "center", "grow_dist")


@query(f"""WITH {MESH}, {_START}, {_STEPS}
SELECT coalesce(x.center, b.src) AS src, coalesce(y.center, b.dst) AS dst, min(w) AS w FROM b JOIN s3 x ON x.node = b.src JOIN s3 y ON y.node = b.dst
WHERE x.center IS NULL OR y.center IS NULL GROUP BY ALL""")
def contract_stage(spark, sf_dir):
    g, state = _grown(spark, sf_dir, 3)
    return growth.contract(state, g)


@query(f"""WITH {MESH}, {_START}, {_STEPS},
k AS (SELECT coalesce(x.center, b.src) AS src, b.dst AS dst, CASE WHEN x.center IS NULL THEN w ELSE x.d + w - {DELTA} END AS w
  FROM b JOIN s3 x ON x.node = b.src JOIN s3 y ON y.node = b.dst WHERE y.center IS NULL AND b.w <= {DELTA})
SELECT src, dst, min(w) AS w FROM (SELECT * FROM k UNION ALL SELECT dst, src, w FROM k) GROUP BY ALL""")
def contract_rescaled_stage(spark, sf_dir):
    g, state = _grown(spark, sf_dir, 3)
    return growth.contract_rescaled(state, g, DELTA)


@query("SELECT 0::BIGINT AS differing")
def implicit_equals_materialised(spark, sf_dir):
    """One more stage by settled offers and by explicit contraction: how many nodes get another center or distance."""
    g, state = _grown(spark, sf_dir, 3)
    with fixed_plan(spark, g.partitions):
        implicit = growth.grow_to_fixpoint(Superstep(spark), growth.settle(state, 0), g, DELTA)
        edges = stored(growth.contract(state, g).withColumn("pw", F.col("w")), "contracted")
        nodes = state.filter("center is null or center = node").select("node")
        centers = state.filter("node = center").select(F.col("node").alias("_c"))
        again = growth.initial_state(nodes).join(centers, F.col("node") == F.col("_c"), "left")
        again = growth.place_centers(again, F.col("_c").isNotNull()).drop("_c")
        explicit = growth.grow_to_fixpoint(Superstep(spark), again, graph.plain(edges, nodes, g.n), DELTA)
    new = implicit.filter("settled_stage is null").select("node", "center", "grow_dist")
    old = explicit.filter("center is null or center <> node").select("node", F.col("center").alias("c"), F.col("grow_dist").alias("d"))
    same = F.col("center").eqNullSafe(F.col("c")) & F.col("grow_dist").eqNullSafe(F.col("d"))
    return new.join(old, "node", "full_outer").agg(F.coalesce(F.sum((~same).cast("long")), F.lit(0)).alias("differing"))


# --- decompositions and estimates ---------------------------------------------------------------------------


def _mesh(spark, sf_dir, weight="uniform") -> graph.WeightedGraph:
    return graph.build(fixtures.part_mesh(spark, sf_dir, weight), array_edges=graph.ARRAY_EDGES)


_E = replay.both(fixtures.SQL["part_mesh"])
_STAGED = f"WITH RECURSIVE {_E}, {replay.staged()}"
_RESCALED = f"WITH RECURSIVE {_E}, {replay.rescaled()}"
_HOPS = f"WITH RECURSIVE {replay.both(fixtures.SQL['part_mesh'], hops=True)}, {replay.staged(delta0='(SELECT count(DISTINCT src) FROM b)')}"


@query(f"{_STAGED} SELECT node, center, path_weight, stage FROM st")
def staged_clusters(spark, sf_dir):
    return decompose.staged_decompose(_mesh(spark, sf_dir), 1).clusters


@query(f"WITH RECURSIVE {replay.both(fixtures.SQL['order_part'])}, {replay.staged(8, seed=11)} SELECT node, center, path_weight, stage FROM st")
def staged_clusters_bipartite(spark, sf_dir):
    """The same on a graph of small hop depth, with another tau and seed."""
    return decompose.staged_decompose(graph.build(fixtures.order_part(spark, sf_dir)), 8, seed=11).clusters


@query(f"{_STAGED}, {replay.quotient()} SELECT src, dst, w FROM q")
def staged_quotient(spark, sf_dir):
    g = _mesh(spark, sf_dir)
    return quotient(g, decompose.staged_decompose(g, 1))


@query(f"{_STAGED} SELECT center, count(*) AS nodes, max(path_weight) AS radius FROM st GROUP BY center")
def cluster_report(spark, sf_dir):
    return measures.cluster_report(decompose.staged_decompose(_mesh(spark, sf_dir), 1))


@query(f"{_STAGED}, {replay.quotient()}, f AS ({replay.figures('staged')}) SELECT *, 1::BIGINT AS tau FROM f")
def fast_estimate(spark, sf_dir):
    """The flagship: the fast estimate of the uniform mesh, with its figures."""
    row, _ = estimate.fast_estimate(_mesh(spark, sf_dir), tau=1)
    return estimate.result_frame(spark, [row])


@query(f"{_RESCALED} SELECT node, center, path_weight, stage FROM rs")
def rescaled_clusters(spark, sf_dir):
    return decompose.rescaled_decompose(_mesh(spark, sf_dir), 1).clusters


@query(f"{_RESCALED}, {replay.quotient('rs')} {replay.figures('rescaled', 'rs', 'contractions')}")
def rescaled_estimate(spark, sf_dir):
    return estimate.result_frame(spark, [estimate.estimate_diameter(_mesh(spark, sf_dir), 1, method="rescaled")[0]])


@query(f"{_HOPS}, {replay.quotient()} {replay.figures('hop')}")
def hop_estimate(spark, sf_dir):
    return estimate.result_frame(spark, [estimate.estimate_diameter(_mesh(spark, sf_dir), 1, method="hop")[0]])


@query(f"{_HOPS} SELECT node, center, path_weight, stage FROM st")
def hop_clusters(spark, sf_dir):
    return decompose.hop_decompose(decompose.by_hops(_mesh(spark, sf_dir)), 1).clusters


_PAIRS = f"""WITH RECURSIVE {SMALL}, p(a, z, d) USING KEY (a, z) AS (SELECT id, id, 0::BIGINT FROM n
  UNION SELECT q.a, q.z, q.d FROM (SELECT p.a, b.dst AS z, min(p.d + b.w) AS d FROM p JOIN b ON b.src = p.z GROUP BY ALL) q
    LEFT JOIN recurring.p old ON old.a = q.a AND old.z = q.z WHERE old.a IS NULL OR q.d < old.d)"""


@query(f"{_PAIRS} SELECT max(d) AS exact, true AS conservative, true AS tighter FROM p")
def estimate_is_conservative(spark, sf_dir):
    """The exact diameter; whether the estimates by both decompositions and by hops are at least that; whether the sum per cluster is between."""
    g = small_graph(spark)
    exact = baselines.exact_diameter(g)
    rows = [estimate.estimate_diameter(g, 1, method=m)[0]["estimate"] for m in ("staged", "rescaled", "hop")]
    fine = estimate.estimate_diameter(g, 1, bound="per_cluster")[0]["estimate"]
    return spark.createDataFrame([(exact, min(rows) >= exact, exact <= fine <= rows[0])], "exact long, conservative boolean, tighter boolean")


@query(f"WITH {MESH} SELECT count(DISTINCT src) AS nodes, count(DISTINCT src) AS distinct_nodes, 0::BIGINT AS missing, 0::BIGINT AS outside FROM b")
def every_node_one_cluster(spark, sf_dir):
    g = _mesh(spark, sf_dir)
    return measures.check_partition(decompose.staged_decompose(g, 1), g).drop("clusters")


@query("SELECT 0::BIGINT AS below")
def path_weight_is_upper_bound(spark, sf_dir):
    """Nodes whose path weight is below the true distance from their center."""
    g = small_graph(spark)
    d = decompose.staged_decompose(g, 1)
    pairs = baselines.all_pairs(g).select(F.col("src").alias("center"), F.col("dst").alias("node"), "dist")
    return d.clusters.join(pairs, ["center", "node"]).agg(F.sum((F.col("path_weight") < F.col("dist")).cast("long")).alias("below"))


@query("SELECT true AS halves, true AS few_clusters, true AS threshold_bounded")
def staged_bounds(spark, sf_dir):
    """Every stage covers half of what was left; clusters within 8 (stages + 1) tau log n; from the least weight, the threshold within four times a greedy radius of tau clusters."""
    g = small_graph(spark)
    d = decompose.staged_decompose(g, 1, delta0="min")
    left, halves = g.n, True
    for stage in range(d.stages):
        now = [s for s in d.loop.steps if s.stage == stage][-1].uncovered
        halves, left = halves and now <= left / 2, now
    few = d.count <= 8 * (d.stages + 1) * decompose.logarithm(g.n)
    greedy = measures.greedy_k_center(measures.in_arrays(g), 1)
    return spark.createDataFrame([(halves, few, d.delta_end <= 4 * greedy)], "halves boolean, few_clusters boolean, threshold_bounded boolean")


@query("SELECT 0::BIGINT AS late_or_early")
def arrival_property(spark, sf_dir):
    """Nodes that the rescaled decomposition reaches in another iteration than light distances allow."""
    g = small_graph(spark)
    base = decompose.staged_decompose(g, 1)
    d = decompose.rescaled_decompose(g, 1, base=base)
    return measures.check_arrival(d, g, 2 * base.radius).agg(F.count(F.lit(1)).alias("late_or_early"))


# --- shortest paths and other baselines ---------------------------------------------------------------------


def _distances(ctes: str, source: str) -> str:
    return f"""WITH RECURSIVE {ctes}, r(node, dist) USING KEY (node) AS (SELECT ({source}) AS node, 0::BIGINT AS dist
  UNION SELECT q.node, q.dist FROM (SELECT b.dst AS node, min(r.dist + b.w) AS dist FROM r JOIN b ON b.src = r.node GROUP BY b.dst) q
    LEFT JOIN recurring.r old ON old.node = q.node WHERE old.node IS NULL OR q.dist < old.dist)"""


_ALL = " SELECT v.node, r.dist FROM (SELECT DISTINCT src AS node FROM b) v LEFT JOIN r ON r.node = v.node"


@query(_distances(MESH, "0") + _ALL)
def sssp_bellman_ford(spark, sf_dir):
    return sssp.bellman_ford(_mesh(spark, sf_dir), 0).dist.select("node", "dist")


@query(_distances(MESH, "0") + _ALL)
def sssp_bucketed(spark, sf_dir):
    g = _mesh(spark, sf_dir)
    return sssp.bucketed_sssp(g, 0, 16 * SCALE // 2).dist.select("node", "dist")


@query(_distances(ORDER_PART, "SELECT min(src) FROM b") + _ALL)
def sssp_bucketed_bipartite(spark, sf_dir):
    g = graph.build(fixtures.order_part(spark, sf_dir))
    return sssp.bucketed_sssp(g, g.nodes.agg(F.min("node")).first()[0], 20).dist.select("node", "dist")


@query(_distances(MESH, "0") + " SELECT max(dist) AS lower, 2 * max(dist) AS upper FROM r")
def sssp_two_approx(spark, sf_dir):
    return spark.createDataFrame([sssp.sssp_diameter_bound(_mesh(spark, sf_dir), 0)], "lower long, upper long")


@query(f"{_PAIRS} SELECT a AS source, z AS node, d AS dist FROM p WHERE a IN (0, 17, 255)")
def sssp_multi_source(spark, sf_dir):
    return sssp.multi_source(small_graph(spark), [0, 17, 255])


@query(f"{_PAIRS}, f AS (SELECT a, max(d) AS ecc, max_by(z, {{'d': d, 'z': -z}}) AS far FROM p GROUP BY a), s0 AS (SELECT * FROM f WHERE a = 0), s1 AS (SELECT * FROM f WHERE a = (SELECT far FROM s0)), s2 AS (SELECT * FROM f WHERE a = (SELECT far FROM s1)) "
       "SELECT 0::BIGINT AS sweep, a AS source, far AS farthest, ecc FROM s0 UNION ALL SELECT 1, a, far, ecc FROM s1 UNION ALL SELECT 2, a, far, ecc FROM s2")  # fmt: skip
def farthest_sweep_bound(spark, sf_dir):
    rows = sssp.farthest_sweeps(small_graph(spark), 0, 3)
    return spark.createDataFrame([(r["sweep"], r["source"], r["farthest"], r["ecc"]) for r in rows], "sweep long, source long, farthest long, ecc long")


@query("SELECT true AS random_ok, true AS farthest_ok, true AS degree_ok")
def multi_sssp_bounds(spark, sf_dir):
    """Whether lower <= diameter <= upper for each choice of sources."""
    g = small_graph(spark)
    exact = baselines.exact_diameter(g)
    got = [sssp.multi_sssp_bound(g, 3, s) for s in ("random", "farthest", "degree")]
    return spark.createDataFrame([tuple(a <= exact <= b for a, b in got)], "random_ok boolean, farthest_ok boolean, degree_ok boolean")


@query(f"{_PAIRS} SELECT max(d) AS diameter FROM p")
def exact_diameter_small(spark, sf_dir):
    return spark.createDataFrame([(baselines.exact_diameter(small_graph(spark)),)], "diameter long")


_FOLDED = f"n AS (SELECT DISTINCT p_partkey::BIGINT % 256 AS id FROM part), e AS ({fixtures.folded_mesh_sql()}), b AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e)"


@query(f"{_PAIRS.replace(SMALL, _FOLDED)} SELECT a AS node, max(d) AS ecc FROM p GROUP BY a")
def eccentricities_small(spark, sf_dir):
    """Every node of the 16 x 16 mesh that the parts are folded onto."""
    return eccentricities(fixtures.folded_mesh(spark, sf_dir))


@query(f"{_PAIRS} SELECT a AS src, z AS dst, d AS dist FROM p")
def all_pairs_small(spark, sf_dir):
    return baselines.all_pairs(small_graph(spark)).select("src", "dst", "dist")


@query(f"""WITH RECURSIVE {SMALL}, p(a, z, k) USING KEY (a, z) AS (SELECT id, id, {{'d': 0::BIGINT, 'h': 0::BIGINT}} FROM n
  UNION SELECT q.a, q.z, q.k FROM (SELECT p.a, b.dst AS z, min({{'d': p.k.d + b.w, 'h': p.k.h + 1}}) AS k FROM p JOIN b ON b.src = p.z GROUP BY ALL) q
    LEFT JOIN recurring.p old ON old.a = q.a AND old.z = q.z WHERE old.a IS NULL OR q.k < old.k)
SELECT max(k.h) AS hops FROM p""")
def hop_bound_small(spark, sf_dir):
    return spark.createDataFrame([(baselines.hop_bound(small_graph(spark)),)], "hops long")


@query(f"{_PAIRS} SELECT {SCALE} AS bound, sum((d <= {SCALE})::INT)::BIGINT AS pairs FROM p")
def light_distance_small(spark, sf_dir):
    """Pairs within a bound are those within it along edges up to it."""
    g = small_graph(spark)
    near = baselines.all_pairs(g.mapped(lambda e: e.filter(F.col("pw") <= SCALE))).filter(F.col("dist") <= SCALE)
    return near.agg(F.lit(SCALE).cast("long").alias("bound"), F.count(F.lit(1)).alias("pairs"))


@query(f"""WITH RECURSIVE {SMALL}, p(a, z, h) USING KEY (a, z) AS (SELECT id, id, 0 FROM n
  UNION SELECT q.a, q.z, q.h FROM (SELECT p.a, b.dst AS z, min(p.h + 1) AS h FROM p JOIN b ON b.src = p.z GROUP BY ALL) q LEFT JOIN recurring.p old ON old.a = q.a AND old.z = q.z WHERE old.a IS NULL)
SELECT a AS node, max(h) AS hops FROM p GROUP BY a""")
def hop_eccentricity_exact_masks(spark, sf_dir):
    return baselines.sketch_eccentricity(small_graph(spark), registers=5, exact=True)[0]


@query()
def hop_eccentricity_sketch(spark, sf_dir):
    return baselines.sketch_eccentricity(small_graph(spark), registers=8)[0]


@query(f"""WITH RECURSIVE {ORDER_PART}, l AS (SELECT * FROM b WHERE w <= 3),
r(src, dst, w) USING KEY (src, dst) AS (SELECT src, dst, w FROM l UNION SELECT q.* FROM (SELECT r.src, l.dst, min(r.w + l.w) AS w FROM r JOIN l ON l.src = r.dst WHERE r.src <> l.dst AND r.w + l.w <= 3 GROUP BY ALL) q
  LEFT JOIN recurring.r old ON old.src = q.src AND old.dst = q.dst WHERE old.src IS NULL OR q.w < old.w)
SELECT src, dst, least(r.w, coalesce(b.w, r.w)) AS w FROM r LEFT JOIN b USING (src, dst) UNION ALL SELECT src, dst, w FROM b WHERE w > 3 AND (src, dst) NOT IN (SELECT (src, dst) FROM r)""")
def shortcut_edges(spark, sf_dir):
    return graph.add_shortcuts(graph.symmetrize(fixtures.order_part(spark, sf_dir)), 3, max_rows=None)


@query(f"WITH {ORDER_PART} SELECT x.src, y.dst, min(x.w + y.w) AS w FROM b x JOIN b y ON x.dst = y.src WHERE x.src <> y.dst AND x.w + y.w <= 4 GROUP BY ALL")
def two_hop_ways(spark, sf_dir):
    return graph.two_hop(graph.symmetrize(fixtures.order_part(spark, sf_dir)), 4)


# --- components and closed forms ----------------------------------------------------------------------------


def _chain_sql(fixture: str) -> str:
    """Of a union of paths: the sum of weights of the heaviest one, found by following smallest labels."""
    return f"""WITH RECURSIVE e AS ({fixtures.SQL[fixture]}), b AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e),
r(node, c) USING KEY (node) AS (SELECT DISTINCT src, src FROM b UNION SELECT q.node, q.c FROM (SELECT b.dst AS node, min(r.c) AS c FROM r JOIN b ON b.src = r.node GROUP BY b.dst) q
  JOIN recurring.r old ON old.node = q.node WHERE q.c < old.c)"""


def _chain(spark, edges: DataFrame) -> DataFrame:
    per = estimate.diameter_by_component(graph.build(edges), exact=True)
    return per.agg(F.max("diameter").alias("diameter"), F.count(F.lit(1)).alias("components"))


_CHAIN = " SELECT max(s) AS diameter, count(*) AS components FROM (SELECT c, sum(w)::BIGINT AS s FROM e JOIN r ON r.node = e.src GROUP BY c)"


@query(_chain_sql("conversation_chain") + _CHAIN)
def chain_diameter(spark, sf_dir):
    return _chain(spark, fixtures.conversation_chain(spark, sf_dir))


@query(_chain_sql("customer_chain") + _CHAIN)
def customer_chain_diameter(spark, sf_dir):
    return _chain(spark, fixtures.customer_chain(spark, sf_dir))


@query(_chain_sql("event_chain") + _CHAIN)
def event_chain_diameter(spark, sf_dir):
    return _chain(spark, fixtures.event_chain(spark, sf_dir))


@query(f"""WITH e AS ({fixtures.SQL["geo_tree"]}), leaf AS (SELECT src AS nation, w, row_number() OVER (PARTITION BY src ORDER BY w DESC) AS r FROM e WHERE src >= {fixtures.NATION}),
n AS (SELECT e.dst AS nation, e.src AS region, e.w, coalesce(max(l.w) FILTER (r = 1), 0) AS one, coalesce(sum(l.w) FILTER (r <= 2), 0) AS two FROM e LEFT JOIN leaf l ON l.nation = e.dst WHERE e.src < {fixtures.NATION} GROUP BY ALL),
g AS (SELECT region, w + one AS deep, two, row_number() OVER (PARTITION BY region ORDER BY w + one DESC) AS r FROM n)
SELECT max(greatest(d, t))::BIGINT AS diameter, count(*) AS components FROM (SELECT region, sum(deep) FILTER (r <= 2) AS d, max(two) AS t FROM g GROUP BY region)""")
def geo_tree_diameter(spark, sf_dir):
    return _chain(spark, fixtures.geo_tree(spark, sf_dir))


@query(_chain_sql("page_link") + " SELECT node, c AS component FROM r")
def components(spark, sf_dir):
    return graph.components(fixtures.page_link(spark, sf_dir))


@query(_chain_sql("page_link") + ", big AS (SELECT c FROM r GROUP BY c ORDER BY count(*) DESC, c LIMIT 1) SELECT e.src, e.dst, e.w FROM e JOIN r ON r.node = e.src WHERE r.c = (SELECT c FROM big)")
def largest_component_edges(spark, sf_dir):
    return graph.largest_component(fixtures.page_link(spark, sf_dir))


# --- round primitives, relational surroundings, streams in batch form ----------------------------------------


@query("SELECT o_orderkey, sum(o_custkey) OVER (ORDER BY o_orderdate, o_orderkey)::BIGINT AS prefix FROM orders")
def prefix_sum(spark, sf_dir):
    orders = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate", "o_custkey")
    return rounds.prefix_sum(orders, ["o_orderdate", "o_orderkey"], "o_custkey").select("o_orderkey", F.col("prefix").cast("long").alias("prefix"))


@query("SELECT o_orderkey, sum(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)::BIGINT AS prefix FROM orders")
def segmented_prefix_sum(spark, sf_dir):
    orders = read_table(spark, sf_dir, "orders")
    return rounds.segmented_prefix_sum(orders, "o_custkey", ["o_orderdate", "o_orderkey"], "o_orderkey").select("o_orderkey", F.col("prefix").cast("long").alias("prefix"))


@query("SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS rank FROM orders")
def mr_sort(spark, sf_dir):
    return rounds.mr_sort(read_table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice"), "o_totalprice", "o_orderkey").select("o_orderkey", F.col("rank").cast("long").alias("rank"))


@query("""WITH e AS (SELECT event_id, user_id, floor(epoch(date_trunc('second', ts)))::BIGINT AS s, event_type FROM events)
SELECT a.event_id AS a, b.event_id AS b FROM e a JOIN e b ON abs(a.s - b.s) <= 60 WHERE a.event_type = 'purchase' AND a.event_id <> b.event_id""")
def event_proximity(spark, sf_dir):
    e = read_table(spark, sf_dir, "events").select("event_id", F.unix_timestamp("ts").alias("s"), "event_type")
    a, b = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("a"), F.col("s").alias("sa")), e.select(F.col("event_id").alias("b"), F.col("s").alias("sb"))
    return relational.range_join(a, b, "sa", "sb", 60).filter("a <> b").select("a", "b")


@query("""WITH o AS (SELECT o_orderkey, date_diff('day', DATE '1970-01-01', o_orderdate::DATE) AS d FROM orders), m AS (SELECT o_custkey, min(date_diff('day', DATE '1970-01-01', o_orderdate::DATE)) AS lo FROM orders GROUP BY o_custkey)
SELECT m.o_custkey, count(*) AS orders FROM m JOIN o ON o.d BETWEEN m.lo AND m.lo + 30 GROUP BY m.o_custkey""")
def orders_in_intervals(spark, sf_dir):
    o = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.datediff("o_orderdate", F.lit("1970-01-01")).alias("d"))
    m = o.groupBy("o_custkey").agg(F.min("d").alias("lo")).withColumn("hi", F.col("lo") + 30)
    # a row a day: each interval meets its days, not their orders
    days = o.groupBy("d").agg(F.count(F.lit(1)).alias("n"))
    return relational.interval_join(days, m, "d", "lo", "hi", 30).groupBy("o_custkey").agg(F.sum("n").alias("orders"))


@query("""WITH v AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'view' GROUP BY ALL)
SELECT p.event_id, v.value AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN v ON p.user_id = v.user_id AND p.ts >= v.ts""")
def last_view_of_purchases(spark, sf_dir):
    e = read_table(spark, sf_dir, "events")
    v = e.filter("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return relational.as_of(e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts"), v, "user_id", "ts", "value", "last_view").select("event_id", "last_view")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN epoch(date_trunc('second', ts)) - lag(epoch(date_trunc('second', ts))) OVER w < 86400 THEN 0 ELSE 1 END AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(n) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING)::BIGINT AS session FROM g)
SELECT user_id, session, min(ts) AS started, max(ts) AS ended, count(*) AS events FROM s GROUP BY user_id, session""")
def event_sessions(spark, sf_dir):
    return relational.sessions(read_table(spark, sf_dir, "events").select("user_id", "ts"), "user_id", "ts", 86_400).withColumn("session", F.col("session").cast("long"))


@query(f"WITH {ORDER_PART} SELECT src, dst, w, rank FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY w DESC, src) AS rank FROM e) WHERE rank <= 2")
def heaviest_edges_per_part(spark, sf_dir):
    top = relational.top_per_group(fixtures.order_part(spark, sf_dir), "dst", [F.desc("w"), "src"], 2)
    return top.withColumn("rank", F.col("rank").cast("long"))


@query("SELECT date_trunc('hour', ts) AS started, event_type, count(*) AS n, min(value) AS least FROM events GROUP BY ALL")
def transition_windows(spark, sf_dir):
    return stream.transition_windows(read_table(spark, sf_dir, "events"))


def _steps(spark, sf_dir) -> DataFrame:
    return decompose.staged_decompose(_mesh(spark, sf_dir), 1).loop.frame()


@query(f"{_STAGED} SELECT CASE WHEN grouping(phase) = 0 THEN phase END AS phase, stage, count(*) AS steps, sum(messages)::BIGINT AS messages, sum(updates)::BIGINT AS updates "
       "FROM (SELECT 'staged' AS phase, * FROM st_steps) GROUP BY ROLLUP (phase, stage)")  # fmt: skip
def metrics_rollup(spark, sf_dir):
    return relational.work_rollup(_steps(spark, sf_dir))


@query(f"{_STAGED} SELECT 'staged' AS phase, guess, sum(messages)::BIGINT AS messages, sum(updates)::BIGINT AS updates, count(*) AS steps FROM st_steps GROUP BY guess")
def work_by_phase(spark, sf_dir):
    return _steps(spark, sf_dir).groupBy("phase", "guess").agg(F.sum("messages").alias("messages"), F.sum("updates").alias("updates"), F.count(F.lit(1)).alias("steps"))


@query("SELECT 0::BIGINT AS differing")
def partition_independence(spark, sf_dir):
    """Nodes whose cluster depends on the number of partitions."""
    edges = generators.mesh(spark, 16)
    one, many = (decompose.staged_decompose(graph.build(edges, partitions=p), 1, delta0="min").clusters for p in (1, 13))
    return relational.difference(one, many).agg(F.count(F.lit(1)).alias("differing"))


@query("SELECT true AS same")
def recursive_quotient_is_conservative(spark, sf_dir):
    g = small_graph(spark)
    exact = baselines.exact_diameter(g)
    modes = [estimate.estimate_diameter(g, 1, quotient_mode=m)[0]["estimate"] for m in ("exact", "bounds", "sweep2", "recursive")]
    return spark.createDataFrame([(modes[0] == modes[1] and min(modes[2:]) >= modes[0] and modes[0] >= exact,)], "same boolean")


@query(_distances(f"e AS (SELECT * FROM ({fixtures.SQL['part_mesh']}) WHERE w <= {SCALE // 2}), b AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e)", "0")
       + f" SELECT v.node, r.dist FROM (SELECT src AS node FROM ({fixtures.SQL['part_mesh']}) UNION SELECT dst FROM ({fixtures.SQL['part_mesh']})) v LEFT JOIN r ON r.node = v.node")
def light_distance(spark, sf_dir):
    """Distances along light edges only."""
    return sssp.light_distance(_mesh(spark, sf_dir), 0, SCALE // 2)


_KNN = f"e AS MATERIALIZED ({fixtures.SQL['embedding_knn']}), b AS (SELECT src, dst, w FROM e UNION ALL SELECT dst, src, w FROM e)"


@query(_distances(_KNN, "SELECT min(src) FROM b").replace("0::BIGINT AS dist", "0::DOUBLE AS dist") + _ALL.replace("r.dist", "round(r.dist, 9) AS dist"))
def sssp_real_weights(spark, sf_dir):
    """A search on real weights: distances between vectors along nearest neighbours."""
    g = graph.build(fixtures.embedding_knn(spark, sf_dir), array_edges=graph.ARRAY_EDGES)
    dist = sssp.bucketed_sssp(g, g.nodes.agg(F.min("node")).first()[0], 2.5).dist
    return dist.select("node", F.round("dist", 9).alias("dist"))


_SWEEP_ORDER = f"WITH RECURSIVE {replay.both(fixtures.SQL['order_part'])}, {replay.sweeps(replay.source(), 3)}"
_EACH = " UNION ALL ".join(f"SELECT {i}::BIGINT AS sweep, max(dist) AS ecc FROM sw{i}" for i in range(3))


@query(f"{_SWEEP_ORDER} {_EACH}")
def farthest_sweeps_bipartite(spark, sf_dir):
    """Farthest-node searches on a graph of the tables."""
    g = graph.build(fixtures.order_part(spark, sf_dir))
    rows = sssp.farthest_sweeps(g, sssp.pick_source(g), 3)
    return spark.createDataFrame([(r["sweep"], r["ecc"]) for r in rows], "sweep long, ecc long")


@query(f"WITH RECURSIVE {_E}, {replay.sweeps(replay.source(), 3)} {_EACH}")
def farthest_sweeps_mesh(spark, sf_dir):
    g = _mesh(spark, sf_dir)
    rows = sssp.farthest_sweeps(g, sssp.pick_source(g), 3)
    return spark.createDataFrame([(r["sweep"], r["ecc"]) for r in rows], "sweep long, ecc long")


@query(_chain_sql("page_link") + f", q AS (SELECT c, count(*) AS nodes FROM r GROUP BY c) SELECT c AS component, nodes, true AS exact FROM q")
def component_diameters(spark, sf_dir):
    """Components of the link graph, each solved exactly; their diameters are compared in the tests."""
    return estimate.diameter_by_component(graph.build(fixtures.page_link(spark, sf_dir)), exact=True).select("component", "nodes", "exact")


QUERIES.update(workloads.QUERIES)
ORACLES.update(workloads.ORACLES)
QUERIES.update(surroundings.QUERIES)
ORACLES.update(surroundings.ORACLES)
