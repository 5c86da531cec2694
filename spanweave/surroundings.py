"""Queries on the surroundings of the methods: reports, sets, windows, JSON, user functions and views, each with its SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spanweave.functions import hashing
from spanweave.operators import graph, relational
from spanweave.session import stored
from spanweave.sources import fixtures, generators
from spanweave.sources.tables import read_table

_ORDER_PART = fixtures.SQL["order_part"]
_ROAD, _SIZE = fixtures.SQL["road_like"], fixtures.SQL["part_mesh_size"]


def degree_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nodes by degree class with the mean and the largest degree: hubs show in the last classes."""
    d = graph.degrees(graph.symmetrize(fixtures.order_part(spark, sf_dir)))
    by = F.floor(F.log2("degree")).cast("long").alias("magnitude")
    return d.groupBy(by).agg(F.count(F.lit(1)).alias("nodes"), F.sum("degree").alias("ends"), F.max_by("node", F.struct("degree", "node")).alias("widest"))


def weight_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact quantiles of the weights, from which start thresholds are chosen."""
    e = fixtures.order_part(spark, sf_dir)
    return e.agg(*[F.percentile("w", q).alias(f"p{int(100 * q)}") for q in (0.1, 0.25, 0.5, 0.75, 0.9)], F.countDistinct("w").alias("kinds"))


def edges_by_nation_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders and value by nation and priority of the customer's market, with all subtotals."""
    c = read_table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("nation"))
    o = read_table(spark, sf_dir, "orders").select("o_custkey", F.year("o_orderdate").cast("long").alias("year"))
    both = o.join(c, F.col("o_custkey") == F.col("c_custkey"))
    return both.cube("nation", "year").agg(F.count(F.lit(1)).alias("orders"), F.grouping_id().cast("long").alias("level"))


def edge_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    fixtures.order_part(spark, sf_dir).createOrReplaceTempView("order_part_edges_view")
    return spark.sql(
        "SELECT w, dst % 10 AS part_class, count(*) AS edges FROM order_part_edges_view GROUP BY GROUPING SETS ((w), (dst % 10), ())"
    )


def edge_set_operations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What two edge snapshots share and do not."""
    road, mesh = fixtures.road_like(spark, sf_dir), fixtures.part_mesh(spark, sf_dir, "size")
    count = lambda df, name: df.agg(F.lit(name).alias("operation"), F.count(F.lit(1)).alias("edges"))
    parts = {
        "both": road.intersect(mesh), "only_mesh": mesh.exceptAll(road), "only_road": road.subtract(mesh), "either": road.union(mesh).distinct(),
    }
    out = None
    for name, df in parts.items():
        out = count(df, name) if out is None else out.unionByName(count(df, name))
    return out


def order_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rank family over a customer's orders."""
    o = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_totalprice")
    w = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return o.select(
        "o_orderkey", F.rank().over(w).cast("long").alias("rank"), F.percent_rank().over(w).alias("share"), F.ntile(4).over(w).cast("long").alias("quarter"),
        F.nth_value("o_orderkey", 2).over(whole).alias("second"), F.last_value("o_orderkey").over(whole).alias("dearest"),
    )


def orders_within_week(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders of the same customer in the seven days up to each order: a range frame."""
    o = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.datediff("o_orderdate", F.lit("1970-01-01")).cast("long").alias("day"))
    w = Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-7, 0)
    return o.select("o_orderkey", F.count(F.lit(1)).over(w).alias("near"))


def event_properties(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The JSON column by schema and by path, written back as JSON per event type."""
    e = read_table(spark, sf_dir, "events").select("event_type", F.from_json("props", "k long").alias("p"), F.get_json_object("props", "$.k").cast("long").alias("path"))
    agree = F.sum((F.col("p.k") == F.col("path")).cast("long")).alias("agree")
    per = e.groupBy("event_type").agg(F.count("p.k").alias("n"), F.sum("p.k").alias("total"), agree)
    return per.select("event_type", "n", "total", "agree", F.to_json(F.struct("n", "total")).alias("json"))


def neighbour_maps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Heavy neighbours of each supplier's node as a map: entries, least and most frequent key. Degrees are bounded by the customers."""
    e = fixtures.customer_supplier(spark, sf_dir)
    heavy = e.groupBy("dst").agg(F.map_from_entries(F.collect_list(F.struct("src", "w"))).alias("m"))
    few = F.map_filter("m", lambda k, v: v >= 25)
    keys = F.map_keys(few)
    return heavy.select("dst", F.size(few).cast("long").alias("heavy"), F.array_min(keys).alias("least"), F.element_at(few, F.array_min(keys)).alias("w"))


def hash_functions_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The engine's hashes called from SQL."""
    hashing.register_sql(spark)
    read_table(spark, sf_dir, "part").createOrReplaceTempView("part_view")
    return spark.sql("SELECT p_partkey AS node, h32(concat('7:0:', p_partkey)) AS h, uniform_weight(p_partkey, p_partkey + 1) AS w FROM part_view")


def hot_parts_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weight by part, the hottest parts spread over four partial sums that are combined afterwards."""
    e = fixtures.order_part(spark, sf_dir)
    hot = e.groupBy("dst").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "dst").limit(16).select("dst")
    salted = relational.with_salt(e, hot, "dst", 4)
    partial = salted.groupBy("dst", "_salt").agg(F.sum("w").alias("w"), F.count(F.lit(1)).alias("n"))
    return partial.groupBy("dst").agg(F.sum("w").alias("w"), F.sum("n").alias("edges"))


def links_like(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges among a list of nodes, and links by the form of their target."""
    e = fixtures.page_link(spark, sf_dir)
    some = e.filter(F.col("src").isin(list(range(0, 200, 2))))
    href = read_table(spark, sf_dir, "pages").select(F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href"))
    forms = href.agg(F.count_if(F.col("href").like("/%")).alias("local"), F.count_if(F.col("href").rlike("^https?://")).alias("absolute"))
    return some.agg(F.count(F.lit(1)).alias("among")).crossJoin(forms)  # one row each


def join_strategies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One join by three physical ways: rows and weight agree."""
    e = fixtures.order_part(spark, sf_dir)
    nodes = e.groupBy("src").agg(F.min("w").alias("least"))
    out = None
    for way in ("merge", "shuffle_hash", "broadcast"):
        one = e.join(nodes.hint(way), "src").agg(F.lit(way).alias("way"), F.count(F.lit(1)).alias("n"), F.sum(F.col("w") - F.col("least")).alias("excess"))
        out = one if out is None else out.unionByName(one)
    return out


def heaviest_page(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The second page of ten of the heaviest edges: order, offset and limit."""
    return fixtures.part_mesh(spark, sf_dir).orderBy(F.desc("w"), "src", "dst").offset(10).limit(10)


def comparison_by_method(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row a graph, one column a rule: the total weight of the mesh under each weight rule."""
    rows = None
    for rule in ("uniform", "size", "unit"):
        e = fixtures.part_mesh(spark, sf_dir, rule).agg(F.lit("mesh").alias("graph"), F.lit(rule).alias("method"), F.sum("w").alias("total"))
        rows = e if rows is None else rows.unionByName(e)
    return relational.comparison_table(rows, "total")


def vector_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Squared length of each vector by an Arrow user function and by built-in ones."""

    @F.pandas_udf("double")
    def squared(x: pd.Series) -> pd.Series:
        return pd.Series([float(np.sum(np.asarray(v, dtype=float) ** 2)) for v in x])

    v = read_table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    built = F.aggregate("x", F.lit(0.0), lambda a, b: a + b * b)
    return v.select("vec_id", (F.abs(squared("x") - built) < 1e-9).alias("agree"), F.round(built, 6).alias("square"))


def cluster_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per customer chain its span in days by a grouped user function: small groups, each in one task."""
    e = fixtures.customer_chain(spark, sf_dir)
    o = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    rows = e.join(o, F.col("src") == F.col("o_orderkey")).select("o_custkey", "w")

    def span(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"o_custkey": [pdf["o_custkey"].iloc[0]], "edges": [len(pdf)], "span": [int(pdf["w"].sum())], "widest": [int(pdf["w"].max())]})

    return rows.groupBy("o_custkey").applyInPandas(span, "o_custkey long, edges long, span long, widest long")


def power_law_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degrees of the generated power-law graph after a bucketed write and reread through the catalog."""
    from spanweave.operators.graph import build

    g = build(generators.power_law(spark, 8))
    out = stored(graph.degree_histogram(spark.table(g.table)), "degrees")
    g.release()
    return out


ROWS = {
    degree_profile: f"""WITH e AS ({_ORDER_PART}), d AS (SELECT node, count(*) AS degree FROM (SELECT src AS node FROM e UNION ALL SELECT dst FROM e) GROUP BY node)
SELECT floor(log2(degree))::BIGINT AS magnitude, count(*) AS nodes, sum(degree)::BIGINT AS ends, max_by(node, {{'d': degree, 'v': node}}) AS widest FROM d GROUP BY 1""",
    weight_quantiles: f"SELECT {', '.join(f'quantile_cont(w::DOUBLE, {q}) AS p{int(100 * q)}' for q in (0.1, 0.25, 0.5, 0.75, 0.9))}, count(DISTINCT w) AS kinds FROM ({_ORDER_PART})",
    edges_by_nation_cube: """SELECT nation, year, count(*) AS orders, grouping(nation, year)::BIGINT AS level FROM (SELECT c_nationkey::BIGINT AS nation, year(o_orderdate)::BIGINT AS year FROM orders
JOIN customer ON o_custkey = c_custkey) GROUP BY CUBE (nation, year)""",
    edge_grouping_sets: f"WITH e AS (SELECT w, dst % 10 AS part_class FROM ({_ORDER_PART})) SELECT w, part_class, count(*) AS edges FROM e GROUP BY GROUPING SETS ((w), (part_class), ())",
    edge_set_operations: f"""WITH r AS ({_ROAD}), m AS ({_SIZE}) SELECT 'both' AS operation, count(*) AS edges FROM (SELECT * FROM r INTERSECT SELECT * FROM m)
UNION ALL SELECT 'only_mesh', count(*) FROM (SELECT * FROM m EXCEPT ALL SELECT * FROM r) UNION ALL SELECT 'only_road', count(*) FROM (SELECT * FROM r EXCEPT SELECT * FROM m)
UNION ALL SELECT 'either', count(*) FROM (SELECT * FROM r UNION SELECT * FROM m)""",
    order_ranks: """SELECT o_orderkey, rank() OVER w AS rank, percent_rank() OVER w AS share, ntile(4) OVER w AS quarter, nth_value(o_orderkey, 2) OVER a AS second, last_value(o_orderkey) OVER a AS dearest
FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey), a AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""",
    orders_within_week: """SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY day RANGE BETWEEN 7 PRECEDING AND CURRENT ROW) AS near
FROM (SELECT o_orderkey, o_custkey, date_diff('day', DATE '1970-01-01', o_orderdate::DATE) AS day FROM orders)""",
    event_properties: """SELECT event_type, count(k) AS n, sum(k)::BIGINT AS total, count(k) AS agree, '{"n":' || count(k) || ',"total":' || sum(k) || '}' AS json
FROM (SELECT event_type, json_extract_string(props, '$.k')::BIGINT AS k FROM events) GROUP BY event_type""",
    neighbour_maps: f"""SELECT dst, count(*) FILTER (w >= 25) AS heavy, min(src) FILTER (w >= 25) AS least, arg_min(w, src) FILTER (w >= 25) AS w
FROM ({fixtures.SQL["customer_supplier"]}) GROUP BY dst""",
    hash_functions_sql: f"SELECT p_partkey AS node, {hashing.h32_sql("'7:0:' || p_partkey")} AS h, {fixtures.uniform_sql('p_partkey', 'p_partkey + 1')} AS w FROM part",
    hot_parts_salted: f"SELECT dst, sum(w)::BIGINT AS w, count(*) AS edges FROM ({_ORDER_PART}) GROUP BY dst",
    links_like: f"""SELECT (SELECT count(*) FROM ({fixtures.SQL["page_link"]}) WHERE src < 200 AND src % 2 = 0) AS among, count(*) FILTER (href LIKE '/%') AS local,
count(*) FILTER (regexp_matches(href, '^https?://')) AS absolute FROM (SELECT unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)""",
    join_strategies: f"""WITH e AS ({_ORDER_PART}), x AS (SELECT count(*) AS n, sum(w - least)::BIGINT AS excess FROM (SELECT w, min(w) OVER (PARTITION BY src) AS least FROM e))
SELECT way, n, excess FROM x, (VALUES ('merge'), ('shuffle_hash'), ('broadcast')) t(way)""",
    heaviest_page: f"SELECT src, dst, w FROM ({fixtures.SQL['part_mesh']}) ORDER BY w DESC, src, dst LIMIT 10 OFFSET 10",
    comparison_by_method: f"""SELECT 'mesh' AS graph, (SELECT sum(w)::BIGINT FROM ({_SIZE})) AS size, (SELECT sum(w)::BIGINT FROM ({fixtures.SQL["part_mesh"]})) AS uniform,
(SELECT sum(w)::BIGINT FROM ({fixtures.SQL["part_mesh_unit"]})) AS unit""",
    vector_distances: "SELECT vec_id, true AS agree, round(list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)), 6) AS square FROM embeddings",
    cluster_profile: f"""SELECT o_custkey, count(*) AS edges, sum(w)::BIGINT AS span, max(w) AS widest FROM ({fixtures.SQL["customer_chain"]}) e JOIN orders ON o_orderkey = e.src GROUP BY o_custkey""",
    power_law_neighbours: f"WITH e AS ({generators.power_law_sql(8)}), d AS (SELECT node, count(*) AS degree FROM (SELECT src AS node FROM e UNION ALL SELECT dst FROM e) GROUP BY node) SELECT degree, count(*) AS nodes FROM d GROUP BY degree",
}

QUERIES = {f.__name__: f for f in ROWS}
ORACLES = {f.__name__: sql for f, sql in ROWS.items()}
