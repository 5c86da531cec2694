"""Weighted graphs derived from the given tables, each as canonical edges (src < dst, one row a pair, least weight).

``SQL`` holds the same graphs in DuckDB SQL for the checks of results."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spanweave.functions.hashing import SCALE, h32_sql, uniform_weight
from spanweave.sources.tables import read_table

#: A tenth of 2^32: the share of heavy edges in the bimodal mesh.
HEAVY_BELOW = 429_496_729
HEAVY = 1_000_000
#: Of the comparison of vectors: queries that meet a block together, pairs whose distances are summed together.
KNN_ROWS, KNN_PAIRS = 256, 1 << 17


def canonical(edges: DataFrame) -> DataFrame:
    """src < dst, no loops, least weight of duplicates."""
    return (
        edges.filter("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "w").groupBy("src", "dst").agg(F.min("w").alias("w"))
    )


def mesh_cells(cells: DataFrame, side: int, w) -> DataFrame:
    """Edges to the right and the lower neighbour of the cells (id, ...) below side^2; ``w(u, v)`` over the rows' columns as structs."""
    cells = cells.filter(F.col("id") < side * side)
    near = [F.when(F.col("id") % side < side - 1, F.col("id") + 1), F.when(F.col("id") < side * (side - 1), F.col("id") + side)]
    out = cells.select(F.struct("*").alias("u"), F.explode(F.array_compact(F.array(*near))).alias("to"))
    if w is None:
        return out.select(F.col("u.id").alias("src"), F.col("to").alias("dst"))
    other = cells.select(F.struct("*").alias("v"))
    out = out.join(other, F.col("to") == F.col("v.id"))
    return out.select(F.col("u.id").alias("src"), F.col("to").alias("dst"), w(F.col("u"), F.col("v")).alias("w"))


def _side(n: int, side: int | None) -> int:
    return math.isqrt(n) if side is None else side


def side_of(spark: SparkSession, sf_dir: str, table: str) -> int:
    """The side of the square mesh over a table's rows."""
    return math.isqrt(read_table(spark, sf_dir, table).count())


def part_mesh(spark: SparkSession, sf_dir: str, weight: str = "uniform", side: int | None = None) -> DataFrame:
    """Square mesh over part keys; weight: uniform, size, bimodal or unit."""
    part = read_table(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("id"), "p_size")
    side = _side(part.count(), side)
    if weight == "size":
        return mesh_cells(part, side, lambda u, v: (F.abs(u["p_size"] - v["p_size"]) + 1).cast("long"))
    # spread over all cores, as a small file is read by one task and each edge takes a hash
    cells = part.select("id").repartition(spark.sparkContext.defaultParallelism)
    return reweight(mesh_cells(cells, side, None), weight)


def reweight(edges: DataFrame, rule: str, seed: int = 7) -> DataFrame:
    """uniform (1..2^32), bimodal (1,000,000 or 1) or unit weights by the edge's ends."""
    u, v = F.col("src"), F.col("dst")
    if rule == "uniform":
        w = uniform_weight(u, v, seed)
    elif rule == "bimodal":
        w = F.when(uniform_weight(u, v, seed) - 1 < HEAVY_BELOW, HEAVY).otherwise(1)
    elif rule == "unit":
        w = F.lit(1)
    else:
        raise ValueError(f"unknown weight rule {rule!r}")
    return edges.select("src", "dst", w.cast("long").alias("w"))


def folded_mesh(spark: SparkSession, sf_dir: str, side: int = 16) -> DataFrame:
    """side x side mesh whose cells hold the parts of equal key modulo side^2; an edge weighs the difference of its cells' total sizes, and one more."""
    part = read_table(spark, sf_dir, "part").groupBy(F.pmod(F.col("p_partkey").cast("long"), F.lit(side * side)).alias("id"))
    return mesh_cells(part.agg(F.sum("p_size").alias("size")), side, lambda u, v: (F.abs(u["size"] - v["size"]) + 1).cast("long"))


def order_mesh(spark: SparkSession, sf_dir: str, side: int | None = None) -> DataFrame:
    orders = read_table(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("long").alias("id"))
    return reweight(mesh_cells(orders, _side(orders.count(), side), None), "uniform")


def road_like(spark: SparkSession, sf_dir: str, side: int | None = None) -> DataFrame:
    """The size-weighted mesh with all columns and row 0 whole, other horizontal edges kept with chance 0.4."""
    edges = part_mesh(spark, sf_dir, "size", side)
    n = read_table(spark, sf_dir, "part").count()
    s = _side(n, side)
    return edges.filter((F.col("dst") - F.col("src") == s) | (F.col("src") < s) | (uniform_weight(F.col("src"), F.col("dst")) - 1 < int(0.4 * SCALE)))


def _bipartite(left: Column, right: Column, w: Column, rows: DataFrame) -> DataFrame:
    return canonical(rows.select((2 * left).cast("long").alias("src"), (2 * right + 1).cast("long").alias("dst"), w.cast("long").alias("w")))


def order_part(spark: SparkSession, sf_dir: str, weight: str = "quantity") -> DataFrame:
    edges = _bipartite(F.col("l_orderkey"), F.col("l_partkey"), F.col("l_quantity"), read_table(spark, sf_dir, "lineitem"))
    return edges if weight == "quantity" else reweight(edges, weight)


def customer_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "orders").join(read_table(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return _bipartite(F.col("o_custkey"), F.col("l_suppkey"), F.col("l_quantity"), rows)


def _chain(rows: DataFrame, by: str, order: list[str], node: str, w) -> DataFrame:
    """Edges from each row to the next one of its group; ``w(next, this)`` over columns by name."""
    win = Window.partitionBy(by).orderBy(*order)
    following = rows.withColumn("_next", F.lead(F.struct("*")).over(win)).filter("_next is not null")
    return following.select(F.col(node).cast("long").alias("src"), F.col(f"_next.{node}").cast("long").alias("dst"), w(lambda c: F.col(f"_next.{c}"), F.col).cast("long").alias("w"))


def customer_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return canonical(_chain(orders, "o_custkey", ["o_orderdate", "o_orderkey"], "o_orderkey", lambda nxt, now: F.datediff(nxt("o_orderdate"), now("o_orderdate")) + 1))


def order_timeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each order to the next one overall and to the customer's next one; ranks come from day counts, so that no task orders all rows."""
    orders = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate").withColumn("day", F.to_date("o_orderdate"))
    days = orders.groupBy("day").agg(F.min(F.struct("o_orderdate", "o_orderkey")).alias("first"), F.max(F.struct("o_orderdate", "o_orderkey")).alias("last"))
    inside = _chain(orders, "day", ["o_orderdate", "o_orderkey"], "o_orderkey", lambda nxt, now: F.datediff(nxt("o_orderdate"), now("o_orderdate")) + 1)
    # one row a day: the calendar bounds this window's single task
    over = Window.orderBy("day")
    between = days.withColumn("n", F.lead("first").over(over)).filter("n is not null").select(
        F.col("last.o_orderkey").alias("src"), F.col("n.o_orderkey").alias("dst"), (F.datediff("n.o_orderdate", "last.o_orderdate") + 1).cast("long").alias("w")
    )
    return canonical(inside.unionByName(between).unionByName(customer_chain(spark, sf_dir)))


def event_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = read_table(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    return canonical(_chain(events, "user_id", ["ts", "event_id"], "event_id", lambda nxt, now: F.greatest(F.unix_timestamp(nxt("ts")) - F.unix_timestamp(now("ts")), F.lit(1))))


def conversation_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "conversations").select("conv_id", (F.col("conv_id") * 1000 + F.col("turn")).alias("node"), "turn", F.length("text").alias("size"))
    return canonical(_chain(rows, "conv_id", ["turn"], "node", lambda nxt, now: nxt("size") + 1))


#: First ids of the levels of the geographic tree.
REGION, NATION, SUPPLIER, CUSTOMER = 0, 1_000, 1_000_000_000_000, 2_000_000_000_000


def geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation, supplier, customer = (read_table(spark, sf_dir, t) for t in ("nation", "supplier", "customer"))
    leaf = lambda t, key, parent, money, base: t.select((F.col(parent) + NATION).cast("long").alias("src"), (F.col(key) + F.lit(base)).cast("long").alias("dst"), (1 + F.floor(F.abs(F.col(money)))).cast("long").alias("w"))
    top = nation.select(F.col("n_regionkey").cast("long").alias("src"), (F.col("n_nationkey") + NATION).cast("long").alias("dst"), (F.col("n_nationkey") + 1).cast("long").alias("w"))
    return canonical(top.unionByName(leaf(supplier, "s_suppkey", "s_nationkey", "s_acctbal", SUPPLIER)).unionByName(leaf(customer, "c_custkey", "c_nationkey", "c_acctbal", CUSTOMER)))


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages and the distinct link targets in their HTML; weight: occurrences. Target ids follow the pages', by sorted text."""
    from spanweave.operators.graph import encode_ids

    links = read_table(spark, sf_dir, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("href"))
    counted = links.groupBy("page_id", "href").agg(F.count(F.lit(1)).alias("w"))
    ids = encode_ids(counted.select("href").distinct(), "href")
    return canonical(counted.join(ids, "href").select((2 * F.col("page_id")).cast("long").alias("src"), (2 * F.col("id") + 1).alias("dst"), "w"))


def event_transition(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users of consecutive events; consecutive within an hour's bucket and across neighbouring buckets, so that no task orders all rows."""
    events = read_table(spark, sf_dir, "events").select("user_id", "ts", "event_id").withColumn("hour", F.date_trunc("hour", "ts"))
    gap = lambda a, b: F.greatest(F.unix_timestamp(b) - F.unix_timestamp(a), F.lit(1))
    inside = _chain(events, "hour", ["ts", "event_id"], "user_id", lambda nxt, now: gap(now("ts"), nxt("ts")))
    hours = events.groupBy("hour").agg(F.min(F.struct("ts", "event_id", "user_id")).alias("first"), F.max(F.struct("ts", "event_id", "user_id")).alias("last"))
    # one row an hour: the calendar bounds this window's single task
    between = hours.withColumn("n", F.lead("first").over(Window.orderBy("hour"))).filter("n is not null").select(
        F.col("last.user_id").cast("long").alias("src"), F.col("n.user_id").cast("long").alias("dst"), gap(F.col("last.ts"), F.col("n.ts")).cast("long").alias("w")
    )
    return canonical(inside.unionByName(between))


def _nearest(a: np.ndarray, b: np.ndarray, left: np.ndarray, right: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(a, b, w): the k nearest of ``right`` (ids b) for each of ``left`` (ids a).

    Products of matrices leave those that rounding may put among the k; of these distances are summed term by term."""
    out, size = [], (right * right).sum(1)
    for at in range(0, len(a), KNN_ROWS):
        ids, x = a[at : at + KNN_ROWS], left[at : at + KNN_ROWS]
        own = (x * x).sum(1)[:, None]
        near = own + size - 2 * (x @ right.T)
        near[ids[:, None] == b] = np.inf
        most = min(k, len(b)) - 1
        limit = np.partition(near, most, axis=1)[:, most, None] + 1e-12 * x.shape[1] * (own + size.max(initial=0))
        row, col = np.nonzero((near <= limit) & (near < np.inf))
        w = np.empty(len(row))
        for c in range(0, len(row), KNN_PAIRS):
            d = x[row[c : c + KNN_PAIRS]] - right[col[c : c + KNN_PAIRS]]
            total = np.zeros(len(d))
            for term in (d * d).T:
                total += term
            w[c : c + KNN_PAIRS] = np.sqrt(total)
        order = np.lexsort((b[col], w, row))
        first = np.searchsorted(row[order], np.arange(len(ids)))
        keep = order[np.arange(len(order)) - first[row[order]] < k]
        out.append((ids[row[keep]], b[col[keep]], w[keep]))
    return tuple(np.concatenate(c) for c in zip(*out))


def embedding_knn(spark: SparkSession, sf_dir: str, k: int = 8, block: int = 4096) -> DataFrame:
    """k nearest vectors by L2 distance (ties by id) of every vector, directions merged; DOUBLE weights.

    Queries meet the vectors in square blocks, each keeps k, and the best k of all blocks stay. Vectors of one length with
    finite numbers only are compared by products of matrices, others in expressions."""
    v = read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    fit = F.coalesce(F.forall("x", lambda e: F.coalesce(F.abs(e) < 1e150, F.lit(False))) & F.col("id").isNotNull(), F.lit(False))
    seen = v.agg(F.count(F.lit(1)).alias("n"), F.min(fit).alias("fit"), F.min(F.size("x")).alias("least"), F.max(F.size("x")).alias("most")).first()
    regular = bool(seen["fit"]) and seen["least"] == seen["most"] and seen["most"] > 0
    parts = max(1, -(-seen["n"] // (block if regular else min(block, 512))))
    side = F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
    if regular:
        def compare(rows: pa.Table) -> pa.Table:
            query = rows.column("query").to_numpy()
            ids, x = rows.column("id").to_numpy(), rows.column("x").combine_chunks().flatten().to_numpy().reshape(rows.num_rows, -1)
            if query.all() or not query.any():
                return pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64()), "w": pa.array([], pa.float64())})
            return pa.table(dict(zip("abw", map(pa.array, _nearest(ids[query], ids[~query], x[query], x[~query], k)))))

        rows = v.select("id", "x", F.lit(True).alias("query"), side.alias("i"), every.alias("j"))
        rows = rows.unionByName(v.select("id", "x", F.lit(False).alias("query"), side.alias("j"), every.alias("i")))
        # a fixed number of tasks: by bytes all blocks would go to one
        rows = rows.repartition(min(parts * parts, 4 * spark.sparkContext.defaultParallelism), "i", "j")
        few = rows.groupBy("i", "j").applyInArrow(compare, "a long, b long, w double")
    else:
        a = v.select(F.col("id").alias("a"), F.col("x").alias("xa"), side.alias("i"), every.alias("j"))
        b = v.select(F.col("id").alias("b"), F.col("x").alias("xb"), side.alias("j"), every.alias("i"))
        squares = F.zip_with("xa", "xb", lambda p, q: (p - q) * (p - q))
        pairs = a.join(b, ["i", "j"]).filter("a <> b").select("a", "b", "i", "j", F.sqrt(F.aggregate(squares, F.lit(0.0), lambda s, d: s + d)).alias("w"))
        few = pairs.withColumn("r", F.row_number().over(Window.partitionBy("a", "i", "j").orderBy("w", "b"))).filter(F.col("r") <= k)
    best = few.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy("w", "b"))).filter(F.col("r") <= k)
    return canonical(best.select(F.col("a").alias("src"), F.col("b").alias("dst"), "w"))


def uniform_sql(u: str, v: str) -> str:
    return f"(1 + {h32_sql(f'concat_ws(chr(58), 7, least({u}, {v}), greatest({u}, {v}))')})"


def mesh_sql(table: str, key: str, w: str, extra: str = "") -> str:
    return f"""
WITH c AS (SELECT {key}::BIGINT AS id{extra} FROM {table}), s AS (SELECT floor(sqrt((SELECT count(*) FROM {table})))::BIGINT AS side),
cell AS (SELECT c.*, side FROM c, s WHERE id < side * side),
near AS (SELECT a.id AS src, b.id AS dst, a.side{', a.p_size AS pu, b.p_size AS pv' if extra else ''} FROM cell a JOIN cell b
         ON (b.id = a.id + 1 AND a.id % a.side < a.side - 1) OR b.id = a.id + a.side)
SELECT src, dst, ({w})::BIGINT AS w FROM near"""


_UNIFORM = uniform_sql("src", "dst")


def folded_mesh_sql(side: int = 16) -> str:
    return f"""WITH c AS (SELECT p_partkey::BIGINT % {side * side} AS id, sum(p_size)::BIGINT AS size FROM part GROUP BY ALL)
SELECT a.id AS src, b.id AS dst, abs(a.size - b.size) + 1 AS w FROM c a JOIN c b ON (b.id = a.id + 1 AND a.id % {side} < {side - 1}) OR b.id = a.id + {side}"""


_LEAST = "SELECT least(a, b) AS src, greatest(a, b) AS dst, min(w) AS w FROM ({}) WHERE a <> b GROUP BY ALL"
_CUSTOMER = "SELECT o_orderkey AS a, lead(o_orderkey) OVER k AS b, (date_diff('day', o_orderdate::DATE, (lead(o_orderdate) OVER k)::DATE) + 1)::BIGINT AS w FROM orders WINDOW k AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"
SQL = {
    "part_mesh": mesh_sql("part", "p_partkey", _UNIFORM),
    "part_mesh_size": mesh_sql("part", "p_partkey", "abs(pu - pv) + 1", ", p_size"),
    "part_mesh_bimodal": mesh_sql("part", "p_partkey", f"CASE WHEN {_UNIFORM} - 1 < {HEAVY_BELOW} THEN {HEAVY} ELSE 1 END"),
    "part_mesh_unit": mesh_sql("part", "p_partkey", "1"),
    "order_mesh": mesh_sql("orders", "o_orderkey", _UNIFORM),
    "order_part": _LEAST.format("SELECT (2 * l_orderkey)::BIGINT AS a, (2 * l_partkey + 1)::BIGINT AS b, l_quantity::BIGINT AS w FROM lineitem"),
    "customer_supplier": _LEAST.format("SELECT (2 * o_custkey)::BIGINT AS a, (2 * l_suppkey + 1)::BIGINT AS b, l_quantity::BIGINT AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey"),
    "customer_chain": _LEAST.format(f"SELECT * FROM ({_CUSTOMER}) WHERE b IS NOT NULL"),
    "order_timeline": _LEAST.format(
        f"SELECT * FROM ({_CUSTOMER}) WHERE b IS NOT NULL UNION ALL SELECT * FROM ({_CUSTOMER.replace('PARTITION BY o_custkey ', '')}) WHERE b IS NOT NULL"
    ),
    "event_chain": _LEAST.format(
        "SELECT event_id AS a, lead(event_id) OVER k AS b, greatest(epoch(lead(ts) OVER k)::BIGINT - epoch(ts)::BIGINT, 1) AS w FROM (SELECT event_id, user_id, ts, date_trunc('second', ts) AS s FROM events) WINDOW k AS (PARTITION BY user_id ORDER BY ts, event_id)"
    ).replace("epoch(lead(ts)", "epoch(lead(s)").replace("epoch(ts)", "epoch(s)").replace("WHERE a <> b", "WHERE b IS NOT NULL"),
    "conversation_chain": _LEAST.format("SELECT conv_id * 1000 + turn AS a, lead(conv_id * 1000 + turn) OVER k AS b, (lead(length(text)) OVER k + 1)::BIGINT AS w FROM conversations WINDOW k AS (PARTITION BY conv_id ORDER BY turn)").replace("WHERE a <> b", "WHERE b IS NOT NULL"),
    "geo_tree": f"""
SELECT n_regionkey::BIGINT AS src, (n_nationkey + {NATION})::BIGINT AS dst, (n_nationkey + 1)::BIGINT AS w FROM nation
UNION ALL SELECT s_nationkey + {NATION}, s_suppkey + {SUPPLIER}, (1 + floor(abs(s_acctbal)))::BIGINT FROM supplier
UNION ALL SELECT c_nationkey + {NATION}, c_custkey + {CUSTOMER}, (1 + floor(abs(c_acctbal)))::BIGINT FROM customer""",
    "page_link": """
WITH l AS (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages),
n AS (SELECT page_id, href, count(*) AS w FROM l GROUP BY ALL), i AS (SELECT href, row_number() OVER (ORDER BY encode(href)) - 1 AS id FROM (SELECT DISTINCT href FROM l))
SELECT least(2 * page_id, 2 * id + 1)::BIGINT AS src, greatest(2 * page_id, 2 * id + 1)::BIGINT AS dst, w FROM n JOIN i USING (href)""",
    "event_transition": _LEAST.format(
        "SELECT user_id AS a, lead(user_id) OVER k AS b, greatest(epoch(lead(s) OVER k)::BIGINT - epoch(s)::BIGINT, 1) AS w FROM (SELECT event_id, user_id, ts, date_trunc('second', ts) AS s FROM events) WINDOW k AS (ORDER BY ts, event_id)"
    ).replace("WHERE a <> b", "WHERE b IS NOT NULL AND a <> b"),
    "embedding_knn": """
WITH v AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings),
p AS (SELECT a.vec_id AS a, b.vec_id AS b, sqrt(list_sum(list_transform(list_zip(a.x, b.x), lambda z: (z[1] - z[2]) * (z[1] - z[2])))) AS w FROM v a, v b WHERE a.vec_id <> b.vec_id),
k AS (SELECT *, row_number() OVER (PARTITION BY a ORDER BY w, b) AS r FROM p)
SELECT least(a, b) AS src, greatest(a, b) AS dst, min(w) AS w FROM k WHERE r <= 8 GROUP BY ALL""",
}
SQL["road_like"] = f"WITH e AS ({SQL['part_mesh_size']}), s AS (SELECT floor(sqrt((SELECT count(*) FROM part)))::BIGINT AS side) SELECT src, dst, w FROM e, s WHERE dst - src = side OR src < side OR {_UNIFORM} - 1 < {int(0.4 * SCALE)}"
SQL["order_part_uniform"] = f"SELECT src, dst, {_UNIFORM}::BIGINT AS w FROM ({SQL['order_part']})"

BUILDERS = {
    "part_mesh": part_mesh,
    "part_mesh_size": lambda s, d: part_mesh(s, d, "size"),
    "part_mesh_bimodal": lambda s, d: part_mesh(s, d, "bimodal"),
    "part_mesh_unit": lambda s, d: part_mesh(s, d, "unit"),
    "order_mesh": order_mesh,
    "road_like": road_like,
    "order_part": order_part,
    "order_part_uniform": lambda s, d: order_part(s, d, "uniform"),
    "customer_supplier": customer_supplier,
    "customer_chain": customer_chain,
    "order_timeline": order_timeline,
    "event_chain": event_chain,
    "conversation_chain": conversation_chain,
    "geo_tree": geo_tree,
    "page_link": page_link,
    "event_transition": event_transition,
    "embedding_knn": embedding_knn,
}
