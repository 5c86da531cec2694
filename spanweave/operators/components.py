"""Connected components by hooking and contraction in a logarithmic number of rounds.

A round orders the nodes by a hash that changes with the round. Every node with a neighbour before it hooks onto
the first of them, hook chains are shortened by pointer jumping until nothing moves, and the edges are rewritten
between what they hang on; loops and repeats vanish. A node is left as a root only if it comes before all its
neighbours, so a round leaves at most half of the nodes in expectation whatever the ids are, and its chains have
logarithmic length. Each round's tables are written to the shared folder and dropped with the next. Joins are
between plain scans, so that adaptive execution can split a node with a third of all edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.session import Stored


def _jump(hooks: Stored) -> Stored:
    """Hooks onto what the hook's target hangs on, until every target is a root."""
    while True:
        on = hooks.df.select(F.col("a").alias("_a"), F.col("to").alias("_to"))
        joined = hooks.df.select("a", "to").join(on, F.col("to") == F.col("_a"), "left")
        shorter = Stored(joined.select("a", F.coalesce("_to", "to").alias("to"), F.col("_to").isNotNull().alias("moved")), "hooks")
        hooks.drop()
        hooks = shorter
        if hooks.df.filter("moved").isEmpty():
            return hooks


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", rounds: list[int] | None = None) -> DataFrame:
    """(node, component) of every node with an edge; component is the least node of it.

    Null ends and loops are ignored; no edges give no rows. ``rounds``: a list that receives the links left per round."""
    pairs = edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).filter("a <> b")
    links = Stored(pairs.union(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "links")
    labels = Stored(links.df.select(F.col("a").alias("node")).distinct().withColumn("component", F.col("node")), "labels")
    turn = 0
    while not links.df.isEmpty():
        place = lambda c: F.struct(F.xxhash64(F.lit(turn), c).alias("h"), F.col(c).alias("id"))  # noqa: B023, E731
        first = links.df.groupBy("a").agg(F.min(place("b")).alias("to")).filter(F.col("to") < place("a"))
        hooks = _jump(Stored(first.select("a", F.col("to.id").alias("to")), "hooks"))
        left = hooks.df.select(F.col("a").alias("_a"), F.col("to").alias("_to"))
        right = hooks.df.select(F.col("a").alias("_b"), F.col("to").alias("_ot"))
        moved = links.df.join(left, F.col("a") == F.col("_a"), "left").join(right, F.col("b") == F.col("_b"), "left")
        moved = moved.select(F.coalesce("_to", "a").alias("a"), F.coalesce("_ot", "b").alias("b")).filter("a <> b")
        new_links = Stored(moved.distinct(), "links")
        onto = labels.df.join(left, F.col("component") == F.col("_a"), "left")
        new_labels = Stored(onto.select("node", F.coalesce("_to", "component").alias("component")), "labels")
        for old in (links, labels, hooks):
            old.drop()
        links, labels, turn = new_links, new_labels, turn + 1
        if rounds is not None:
            rounds.append(links.df.count())
    links.drop()
    least = labels.df.groupBy(F.col("component").alias("_root")).agg(F.min("node").alias("_least"))
    found = labels.df.join(least, F.col("component") == F.col("_root"))
    named = Stored(found.select("node", F.col("_least").alias("component")), "components")
    labels.drop()
    return named.df
