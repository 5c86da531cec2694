"""Headline figures as one JSON line: the estimator against bucketed shortest paths on the tables of $BENCH_SF_DIR.

``python bench.py scale_out`` times the estimate at 1, 2, 4 and 8 cores instead (one session each), ``python bench.py scale_up``
over the growing graphs of ``workloads.scaled``."""

from __future__ import annotations

import json
import os
import re
import sys
import time


def session(cpus: str):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def timed(seconds: dict, name: str, work):
    began = time.time()
    out = work()
    seconds[name] = round(time.time() - began, 3)
    return out


def main(cpus: str, sf_dir: str) -> dict:
    spark = session(cpus)
    from spanweave import workloads
    from spanweave.operators import estimate, graph, sssp
    from spanweave.sources import fixtures

    seconds: dict[str, float] = {}
    figures: dict[str, dict] = {}
    warm = graph.build(fixtures.part_mesh(spark, sf_dir, side=16))  # starts the engine
    estimate.fast_estimate(warm, tau=1)

    for name in ("mesh", "road_like", "order_part"):
        edges = workloads.GRAPHS[name](spark, sf_dir)
        title = "part_mesh" if name == "mesh" else name
        g = timed(seconds, f"{title}_build", lambda: graph.build(edges))
        most = max(500, g.n // 10)
        row, _ = timed(seconds, f"{title}_estimate", lambda: estimate.fast_estimate(g, max_quotient_nodes=most, bound="per_cluster", quotient_mode="auto"))
        paths = timed(seconds, f"{title}_sssp", lambda: sssp.bellman_ford(g, sssp.pick_source(g)))
        ecc = paths.dist.groupBy().max("dist").first()[0]
        paths.loop.release()
        lower = workloads.lower_bound(g)
        printed = row["quotient_diameter"] + 2 * row["radius"]
        figures[title] = {
            "nodes": g.n, "estimate": int(row["estimate"]), "lower_by_sweeps": int(lower), "ratio_at_most": round(row["estimate"] / lower, 3),
            "ratio_of_printed_sum": round(printed / lower, 3), "rounds": row["rounds"], "work": row["work"], "tau": row["tau"],
            "clusters": row["clusters"], "quotient_seconds": round(row["quotient_seconds"], 2), "sssp_ratio_at_most": round(2 * ecc / lower, 3),
            "sssp_rounds": paths.rounds, "sssp_work": paths.loop.work,
            "times_faster": round(seconds[f"{title}_sssp"] / seconds[f"{title}_estimate"], 2),
        }
        g.release()
    total = sum(v for k, v in seconds.items() if k.endswith("_estimate"))
    return {"metric": "diameter_estimates_total", "value": round(total, 3), "unit": "sec", "queries": seconds, "figures": figures}


def scale_out(sf_dir: str) -> dict:
    """One session after the other; the graph by the mesh over orders and its partitions by the cores."""
    seconds: dict[str, float] = {}
    for cpus in ("1", "2", "4", "8"):
        spark = session(cpus)
        from spanweave.operators import estimate, graph
        from spanweave.sources import fixtures

        estimate.fast_estimate(graph.build(fixtures.part_mesh(spark, sf_dir, side=16)), tau=1)
        for name, edges in (("order_mesh", fixtures.order_mesh(spark, sf_dir)), ("order_part", fixtures.order_part(spark, sf_dir))):
            g = graph.build(edges)
            timed(seconds, f"{name}_{cpus}", lambda g=g: estimate.fast_estimate(g, max_quotient_nodes=max(500, g.n // 100), quotient_mode="auto"))
        spark.stop()
    return {"metric": "scale_out", "value": seconds["order_part_8"], "unit": "sec", "queries": seconds}


def scale_up(cpus: str, sf_dir: str) -> dict:
    spark = session(cpus)
    from spanweave import workloads
    from spanweave.operators import estimate, graph

    seconds: dict[str, float] = {}
    for name, edges in workloads.scaled(spark, sf_dir).items():
        g = graph.build(edges)
        timed(seconds, f"{name}_{g.n}", lambda g=g: estimate.fast_estimate(g, max_quotient_nodes=workloads.room(g.n), quotient_mode="auto"))
        g.release()
    return {"metric": "scale_up", "value": max(seconds.values()), "unit": "sec", "queries": seconds}


if __name__ == "__main__":
    cores, folder = os.environ.get("BENCH_CPUS", "8"), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    kind = sys.argv[1] if len(sys.argv) > 1 else "compare"
    result = {"compare": lambda: main(cores, folder), "scale_out": lambda: scale_out(folder), "scale_up": lambda: scale_up(cores, folder)}[kind]()
    sf = re.search(r"sf([0-9.]+)", folder)
    print(json.dumps(result | {"sf": float(sf[1]) if sf else None}))
