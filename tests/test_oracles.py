"""Queries against their SQL at the smallest scale."""

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as entry
from spanweave import surroundings

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: One of each kind; all of them run in the driver's own comparison.
QUICK = [
    "mesh_edges", "road_like_edges", "order_part_edges", "page_link_edges", "light_heavy_counts", "degree_distribution", "center_draw", "grow_one_step",
    "contract_stage", "staged_clusters", "fast_estimate", "rescaled_estimate", "hop_estimate", "work_by_phase", "component_diameters", "sssp_bucketed",
    "farthest_sweeps_mesh", "bench_compare_mesh", "bench_method", "prefix_sum", "event_sessions", "transition_windows", *surroundings.QUERIES,
]


@pytest.fixture(scope="module")
def duck(data):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{data}/{t}.parquet'")
    return c


def plain(df):
    def value(v):
        if isinstance(v, pd.Timestamp):
            return v.tz_localize(None).isoformat()
        return None if pd.isna(v) else float(v) if hasattr(v, "dtype") or isinstance(v, (int, float)) else v

    return sorted(repr([value(v) for v in r]) for r in df[sorted(df.columns)].itertuples(index=False))


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_sql(spark, data, duck, name):
    assert plain(entry.queries()[name](spark, data).toPandas()) == plain(duck.sql(entry.oracle_sql()[name]).df())


def test_entry(spark):
    assert entry.entry(spark).count() == 1


def test_intervals_meet_days_not_orders(spark, data):
    """The join of intervals has as many rows as days in them: it was a row for every order within."""
    got = entry.queries()["orders_in_intervals"](spark, data)
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "sum(n#" in plan
