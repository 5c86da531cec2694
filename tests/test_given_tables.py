"""Queries that once made their data up: Spark reads a given table for them, and their rows are those of the SQL."""

import duckdb
import pytest

from spanweave import catalog
from spanweave.sources import fixtures

READS = {
    "data_source_edges": "part", "generated_mesh_edges": "customer", "grid_neighbours_sql": "part", "hub_and_tail_edges": "customer",
    "power_law_edges": "customer", "eccentricities_small": "part",
}


@pytest.mark.parametrize("name", READS)
def test_rows_come_from_a_given_table(spark, data, name):
    got = catalog.queries()[name](spark, data)
    # the graph whose eccentricities are asked for is read when the query is built
    files = fixtures.folded_mesh(spark, data).inputFiles() if name == "eccentricities_small" else got.inputFiles()
    assert any(f.endswith(f"/{READS[name]}.parquet") for f in files)
    con = duckdb.connect()
    for t in ("part", "customer"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{data}/{t}.parquet'")
    want = con.execute(catalog.oracle_sql()[name])
    names = [c[0] for c in want.description]
    assert got.columns == names and sorted(map(tuple, got.collect())) == sorted(want.fetchall())


@pytest.mark.parametrize("block", [64, 8192])
def test_nearest_vectors_are_compared_by_products(spark, data, tmp_path, block):
    con = duckdb.connect()
    # copies and ties, too
    con.execute(f"COPY (SELECT * FROM '{data}/embeddings.parquet' UNION ALL SELECT * REPLACE (vec_id + 100000 AS vec_id) FROM '{data}/embeddings.parquet' WHERE vec_id % 7 = 0) TO '{tmp_path}/embeddings.parquet'")
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet'")
    got = fixtures.embedding_knn(spark, str(tmp_path), block=block)
    assert "FlatMapGroupsInArrow" in got._jdf.queryExecution().toString()
    assert sorted(map(tuple, got.collect())) == sorted(con.execute(fixtures.SQL["embedding_knn"]).fetchall())
