import time

import pandas as pd
from pyspark.sql import functions as F

from spanweave.operators import graph, measures
from spanweave.sources import fixtures, generators, sinks, tables
from spanweave.streaming import edges as stream


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_edge_files_round_trip(spark, edges, tmp_path):
    e = edges([(1, 2, 3), (2, 3, 4)])
    e.write.csv(str(tmp_path / "c"))
    e.write.json(str(tmp_path / "j"))
    e.write.orc(str(tmp_path / "o"))
    (tmp_path / "t.txt").write_text("# comment\n1 2 3\n2\t3 4\n\n5 6\n")
    assert rows(tables.read_edge_csv(spark, str(tmp_path / "c"))) == rows(tables.read_edge_json(spark, str(tmp_path / "j"))) == rows(tables.read_edge_orc(spark, str(tmp_path / "o"))) == rows(e)
    assert rows(tables.read_edge_text(spark, str(tmp_path / "t.txt"))) == [(1, 2, 3), (2, 3, 4), (5, 6, 1)]


def test_data_source_equals_generator(spark):
    generators.register(spark)
    got = spark.read.format("diameter_graphs").options(graph="mesh", size="5", partitions="3").load()
    assert rows(got) == rows(generators.mesh(spark, 5))


def test_sinks(spark, edges, tmp_path):
    clusters = spark.createDataFrame([(1, 1, 0, 0), (2, 1, 3, 1)], "node long, center long, path_weight long, stage int")
    sinks.write_assignment(clusters, str(tmp_path / "a"))
    assert spark.read.parquet(str(tmp_path / "a")).count() == 2
    sinks.append_metrics(clusters, str(tmp_path / "m"), "json")
    sinks.append_metrics(clusters, str(tmp_path / "m"), "json")
    assert spark.read.json(str(tmp_path / "m")).count() == 4
    sinks.time_only(clusters)


def test_dense_ids(spark):
    ids = graph.encode_ids(spark.createDataFrame([("b",), ("a",), ("c",)], "k string"), "k")
    assert rows(ids) == [("a", 0), ("b", 1), ("c", 2)]


def _slices(spark, data, tmp_path, n=3):
    pdf = tables.read_table(spark, data, "events").select("event_id", "user_id", "ts", "event_type", "value").orderBy("ts", "event_id").toPandas()
    for i in range(n):
        part = pdf.iloc[i * len(pdf) // n : (i + 1) * len(pdf) // n]
        spark.createDataFrame(part).coalesce(1).write.parquet(str(tmp_path / "in" / f"p{i}"))
    return pdf


def _run(query):
    query.processAllAvailable()
    query.stop()


def test_streamed_chain_equals_batch_chain(spark, data, tmp_path):
    _slices(spark, data, tmp_path)
    events = spark.readStream.schema("event_id long, user_id long, ts timestamp, event_type string, value double").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))
    _run(stream.chain_edges(events, late="3650 days").writeStream.format("memory").queryName("chain").outputMode("append").option("checkpointLocation", str(tmp_path / "cp")).start())
    got = spark.table("chain").select("src", "dst", "w")
    assert rows(got.groupBy("src", "dst").agg(F.min("w"))) == rows(fixtures.event_chain(spark, data))


def _files(spark, tmp_path, rows, columns):
    for i, row in enumerate(rows):
        pdf = pd.DataFrame({c: [pd.Timestamp(v) if c == "ts" else v] for c, v in zip(columns, row)})
        spark.createDataFrame(pdf).coalesce(1).write.parquet(str(tmp_path / "in" / f"p{i}"))
        time.sleep(1.1)  # files are taken in the order of their times


def _read(spark, tmp_path, schema):
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True)
    return reader.parquet(str(tmp_path / "in"))


def test_late_rows_are_dropped_after_the_watermark(spark, tmp_path):
    """The fourth file's row lies in a window that the second file's watermark closed when the third was read."""
    rows = [("2024-01-01 10:00:00", "v", 1.0), ("2024-01-03 10:00:00", "v", 2.0), ("2024-01-03 10:01:00", "v", 3.0)]
    rows += [("2024-01-01 10:05:00", "v", 0.5), ("2024-01-09 10:00:00", "v", 4.0)]
    _files(spark, tmp_path, rows, ["ts", "event_type", "value"])
    source = _read(spark, tmp_path, "ts timestamp, event_type string, value double")
    out = stream.transition_windows(source, late="1 hour").writeStream.format("memory").queryName("windows").outputMode("append")
    _run(out.option("checkpointLocation", str(tmp_path / "cp")).start())
    assert sorted((r["least"], r["n"]) for r in spark.table("windows").collect()) == [(1.0, 1), (2.0, 2)]


def test_streams_of_sessions_repeats_users_and_near_events(spark, tmp_path):
    rows = [("2024-01-01 10:00:00", 1, 7), ("2024-01-01 10:05:00", 2, 7), ("2024-01-01 10:05:00", 2, 7), ("2024-01-01 12:00:00", 3, 7), ("2024-01-02 12:00:00", 4, 8)]
    _files(spark, tmp_path, rows, ["ts", "event_id", "user_id"])
    schema = "ts timestamp, event_id long, user_id long"
    users = spark.createDataFrame([(7, "seven")], "user_id long, name string")
    once = stream.distinct_events(tables.edge_stream(spark, str(tmp_path / "in" / "p*"), schema))
    _run(stream.with_user(once, users).writeStream.format("memory").queryName("named").option("checkpointLocation", str(tmp_path / "c1")).start())
    assert sorted((r["event_id"], r["name"]) for r in spark.table("named").collect()) == [(1, "seven"), (2, "seven"), (3, "seven")]
    batch = spark.read.schema(schema).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))
    assert sorted((r["user_id"], r["n"]) for r in stream.session_windows(batch).collect()) == [(7, 1), (7, 3), (8, 1)]
    near = stream.proximity(_read(spark, tmp_path, schema), _read(spark, tmp_path, schema), 600)
    _run(near.writeStream.format("memory").queryName("near").option("checkpointLocation", str(tmp_path / "c2")).start())
    assert {(r["event_a"], r["event_b"]) for r in spark.table("near").collect()} == {(1, 2), (2, 1)}


def test_new_edges_keep_or_renew_the_estimate(spark, edges):
    known = {"result": {"estimate": 9}}
    merge = stream.keep_estimate(edges([(1, 2, 5), (2, 3, 4), (7, 8, 1)]), lambda e: {"estimate": e.count()}, known)
    merge(edges([(1, 3, 1)]), 0)
    assert known["result"] == {"estimate": 9} and known["edges"].count() == 4
    merge(edges([(3, 4, 1)]), 1)  # a new node
    assert known["result"] == {"estimate": 5} and known["runs"] == 1
    merge(edges([(4, 8, 6)]), 2)  # two known components become one
    assert known["result"] == {"estimate": 6} and known["runs"] == 2
    merge(edges([(4, 8, 6)]), 2)
    assert known["runs"] == 2 and known["edges"].count() == 6


def test_edges_of_the_catalog(spark, edges):
    sinks.write_bucketed(edges([(1, 2, 3), (2, 3, 4)]), "kept_edges", 2)
    assert rows(tables.edges_from_catalog(spark, "kept_edges")) == [(1, 2, 3), (2, 3, 4)]
    spark.sql("DROP TABLE kept_edges")


def test_one_reducer_holds_a_part(spark):
    """Rows of the largest partition against all: linear in total, sublinear in each."""
    got = measures.memory_report(graph.symmetrize(generators.mesh(spark, 20)).repartition(8, "src")).first()
    assert got["rows"] == 2 * 2 * 20 * 19 and got["partitions"] == 8 and got["largest"] <= got["rows"] / 4
