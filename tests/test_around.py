"""Sources, sinks, builders, views, functions, streams, measures on small graphs, and plans."""

import datetime as dt
import time

import duckdb
import pytest
from pyspark.sql.types import LongType, StructField, StructType

from spanweave import graphs
from spanweave.functions.udfs import register_functions
from spanweave.operators import measures
from spanweave.plans import sqlviews
from spanweave.schema import EDGES, conform, vertex
from spanweave.sources.tables import from_rows, read_edges, read_table, write_result
from spanweave.streaming import edges as stream


def test_fixture_profile(spark, sf):
    g = graphs.trade_sparse(spark, sf)
    assert g.count() == 86 and graphs.ring_cactus(spark, sf).count() == 1855 and graphs.fk_forest(spark, sf).count() == 1685
    assert graphs.part_supp(spark, sf).count() == 1905 and graphs.order_part(spark, sf).count() == 589
    assert graphs.line_share(spark, sf).count() == 333 and graphs.links(spark, sf).count() == 279 and graphs.chains(spark, sf).count() == 67


def test_edge_files(spark, tmp_path):
    edges = from_rows(spark, [(1, 2), (2, 3)])
    for fmt in ("csv", "json", "orc", "parquet"):
        write_result(edges, str(tmp_path / fmt), fmt)
        assert {tuple(r) for r in read_edges(spark, str(tmp_path / fmt), fmt).collect()} == {(1, 2), (2, 3)}
    write_result(edges, fmt="noop")
    write_result(edges.withColumn("part", edges.src % 2), str(tmp_path / "split"), partition_by=["part"])
    assert read_edges(spark, str(tmp_path / "split")).count() == 2
    with pytest.raises(ValueError, match="format"):
        read_edges(spark, "x", "xml")
    with pytest.raises(ValueError, match="missing"):
        conform(edges, StructType([*EDGES.fields, StructField("w", LongType())]))


def test_bucketed_tables_join_without_a_shuffle(spark, tmp_path):
    edges = from_rows(spark, [(k, k + 1) for k in range(50)])
    for name in ("left_side", "right_side"):
        spark.sql(f"DROP TABLE IF EXISTS {name}")
        write_result(edges, table=name, buckets=(4, "src"), mode="overwrite")
    plan = spark.table("left_side").hint("merge").join(spark.table("right_side"), "src")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in plan
    for name in ("left_side", "right_side"):
        spark.sql(f"DROP TABLE {name}")


def test_cuts_reach_the_scan(spark, sf):
    spark.conf.set("spark.sql.maxMetadataStringLength", "4000")
    plan = graphs.trade_sparse(spark, sf)._jdf.queryExecution().executedPlan().toString()
    spark.conf.unset("spark.sql.maxMetadataStringLength")
    assert "GreaterThanOrEqual(l_quantity,49.0)" in plan and "EqualTo(l_returnflag,R)" in plan
    assert "l_extendedprice" not in plan


def test_builders(spark):
    rows = spark.createDataFrame([("a", 1, 10), ("a", 2, 11), ("a", 3, 12), ("b", 1, 20), ("c", 1, 30), ("c", 2, 31)], "part string, ord long, v long")
    assert {tuple(r) for r in graphs.chain(rows, "part", "ord").collect()} == {(10, 11), (11, 12), (30, 31)}
    assert {tuple(r) for r in graphs.ring(rows, "part", "ord").collect()} == {(10, 11), (11, 12), (10, 12), (30, 31)}
    some = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.9, 0.1]), (3, [0.0, 1.0]), (4, [0.1, 0.9])], "v long, x array<float>")
    assert {tuple(r) for r in graphs.knn(some).collect()} == {(1, 2), (3, 4)}
    with pytest.raises(ValueError, match="one by one"):
        graphs.knn(some, rows=3)


def test_views_and_functions(spark):
    edges = from_rows(spark, [(0, 1), (1, 2), (2, 0), (2, 3)])
    sqlviews.register(spark, edges, "g")
    assert [tuple(r) for r in spark.sql("SELECT * FROM g_bridges").collect()] == [(2, 3)]
    assert spark.sql("SELECT v FROM g_cut_vertices").collect()[0].v == 2
    register_functions(spark)
    assert [tuple(r) for r in spark.sql("SELECT * FROM bridges_of(TABLE(g_edges) WITH SINGLE PARTITION)").collect()] == [(2, 3)]
    spark.createDataFrame([("1-2 2-3 1-3",), ("1-3 3-4 1-4",)], "c string").createOrReplaceTempView("cycles")
    assert spark.sql("SELECT xor_edges(c) AS x FROM cycles").first().x == "1-2 1-4 2-3 3-4"


def test_measures_of_small_graphs(spark):
    k23 = from_rows(spark, [(a, b) for a in (0, 1) for b in (2, 3, 4)])
    assert [r.length for r in measures.bi_diameter(k23).collect()] == [4]
    ring = from_rows(spark, [(k, (k + 1) % 9) for k in range(9)] + [(8, 20)])
    assert [r.length for r in measures.bi_diameter(ring).collect()] == [9]
    assert measures.bi_diameter(from_rows(spark, [(0, 1), (1, 2)])).collect() == []
    assert [r.diameter for r in measures.diameter(ring, "exact").collect()] == [5]
    assert [r.diameter for r in measures.diameter(from_rows(spark, [(k, k + 1) for k in range(12)]), "lower").collect()] == [12]
    assert {r.source: r.ecc for r in measures.eccentricities(ring, spark.createDataFrame([(20,), (0,)], "v long")).collect()} == {20: 5, 0: 4}
    report = measures.aux_report(ring).first()
    assert report.aux_vertices == report.n - 1 and report.aux_edges <= report.m
    assert measures.aux_diameter(ring) <= 4 * report.depth * 9
    assert measures.parity(spark.createDataFrame([(5,), (3,), (None,)], "x long"), "x").first().parity == 6


def test_streams(spark, sf, tmp_path):
    events = read_table(spark, sf, "events")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    schema = events.schema
    flow = stream.event_stream(spark, str(tmp_path / "in"), schema)
    keeper = stream.ComponentKeeper(spark)
    run = stream.keep_components(stream.edge_stream(flow, "10000 days"), str(tmp_path / "check"), keeper)
    run.awaitTermination(180)
    pairs = events.select(vertex("user", "user_id").alias("src")).distinct().count()
    labels = keeper.labels.collect()
    assert len(labels) == pairs + 5 and len({r.comp for r in labels}) == 1
    assert keeper.bridges().count() == 0 or keeper.edges.count() > 0
    query = stream.tumbling(flow, "30 days", "1 day").writeStream.format("memory").queryName("windows").outputMode("complete").option("checkpointLocation", str(tmp_path / "w")).trigger(availableNow=True).start()
    query.awaitTermination(180)
    assert spark.sql("SELECT sum(events) AS n FROM windows").first().n >= 1
    assert stream.tumbling(events).agg({"events": "sum"}).first()[0] == events.count()
    assert stream.sliding(events).agg({"events": "sum"}).first()[0] == 4 * events.count()


_EVENT = "event_id long, user_id long, event_type string, ts timestamp"


def _files(spark, folder, batches):
    """One file a batch, taken in this order."""
    for rows in batches:
        spark.createDataFrame(rows, _EVENT).coalesce(1).write.mode("append").parquet(folder)
        time.sleep(1.1)  # the stream takes files by their times
    return stream.event_stream(spark, folder, spark.read.parquet(folder).schema)


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    t = dt.datetime(2020, 1, 1)
    days = lambda n: t + dt.timedelta(days=n)
    flow = _files(spark, str(tmp_path / "in"), [[(1, 1, "a", days(0)), (2, 1, "a", days(30))], [(3, 1, "a", days(31))], [(4, 1, "a", days(1)), (5, 1, "a", days(32)), (6, 2, "b", days(2))]])
    run = stream.tumbling(flow, "1 day", "1 day").writeStream.format("memory").queryName("late").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    run.awaitTermination(180)
    assert stream.late_rows(run) == 2
    assert spark.sql("SELECT sum(events) AS n FROM late").first().n == 4


def test_last_events_across_batches(spark, tmp_path):
    t = dt.datetime(2020, 1, 1)
    hours = lambda n: t + dt.timedelta(hours=n)
    flow = _files(spark, str(tmp_path / "in"), [[(1, 1, "a", hours(0)), (2, 1, "b", hours(1)), (3, 2, "c", hours(0))], [(4, 1, "c", hours(3)), (5, 1, "a", hours(2))]])
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        run = stream.last_events(flow).writeStream.format("memory").queryName("last_types").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
        run.awaitTermination(180)
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    found = {(r.user_id, r.ts): (r.last_type, r.event_type) for r in spark.sql("SELECT * FROM last_types").collect()}
    assert found == {(1, hours(0)): (None, "a"), (1, hours(1)): ("a", "b"), (1, hours(2)): ("b", "a"), (1, hours(3)): ("a", "c"), (2, hours(0)): (None, "c")}


def test_a_keeper_goes_on_where_it_ended(spark, tmp_path):
    folder = str(tmp_path / "keeper")
    first = stream.ComponentKeeper(spark, folder)
    first(from_rows(spark, [(1, 2), (2, 3), (1, 3)]), 0)
    first(from_rows(spark, [(5, 6)]), 1)
    again = stream.ComponentKeeper(spark, folder)
    assert again.version == 1 and {tuple(r) for r in again.labels.collect()} == {(1, 1), (2, 1), (3, 1), (5, 5), (6, 5)}
    again(from_rows(spark, [(7, 8)]), 1)  # played again: taken up before
    assert again.labels.count() == 5
    again(from_rows(spark, [(3, 3)]), 2)  # a loop is no edge
    again(from_rows(spark, [(3, 5)]), 3)
    assert {r.comp for r in again.labels.collect()} == {1} and again.edges.count() == 5
    assert {tuple(r) for r in again.bridges().collect()} == {(3, 5), (5, 6)}


def test_words_of_a_list_have_its_numbers(spark):
    events = spark.createDataFrame([(1, 9, "b", dt.datetime(2020, 1, 1))], _EVENT)
    assert stream.edge_stream(events, words=["a", "b"]).select("dst").first() == spark.range(1).select(vertex("token", "id") + 2).first()
    with pytest.raises(Exception, match="no such word"):
        stream.edge_stream(events, words=["a"]).collect()


def test_sessions(spark):
    t = dt.datetime(2020, 1, 1)
    rows = spark.createDataFrame([(1, t), (1, t + dt.timedelta(minutes=30)), (1, t + dt.timedelta(hours=3)), (2, t)], "user_id long, ts timestamp")
    assert sorted((r.user_id, r.events) for r in stream.sessions(rows).collect()) == [(1, 1), (1, 2), (2, 1)]


@pytest.mark.parametrize("name", ["workload_w7", "op_degree_approx", "lca_broom_far", "compress_report_broom"])
def test_queries_with_closed_forms_agree_with_their_sql(spark, sf, name):
    from spanweave.plans.catalog import ORACLES, QUERIES

    got = QUERIES[name](spark, sf)
    names = sorted(got.columns)
    with duckdb.connect() as db:
        for table in ("part", "events", "lineitem"):
            db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{sf}/{table}.parquet'")
        want = db.execute(f"SELECT {', '.join(names)} FROM ({ORACLES[name]})").fetchall()
    assert sorted(map(str, want)) == sorted(str(tuple(r)) for r in got.select(names).collect()) and want


def test_entry_without_the_corpus_package():
    import __spark_entry__ as e

    began = time.time()
    assert {"bridges_trade", "blocks_trade", "op_degree"} <= set(e.queries()) and set(e.oracle_sql()) <= set(e.queries())
    assert time.time() - began < 5
