"""Sources, stores, SQL, streaming and the queries with their SQL."""

import duckdb
import pytest

from rankflow.functions import relational, sqlapi
from rankflow.operators import methods
from rankflow.operators.graph import Graph
from rankflow.params import Params
from rankflow.plans import registry, workloads
from rankflow.sources import catalog, readers
from rankflow.sources.stores import VersionStore
from rankflow.streaming import maintain
from rankflow.streaming.maintain import Maintainer


def rows_of(frame):
    cols = sorted(frame.columns)
    plain = lambda x: None if x is None or x != x else round(x, 9) if isinstance(x, float) else int(x) if hasattr(x, "__int__") and not isinstance(x, (bool, str)) else x
    return cols, sorted((tuple(str(plain(x)) for x in r) for r in frame[cols].itertuples(index=False, name=None)))


@pytest.mark.parametrize("name", ["graph_trade_edges", "graph_web_edges", "batch_apply", "mark_reach", "frontier_sync_web", "frontier_async_web", "rank_rollup_geo", "stream_handoff_edges", "stream_interval_join"])
def test_queries_agree_with_their_sql(spark, sf, name):
    import os

    con = duckdb.connect()
    for f in os.listdir(sf):
        con.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{sf}/{f}'")
    assert rows_of(registry.QUERIES[name](spark, sf).toPandas()) == rows_of(con.sql(registry.ORACLES[name]).df())


def test_edge_lists(spark, tmp_path):
    (tmp_path / "a.txt").write_text("# comment\n1 2\n2\t3\n\nbad line\n3,1\n")
    assert {tuple(r) for r in readers.edge_rows(spark, str(tmp_path / "a.txt")).collect()} == {(1, 2), (2, 3), (3, 1)}
    (tmp_path / "m.mtx").write_text("%%MatrixMarket matrix coordinate pattern general\n% c\n3 3 2\n1 2\n2 3\n")
    assert {tuple(r) for r in readers.edge_rows(spark, str(tmp_path / "m.mtx")).collect()} == {(1, 2), (2, 3)}
    (tmp_path / "t.txt").write_text("1 2 30\n2 3 10\n1 2 20\n")
    t = readers.edge_list(spark, str(tmp_path / "t.txt"), temporal=True)
    assert [(r.src, r.dst) for r in t.rows.orderBy("seq").collect()] == [(2, 3), (1, 2), (1, 2)]


def test_store_writes_a_version_once(spark, tmp_path):
    store = VersionStore(spark, str(tmp_path / "s"), 2)
    g = Graph.build(spark.createDataFrame([(1, 2), (2, 1)], "src long, dst long"))
    assert store.latest("ranks") is None
    assert store.put_graph(0, g) and not store.put_graph(0, g)
    assert store.put_ranks(0, methods.uniform(g)) and store.versions("ranks") == [0]
    assert {tuple(e) for e in store.graph(0).edges.collect()} == {tuple(e) for e in g.edges.collect()}


def test_maintainer_skips_what_it_has(spark, tmp_path):
    g = Graph.build(spark.createDataFrame([(1, 2), (2, 3), (3, 1)], "src long, dst long"))
    store = VersionStore(spark, str(tmp_path / "s"), 2)
    keeper = Maintainer(store, g)
    change = spark.createDataFrame([(1, 3, "+")], "src long, dst long, op string")
    keeper.on_batch(change, 0)
    first = {r.vid: r.rank for r in store.ranks(1).collect()}
    Maintainer(store, g).on_batch(change, 0)
    assert store.versions("ranks") == [0, 1]
    want = {r.vid: r.rank for r in methods.cold_sync(g.apply(change)).ranks.collect()}
    assert max(abs(first[v] - want[v]) for v in want) < 1e-9


def test_sql_call(spark):
    spark.createDataFrame([(1, 2), (2, 1), (2, 3)], "src long, dst long").createOrReplaceTempView("some_edges")
    sqlapi.call(spark, "cold_sync", "some_edges", version=3)
    assert spark.sql("select count(*) n from ranks_cold_sync_t3").first().n == 3


def test_range_join_and_as_of(spark):
    p = spark.createDataFrame([(1,), (10,), (25,)], "x long")
    s = spark.createDataFrame([("a", 0, 11), ("b", 10, 26)], "k string, lo long, hi long")
    assert {(r.x, r.k) for r in relational.range_join(p, s, "x", "lo", "hi", 7).collect()} == {(1, "a"), (10, "a"), (10, "b"), (25, "b")}


def test_replay_and_round_trip(spark, sf):
    rows = workloads.replay(spark, "handoff", catalog.handoff(spark, sf), 0.02, ("frontier_sync",), most=2, with_error=True).collect()
    assert len(rows) == 2 and all(r.converged and r.error < 1e-9 for r in rows)
    assert workloads.round_trip(registry.graph(spark, sf, "web"), 1e-2, "frontier_async", params=Params(blocks=2)) < 1e-9


def test_crash_and_delay_tables():
    costs = [{b: (50, 10) for b in range(64)}] * 5
    crashed = workloads.crashes(costs, costs, (0, 8, 32), workers=64)
    assert crashed[0][1] and not crashed[1][1] and crashed[2][3] < crashed[0][3] == 1
    slow = workloads.delays(costs, costs, (500,), (1e-3,), workers=16)
    assert slow[0][5] >= 1
    speed = workloads.scaling(costs, costs, (1, 4, 16))
    assert speed[0][1] == 1 and speed[2][2] > speed[1][2] > 1


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 100
    assert set(e.oracle_sql()) <= set(e.queries())


def test_restarted_stream_goes_on_where_it_was(spark, tmp_path):
    """A checkpointed query that stops and starts again reads each file once."""
    folder, out, mark = (str(tmp_path / n) for n in ("in", "out", "mark"))

    def turn():
        stream = spark.readStream.schema("event_id long, ts timestamp").parquet(folder)
        maintain.once(stream).writeStream.format("parquet").option("path", out).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
        return sorted(r.event_id for r in spark.read.parquet(out).collect())

    spark.sql("SELECT 1L AS event_id, timestamp'2024-01-01 00:00:00' AS ts UNION ALL SELECT 2L, timestamp'2024-01-01 00:10:00'").write.parquet(folder)
    assert turn() == [1, 2]
    spark.sql("SELECT 2L AS event_id, timestamp'2024-01-01 00:10:00' AS ts UNION ALL SELECT 3L, timestamp'2024-01-01 00:20:00'").write.mode("append").parquet(folder)
    assert turn() == [1, 2, 3]
    assert turn() == [1, 2, 3]


def test_late_deletions_are_dropped(spark, tmp_path):
    folder, mark, out = str(tmp_path / "in"), str(tmp_path / "mark"), str(tmp_path / "out")
    schema = "src long, dst long, op string, ts timestamp"

    def turn(sql):
        spark.sql(sql).write.mode("append").parquet(folder)
        stream = spark.readStream.schema(schema).parquet(folder)
        maintain.on_time(stream, "1 hour").writeStream.format("parquet").option("path", out).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()

    turn("SELECT 1L AS src, 2L AS dst, '-' AS op, timestamp'2024-01-01 00:00:00' AS ts UNION ALL SELECT 5L, 6L, '-', timestamp'2024-01-01 12:00:00'")
    turn("SELECT 3L AS src, 4L AS dst, '-' AS op, timestamp'2024-01-01 01:00:00' AS ts UNION ALL SELECT 3L, 4L, '+', timestamp'2024-01-01 01:00:00' UNION ALL SELECT 7L, 8L, '-', timestamp'2024-01-02 12:00:00'")
    got = {(r.src, r.op) for r in spark.read.parquet(out).collect()}
    assert (1, "-") in got and (5, "-") in got and (3, "+") in got and (3, "-") not in got


def test_stage_totals_count_what_moved(spark):
    from rankflow.operators import measures

    last = measures.stage_totals(spark)["last_stage"]
    spark.range(1000).repartition(3).groupBy((registry.F.col("id") % 7).alias("k")).count().collect()
    got = measures.stage_totals(spark, last)
    assert got["last_stage"] > last and got["tasks"] >= 3 and got["shuffle_bytes"] > 0


@pytest.mark.parametrize("name", ["stream_session", "stream_dedup", "stream_static_join", "stream_handoff_edges", "stream_update_mode"])
def test_streams_are_drained_into_files(spark, sf, name):
    """Before, all rows of a stream were held by the driver, in a memory table."""
    assert registry.QUERIES[name](spark, sf).inputFiles()
    test_queries_agree_with_their_sql(spark, sf, name)


@pytest.mark.parametrize("name", ["stream_static_join", "stream_handoff_edges", "stream_dedup", "stream_interval_join"])
def test_streams_read_a_table_in_many_files(spark, sf, tmp_path, name):
    """Before, a stream over a table that is a folder of files had no rows. The files are not in time order."""
    events = duckdb.sql(f"SELECT * FROM '{sf}/events.parquet' ORDER BY ts DESC").df()
    (tmp_path / "events.parquet").mkdir()
    for k in range(5):
        events.iloc[k * len(events) // 5 : (k + 1) * len(events) // 5].to_parquet(tmp_path / "events.parquet" / f"part-{k:05d}.parquet", coerce_timestamps="us")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    got = rows_of(registry.QUERIES[name](spark, str(tmp_path)).toPandas())
    assert got[1] and got == rows_of(con.sql(registry.ORACLES[name]).df())


def test_queries_start_from_tables_whatever_was_made(spark, sf, monkeypatch):
    """Before, a query that followed others of its session read no table."""
    registry.QUERIES["batch_apply"](spark, sf)
    built = []
    build = catalog.build
    monkeypatch.setattr(registry.catalog, "build", lambda name, *a: built.append(name) or build(name, *a))
    for name in ("batch_diff", "mark_expand_example14"):
        test_queries_agree_with_their_sql(spark, sf, name)
    test_queries_agree_with_their_sql(spark, sf, "graph_profile")
    assert built[:2] == ["line", "grid"]
