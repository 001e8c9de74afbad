import datetime as dt

from graphs import dijkstra, edges_frame

from tideline.functions.scalars import edge_schema, register_sql
from tideline.sources.graphs import pack_adjacency
from tideline.streaming.incremental import LiveDistances, deduplicated, edges_of_events

EVENT = "event_id long, ts timestamp, user_id long"


def events(spark, path, batches):
    at = dt.datetime(2024, 1, 1)
    for n, rows in enumerate(batches):
        frame = spark.createDataFrame([(e, at + dt.timedelta(seconds=s), u) for e, s, u in rows], EVENT)
        frame.coalesce(1).write.parquet(f"{path}/b{n}")
    return spark.readStream.schema(EVENT).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(path)


def collected(spark, stream, name):
    q = stream.writeStream.format("memory").queryName(name).outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    return sorted(map(tuple, spark.table(name).collect()))


def test_events_become_edges_across_batches(spark, tmp_path):
    batches = [[(1, 0, 7), (2, 10, 8)], [(3, 25, 7), (4, 30, 7)], [(5, 31, 8)]]
    got = collected(spark, edges_of_events(events(spark, str(tmp_path / "e"), batches)), "edges_seen")
    assert got == [(1, 3, 26), (2, 5, 22), (3, 4, 6)]


def test_repeats_within_the_watermark_come_once(spark, tmp_path):
    batches = [[(1, 0, 7), (2, 10, 8)], [(1, 0, 7), (3, 25, 7)], [(3, 25, 7)]]
    got = collected(spark, deduplicated(events(spark, str(tmp_path / "d"), batches)), "events_once")
    assert [e for e, *_ in got] == [1, 2, 3]


def test_distances_follow_a_stream_of_edges(spark, tmp_path):
    parts = [[(0, 1, 9), (1, 2, 9)], [(0, 2, 3), (2, 1, 2), (2, 3, 1)]]
    for n, e in enumerate(parts):
        edges_frame(spark, e).coalesce(1).write.parquet(str(tmp_path / "in" / f"b{n}"))
    stream = spark.readStream.schema(edge_schema()).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    live = LiveDistances(spark, str(tmp_path / "state"), 0)
    live.follow(stream, str(tmp_path / "check")).awaitTermination(180)
    assert {r["id"]: r["value"] for r in live.state().where("value is not null").collect()} == dijkstra(parts[0] + parts[1], 0)


def test_table_functions(spark):
    register_sql(spark)
    assert [tuple(r) for r in spark.sql("SELECT * FROM path_steps(array(4L, 2L))").collect()] == [(0, 4), (1, 2)]
    pack_adjacency(edges_frame(spark, [(1, 2, 5), (1, 3, 6)])).createOrReplaceTempView("packed")
    assert sorted(tuple(r) for r in spark.sql("SELECT n.* FROM packed, LATERAL neighbours(adj) n").collect()) == [(2, 5), (3, 6)]
