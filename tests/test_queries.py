import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
import __spark_entry__ as entry
from tideline import queries as base


def test_registry_is_consistent():
    q, sql = base.entries()
    assert set(sql) <= set(q) and len(q) > 80
    assert set(q) <= set(entry.queries())


def test_entry_runs(spark):
    df = entry.entry(spark)
    assert df.columns == ["id", "coreness"] and df.count() == 200


def test_stream_follows_insertions(spark, tmp_path):
    from graphs import dijkstra, edges_frame

    from tideline.streaming.incremental import LiveDistances

    live = LiveDistances(spark, str(tmp_path / "s"), 0)
    first, second = [(0, 1, 9), (1, 2, 9)], [(0, 2, 3), (2, 1, 2), (2, 3, 1)]
    live.batch(edges_frame(spark, first), 0)
    live.batch(edges_frame(spark, second), 1)
    got = {r["id"]: r["value"] for r in live.state().where("value is not null").collect()}
    assert got == dijkstra(first + second, 0)
