"""Rounds over packed edges in files: the same answers and counters as those of relational rounds, without a job for a round."""

import random

import pytest
from graphs import both_ways, dijkstra, edges_frame, peel, some_graph

from tideline.operators import kcore as K
from tideline.operators import paths as P
from tideline.plans.schedule import UNBOUNDED, Schedule
from tideline.sources import packed
from tideline.sources.graphs import Graph, g_social, g_trade

EDGES = [*some_graph(), (70, 71, 3), (0, 90, 2), (91, 0, 1)]
COUNTERS = ("rounds", "buckets", "revisits", "relaxations", "inserts", "visited", "violations", "order")


def both(spark, edges, monkeypatch):
    monkeypatch.setattr(packed.pack, "__defaults__", (False, 7))  # many rows, and files of several rows
    g = Graph.packed_from(edges_frame(spark, edges))
    assert g.rows.count() > 1 and g.numbered().edges == len(edges)
    return Graph(edges_frame(spark, edges)), g


@pytest.mark.parametrize("how", [Schedule(), Schedule(delta=8), Schedule(delta=4, width=3), Schedule(delta=UNBOUNDED)])
def test_distances_and_counters_are_those_of_relational_rounds(spark, how, monkeypatch):
    plain, g = both(spark, EDGES, monkeypatch)
    a, b = P.sssp(plain, 0, how), P.sssp(g, 0, how)
    assert dict(map(tuple, b.values().collect())) == dijkstra(EDGES, 0)
    assert sorted(map(tuple, a.state.collect()), key=str) == sorted(map(tuple, b.state.collect()), key=str)
    assert [getattr(a.metrics, c) for c in COUNTERS] == [getattr(b.metrics, c) for c in COUNTERS]


def test_a_width_takes_no_job_for_a_round(spark, sf):
    res = P.sssp(g_social(spark, sf), 0, Schedule(delta=1))
    assert res.metrics.rounds > 20 and res.metrics.jobs < 5


def test_a_target_stops_the_rounds(spark, monkeypatch):
    plain, g = both(spark, EDGES, monkeypatch)
    want = dijkstra(EDGES, 0)
    for t in (0, 90, 13, 999):
        a, b = (P.ppsp(x, 0, t, Schedule(delta=16)) for x in (plain, g))
        assert P.distance_to(b, 0, t).first()["dist"] == want.get(t)
        assert [getattr(a.metrics, c) for c in COUNTERS] == [getattr(b.metrics, c) for c in COUNTERS] and b.metrics.jobs < 5


def test_several_sources_share_rounds_in_one_task(spark, monkeypatch):
    plain, g = both(spark, EDGES, monkeypatch)
    pairs = {0: 13, 5: 90, 7: 999, 400: 3}
    for targets in (None, pairs):
        a, b = (sorted(map(tuple, P.many(x, list(pairs), 4, targets).collect())) for x in (plain, g))
        assert a == b and (400, 400, 0) in b


def test_the_guess_of_a_size_does_not_grow_with_rounds(spark):
    chain = [(i, i + 1, 1) for i in range(9)]
    got = P.many(Graph(edges_frame(spark, chain)), [0], 1, {0: 9})
    assert got.count() == 10
    assert got._jdf.queryExecution().optimizedPlan().stats().sizeInBytes().bit_length() < 100


@pytest.mark.parametrize("how", [Schedule(update="lazy_count"), Schedule(), Schedule(update="eager", fuse_limit=0, blocks=3)])
def test_peeling_and_its_counters_are_those_of_relational_rounds(spark, how, monkeypatch):
    rng = random.Random(5)
    sym = both_ways([(rng.randrange(60), rng.randrange(rng.choice([8, 60])), 1) for _ in range(400)])
    plain, g = both(spark, sym, monkeypatch)
    a, b = K.kcore(plain, how), K.kcore(g, how)
    assert {r["id"]: r["coreness"] for r in K.coreness(b).collect()} == peel(sym)
    assert [getattr(a.metrics, c) for c in COUNTERS] == [getattr(b.metrics, c) for c in COUNTERS]
    assert b.metrics.jobs < 5 < b.metrics.rounds


def test_packed_graphs_have_the_edges_that_they_are_made_of(spark, monkeypatch):
    odd = [(1, 2, 5), (1, 2, 5), (-4, 1, 1 << 40), (3, 3, 0), (2, None, 1), (None, 2, 1)]
    g = Graph.packed_from(edges_frame(spark, odd))
    key = lambda rows: sorted(map(tuple, rows), key=str)
    assert key(g.edges.collect()) == key(odd) and g.numbered() is None
    assert len(Graph.packed_from(edges_frame(spark, odd), True).edges.collect()) == len(odd) - 1
    with pytest.raises(ValueError):
        Graph.packed_from(edges_frame(spark, [(0, 1, -1)])).checked()
    empty = Graph.packed_from(edges_frame(spark, []))
    assert empty.edges.count() == 0 and [tuple(r) for r in P.sssp(empty, 7).values().collect()] == [(7, 0)]


def test_the_trade_graph_is_packed(spark, sf):
    g = g_trade(spark, sf)
    n, ends = g.edges.count(), g.all_vertices().count()
    assert g.numbered().edges == n and g.numbered().count == ends == g.edges.select("src").distinct().count()
