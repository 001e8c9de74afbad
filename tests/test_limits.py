"""Work that must not grow with rounds or repeats: what is made once, what is worked off without a barrier."""

import random

import corpus_pipeline
import numpy as np
from graphs import dijkstra, edges_frame

from tideline.operators import paths as P
from tideline.operators import setcover as C
from tideline.plans.schedule import Schedule
from tideline.sources import graphs as G


def plan(df):
    return df._jdf.queryExecution().toString()


def test_neighbours_are_found_once_and_exactly(spark, sf):
    assert "FlatMapCoGroups" not in plan(G.g_vec(spark, sf).edges)
    rng = np.random.default_rng(4)
    far = 1e6 + rng.integers(0, 5, (60, 6)).astype(float)  # many ties, and norms that hide the distances
    odd = [(60, [float("nan")] * 6), (61, [float("inf")] * 6)]
    rows = [(i, v.tolist()) for i, v in enumerate(far)] + odd
    got = {}
    for r in G.nearest_rows(spark.createDataFrame(rows, "id long, v array<double>"), 4, block=16).collect():
        got.setdefault(r["src"], []).append((r["d"], r["dst"]))
    assert set(got) == set(range(60))
    for i, v in enumerate(far):
        d = np.sqrt(((far - v) ** 2).sum(1))
        assert sorted(got[i]) == sorted((float(d[j]), j) for j in range(60) if j != i)[:4]


def system_of(spark, seed, n=40, top=120):
    rng = random.Random(seed)
    sets = {s: set(rng.sample(range(top), rng.randint(1, 30))) for s in range(n)}
    return sets, spark.createDataFrame([(s, e) for s, es in sets.items() for e in es], "set_id long, elem_id long")


def test_greedy_cover_takes_no_job_for_a_step(spark):
    sets, system = system_of(spark, 1, n=90, top=600)
    want, left = [], set().union(*sets.values())
    while left:
        best = min(sets, key=lambda s: (-len(sets[s] & left), s))
        want.append((len(want) + 1, best, len(sets[best] & left)))
        left -= sets[best]
    assert [tuple(r) for r in C.greedy(system, at_once=900).orderBy("step").collect()] == want
    spark.sparkContext.setJobGroup("greedy", "")
    assert [tuple(r) for r in C.greedy(system).orderBy("step").collect()] == want
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("greedy")) < len(want)


def test_elections_of_a_window_need_no_barrier(spark):
    sets, system = system_of(spark, 2)
    got = C.set_cover(system, costs=spark.createDataFrame([(s, 1 + s % 7) for s in sets], "set_id long, cost long"))
    assert C.verdict(system, got.chosen).first().asDict() == {"n_elements": len(set().union(*sets.values())), "uncovered": 0, "empty_picks": 0}
    assert got.rounds < got.chosen.select("round").distinct().count()


def test_rounds_read_packed_edges_of_hubs_too(spark):
    edges = [(0, i, 1 + i % 7) for i in range(1, 12_001)] + [(i, i % 97, 2) for i in range(1, 12_001, 50)]
    want = dijkstra(edges, 0)
    g = G.Graph(edges_frame(spark, edges))
    for how in (Schedule(delta=4), Schedule(update="eager_fused", delta=4, layout="hash")):
        assert dict(map(tuple, P.sssp(g, 0, how).values("dist").collect())) == want
    assert {r["id"]: r["dist"] for r in P.many(g, [0, 5], 4).where("source = 0").collect()} == want
    assert g.adjacent().count() < 300 and g.adjacent().where("src = 0").count() > 1 and g.packed_blocks(8, "hash")[1].count() < 50


def test_the_pipeline_deduplicates_by_fingerprints(spark, sf, monkeypatch):
    seen = []
    own = corpus_pipeline.simhash.near_duplicates
    monkeypatch.setattr(corpus_pipeline.simhash, "near_duplicates", lambda *a: seen.append(1) or own(*a))
    docs = spark.createDataFrame([(i, f"one two three {'x' * i}", "en", "s", 9) for i in (1, 1, 2)], "doc_id long, text string, lang string, source string, n_chars long")
    out = corpus_pipeline.drop_near_duplicates(spark, docs, sf)
    assert seen and sorted(r["doc_id"] for r in out.collect()) == [1, 2]
