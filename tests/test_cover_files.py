"""Covers over files of pairs: the same picks as those of relational rounds, without a job for an election or a step."""

import random

from tideline.operators import setcover as C
from tideline.operators import verify as V


def system_of(spark, seed, n=60, top=200):
    rng = random.Random(seed)
    sets = {s * 3: set(rng.sample(range(top), rng.randint(1, 40))) for s in range(n)}
    return sets, spark.createDataFrame([(s, e) for s, es in sets.items() for e in [*es, min(es)]], "set_id long, elem_id long")


def test_greedy_steps_over_files(spark):
    sets, system = system_of(spark, 3)
    want, left = [], set().union(*sets.values())
    while left:
        best = min(sets, key=lambda s: (-len(sets[s] & left), s))
        want.append((len(want) + 1, best, len(sets[best] & left)))
        left -= sets[best]
    spark.sparkContext.setJobGroup("files", "")
    got = C.greedy(system, at_once=10)
    assert [tuple(r) for r in got.orderBy("step").collect()] == want
    over_files = len(spark.sparkContext.statusTracker().getJobIdsForGroup("files"))
    spark.sparkContext.setJobGroup("jobs", "")
    assert [tuple(r) for r in C.greedy(system, at_once=10, filed=0).orderBy("step").collect()] == want
    assert over_files < len(spark.sparkContext.statusTracker().getJobIdsForGroup("jobs"))


def test_elections_over_files(spark):
    sets, system = system_of(spark, 4)
    cost = spark.createDataFrame([(s, 1 + s % 7) for s in sets if s], "set_id long, cost long")
    for costs in (None, cost):
        a, b = C.set_cover(system, costs=costs), C.set_cover(system, costs=costs, at_once=10)
        assert sorted(map(tuple, a.chosen.collect())) == sorted(map(tuple, b.chosen.collect()))
        assert b.rounds == a.rounds < b.chosen.select("round").distinct().count()


def test_quality_reads_its_system_once(spark):
    sets, system = system_of(spark, 5)
    odd = system.unionByName(spark.createDataFrame([(None, 5), (1, None)], "set_id long, elem_id long"))
    a = V.cover_quality(system, 0.1, 0.1).first()
    assert a["n_elements"] == len(set().union(*sets.values())) and a["uncovered"] == 0 and a["within_bound"]
    assert V.cover_quality(odd, 0.1, 0.1).first()["greedy_sets"] == a["greedy_sets"]
