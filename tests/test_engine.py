import random

import pytest
from graphs import both_ways, dijkstra, edges_frame, peel, some_graph

from tideline.functions import heuristics as H
from tideline.operators import kcore as K
from tideline.operators import paths as P
from tideline.operators import setcover as C
from tideline.operators.components import connected_components
from tideline.operators.engine import BucketQueue
from tideline.plans import rules as R
from tideline.plans.autotune import autotune
from tideline.plans.explain import explain_schedule
from tideline.plans.schedule import PRESETS, UNBOUNDED, Schedule, validate
from tideline.sources import files
from tideline.sources.graphs import Graph, encode_ids, nearest_rows, ranked, tiles

EDGES = some_graph()
SCHEDULES = {
    "lazy": Schedule(delta=8), "pull": Schedule(delta=8, direction="pull"), "auto": Schedule(delta=16, direction="auto"), "hops": Schedule(delta=16, plan_hops=2),
    "overflow": Schedule(delta=8, open_buckets=2), "eager": Schedule(update="eager", delta=8, fuse_limit=0, blocks=3), "fused": Schedule(update="eager_fused", delta=8, blocks=3),
    "fused small": Schedule(update="eager_fused", delta=16, fuse_limit=2, blocks=2, layout="hash"), "relaxed": Schedule(delta=4, width=3), "unordered": Schedule(delta=UNBOUNDED),
    "callback": Schedule(delta=16, callback=True), "salted": Schedule(delta=16, balance="salted"),
}


def values(res, name="value"):
    return {r["id"]: r[name] for r in res.values(name).collect()}


@pytest.mark.parametrize("name", SCHEDULES)
def test_every_schedule_gives_the_same_distances(spark, name):
    res = P.sssp(Graph(edges_frame(spark, EDGES)), 0, SCHEDULES[name])
    assert values(res) == dijkstra(EDGES, 0)
    assert res.metrics.rounds >= res.metrics.buckets
    if name in ("lazy", "fused", "eager"):
        assert res.metrics.order == sorted(res.metrics.order)


def test_micro_graphs(spark):
    diamond = [(0, 1, 1), (0, 2, 1), (1, 3, 5), (2, 3, 5), (3, 3, 0), (0, 1, 4), (5, 6, 1)]
    assert values(P.sssp(Graph(edges_frame(spark, diamond)), 0)) == dijkstra(diamond, 0)
    assert values(P.sssp(Graph(edges_frame(spark, [])), 7)) == {7: 0}
    zero = [(0, 1, 0), (1, 2, 0), (2, 0, 0)]
    assert values(P.sssp(Graph(edges_frame(spark, zero)), 0, Schedule(update="eager_fused"))) == {0: 0, 1: 0, 2: 0}
    with pytest.raises(ValueError):
        P.sssp(Graph(edges_frame(spark, [(0, 1, -1)])), 0)
    with pytest.raises(ValueError):
        P.wbfs(Graph(edges_frame(spark, zero)), 0)


def test_targets_estimates_and_paths(spark):
    grid = [(5 * x + y, 5 * (x + dx) + y + dy, 3 + (x * y) % 4) for x in range(5) for y in range(5) for dx, dy in ((0, 1), (1, 0), (0, -1), (-1, 0)) if 0 <= x + dx < 5 and 0 <= y + dy < 5]
    verts = spark.createDataFrame([(5 * x + y, x, y) for x in range(5) for y in range(5)], "id long, x long, y long")
    g, want = Graph(edges_frame(spark, grid), verts), dijkstra(grid, 0)
    p = P.ppsp(g, 0, 24, Schedule(delta=4))
    a = P.astar(g, 0, 24, H.manhattan(verts, 24, 3), Schedule(delta=1))
    assert [r["dist"] for x in (p, a) for r in P.distance_to(x, 0, 24).collect()] == [want[24]] * 2
    assert P.check_estimate(g, H.manhattan(verts, 24, 3)).first()[0] == 0
    full = P.sssp(g, 0, Schedule(delta=8))
    path = P.extract_path(P.parents(g, full, 0), 0, 24)
    assert path[0] == 0 and path[-1] == 24 and len(path) == 9
    assert P.distance_to(P.ppsp(g, 0, 0), 0, 0).first()["dist"] == 0
    assert P.distance_to(P.ppsp(g, 0, 99, Schedule(delta=8)), 0, 99).first()["dist"] is None
    many = {(r["source"], r["id"]): r["dist"] for r in P.many(g, [0, 7], 4).collect()}
    assert many == {(s, v): d for s in (0, 7) for v, d in dijkstra(grid, s).items()}


@pytest.mark.parametrize("how", [Schedule(update="lazy_count"), Schedule(), Schedule(update="eager", fuse_limit=0, blocks=3)])
def test_coreness(spark, how):
    sym = both_ways(EDGES)
    got = {r["id"]: r["coreness"] for r in K.coreness(K.kcore(Graph(edges_frame(spark, sym)), how)).collect()}
    assert got == peel(sym)


def test_unordered_coreness_and_subgraph(spark):
    tail = both_ways([(0, 1, 1), (1, 2, 1), (2, 0, 1), (2, 3, 1), (7, 8, 1), (8, 9, 1), (9, 7, 1)])
    g = Graph(edges_frame(spark, tail))
    want = peel(tail)
    assert {r[0]: r[1] for r in K.h_index_rounds(g)[0].collect()} == want
    assert {r[0]: r[1] for r in K.rescan(g).collect()} == want
    core = K.coreness(K.kcore(g))
    assert {tuple(r) for r in K.subgraph(g, core, 2).collect()} == {(0, 0), (1, 0), (2, 0), (7, 7), (8, 7), (9, 7)}


def test_h_index_in_packed_rounds_and_in_joins(spark, monkeypatch):
    ring = both_ways([(i, (i + j) % 60, 1) for i in range(60) for j in (1, 2, 5)] + [(100 + i, i, 1) for i in range(40)])
    g = Graph(edges_frame(spark, ring))
    joined, rounds = K.h_index_rounds(g, held=10)
    want = peel(ring)
    assert {r[0]: r[1] for r in joined.collect()} == want
    monkeypatch.setattr(K, "_h_index_joins", None)
    got, again = K.h_index_rounds(g, most=7)
    assert {r[0]: r[1] for r in got.collect()} == want and again == rounds


def test_cover(spark):
    system = spark.createDataFrame([(1, e) for e in range(6)] + [(2, e) for e in range(6, 10)] + [(3, 0), (3, 7), (4, 9)], "set_id long, elem_id long")
    got = C.set_cover(system)
    assert C.verdict(system, got.chosen).first().asDict() == {"n_elements": 10, "uncovered": 0, "empty_picks": 0}
    assert sorted(r["set_id"] for r in got.chosen.collect()) == [1, 2]
    assert [r["set_id"] for r in C.greedy(system).orderBy("step").collect()] == [1, 2]
    again = C.set_cover(system)
    assert got.chosen.collect() == again.chosen.collect()


def test_components(spark):
    path = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (5, 5), (None, 3)], "a long, b long")
    assert {tuple(r) for r in connected_components(path).collect()} == {(i, 0) for i in range(41)} | {(100, 100), (101, 100)}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_legality():
    for program, bad in ((P.SSSP, "update=lazy_count"), (P.WBFS, "delta=4"), (K.KCORE, "update=eager_fused"), (K.KCORE, "delta=2"), (P.SSSP, "update=eager direction=pull"), (P.SSSP, "update=other")):
        with pytest.raises(ValueError):
            validate(program, Schedule.parse(bad))
    for s in PRESETS.values():
        validate(P.SSSP if s.update != "lazy_count" else K.KCORE, s)
    hooked = R.OrderedProgram("cover", P.SSSP.spec, P.SSSP.rule, hooks=("recount",))
    assert not R.eager_legal(hooked).ok and R.eager_legal(P.SSSP).ok
    assert R.constant_sum(K.KCORE.rule) == R.ConstSum(-1, "current") and R.constant_sum(P.SSSP.rule) is None
    assert not R.check_monotone(R.PrioritySpec("high"), P.SSSP.rule).ok
    assert Schedule.parse(Schedule(delta=64, layout="hash").text()) == Schedule(delta=64, layout="hash")
    with pytest.raises(ValueError):
        Schedule.parse("speed=fast")


def test_clamping_once_is_clamping_each_time():
    for p in range(12):
        for a in range(0, -6, -1):
            for b in range(0, -6, -1):
                assert max(max(p + a, 3) + b, 3) == max(p + a + b, 3)


def test_a_push_round_has_one_exchange_and_a_pull_none(spark):
    g = Graph(edges_frame(spark, EDGES))
    push = explain_schedule(P.SSSP, g, Schedule(delta=8), {0: 0})
    assert push.count("Exchange hashpartitioning") == 1
    pull = explain_schedule(P.SSSP, g, Schedule(delta=8, direction="pull"), {0: 0})
    assert "Exchange hashpartitioning" not in pull and "BroadcastHashJoin" in pull
    assert "BatchEvalPython" not in push and "ArrowEvalPython" not in push


def test_an_inconsistent_estimate_is_counted(spark):
    g = Graph(edges_frame(spark, [(0, 1, 1), (1, 2, 1)]))
    jump = spark.createDataFrame([(0, 9), (1, 0), (2, 0)], "id long, h long")
    assert P.astar(g, 0, 2, jump).metrics.violations > 0
    assert P.sssp(g, 0).metrics.violations == 0


def test_fusion_takes_fewer_rounds(spark):
    chain = [(i, i + 1, 1) for i in range(30)] + [(i + 1, i, 1) for i in range(30)]
    g = Graph(edges_frame(spark, chain))
    plain = P.sssp(g, 0, Schedule(update="eager", fuse_limit=0, delta=64, blocks=2))
    fused = P.sssp(g, 0, Schedule(update="eager_fused", delta=64, blocks=2))
    assert values(plain) == values(fused) == dijkstra(chain, 0)
    assert fused.metrics.rounds < plain.metrics.rounds


def test_queue_operators(spark):
    res = P.sssp(Graph(edges_frame(spark, EDGES)), 0, Schedule(delta=8))
    q = BucketQueue(P.SSSP, Schedule(delta=8), res.state)
    assert q.done() and q.is_final(0)
    assert q.final(spark.createDataFrame([(0,), (999,)], "id long")).where("final").count() == 1


def test_files_ids_and_tuner(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# edges\n0 1 5\n1 2 7\n")
    assert sorted(map(tuple, files.edge_list(spark, str(tmp_path / "e.txt")).collect())) == [(0, 1, 5), (1, 2, 7)]
    (tmp_path / "r.gr").write_text("c x\np sp 2 1\na 1 2 9\n")
    assert [tuple(r) for r in files.dimacs(spark, str(tmp_path / "r.gr")).collect()] == [(1, 2, 9)]
    files.write(edges_frame(spark, EDGES), str(tmp_path / "o"), "orc")
    assert spark.read.orc(str(tmp_path / "o")).count() == len(EDGES)
    keys = spark.createDataFrame([(x,) for x in "dbcaé"], "k string")
    assert {r["k"]: r["id"] for r in encode_ids(keys, "k").collect()} == {"a": 0, "b": 1, "c": 2, "d": 3, "é": 4}
    g = Graph(edges_frame(spark, EDGES[:40]))
    rep = autotune(P.SSSP, lambda s: P.sssp(g, 0, s), limit_s=60, max_trials=3, space={"delta": [4, 16, 64], "update": ["lazy", "eager_fused"]})
    assert len(rep.trials) == 3 and rep.best_seconds <= rep.trials[0][1]


def test_parents_on_zero_weights_form_no_cycle(spark):
    loop = [(9, 1, 0), (1, 2, 0), (2, 1, 0), (2, 3, 4)]
    g = Graph(edges_frame(spark, loop))
    assert P.extract_path(P.parents(g, P.sssp(g, 9), 9), 9, 3) == [9, 1, 2, 3]
    rng = random.Random(6)
    edges = [(rng.randrange(25), rng.randrange(25), rng.choice([0, 0, 0, 2])) for _ in range(90)]
    g, want = Graph(edges_frame(spark, edges)), dijkstra(edges, 0)
    tree = {r["id"]: (r["dist"], r["parent"]) for r in P.parents(g, P.sssp(g, 0, Schedule(delta=4)), 0).collect()}
    assert {v: d for v, (d, _) in tree.items()} == want
    best = {(a, b): min(w for x, y, w in edges if (x, y) == (a, b)) for a, b, _ in edges}
    for v in tree:
        hops = 0
        while v != 0:
            d, up = tree[v]
            assert tree[up][0] + best[up, v] == d
            v, hops = up, hops + 1
            assert hops <= len(tree)


def test_balanced_edges_stay_where_they_are(spark):
    g = Graph(edges_frame(spark, EDGES))
    for balance in ("vertex", "edge", "salted"):
        for frontier, most in ((1, 1), (500_000, 2 if balance == "salted" else 1)):
            plan = explain_schedule(P.SSSP, g, Schedule(delta=8, balance=balance), {0: 0}, frontier)
            assert plan.count("Exchange hashpartitioning") == most and "Exchange rangepartitioning" not in plan
    assert values(P.sssp(g, 0, Schedule(delta=8, balance="edge"))) == dijkstra(EDGES, 0)


def test_rounds_give_their_folders_back(spark):
    from pathlib import Path

    chain = Graph(edges_frame(spark, [(i, i + 1, 1) for i in range(9)]))
    chain.pushed()
    here = Path(spark.sparkContext.getCheckpointDir().removeprefix("file:"))
    for how in (Schedule(), Schedule(update="eager", fuse_limit=0, blocks=2), Schedule(open_buckets=2)):
        before = set(here.iterdir())
        res = P.sssp(chain, 0, how)
        assert res.metrics.rounds >= 10 and res.metrics.released >= 5
        assert how.open_buckets or len(set(here.iterdir()) - before) < 8
        assert values(res) == {i: i for i in range(10)}


def test_additions_must_say_where_they_go():
    low, high = R.PrioritySpec("low", False), R.PrioritySpec("high", False)
    ok = lambda spec, rule: R.check_monotone(spec, rule).ok
    assert ok(low, R.EdgeRule.add(-1, "current")) and ok(low, R.EdgeRule.add(2)) and ok(high, R.EdgeRule.add(-3))
    assert not ok(low, R.EdgeRule.add(-1)) and not ok(high, R.EdgeRule.add(1)) and not ok(low, R.EdgeRule.add(0))
    assert not ok(low, R.EdgeRule.add(lambda w: w)) and ok(low, R.EdgeRule.add(lambda w: w, sign=1))


def test_inconsistent_estimates_are_counted_by_every_update(spark):
    g = Graph(edges_frame(spark, [(0, 1, 1), (1, 2, 1)]))
    jump = spark.createDataFrame([(0, 9), (1, 0), (2, 0)], "id long, h long")
    for how in (Schedule(plan_hops=2), Schedule(update="eager", fuse_limit=0, blocks=1)):
        assert P.astar(g, 0, 2, jump, how).metrics.violations > 0
        assert P.sssp(g, 0, how).metrics.violations == 0


def test_cover_runs_in_the_engine_and_winners_overlap_little(spark):
    rng = random.Random(2)
    sets = {s: set(rng.sample(range(120), rng.randint(1, 30))) for s in range(40)}
    system = spark.createDataFrame([(s, e) for s, es in sets.items() for e in es], "set_id long, elem_id long")
    got = C.set_cover(system)
    rows = got.chosen.collect()
    assert got.metrics.rounds >= got.metrics.buckets >= 1 and got.metrics.violations == 0
    assert got.metrics.order == sorted(got.metrics.order, reverse=True)
    everything, covered = set().union(*sets.values()), set()
    for n in sorted({r["round"] for r in rows}):
        now = [r for r in rows if r["round"] == n]
        fresh = [sets[r["set_id"]] - covered for r in now]
        for r, new in zip(now, fresh):
            # each was worth its bucket, and keeps nearly all of that beside the others of its round
            assert len(new) >= 1.1 ** r["bucket"] - 1e-6 and r["gain"] >= 0.9 * 1.1 ** r["bucket"] - 1e-6
        assert sum(r["gain"] for r in now) <= len(set().union(*fresh))
        covered |= set().union(*fresh)
    assert covered == everything
    cost = spark.createDataFrame([(s, 1 + s % 7) for s in sets], "set_id long, cost long")
    assert C.verdict(system, C.set_cover(system, costs=cost).chosen).first()["uncovered"] == 0
    assert C.set_cover(system.limit(0)).chosen.count() == 0
    with pytest.raises(ValueError):
        validate(R.OrderedProgram("x", R.PrioritySpec("high", False), R.EdgeRule("hook")), Schedule())


def test_ranks_tiles_and_blocked_neighbours(spark):
    rows = spark.createDataFrame([(i, i % 7) for i in range(53)], "id long, d long").repartition(5)
    order = sorted((i % 7, i) for i in range(53))
    assert {r["id"]: r["rank"] for r in ranked(rows, ["d", "id"]).collect()} == {i: k for k, (_, i) in enumerate(order)}
    sizes = [53 // 10 + (k < 53 % 10) for k in range(10)]
    want = [k + 1 for k, n in enumerate(sizes) for _ in range(n)]
    assert {r["id"]: r["part"] for r in tiles(rows, 10, ["d", "id"]).collect()} == {i: want[k] for k, (_, i) in enumerate(order)}
    rng = random.Random(1)
    vs = [(i, [rng.random() for _ in range(3)]) for i in range(40)]
    got = {}
    for r in nearest_rows(spark.createDataFrame(vs, "id long, v array<double>"), 3, block=9).collect():
        got.setdefault(r["src"], set()).add(r["dst"])
    for i, v in vs:
        assert got[i] == {j for _, j in sorted((sum((a - b) ** 2 for a, b in zip(v, u)), j) for j, u in vs if j != i)[:3]}
