"""The published experiments on the stand-in graphs: ``python experiments.py [NAME...]`` prints a table for each.

$BENCH_SF_DIR names the tables (default sf0.01) and $BENCH_CPUS the cores (default 8). Times are wall clock with the graph loaded.
"""

from __future__ import annotations

import os
import subprocess
import sys

from pyspark.sql import SparkSession

from tideline import report as R
from tideline.functions import heuristics as H
from tideline.functions.scalars import suggest_delta
from tideline.operators import kcore as K
from tideline.operators import paths as P
from tideline.operators import setcover as C
from tideline.operators.verify import cover_ratio
from tideline.plans.autotune import autotune
from tideline.plans.schedule import PRESETS, UNBOUNDED, Schedule
from tideline.sources import graphs as G

SF, CPUS = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.01"), os.environ.get("BENCH_CPUS", "8")
COLUMNS = ["rounds", "inner_rounds", "buckets", "relaxations", "inserts", "work", "jobs", "shuffles", "seconds"]


def session(cpus: str) -> SparkSession:
    conf = {"spark.sql.shuffle.partitions": cpus, "spark.driver.memory": "12g", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC"}
    b = SparkSession.builder.master(f"local[{cpus}]")
    for k, v in conf.items():
        b = b.config(k, v)
    spark = b.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def graphs(spark: SparkSession) -> dict[str, tuple[G.Graph, int]]:
    """The four graphs and a bucket width for each: wide on the lattice, narrow on the dense one."""
    made = {"road": (G.g_road(spark, SF), 16_384), "social": (G.g_social(spark, SF), 64), "web": (G.g_web(spark, SF, True), 512), "vector": (G.g_vec(spark, SF), 2048)}
    for g, _ in made.values():
        g.pushed()
    return made


def show(title: str, rows: list[tuple]) -> None:
    print(f"\n### {title}\n")
    head, *body = rows
    print("| " + " | ".join(map(str, head)) + " |\n|" + "-|" * len(head))
    for r in body:
        print("| " + " | ".join(f"{x:.2f}" if isinstance(x, float) else str(x) for x in r) + " |")
    sys.stdout.flush()


def measured(name: str, res) -> tuple:
    m = res.metrics.row()
    return (name, *[m[c] for c in COLUMNS])


def ordered_gain(spark: SparkSession) -> None:
    """Ordered against unordered, shortest paths and coreness."""
    rows = [("run", *COLUMNS)]
    for n, (g, delta) in graphs(spark).items():
        if n in ("road", "social"):
            rows += [measured(f"{n} ordered", P.sssp(g, 0, Schedule(update="eager_fused", delta=delta))), measured(f"{n} unordered", P.bellman_ford(g, 0))]
    show("Ordered and unordered shortest paths", rows)
    g = G.g_road(spark, SF)
    rows = [("run", "seconds")]
    for n, f in (("peeling with counts", lambda: K.coreness(K.kcore(g))), ("rescan", lambda: K.rescan(g)), ("h-index rounds", lambda: K.h_index_rounds(g)[0])):
        rows.append((n, R.seconds(lambda: f().count())))
    show("Ordered and unordered coreness, road", rows)


def compare(spark: SparkSession) -> None:
    """Every kind of framework at its own width."""
    for n, (g, delta) in graphs(spark).items():
        if n not in ("road", "social"):
            continue
        runs = {}
        for name, s in PRESETS.items():
            if s.update != "lazy_count":
                s = s if s.delta > 1 else s.with_(delta=delta)
                runs[name] = P.sssp(g, 0, s)
        t = R.table_of(spark, runs)
        rows = {r["run"]: r["times_base"] for r in R.speedup(t, "eager_fused").collect()}
        show(f"Frameworks, shortest paths, {n}", [("run", *COLUMNS, "speed against eager_fused"), *[(*measured(k, r), rows[k]) for k, r in runs.items()]])


def fusion(spark: SparkSession) -> None:
    for n, (g, delta) in graphs(spark).items():
        t = R.fusion_table(spark, lambda s: P.sssp(g, 0, s), delta).collect()
        show(f"Fusion, {n}", [("run", "rounds", "inner_rounds", "seconds"), *[(r["run"], r["rounds"], r["inner_rounds"], r["seconds"]) for r in t]])


def update(spark: SparkSession) -> None:
    """Eager and lazy buckets."""
    for n, (g, delta) in graphs(spark).items():
        t = R.update_table(spark, lambda s: P.sssp(g, 0, s), ["lazy", "eager"], delta).collect()
        show(f"Updates, shortest paths, {n}", [("run", "rounds", "inserts", "seconds"), *[(r["run"], r["rounds"], r["inserts"], r["seconds"]) for r in t]])
    for n, g in (("road", G.g_road(spark, SF)), ("trade", G.g_trade(spark, SF))):
        t = R.update_table(spark, lambda s: K.kcore(g, s), ["lazy_count", "lazy", "eager"]).collect()
        show(f"Updates, coreness, {n}", [("run", "rounds", "inserts", "seconds"), *[(r["run"], r["rounds"], r["inserts"], r["seconds"]) for r in t]])


def sweep(spark: SparkSession) -> None:
    """Bucket widths from 1 to 2^17."""
    made = graphs(spark)
    for n, widths in (("social", [1 << k for k in range(0, 18)]), ("road", [1 << k for k in range(9, 18)])):
        g, rows = made[n][0], [("width", *COLUMNS)]
        how = Schedule() if n == "social" else Schedule(update="eager_fused")
        for w in widths:
            rows.append(measured(str(w), P.sssp(g, 0, how.with_(delta=w))))
        show(f"Widths, {n} (suggested: {suggest_delta(g.edges)})", rows)


def starts(spark: SparkSession) -> None:
    """Means over ten starts, and over ten targets balanced by distance."""
    rows = [("graph", "mean seconds, 10 starts", "mean seconds, 10 balanced targets")]
    for n, (g, delta) in graphs(spark).items():
        if n in ("road", "social"):
            how = Schedule(update="eager_fused", delta=delta)
            ids = [r["id"] for r in g.all_vertices().orderBy("id").limit(10).collect()]
            pairs = P.pairs_by_distance(g, ids[0])
            rows.append((n, R.mean_over(lambda s: P.sssp(g, s, how), ids), R.mean_over(lambda t: P.ppsp(g, ids[0], t, how), pairs)))
    show("Means", rows)


def estimates(spark: SparkSession) -> None:
    """Point to point with and without an estimate, and what the unordered run relaxes in vain."""
    g, how = G.g_road(spark, SF), Schedule(update="eager_fused", delta=4096)
    runs = {"no estimate": P.ppsp(g, 0, 500, how, prune=False), "manhattan": P.astar(g, 0, 500, H.manhattan(g.vertices, 500, 500), how), "great circle": P.astar(g, 0, 500, H.great_circle(g.vertices, 500, 4.0), how), "unordered": P.sssp(g, 0, how.with_(delta=UNBOUNDED))}
    show("Visited until the target is final, road", [("run", "visited", "relaxations", "redundant share", "seconds"), *[(k, r.metrics.visited, r.metrics.relaxations, R.redundant(g, r), r.metrics.seconds) for k, r in runs.items()]])


def cover(spark: SparkSession) -> None:
    rows = [("system", "rounds", "buckets", "sets", "ratio to greedy", "seconds")]
    for n, make in (("supplier", G.s_supplier), ("road", lambda s, d: G.s_neighbours(G.g_road(s, d, 182)))):
        system = make(spark, SF).cache()
        got = C.set_cover(system)
        rows.append((n, got.rounds, got.buckets, got.chosen.count(), cover_ratio(system, got.chosen), got.metrics.seconds))
    show("Set cover", rows)


def tune(spark: SparkSession) -> None:
    g, delta = graphs(spark)["road"]
    hand = P.sssp(g, 0, Schedule(update="eager_fused", delta=delta)).metrics.seconds
    rep = autotune(P.SSSP, lambda s: P.sssp(g, 0, s), limit_s=300, max_trials=30)
    show("Tuner, road", [("best", "seconds", "by hand", "gap", "trials", "search seconds"), (rep.best.text(), rep.best_seconds, hand, rep.gap(hand), len(rep.trials), rep.seconds)])


def scale(spark: SparkSession) -> None:
    """The same run in sessions of 1, 2, 4 and 8 cores."""
    rows = [("cores", "road", "social")]
    for n in (1, 2, 4, 8):
        out = subprocess.run([sys.executable, __file__, "--one"], env=os.environ | {"BENCH_CPUS": str(n)}, capture_output=True, text=True).stdout.split()
        rows.append((n, *out[-2:]))
    show("Seconds by cores, shortest paths", rows)


def one(spark: SparkSession) -> None:
    made = graphs(spark)
    for n in ("road", "social"):
        g, delta = made[n]
        P.sssp(g, 0, Schedule(update="eager_fused", delta=delta))
        print(f"{P.sssp(g, 0, Schedule(update='eager_fused', delta=delta)).metrics.seconds:.2f}")


def lines(spark: SparkSession) -> None:
    show("Lines of code", [("module", "lines"), *R.loc().items()])


ALL = {f.__name__: f for f in (ordered_gain, compare, fusion, update, sweep, starts, estimates, cover, tune, scale, lines)}

if __name__ == "__main__":
    spark_ = session(CPUS)
    if sys.argv[1:] == ["--one"]:
        one(spark_)
    else:
        for name_ in sys.argv[1:] or ALL:
            ALL[name_](spark_)
