"""Plain-Python answers for small graphs."""

import heapq
import random


def edges_frame(spark, edges):
    return spark.createDataFrame(edges or [], "src long, dst long, weight long")


def dijkstra(edges, source):
    out = {}
    for a, b, w in edges:
        out.setdefault(a, []).append((b, w))
    dist, heap = {}, [(0, source)]
    while heap:
        d, v = heapq.heappop(heap)
        if v in dist:
            continue
        dist[v] = d
        for u, w in out.get(v, []):
            heapq.heappush(heap, (d + w, u))
    return dist


def peel(edges):
    near = {}
    for a, b, _ in edges:
        near.setdefault(a, set()).add(b)
    core, k = {}, 0
    while near:
        k = max(k, min(map(len, near.values())))
        low = [v for v in near if len(near[v]) <= k]
        for v in low:
            core[v] = k
            for u in near.pop(v):
                if u in near:
                    near[u].discard(v)
    return core


def some_graph(n=60, m=220, top=30, seed=4):
    rng = random.Random(seed)
    return [(rng.randrange(n), rng.randrange(n), rng.randint(0, top)) for _ in range(m)]


def both_ways(edges):
    best = {}
    for a, b, w in edges:
        if a != b:
            for e in ((a, b), (b, a)):
                best[e] = min(w, best.get(e, w))
    return [(a, b, w) for (a, b), w in best.items()]
