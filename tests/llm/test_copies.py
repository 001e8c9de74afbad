import hashlib
from collections import Counter

import corpus_pipeline as C

from tideline.llm import mixing

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def rows():
    """Three sources of unequal size; null ids, repeated rows, and two texts under one id."""
    out = []
    for s, n in (("a", 12), ("b", 60), ("c", 60)):
        out += [(ord(s) * 1000 + i, " ".join([f"{s}{i}"] * (5 + i % 7)), "en", s, 1) for i in range(n)]
    out += [(None, f"null {i} of a source", "en", s, 1) for i, s in enumerate("aabbc")]
    return out + out[3:5] * 2 + [(out[3][0], "another text with that id", "en", "a", 1)]


def brute(found):
    """(position, copy, text) of every whole copy; shares 5, 2, 1 and a cap of 3 times a source."""
    size = Counter()
    for r in found:
        size[r[3]] += len(r[1].split())
    shares, cap = dict(zip("abc", (5, 2, 1))), {s: 3.0 * n for s, n in size.items()}
    goal, rest, open_ = dict.fromkeys("abc", 0.0), float(sum(size.values())), set("abc")
    while rest > 1e-9 and open_:
        add = {s: rest * shares[s] / sum(shares[x] for x in open_) for s in open_}
        rest = 0.0
        for s, x in add.items():
            goal[s] += x
            if goal[s] >= cap[s]:
                rest += goal[s] - cap[s]
                goal[s] = cap[s]
                open_.discard(s)
    out = []
    for s, knots in zip("abc", mixing.CURRICULUM):
        at, budget = 0, int(goal[s] + 0.5)
        order = sorted((r for r in found if r[3] == s), key=lambda r: (hashlib.md5(("mix" + ("" if r[0] is None else str(r[0]))).encode()).hexdigest(), len(r[1].split())))
        for r in order:
            n = len(r[1].split())
            for c in range(3):
                begin = at + c * size[s]
                if 2 * (budget - begin) >= n:
                    out.append((time_at(begin / goal[s], knots), c, r[1]))
            at += n
    return out


def time_at(share, knots):
    """By bisection, the time at which the schedule's integral has reached a share of its whole."""
    def done(t):
        return sum(max(0, min(t, b) - a) * (2 * u + (v - u) * (min(max(t, a), b) - a) / (b - a)) / 2 for (a, u), (b, v) in zip(knots, knots[1:]))

    low, high = 0.0, 1.0
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if done(mid) < share * done(1.0) else (low, mid)
    return low


def test_null_and_repeated_ids_get_the_copies_of_their_rows(spark, sf):
    found = rows()
    got = C.mix_sources(spark, spark.createDataFrame(found, SCHEMA), sf).collect()
    want = Counter(t for _, _, t in brute(found))
    assert Counter(r["text"] for r in got) == want
    assert any(r["doc_id"] is None for r in got)
    assert all(n <= 3 * sum(r[1] == t for r in found) for t, n in want.items())


def test_copies_stand_where_their_own_time_puts_them(spark, sf):
    found = [r for r in rows() if r[0] is not None][:132]
    got = [r["text"] for r in C.mix_sources(spark, spark.createDataFrame(found, SCHEMA), sf).collect()]
    want = [t for _, _, t in sorted(brute(found), key=lambda x: x[0])]
    # Sources begin together at time 0; everything later has a time of its own.
    assert got[3:] == want[3:] and sorted(got[:3]) == sorted(want[:3])
    last = {s: max(i for i, t in enumerate(got) if t[0] == s) for s in "abc"}
    assert min(last.values()) > 0.9 * len(got)
