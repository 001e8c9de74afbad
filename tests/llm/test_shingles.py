import random

import corpus_pipeline as C
import numpy as np
import pytest

from tideline.llm import shingles
from tideline.operators.components import connected_components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def brute_leaders(texts):
    """Places of the first of each group of texts with a Jaccard similarity of 5-word shingles of 4/5 and more."""
    sets = []
    for t in texts:
        ws = (t or "").lower().split()
        sets.append({tuple(ws[i : i + 5]) for i in range(max(1, len(ws) - 4))})
    up = list(range(len(sets)))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if 9 * both >= 4 * (len(sets[i]) + len(sets[j])):
                x, y = find(i), find(j)
                up[max(x, y)] = min(x, y)
    return {find(i) for i in range(len(sets))}


def edited():
    """Texts around a common passage, chains of copies with replaced words, short and empty ones."""
    r = random.Random(5)
    words = [f"w{i}" for i in range(3000)]
    passage = r.choices(words, k=50)
    out = [None, "", "  ", "a b", "A b", "a b c", "x y z u v", "x y z u w"]
    for _ in range(40):
        ws = passage + r.choices(words, k=r.randint(1, 150))
        for _ in range(r.randint(1, 6)):
            out.append(" ".join(ws))
            ws = list(ws)
            for _ in range(r.randint(0, 4)):
                ws[r.randrange(len(ws))] = r.choice(words)
    return out


def test_sketches_bound_the_difference():
    r = random.Random(3)
    for _ in range(200):
        a = np.unique(np.array([r.getrandbits(64) for _ in range(r.randint(0, 900))], np.uint64))
        b = np.unique(np.concatenate([a[: r.randint(0, len(a))], np.array([r.getrandbits(64) for _ in range(r.randint(0, 300))], np.uint64)]))
        if shingles.similar(a, b):
            assert shingles.may_be(shingles.sketch(a), shingles.sketch(b), len(a) + len(b))
    far = [np.array([r.getrandbits(64) for _ in range(5000)], np.uint64) for _ in range(2)]
    assert not shingles.may_be(shingles.sketch(far[0]), shingles.sketch(far[1]), 10_000)


@pytest.mark.parametrize("small,sieve", [(0, 0), (2, 2_000_000)])
def test_plans_for_other_sizes_give_the_same_groups(spark, monkeypatch, small, sieve):
    texts = edited()
    monkeypatch.setattr(shingles, "SIEVE", sieve)
    told, sets = shingles.groups(frame(spark, enumerate(texts)), block=5, fan=2, small=small)
    lead = told.join(sets, "th").groupBy("c").agg({"doc_id": "min"}).collect()
    assert sorted(r[1] for r in lead) == sorted(brute_leaders(texts))


def frame(spark, rows):
    return spark.createDataFrame([(d, t, "en", "s", len(t or "")) for d, t in rows], SCHEMA)


@pytest.mark.parametrize("block", [4096, 5])
def test_groups_are_those_of_brute_force(spark, block):
    texts = edited()
    got = shingles.keep_one(frame(spark, enumerate(texts)), block=block).collect()
    assert sorted(r["doc_id"] for r in got) == sorted(brute_leaders(texts))


def test_pipeline_stage_drops_edited_copies(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    a = docs.toPandas().sort_values("doc_id")
    ids = a.doc_id.tolist()
    assert sorted(r["doc_id"] for r in C.drop_near_duplicates(spark, docs, sf).collect()) == sorted(ids[i] for i in brute_leaders(a.text))


def test_two_texts_under_one_id_and_null_ids(spark):
    one, two = " ".join(f"p{i}" for i in range(60)), " ".join(f"q{i}" for i in range(60))
    rows = [(1, one), (1, two), (1, two), (2, one), (None, one), (None, one)]
    got = [(r["doc_id"], r["text"]) for r in shingles.keep_one(frame(spark, rows)).collect()]
    assert sorted(got, key=str) == sorted([(1, one), (1, two), (None, one), (None, one)], key=str)
    assert shingles.keep_one(frame(spark, rows).where("false")).count() == 0


def near_copies(n):
    """Copies of one text with three words replaced in each: two of them share about 4/5 of their shingles, a little more or less."""
    r = random.Random(9)
    first = [f"w{i}" for i in range(300)]
    out = []
    for _ in range(n):
        ws = list(first)
        for _ in range(3):
            ws[r.randrange(300)] = f"x{r.randrange(10**6)}"
        out.append(" ".join(ws))
    return out


def together(n, pairs):
    up = list(range(n))

    def find(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in pairs:
        up[find(a)] = find(b)
    return {frozenset(i for i in range(n) if find(i) == r) for r in map(find, range(n))}


def test_a_large_bucket_answers_with_a_forest_of_its_possible_pairs():
    sets = [shingles.shingles(t) for t in near_copies(150)]
    bits = [shingles.sketch(s) for s in sets]
    may = [(a, b) for a in range(150) for b in range(a) if a % 7 != b % 7 and shingles.may_be(bits[a], bits[b], len(sets[a]) + len(sets[b]))]
    got = list(shingles._many({"v": list(range(150)), "c": [a % 7 for a in range(150)], "n": [len(s) for s in sets], "sketch": bits}))
    assert len(may) > 1000 and len(got) < 150 and set(got) <= {(b, a) for a, b in may}
    assert together(150, got) == together(150, may)


def test_links_within_a_cell_join_what_all_similar_pairs_join():
    sets = [s for t in edited() + near_copies(60) if len(s := shingles.shingles(t))]
    n = len(sets)
    group = [i if i % 5 else 0 for i in range(n)]
    known = [(i, 0) for i in range(n) if i % 5 == 0]
    all_pairs = [(a, b) for a in range(n) for b in range(a) if shingles.similar(sets[a], sets[b])]
    got = shingles._links(list(range(n)), group, sets)
    assert all(shingles.similar(sets[a], sets[b]) for a, b in got) and len(got) < n
    assert together(n, got + known) == together(n, all_pairs + known)


@pytest.mark.parametrize("deal", [400, 1 << 17])
def test_cells_of_large_buckets_in_one_and_in_many_parts(spark, deal):
    texts = edited() + near_copies(60)
    told, sets = shingles.groups(frame(spark, enumerate(texts)), block=20, small=0, deal=deal)
    lead = told.join(sets, "th").groupBy("c").agg({"doc_id": "min"}).collect()
    assert sorted(r[1] for r in lead) == sorted(brute_leaders(texts))


def test_components_in_one_task_are_those_of_rounds(spark):
    r = random.Random(2)
    rows = [(r.randrange(400), r.randrange(400)) for _ in range(220)] + [(1000 + i, 1001 + i) for i in range(60)] + [(5, 5), (None, 7)]
    edges = spark.createDataFrame(rows, "a long, b long")
    want, got = ({tuple(x) for x in connected_components(edges, small=k).collect()} for k in (0, 10_000))
    assert got == want and len(got) > 100
    assert connected_components(edges.where("false"), small=10).count() == 0
