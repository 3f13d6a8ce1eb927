from __future__ import annotations

import random

import corpus_pipeline as cp
from kgfeat.llm import neardup as nd
from kgfeat.llm import simhash as sh


def brute_set(text):
    w = (text or "").lower().split()
    return {" ".join(w[i : i + 5]) for i in range(len(w) - 4)} or ({" ".join(w)} if w else set())


def brute_left(rows):
    sets = [brute_set(t) for _, t in rows]
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            a, b = sets[i], sets[j]
            if a == b or len(a & b) >= 0.8 * len(a | b):
                parent[find(i)] = find(j)
    least = {}
    for k, (i, _) in enumerate(rows):
        least[find(k)] = min(least.get(find(k), i), i)
    return sorted(least.values())


def _rows(seed=5):
    rng = random.Random(seed)
    rows = []
    for base in range(40):
        w = [f"w{rng.randrange(5000)}" for _ in range(rng.randrange(20, 200))]
        for copy in range(rng.randrange(1, 6)):
            c = list(w)
            for _ in range(rng.randrange(0, 1 + len(w) // 30)):
                c[rng.randrange(len(c))] = f"edit{rng.randrange(10**6)}"
            rows.append((100 * base + copy, " ".join(c)))
    return [*rows, (9000, None), (9001, ""), (9002, "a b"), (9003, "A  b"), (9004, "a b c")]


def test_stage_against_brute_force(spark):
    rows = _rows()
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = brute_left(rows)
    for out in (cp.near_duplicates(spark, docs, ""), nd.one_of_each(spark, docs, cell_rows=2)):
        assert out.columns == docs.columns
        assert sorted(r["doc_id"] for r in out.collect()) == want
    four_bits = [r["doc_id"] for r in sh.one_of_each(spark, docs).collect()]
    assert len(four_bits) > len(want)


def test_forest_links_chains_and_nothing_else():
    rng = random.Random(1)
    sets = [nd.shingle_set(t) for _, t in _rows(8) if t]
    rng.shuffle(sets)
    got = nd.forest(sets)
    assert all(nd.jaccard(sets[x], sets[y]) >= 0.8 for x, y in got)
    group = list(range(len(sets)))
    for x, y in got:
        group = [group[x] if g == group[y] else g for g in group]
    for i in range(len(sets)):
        for j in range(i):
            if nd.jaccard(sets[i], sets[j]) >= 0.8:
                assert group[i] == group[j]


def test_repeated_ids_and_empty_table(spark):
    text = " ".join(f"x{i}" for i in range(50))
    docs = spark.createDataFrame([(1, text), (1, "another text with enough words in it"), (2, text + " end"), (3, text), (3, text), (None, text)], "doc_id long, text string")
    assert sorted(map(tuple, nd.one_of_each(spark, docs).collect())) == [(1, "another text with enough words in it"), (1, text)]
    assert nd.one_of_each(spark, docs.limit(0)).count() == 0
