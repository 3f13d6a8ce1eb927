from __future__ import annotations

import random
import re

import numpy as np
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from kgfeat.llm import simhash as sh
from kgfeat.plans.state import Workspace

WS = re.compile(r"[^\x20\x09-\x0D]+")


def brute_fp(text):
    t = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    w = WS.findall(t)
    if not w:
        return 0
    g = [" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or [" ".join(w)]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in g]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(ids, fps, bits=4):
    parent = list(range(len(fps)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= bits:
                parent[find(i)] = find(j)
    least = {}
    for k, i in enumerate(ids):
        least[find(k)] = min(least.get(find(k), i), i)
    return [least[find(k)] for k in range(len(fps))]


@settings(max_examples=60, deadline=None)
@given(st.text(alphabet="aBé ßÉ\n\t x", max_size=60))
def test_fingerprint(text):
    assert sh.fingerprint(text) == brute_fp(text)


def test_fingerprint_of_long_text_in_slices():
    t = " ".join(str(i * i) for i in range(70_000))
    assert sh.fingerprint(t) == brute_fp(t)


def test_every_linked_pair_shares_a_cell():
    rng = random.Random(3)
    for blocks in range(5, 9):
        masks = sh.cell_masks(blocks, 4)
        for _ in range(200):
            x = rng.getrandbits(64)
            y = x
            for b in rng.sample(range(64), 4):
                y ^= 1 << b
            assert any(x & m == y & m for m in masks)


def test_pivot_distances_bound_the_distance():
    rng = random.Random(1)
    fp = np.array([rng.getrandbits(64) for _ in range(300)], np.uint64)
    t = sh.distance_table(fp, sh.spread_references())
    for i, j in [(rng.randrange(300), rng.randrange(300)) for _ in range(500)]:
        assert np.abs(t[i].astype(int) - t[j]).max() <= int(fp[i] ^ fp[j]).bit_count()


def _clusters(rng, n, centre_count, flips):
    out = []
    for _ in range(centre_count):
        c = rng.getrandbits(64)
        for _ in range(n):
            x = c
            for b in rng.sample(range(64), rng.randrange(flips + 1)):
                x ^= 1 << b
            out.append(x)
    return out


def test_links_connect_what_brute_force_connects(spark):
    rng = random.Random(9)
    fps = sorted({*_clusters(rng, 40, 4, 3), *_clusters(rng, 3, 40, 6), *(rng.getrandbits(64) for _ in range(200))})
    want = brute_components(fps, fps)
    for blocks, cell_rows in ((5, 4096), (6, 4096), (8, 4096), (6, 7)):
        ws = Workspace(spark, "t")
        df = spark.createDataFrame([(f - (1 << 64) if f >> 63 else f,) for f in fps], "fp long")
        parent = {f: f for f in fps}

        def find(x, parent=parent):
            while parent[x] != x:
                x = parent[x]
            return x

        for r in sh.links(ws, df, len(fps), blocks=blocks, cell_rows=cell_rows).collect():
            a, b = r["a"] % (1 << 64), r["b"] % (1 << 64)
            assert (a ^ b).bit_count() <= 4
            parent[max(find(a), find(b))] = min(find(a), find(b))
        assert [find(f) for f in fps] == want


def test_near_duplicates_against_brute_force(spark):
    rng = random.Random(2)
    base = [" ".join(rng.choice("abcdefghijkl") * rng.randrange(1, 4) for _ in range(300)) for _ in range(12)]
    rows = [(i, t) for i, t in enumerate(base)]
    for i in range(12, 60):
        w = rng.choice(base).split()
        if i % 2:
            w[rng.randrange(300)] = "changed"
        rows.append((i, " ".join(w)))
    rows += [(100, None), (101, ""), (102, " \t\n"), (103, "one"), (104, "ONE"), (104, "ONE")]
    df = spark.createDataFrame([(i, t, "x", 0) for i, t in rows], "doc_id long, text string, fp string, id int")
    got = sorted((r["id"], r["fp"] % (1 << 64), r["component_id"]) for r in sh.near_duplicates(spark, df).collect())
    fps = [brute_fp(t) for _, t in rows]
    want = sorted(zip([i for i, _ in rows], fps, brute_components([i for i, _ in rows], fps), strict=True))
    assert got == want
    left = sh.one_of_each(spark, df)
    assert left.columns == df.columns
    assert sorted(r["doc_id"] for r in left.collect()) == sorted({c for *_, c in want})
    assert sh.near_duplicates(spark, df.limit(0)).count() == 0


def test_one_of_each_where_ids_repeat(spark):
    rng = random.Random(3)
    a, b, c = (" ".join(rng.choice("abcdefghijkl") * rng.randrange(1, 4) for _ in range(200)) for _ in range(3))
    rows = [(3, a), (5, a), (5, b), (5, b), (5, c), (9, c), (None, b), (None, "alone")]
    df = spark.createDataFrame([(i, t, k) for k, (i, t) in enumerate(rows)], "doc_id long, text string, _row int")
    left = sh.one_of_each(spark, df)
    assert left.columns == df.columns
    # one row of each group of texts: of a under 3, of b and c under 5, and the text that stands alone
    assert sorted((str(r["doc_id"]), r["text"]) for r in left.collect()) == sorted([("3", a), ("5", b), ("5", c), ("None", "alone")])
    assert sh.one_of_each(spark, df.limit(0)).count() == 0
