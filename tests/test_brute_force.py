from __future__ import annotations

import random

import numpy as np
import pytest
from brute import brute_mine, count_generalisations
from fixture_graph import GOLD, SEEDS, TRIPLES
from pyspark.sql import functions as F

from kgfeat.api import mine
from kgfeat.functions.render import generalisations


def random_graph(seed):
    """Cycles, parallel arcs, a hierarchy with several parents (and a cycle in some), vertices without class."""
    rng = random.Random(seed)
    v = [f"v{i}" for i in range(14)]
    s = [f"s{i}" for i in range(5)]
    c = [f"C{i}" for i in range(7)]
    t = [(rng.choice(s), rng.choice(["p", "q"]), rng.choice(v)) for _ in range(16)]
    t += [(rng.choice(v), rng.choice(["p", "q", "r"]), rng.choice(v)) for _ in range(26)]
    t += [(x, "rdf:type", rng.choice(c)) for x in v for _ in range(rng.randrange(3))]
    t += [(c[i], "rdfs:subClassOf", c[j]) for i in range(7) for j in range(i + 1, 7) if rng.random() < 0.25]
    if seed % 3 == 0:
        t += [("v0", "p", "v0"), ("s0", "q", "s1"), ("s1", "p", "s0")]
    return t, s


def test_brute_force_gives_the_gold():
    near, tsup, found, generated = brute_mine(TRIPLES, SEEDS, 3, 2, 4, 2, 3)
    assert set(found) == GOLD and generated == [11, 10, 6]
    assert {c for c, s in tsup.items() if len(s) >= 2} == {"T1", "T3", "T5", "T6", "TOP"}


@pytest.mark.parametrize(("seed", "changes"), [(0, {}), (1, {"t": 1, "d": 4}), (2, {"u": True, "k": 2}), (3, {"t": 3, "l_max": 3}), (4, {"t": 0})])
def test_engines_against_brute_force(spark, seed, changes):
    t, s = random_graph(seed)
    p = {"k": 3, "t": 2, "d": 6, "l_min": 2, "l_max": None, "u": False} | changes
    near, tsup, want, generated = brute_mine(t, s, **p)
    df = spark.createDataFrame(t, "s string, p string, o string")
    sd = spark.createDataFrame([(x,) for x in s], "seed string")
    for engine, specificity in (("factorised", "join"), ("faithful", "trie")):
        r = mine(spark, df, sd, engine=engine, specificity=specificity, **p)
        got = {(x["feature"], x["n"]) for x in r.path_features().collect()}
        assert got == {(f, len(ss)) for f, ss in want.items()}, (engine, seed)
        if engine == "faithful":
            assert r.mined.generated == generated
    v = r.context.vertex()
    sup = {x["uri"]: x["n"] for x in r.context.reach.groupBy("v").agg(F.count("*").alias("n")).join(v, "v").collect()}
    assert sup == {x: len(ss) for x, ss in near.items()}
    cls = {x["uri"]: x["n"] for x in r.context.type_support.join(v, r.context.type_support["class"] == v["v"]).collect()}
    assert cls == {c: len(ss) for c, ss in tsup.items()}
    cells = {(x["seed"], x["feature"]) for x in r.named_matrix().collect()}
    near_ok = {(s, x) for x, ss in near.items() if len(ss) >= p["l_min"] and (p["l_max"] is None or len(ss) <= p["l_max"]) for s in ss}
    assert cells == near_ok | {(s, f) for f, ss in want.items() for s in ss}


def test_counts_of_generalisations(spark):
    """The worked example's two paths: 11 and 23."""
    rows = spark.createDataFrame([([2, 3],), ([2, 3, 1],)], "g array<int>").select(generalisations(F.col("g")).alias("n")).collect()
    assert [r["n"] for r in rows] == [11, 23] == [count_generalisations([2, 3]), count_generalisations([2, 3, 1])]


@pytest.mark.parametrize(("seed", "changes"), [(3, {"t": 1}), (6, {"k": 2, "u": True}), (7, {"drop_single": False, "c2": False, "l_max": 4})])
def test_last_iteration_without_rows_of_paths(spark, monkeypatch, seed, changes):
    """The last iteration of the factorised engine lists neither captured paths nor unions, with large sets in
    pieces, heavy elements dealt out and one group at a time; features, sets and cells are the faithful engine's."""
    from pathlib import Path

    from kgfeat.plans import last

    for name, value in (("PIECE", 2), ("HEAVY", 8), ("AT_ONCE", 1)):
        monkeypatch.setattr(last, name, value)
    t, s = random_graph(seed)
    df, sd = spark.createDataFrame(t, "s string, p string, o string"), spark.createDataFrame([(x,) for x in s], "seed string")
    p = {"k": 3, "t": 2, "d": 6, "l_min": 2} | changes
    got, cells, counts, sets = {}, {}, {}, {}
    for engine in ("factorised", "faithful"):
        r = mine(spark, df, sd, engine=engine, **p)
        got[engine] = sorted(tuple(x) for x in r.path_features().select("kind", "len", "n", "feature").collect())
        cells[engine] = sorted(tuple(x) for x in r.named_matrix().collect())
        counts[engine] = sorted(tuple(x) for x in r.counted().collect())
        sets[engine] = sorted(tuple(x) for x in r.mined.features.select("fid", "sset").collect())
        names = {x.name[4:] for x in Path(r.context.ws.base.removeprefix("file://")).iterdir()}
        assert (f"found-{p['k']}" in names) == (f"generated-{p['k']}" not in names) == (engine == "factorised")
        last_made = r.mined.generated
        r.close()
    assert got["faithful"] and len(last_made) == p["k"]
    for x in (got, cells, counts, sets):
        assert x["factorised"] == x["faithful"]


@pytest.mark.parametrize(("seed", "changes"), [(3, {"t": 1}), (7, {"k": 2, "l_max": 4, "prune": False})])
def test_last_iteration_of_the_faithful_engine_at_size(spark, monkeypatch, seed, changes):
    """Of many rows to grow from, the faithful engine does not list the last iteration's pairs of path and feature;
    it generates as many path features as if it did, and features, cells and counts are the same."""
    from pathlib import Path

    from kgfeat.plans import last

    t, s = random_graph(seed)
    df, sd = spark.createDataFrame(t, "s string, p string, o string"), spark.createDataFrame([(x,) for x in s], "seed string")
    p = {"k": 3, "t": 2, "d": 6, "l_min": 2} | changes
    got = []
    for listed in (1 << 60, 0):
        monkeypatch.setattr(last, "LISTED", listed)
        r = mine(spark, df, sd, engine="faithful", **p)
        names = {x.name[4:] for x in Path(r.context.ws.base.removeprefix("file://")).iterdir()}
        assert (f"generated-{p['k']}" in names) == bool(listed)
        rows = (r.path_features().select("kind", "len", "n", "feature"), r.named_matrix(), r.counted(), r.mined.features.select("fid", "sset"))
        got.append((r.mined.generated, *(sorted(tuple(x) for x in y.collect()) for y in rows)))
        r.close()
    assert len(got[0][0]) == p["k"] and got[0][1]
    assert got[0] == got[1]


def test_hashes_of_seeds_are_those_of_set_ids(spark):
    from kgfeat.plans import last

    seeds = [0, 1, -1, 5, 2**62, -(2**63), 2**63 - 1]
    rows = spark.createDataFrame([(x,) for x in seeds], "seed long").select(F.xxhash64("seed").alias("x"), F.xxhash64("seed", F.lit(1)).alias("y")).collect()
    x, y = last._hashes(np.array(seeds))
    assert [tuple(r) for r in rows] == list(zip(x.tolist(), y.tolist(), strict=True))
