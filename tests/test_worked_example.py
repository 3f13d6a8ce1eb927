from __future__ import annotations

import pytest
from fixture_graph import BASE, GOLD, SEEDS, TRIPLES
from pyspark.sql import functions as F

from kgfeat.api import mine


def run(spark, triples=TRIPLES, seeds=SEEDS, **changes):
    t = spark.createDataFrame(triples, "s string, p string, o string")
    s = spark.createDataFrame([(x,) for x in seeds], "seed string")
    return mine(spark, t, s, **(BASE | changes))


def found(r):
    return {x["feature"] for x in r.path_features().collect()}


@pytest.mark.parametrize(("engine", "specificity"), [("factorised", "join"), ("faithful", "trie"), ("factorised", "hierarchy")])
def test_gold_features(spark, engine, specificity):
    r = run(spark, engine=engine, specificity=specificity)
    assert found(r) == GOLD
    if engine == "faithful":
        assert r.mined.generated == [11, 10, 6]
    assert r.matrix().count() == 2 * (2 + 4)


def test_neighbours_and_classes(spark):
    r = run(spark)
    v = r.context.vertex()
    sup = {x["uri"]: x["n"] for x in r.context.reach.groupBy("v").count().withColumnRenamed("count", "n").join(v, "v").collect()}
    assert sup == {"v1": 2, "v6": 2, "v2": 1, "v3": 1, "v8": 1, "v4": 1, "v5": 1, "v9": 1}
    assert {x["feature"] for x in r.neighbour_features().collect()} == {"v1", "v6"}
    cls = {x["uri"] for x in r.context.usable_types.join(v, r.context.usable_types["class"] == v["v"]).collect()}
    assert cls == {"T1", "T3", "T5", "T6", "TOP"}
    lev = r.context.inst_levels.join(v, "v").filter("uri = 'v3'").drop("uri")
    names = {(x["uri"], x["level"]) for x in lev.join(v.select(F.col("v").alias("class"), "uri"), "class").collect()}
    assert names == {("T2", 1), ("T3", 2), ("TOP", 0)}


CASES = [
    (dict(k=1), {"-[p4]-> v1", "-[p1]-> T1", "-[p6]-> T5", "-[p6]-> T6"}),
    (dict(k=2), {"-[p4]-> v1", "-[p1]-> T1", "-[p6]-> T5", "-[p6]-> T6"}),
    (dict(t=0), {"-[p4]-> v1", "-[p6]-> TOP", "-[p1]-> TOP -[p2]-> TOP -[p3]-> v6"}),
    (dict(t=1), {"-[p4]-> v1", "-[p6]-> T5", "-[p6]-> T6", "-[p1]-> T1 -[p2]-> TOP -[p3]-> v6"}),
    (dict(l_min=3), set()),
]


@pytest.mark.parametrize(("engine", "changes", "want"), [*(("factorised", *c) for c in CASES), ("faithful", *CASES[1]), ("faithful", *CASES[3])])
def test_variations(spark, engine, changes, want):
    assert found(run(spark, engine=engine, **changes)) == want


def test_blacklisted_class_is_not_reached(spark):
    r = run(spark, b_exp_types=("T3",))
    v = r.context.vertex()
    assert {x["uri"] for x in r.context.reach.select("v").distinct().join(v, "v").collect()} == {"v1", "v2", "v4", "v8", "v9"}


def test_both_directions(spark):
    r = run(spark, u=True)
    v = r.context.vertex()
    sup = {x["uri"]: x["n"] for x in r.context.reach.groupBy("v").agg(F.count("*").alias("n")).join(v, "v").collect()}
    assert sup["v7"] == 1


def test_same_as(spark):
    split = [(a, b, c) for a, b, c in TRIPLES if c != "v6"] + [("v3", "p3", "v6a"), ("v5", "p3", "v6b")]
    joined = run(spark, [*split, ("v6a", "owl:sameAs", "v6b")])
    assert found(joined) == {f.replace("v6", "v6a") for f in GOLD}
    apart = run(spark, [*split, ("v6a", "owl:sameAs", "v6b")], canonicalise=False, b_predicates=("rdf:type", "rdfs:subClassOf", "owl:sameAs"))
    assert "-[p1]-> T1" in found(apart) and {x["feature"] for x in apart.neighbour_features().collect()} == {"v1"}


def test_lossy_pruning_is_the_procedures(spark):
    t = [("n1", "p", "a"), ("n2", "p", "b"), ("n2", "p", "c"), ("a", "q", "x"), ("c", "q", "y"), ("a", "rdf:type", "T1"), ("b", "rdf:type", "T1"), ("x", "rdf:type", "T3"), ("y", "rdf:type", "T3")]
    for engine in ("factorised", "faithful"):
        assert found(run(spark, t, k=2, t=1, l_max=None, engine=engine)) == {"-[p]-> T1"}
    full = run(spark, t, k=2, t=1, l_max=None, specificity="off", c2=False, c3=False)
    assert "-[p]-> TOP -[q]-> T3" in found(full)


def test_no_seeds_and_isolated_seed(spark):
    assert found(run(spark, seeds=["nobody"])) == set()
    assert found(run(spark, seeds=[])) == set()
