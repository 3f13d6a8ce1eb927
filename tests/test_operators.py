from __future__ import annotations

import random
from pathlib import Path

import pytest
from fixture_graph import BASE, GOLD, SEEDS, TRIPLES
from pyspark.sql import functions as F

from kgfeat import extensions as ext
from kgfeat.api import mine, mine_sql
from kgfeat.functions import udtf
from kgfeat.operators import blacklist, canon, degree, dictionary, domain, matrix, reach, specific, supports, types
from kgfeat.operators.prefix import prefix_sums
from kgfeat.params import MiningParams
from kgfeat.plans import baselines, metrics, state
from kgfeat.plans.state import Workspace
from kgfeat.sources import io, kgview


@pytest.fixture
def ws(spark):
    return Workspace(spark, "test")


def brute_components(edges):
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        ra, rb = find(a), find(b)
        parent[max(ra, rb)] = min(ra, rb)
    return {x: find(x) for x in parent}


@pytest.mark.parametrize("method", ["star", "minlabel"])
def test_components(spark, method):
    rng = random.Random(4)
    edges = [(rng.randrange(60), rng.randrange(60)) for _ in range(38)]
    edges += [(i, i + 1) for i in range(100, 130)] + [(200, i) for i in range(201, 240)] + [(300, 301), (301, 300), (302, 302)]
    df = spark.createDataFrame([*edges, (None, 1)], "a long, b long")
    got = {r["v"]: r["c"] for r in canon.components(spark, df, method=method).collect()}
    want = brute_components([(a, b) for a, b in edges if a != b])
    assert got == want


def test_contract(spark):
    t = spark.createDataFrame([("a", "p", "x"), ("b", "p", "x"), ("a", "owl:sameAs", "b"), ("a", "q", "b")], "s string, p string, o string")
    c = canon.canonical_map(spark, t.filter("p = 'owl:sameAs'"), "s", "o")
    assert {tuple(r) for r in canon.contract(t, c).collect()} == {("a", "p", "x"), ("a", "q", "a")}
    merged = canon.contract(t, c, pred_canon=spark.createDataFrame([("q", "p")], "v string, c string"))
    assert {r["p"] for r in merged.collect()} == {"p"}
    assert [r["seed"] for r in canon.contract_seeds(spark.createDataFrame([("a",), ("b",)], "seed string"), c).collect()] == ["a"]


def test_prefix_sums_over_hot_and_small_groups(spark, ws):
    rng = random.Random(7)
    rows = [("hot" if rng.random() < 0.5 else f"g{rng.randrange(50)}", i, rng.randrange(9)) for i in range(4000)]
    df = spark.createDataFrame(rows, "g string, i long, x long").repartition(7)
    got = {(r["g"], r["i"]): r["before_x"] for r in prefix_sums(ws, df, "g", ["i"], ["x"]).collect()}
    run = {}
    for g, i, x in sorted(rows):
        assert got[g, i] == run.get(g, 0)
        run[g] = run.get(g, 0) + x
    assert prefix_sums(ws, df.limit(0), None, ["i"], ["x"]).count() == 0


def test_dense_ids_and_collisions(spark, ws):
    df = spark.createDataFrame([(x,) for x in ["b", "a", "é", None, "a"]], "u string")
    assert {tuple(r) for r in dictionary.dense_ids(spark, df).collect()} == {("a", 0), ("b", 1), ("é", 2)}
    with pytest.raises(ValueError):
        dictionary.check_collisions(spark.createDataFrame([(1, "a"), (1, "b")], "v long, uri string"))


def test_blacklist_and_degrees(spark):
    v = spark.createDataFrame([("prov:a",), ("rdf:type",), ("rdf:typed",), (None,)], "uri string")
    assert {r[0] for r in blacklist.match(v, ("prov:*", "rdf:type")).collect()} == {"prov:a", "rdf:type"}
    arc = spark.createDataFrame([(1, 9, 2), (1, 9, 3), (2, 9, 1), (4, 9, 4)], "src long, pred long, dst long")
    assert {tuple(r) for r in degree.degrees(arc).collect()} == {(1, 2), (2, 1), (4, 1)}
    assert {tuple(r) for r in degree.degrees(arc, True).collect()} == {(1, 3), (2, 2), (3, 1), (4, 1)}
    ok = degree.allowed(arc, 1, False, spark.createDataFrame([(4,)], "v long"))
    assert {tuple(r) for r in ok.collect()} == {(2, 9, 1)}
    t = spark.createDataFrame([("a", "p", str(i)) for i in range(5)] + [("b", "p", "0"), ("c", "p", "0")], "s string, p string, o string")
    assert degree.drop_frequent_pairs(t, 4, 9).count() == 2 and degree.drop_frequent_pairs(t, 9, 2).count() == 4


def test_reach_and_fixpoint(spark, ws):
    arc = spark.createDataFrame([(i, 0, i + 1) for i in range(6)] + [(6, 0, 0)], "src long, pred long, dst long")
    seeds = spark.createDataFrame([(0,), (3,)], "seed long")
    got, h = reach.bfs(ws, arc, seeds, 2)
    assert {tuple(r) for r in got.collect()} == {(0, 1, 1), (0, 2, 2), (3, 4, 1), (3, 5, 2)} and h == 2
    full, k = reach.fixpoint(ws, arc, seeds)
    assert full.count() == 12 and k == 4  # from 3 round to 0


def test_class_levels_with_a_cycle(spark, ws):
    inst = spark.createDataFrame([(1, 10), (2, 11)], "v long, class long")
    sub = spark.createDataFrame([(10, 11), (11, 12), (12, 10), (10, 12)], "class long, super long")
    v = spark.createDataFrame([(1,), (2,), (3,)], "v long")
    lev = types.levels(ws, v, inst, sub, None)
    got = {(r["v"], r["class"]): r["level"] for r in lev.collect()}
    assert got == {(1, 10): 1, (1, 11): 2, (1, 12): 2, (2, 11): 1, (2, 12): 2, (2, 10): 3, (1, -1): 0, (2, -1): 0, (3, -1): 0}
    assert {(r["v"], r["class"]) for r in types.levels(ws, v, inst, sub, 2, use_top=False).collect()} == {x for x, n in got.items() if 0 < n <= 2}
    assert {(r["v"], r["class"]) for r in types.levels(ws, v, inst, sub, 1).collect()} == {x for x, n in got.items() if n <= 1}
    assert types.levels(ws, v, inst, sub, 0).count() == 3
    assert {r[0] for r in types.instances_of(ws, inst, sub, spark.createDataFrame([(12,)], "class long")).collect()} == {1, 2}
    anc = {r["e"]: set(r["ancs"]) for r in types.ancestors(ws, v, inst, sub).collect()}
    assert anc[3] == {3, -1} and anc[1] == {1, 10, 11, 12, -1}


def test_specificity_ways_agree(spark):
    rng = random.Random(11)
    up = {e: sorted({e, -1, *(x for x in range(1, e) if rng.random() < 0.3)}) for e in range(1, 9)}
    rows, seen = [], set()
    for i in range(150):
        n = rng.randrange(1, 3)
        e = [rng.choice([-1, *range(1, 9)]) for _ in range(n)]
        key = (i % 3, tuple([0] * n), tuple(e))
        if key in seen:
            continue
        seen.add(key)
        rows.append((i, f"s{i % 3}", [0] * n, e, [up.get(x, [-1]) for x in e]))
    # close the sample under the order: an element is only below what its own ancestors are below
    df = spark.createDataFrame(rows, "fid long, sset string, preds array<bigint>, elems array<bigint>, ancs array<array<bigint>>")
    got = {impl: {r[0] for r in specific.dominated(df, impl).collect()} for impl in ("join", "hierarchy")}
    assert got["join"] == got["hierarchy"]
    want = {b[0] for b in rows for a in rows if a[0] != b[0] and a[1:3] == b[1:3] and all(y in s for y, s in zip(b[3], a[4], strict=True))}
    assert got["join"] == want


def test_support_unions(spark):
    m = spark.createDataFrame([(1, "a"), (1, "b"), (1, "b"), (2, "a"), (3, "c"), (4, "b"), (4, "a")], "fid long, sset string")
    s = spark.createDataFrame([("a", 1), ("a", 2), ("b", 2), ("b", 40_000), ("c", 40_000), ("c", 1), ("c", 2)], "sset string, seed long")
    u = supports.unions(m, s)
    assert {tuple(r) for r in u.filter("fid = 1").collect()} == {(1, 1), (1, 2), (1, 40_000)}
    got = {r["fid"]: (r["sset"], r["n"]) for r in supports.sized(u).collect()}
    assert {k: n for k, (_, n) in got.items()} == {1: 3, 2: 2, 3: 3, 4: 3}
    assert got[1] == got[3] == got[4] != got[2]  # a set's id does not depend on what it was joined from
    dense = spark.createDataFrame([(1, 1), (2, 2), (40_000, 40_000)], "seed long, id long")
    bits = supports.bitmaps(u, dense).groupBy("fid").agg(F.sum(F.bitmap_count("bits")).alias("n"), F.count("*").alias("buckets"))
    assert {r["fid"]: (r["n"], r["buckets"]) for r in bits.collect()} == {1: (3, 2), 2: (2, 1), 3: (3, 2), 4: (3, 2)}


def test_neighbour_of_a_million_seeds(spark, ws):
    """Support sets are rows: no value of a run grows with the number of seeds."""
    n = 1_000_000
    seeds = spark.range(n).select(F.concat(F.lit("s"), "id").alias("seed"))
    t = seeds.select(F.col("seed").alias("s"), F.lit("p").alias("p"), F.lit("hub").alias("o"))
    t = t.union(spark.createDataFrame([("hub", "q", "x"), ("hub", "rdf:type", "T"), ("x", "rdf:type", "T")], "s string, p string, o string"))
    r = mine(spark, t, seeds, k=2, t=1, ws=ws)
    assert {(x["feature"], x["n"]) for x in r.features().collect()} == {("hub", n), ("x", n), ("-[p]-> hub", n)}
    assert r.matrix().count() == 3 * n
    for df in (r.mined.sets, r.mined.unions, r.mined.features.drop("preds", "elems", "classes")):
        assert not any(f.dataType.typeName() in ("array", "binary", "map") for f in df.schema.fields)


def test_domain_filter(spark):
    atoms = {"p": domain.Atom(individuals=("path:*",)), "m": domain.Atom(classes=("mesh:*",))}
    e = spark.createDataFrame([(1, "path:1", False), (2, "mesh:2", True), (2, "x", False), (3, "mesh:3", False)], "fid long, uri string, is_class boolean")
    f = spark.createDataFrame([(1,), (2,), (3,)], "fid long")
    left = lambda m: {r[0] for r in domain.apply(e, f, domain.DomainFilter.parse(m, atoms)).collect()}
    assert (left("p"), left("m"), left("pm"), left("none")) == ({1}, {2}, {1, 2}, {1, 2, 3})
    for bad in ("z", "pz", "", 3):
        with pytest.raises(ValueError):
            domain.DomainFilter.parse(bad, atoms)


def test_m_is_the_fourth_step_of_a_run(spark):
    t = spark.createDataFrame(TRIPLES, "s string, p string, o string")
    s = spark.createDataFrame([(x,) for x in SEEDS], "seed string")
    atoms = {"v": domain.Atom(individuals=("v1",)), "t": domain.Atom(classes=("T5",)), "i": domain.Atom(instances_of=("T3",))}
    all_ = mine(spark, t, s, **BASE)
    for m in ("vt", "i", "none"):
        r = mine(spark, t, s, **BASE, m=m, atoms=atoms)
        assert {x["feature"] for x in r.features().collect()} == {x["feature"] for x in all_.filtered(domain.DomainFilter.parse(m, atoms)).collect()}
        want = {"vt": {"v1", "-[p4]-> v1", "-[p6]-> T5"}, "i": set()}.get(m)
        got = {x["feature"] for x in r.named_matrix().collect()}
        assert got == (want if want is not None else GOLD | {"v1", "v6"})
    for bad in ("garbage", "pg", ""):
        with pytest.raises(ValueError):
            mine(spark, t, s, **BASE, m=bad, atoms=atoms)


def test_individuals_of_a_class(spark):
    t = spark.createDataFrame([("a", "p", "x"), ("b", "p", "x"), ("a", "p", "y"), ("b", "p", "y"), ("x", "rdf:type", "Low"), ("Low", "rdfs:subClassOf", "High")], "s string, p string, o string")
    s = spark.createDataFrame([("a",), ("b",)], "seed string")
    r = mine(spark, t, s, k=1, t=0, l_min=2, m="h", atoms={"h": domain.Atom(instances_of=("High",))})
    assert {x["feature"] for x in r.features().collect()} == {"x", "-[p]-> x"}
    assert r.unfiltered is not None and r.unfiltered.features().count() == 4


def test_golden_counts_of_generalisations(spark):
    """The worked example's paths: 11 patterns for two vertices, 23 for three."""
    t = spark.createDataFrame(TRIPLES, "s string, p string, o string")
    s = spark.createDataFrame([(x,) for x in SEEDS], "seed string")
    got = {x["path"]: (x["len"], x["n"]) for x in ext.generalisation_counts(spark, t, s, MiningParams(**BASE)).collect()}
    assert got["-[p1]-> v2 -[p2]-> v3"] == (2, 11) and got["-[p1]-> v2 -[p2]-> v3 -[p3]-> v6"] == (3, 23)
    assert got["-[p4]-> v1"] == (1, 1) and len(got) == 9


def test_counts_of_longer_features(spark):
    t = spark.createDataFrame([("s", "p", f"a{i}") for i in range(3)] + [(f"a{i}", "q", "z") for i in range(3)] + [("r", "p", "b"), ("b", "q", "z"), ("b", "rdf:type", "T")] + [(f"a{i}", "rdf:type", "T") for i in range(3)], "s string, p string, o string")
    s = spark.createDataFrame([("s",), ("r",)], "seed string")
    got = {(x["seed"], x["feature"]): x["n"] for x in ext.counted_features(mine(spark, t, s, k=2, t=1, l_min=2)).collect()}
    assert got[("s", "-[p]-> T -[q]-> z")] == 3 and got[("r", "-[p]-> T -[q]-> z")] == 1


def test_dense_ids_give_the_same_features(spark):
    t = spark.createDataFrame(TRIPLES, "s string, p string, o string")
    s = spark.createDataFrame([(x,) for x in [*SEEDS, "nobody"]], "seed string")
    r = mine(spark, t, s, **BASE, ids="dense")
    assert {x["feature"] for x in r.path_features().collect()} == GOLD
    assert r.context.coding.vertex.agg(F.min("v"), F.max("v") + 1, F.count("*")).first()[:] == (0, *[r.context.coding.vertex.count()] * 2)


def test_hot_roots_of_components(spark, ws, monkeypatch):
    monkeypatch.setattr(canon, "SMALL", 0)
    monkeypatch.setattr(canon, "SPREAD", 4)
    edges = [(0, i) for i in range(1, 200)] + [(500, 501), (501, 502)]
    got = {r["v"]: r["c"] for r in canon.components(spark, spark.createDataFrame(edges, "a long, b long"), ws=ws).collect()}
    assert got == brute_components(edges)


def test_state_needs_a_shared_folder():
    unset = type("Conf", (), {"get": lambda self, key, other=None: other})()

    def session(master):
        return type("S", (), {"conf": unset, "sparkContext": type("C", (), {"master": master, "getConf": lambda self: unset})()})()

    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        state.shared_root(session("spark://far:7077"))
    assert state.shared_root(session("local[2]")).startswith("file://")


def test_a_result_can_be_deleted(spark):
    t = spark.createDataFrame(TRIPLES, "s string, p string, o string")
    with mine(spark, t, spark.createDataFrame([(x,) for x in SEEDS], "seed string"), **BASE) as r:
        folder = Path(r.context.ws.base.removeprefix("file://"))
        assert folder.exists() and r.features().count() == 6
    assert not folder.exists()


def test_sql_and_cost(spark):
    spark.createDataFrame(TRIPLES, "s string, p string, o string").createOrReplaceTempView("graph_rows")
    with metrics.Cost(spark) as cost:
        mine_sql(spark, "SELECT s, p, o FROM graph_rows", "SELECT explode(array('n1', 'n2')) AS x", "worked", **BASE)
    assert {r["feature"] for r in spark.sql("SELECT feature FROM worked_features WHERE kind <> 'neighbour'").collect()} == GOLD
    assert cost.values["stages"] > 5 and cost.values["seconds"] > 0 and cost.values["shuffle_write_mb"] >= 0


def test_exhaustive_mode_refuses(spark):
    t = spark.createDataFrame(TRIPLES, "s string, p string, o string")
    s = spark.createDataFrame([(x,) for x in SEEDS], "seed string")
    with pytest.raises(ValueError, match="path features"):
        baselines.run(spark, "exhaustive", t, s, MiningParams(**BASE), max_rows=3)
    every = {x["feature"] for x in baselines.run(spark, "exhaustive", t, s, MiningParams(**BASE)).path_features().collect()}
    assert every > GOLD


def test_sinks(spark, tmp_path):
    t = spark.createDataFrame(TRIPLES, "s string, p string, o string")
    r = mine(spark, t, spark.createDataFrame([(x,) for x in SEEDS], "seed string"), **BASE)
    io.write(r, f"{tmp_path}/out")
    assert spark.read.parquet(f"{tmp_path}/out/features").count() == 6 and spark.read.parquet(f"{tmp_path}/out/matrix").count() == 12
    io.write_sparse_text(r, f"{tmp_path}/text")
    lines = [x["value"] for x in spark.read.text(f"{tmp_path}/text").collect()]
    assert sorted(x.split()[0] for x in lines) == SEEDS and all(len(x.split()) == 7 for x in lines)


def test_quotes_by_pieces(spark, tmp_path):
    item = "the quick brown fox jumps over the lazy dog and runs away"
    docs = [(1, f"xx{item}yy"), (2, f"a {item} b {item}"), (3, item.replace("lazy", "mad")), (4, None), (5, "say short"), (6, item)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item), (2, "short"), (3, None), (4, "brown\nfox")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {(r["s"], r["o"]) for r in kgview.quotes(spark, str(tmp_path)).collect()}
    assert got == {("doc:1", "bench:1"), ("doc:2", "bench:1"), ("doc:6", "bench:1"), ("doc:5", "bench:2")}


def test_matrix_forms(spark):
    f = spark.createDataFrame([(7, "a"), (8, "b")], "fid long, sset string")
    s = spark.createDataFrame([("a", 1), ("a", 2), ("b", 2)], "sset string, seed long")
    cells = matrix.build(f, s)
    assert {tuple(r) for r in cells.collect()} == {(1, 7), (2, 7), (2, 8)}
    assert {(r["seed"], r["7"], r["8"]) for r in matrix.wide(cells, [7, 8]).collect()} == {(1, True, False), (2, True, True)}
    assert {r["seed"]: r["features"] for r in matrix.csr(cells).collect()} == {1: [7], 2: [7, 8]}
    with pytest.raises(ValueError):
        matrix.wide(cells, list(range(5)), max_cols=3)


@pytest.mark.parametrize("bad", [{"k": 0}, {"t": -1}, {"d": -1}, {"l_min": 3, "l_max": 2}, {"engine": "x"}, {"specificity": "x"}, {"kinds": frozenset(("x",))}, {"m": "pg"}, {"ids": "x"}, {"predicate_levels": -1}])
def test_parameters_are_checked(bad):
    with pytest.raises(ValueError):
        MiningParams(**bad)


def test_ntriples(spark, tmp_path):
    (tmp_path / "g.nt").write_text('<a> <p> <b> .\n# comment\n\n_:x <q> "li\\"t"@en .\n<a> <p> "3"^^<int> . # end\nbroken line\n')
    rows = io.read_ntriples(spark, str(tmp_path / "g.nt"), keep_bad=True)
    assert [r["bad"] for r in rows.filter("bad is not null").collect()] == ["broken line"]
    t = io.drop_literals(io.read_ntriples(spark, str(tmp_path / "g.nt")))
    assert [tuple(r) for r in t.collect()] == [("a", "p", "b")]
    t.write.csv(f"{tmp_path}/csv")
    assert io.read_triples(spark, f"{tmp_path}/csv", "csv").count() == 1


def test_extensions(spark, ws):
    t = spark.createDataFrame([("a", "next", "b"), ("b", "next", "c"), ("c", "next", "a"), ("a", "p", "z"), ("p", "rdfs:subPropertyOf", "q")], "s string, p string, o string")
    closed = ext.transitive(ws, t, "next").filter("p = 'next'")
    assert closed.count() == 9
    assert ("a", "q", "z") in {tuple(r) for r in ext.generalise_predicates(ws, t, 1).collect()}
    lit = spark.createDataFrame([("a", "w", "1.0"), ("b", "w", "1"), ("c", "w", "x"), ("d", "w", "2.5")], "s string, p string, value string")
    assert {r["o"] for r in ext.literal_vertices(lit, 1.0).collect()} == {"num:w/1", "num:w/2"}


def test_classifier(spark, ws):
    cells = spark.createDataFrame([(s, 7) for s in range(40) if s % 2] + [(s, 8) for s in range(40)] + [(s, 100 + s) for s in range(40)], "seed long, fid long")
    lab = spark.createDataFrame([(s, s % 2, s > 30) for s in range(41)], "seed long, label int, held_out boolean")
    model, data = ext.classifier(ws, cells, lab)
    assert model.numFeatures == 42  # all columns of the matrix
    out = model.transform(data)
    assert out.count() == 41 and out.filter("held_out and prediction = label").count() >= 9


def test_udtf(spark):
    udtf.register(spark)
    rows = spark.sql("SELECT * FROM explain_feature('-[p]-> a b -[q]-> TOP')").collect()
    assert [tuple(r) for r in rows] == [(1, "p", "a b"), (2, "q", "TOP")]


def test_saved_tables_survive_and_can_be_bucketed(spark, ws):
    df = spark.range(10).withColumnRenamed("id", "src")
    t = ws.save_bucketed(df, "arc", 4, "src")
    assert t.count() == 10
    s = ws.save(df, "x")
    assert "parquet" in s._jdf.queryExecution().executedPlan().toString().lower()
    ws.drop(s)
    assert F is not None


def test_nearest_equals_pairs(spark):
    """The least distance from another seed, on a random graph with cycles, seeds among the vertices and hubs."""
    rng = random.Random(5)
    arcs = [(rng.randrange(14), 1, rng.randrange(14)) for _ in range(28)]
    ws = Workspace(spark, "nearest")
    arc, seeds = spark.createDataFrame(arcs, "src long, pred long, dst long"), spark.createDataFrame([(0,), (7,), (8,)], "seed long")
    pairs, _ = reach.bfs(ws, arc, seeds, None)
    want = {(r.v, r.dist) for r in pairs.groupBy("v").agg(F.min("dist").alias("dist")).collect()}
    assert {(r.v, r.dist) for r in reach.nearest(ws, arc, seeds).collect()} == want
    pairs_d, _ = reach.bfs(ws, degree.allowed(arc.distinct(), 2, False, None), seeds, None)
    want = {(r.v, r.dist) for r in pairs_d.groupBy("v").agg(F.min("dist").alias("dist")).collect()}
    assert {(r.v, r.dist) for r in reach.nearest(ws, arc, seeds, degree.hubs(arc.distinct(), 2)).collect()} == want
    part, seen = reach.nearby_arcs(ws, arc.union(arc), seeds, 2)
    assert {tuple(r) for r in part.collect()} == {a for a in arcs if a[0] in {0, 7, 8} | {r.v for r in pairs.filter("dist = 1").collect()}}
    assert {r.v for r in seen.collect()} == {0, 7, 8} | {r.v for r in pairs.filter("dist <= 2").collect()}


def test_sieve_reads_rows_without_shuffling_them(spark, monkeypatch):
    """Exact with bitmaps, and no exchange of rows comes before the bitmap has discarded most of them."""
    from kgfeat.operators import sieve

    monkeypatch.setattr(sieve, "FEW", 10)
    keys = spark.range(0, 9000, 9).select((F.col("id") * 7919 - 30_000_000).alias("k"))
    rows = spark.range(9000).select((F.col("id") * 7919 - 30_000_000).alias("k"), "id")
    got = sieve.semi(rows, "k", keys, 1000)
    assert {r.id for r in got.collect()} == set(range(0, 9000, 9))
    assert sieve.sift(rows, "k", keys, 1000).count() < 1800


def test_near_part_gives_the_same_features(spark):
    """Mining on the part of the graph around the seeds; the arcs stored are no longer all of the graph."""
    from kgfeat.plans.context import prepare, search
    from kgfeat.queries import mining as q
    from kgfeat.sources import kgview

    d = "/root/testdata/sf0.001"
    t, s = kgview.triples(spark, d, "customer", False), kgview.seeds(spark, d, "customer")
    whole, part = search(prepare(spark, t, s, q.CUST)), search(prepare(spark, t, s, q.CUST, around=q.CUST.k))
    rows = lambda x: {tuple(r) for r in x.collect()}
    assert rows(whole.reach) == rows(part.reach)
    assert rows(whole.inst_levels) == rows(part.inst_levels)
    assert part.arc.count() < whole.arc.count()


def test_patterns_of_the_same_sets_share_a_union(spark):
    """Unions of support sets are stored once for all patterns that join the same sets, not once a pattern."""
    t = [(f"s{i}", "p", f"a{i % 3}") for i in range(9)] + [(f"a{j}", "q", f"b{j}") for j in range(3)]
    t += [(x, "rdf:type", "C") for j in range(3) for x in (f"a{j}", f"b{j}")] + [("C", "rdfs:subClassOf", "D")]
    seeds = spark.createDataFrame([(f"s{i}",) for i in range(9)], "seed string")
    r = mine(spark, spark.createDataFrame(t, "s string, p string, o string"), seeds, k=2, t=2, l_min=2, specificity="off", c2=False, c3=False)
    joined = r.mined.features.filter("joined")
    assert joined.count() == 12 and joined.filter("n = 9").count() == 12  # 3 classes for a, 9 pairs of classes for a and b
    assert r.mined.unions.count() == 9
    assert r.matrix().join(joined, "fid", "left_semi").distinct().count() == 12 * 9


@pytest.mark.parametrize(("sent", "many"), [(1 << 20, 1000), (400, 1000), (1 << 20, 8)])
def test_support_counts_equal_pairs(spark, ws, monkeypatch, sent, many):
    """Numbers of seeds without the pairs of the last round, in one or several parts, with vertices of many sources."""
    monkeypatch.setattr(reach, "SENT", sent)
    monkeypatch.setattr(reach, "MANY", many)
    monkeypatch.setattr(reach, "PIECE", 3)
    rng = random.Random(6)
    arc = [(rng.randrange(60), 1, rng.randrange(60)) for _ in range(90)] + [(i, 1, 61) for i in range(12)]
    arc = degree.both_ways(spark.createDataFrame(arc, "src long, pred long, dst long")).distinct().persist()
    seeds = spark.createDataFrame([(x,) for x in range(0, 60, 3)], "seed long")
    rows = lambda x: sorted(tuple(r) for r in x.select("v", "n").collect())
    for k in (1, 2):
        assert rows(reach.support_counts(ws, arc, seeds, k)) == rows(supports.counts(reach.bfs(ws, arc, seeds, k)[0]))


def test_no_links_of_the_last_iteration(spark, ws):
    """Nothing grows after the last iteration, so its pairs of path and pattern, the largest table, are not stored."""
    seeds = spark.createDataFrame([(s,) for s in SEEDS], "seed string")
    mine(spark, spark.createDataFrame(TRIPLES, "s string, p string, o string"), seeds, ws=ws, **(BASE | {"k": 2, "engine": "faithful"}))
    names = {x.name[4:] for x in Path(ws.base.removeprefix("file://")).iterdir()}
    assert "links-1" in names and "generated-2" in names and "links-2" not in names
