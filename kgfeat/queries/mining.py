"""Driver queries of the mining methods: workloads on the given tables, each with its DuckDB twin."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat import extensions
from kgfeat.api import MiningResult, mine
from kgfeat.operators import canon, degree, dictionary, domain, reach, supports
from kgfeat.params import TYPE, MiningParams
from kgfeat.plans import baselines, metrics
from kgfeat.plans.context import Context, prepare, search
from kgfeat.plans.state import Workspace
from kgfeat.queries import oracle
from kgfeat.sources import kgview

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

PART = MiningParams(k=3, t=3, d=500, l_min=5)
CUST = MiningParams(k=2, t=2, d=500, l_min=5)
DOC = MiningParams(k=1, t=1, d=500, l_min=5)
PAGE = MiningParams(k=2, t=2, d=500, l_min=5)
CONV = MiningParams(k=4, t=2, d=500, l_min=1)

#: kinds of the star's things, in place of the paper's biomedical ones
ATOMS = {
    "p": domain.Atom(instances_of=("cls:Supplier",)),
    "g": domain.Atom(instances_of=("cls:Nation",), classes=("cls:Region", "cls:Place")),
    "m": domain.Atom(classes=("cls:NationOf/*",)),
}


def _result(spark: SparkSession, sf_dir: str, view: str, seed: str, p: MiningParams) -> MiningResult:
    return mine(spark, kgview.triples(spark, sf_dir, view, False), kgview.seeds(spark, sf_dir, seed), p)


def _context(spark: SparkSession, sf_dir: str, view: str, seed: str, p: MiningParams, found: bool = True) -> Context:
    ctx = prepare(spark, kgview.triples(spark, sf_dir, view, False), kgview.seeds(spark, sf_dir, seed), p)
    return search(ctx) if found else ctx


def add(name: str, run: Query, sql: str | None) -> None:
    QUERIES[name] = run
    if sql is not None:
        ORACLES[name] = sql


def _features(view: str, seed: str, p: MiningParams) -> Query:
    return lambda spark, d: _result(spark, d, view, seed, p).features().select("feature", "kind", "len", F.col("n").alias("support"))


def _neighbours(view: str, seed: str, p: MiningParams) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        if p.d is None:  # without a limit on degrees the pairs of the last round can be many times the arcs
            ctx = prepare(spark, kgview.triples(spark, d, view, False), kgview.seeds(spark, d, seed), replace(p, t=0), around=p.k)
            near = reach.support_counts(ctx.ws, ctx.arc, ctx.seeds, p.k)
        else:
            ctx = _context(spark, d, view, seed, replace(p, t=0))
            near = supports.counts(ctx.reach)
        near = near.filter(supports.within(F.col("n"), p.l_min, p.l_max))
        return near.join(ctx.vertex(), "v").select(F.col("uri").alias("vertex"), F.col("n").alias("support"))

    return run


def _types(view: str, seed: str, p: MiningParams) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        ctx = _context(spark, d, view, seed, p)
        got = ctx.type_support.join(ctx.usable_types, "class", "left_semi")
        return got.join(ctx.vertex(), F.col("class") == F.col("v")).select(F.col("uri").alias("class"), F.col("n").alias("support"))

    return run




# graph, canonicalisation, degrees -------------------------------------------------------------------

def kg_triples_summary(spark: SparkSession, d: str) -> DataFrame:
    return kgview.triples(spark, d, "star").union(kgview.triples(spark, d, "page")).groupBy("p").agg(F.count("*").alias("n"))


add("kg_triples_summary", kg_triples_summary, f"SELECT p, count(*) AS n FROM (SELECT DISTINCT * FROM ({kgview.duck_triples('star')}) UNION ALL SELECT DISTINCT * FROM ({kgview.duck_triples('page')})) GROUP BY p")


def _canon(part: str, method: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        return canon.canonical_map(spark, kgview.triples(spark, d, (part,)), "s", "o", method)

    return run


for _name, _part, _method in (("canon_parts", "same_part", "star"), ("canon_parts_minlabel", "same_part", "minlabel"), ("canon_docs", "same_doc", "star"), ("canon_users", "same_user", "star")):
    add(_name, _canon(_part, _method), f"SELECT DISTINCT v, c FROM ({oracle.CANON[_part]}) WHERE v <> c")


def _degrees(u: bool) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        t = kgview.triples(spark, d, "star", False).filter(~F.col("p").isin(*PART.b_predicates))
        code = lambda c: dictionary.code(F.col(c))
        arc = t.select(code("s").alias("src"), code("p").alias("pred"), code("o").alias("dst"), "s", "o").groupBy("src", "pred", "dst").agg(F.first("s").alias("s"), F.first("o").alias("o"))
        ends = F.explode(F.array_distinct(F.array("s", "o"))) if u else F.col("s")
        return arc.select(ends.alias("v")).groupBy("v").agg(F.count("*").alias("n"))

    return run


for _u in (False, True):
    add(f"degree_{'all' if _u else 'out'}", _degrees(_u), oracle.with_(oracle.base("star", "part", replace(PART, u=_u))[:8], "SELECT v, n FROM deg"))


def degree_pairs(spark: SparkSession, d: str) -> DataFrame:
    t = kgview.triples(spark, d, kgview.STAR)
    return degree.drop_frequent_pairs(t, 8, 60).groupBy("p").agg(F.count("*").alias("n"))


add("degree_pairs", degree_pairs, f"""WITH t AS MATERIALIZED (SELECT DISTINCT s, p, o FROM ({kgview.duck_triples(kgview.STAR)})), a AS (SELECT s, p FROM t GROUP BY ALL HAVING count(*) > 8), b AS (SELECT p, o FROM t GROUP BY ALL HAVING count(*) > 60)
SELECT p, count(*) AS n FROM t WHERE NOT EXISTS (SELECT 1 FROM a WHERE a.s = t.s AND a.p = t.p) AND NOT EXISTS (SELECT 1 FROM b WHERE b.p = t.p AND b.o = t.o) GROUP BY p""")


def dense_dictionary(spark: SparkSession, d: str) -> DataFrame:
    t = kgview.triples(spark, d, "part")
    return dictionary.dense_ids(spark, t.select("s").union(t.select("o")))


add("dense_dictionary", dense_dictionary, f"SELECT uri, row_number() OVER (ORDER BY uri) - 1 AS id FROM (SELECT s AS uri FROM ({kgview.duck_triples('part')}) UNION SELECT o FROM ({kgview.duck_triples('part')}))")

# neighbours and classes -----------------------------------------------------------------------------

for _k in (1, 2, 3, 4):
    _p = replace(CUST, k=_k)
    add(f"cust_neighbours_k{_k}", _neighbours("customer", "customer", _p), oracle.neighbours("customer", "customer", replace(_p, t=0)))
for _t in (0, 1, 2, 3):
    _p = replace(CUST, t=_t)
    add(f"cust_types_t{_t}", _types("customer", "customer", _p), oracle.class_supports("customer", "customer", _p))
add("doc_neighbours", _neighbours("doc", "doc", replace(DOC, k=2)), oracle.neighbours("doc", "doc", replace(DOC, k=2, t=0)))
add("page_neighbours", _neighbours("page", "page", PAGE), oracle.neighbours("page", "page", replace(PAGE, t=0)))
add("cross_set_neighbours", _neighbours("customer", "customer", replace(CUST, k=1, l_min=1)), oracle.neighbours("customer", "customer", replace(CUST, k=1, l_min=1, t=0)))
for _d in (50, 100, 500, None):
    _p = replace(PART, k=2, u=True, d=_d)
    add(f"hub_stop_d{_d or 'inf'}", _neighbours("part", "part", _p), oracle.neighbours("part", "part", replace(_p, t=0)))


def neighbours_with_distance(spark: SparkSession, d: str) -> DataFrame:
    ctx = _context(spark, d, "part", "part", replace(PART, t=0))
    v = ctx.vertex()
    return ctx.reach.join(v.withColumnRenamed("uri", "vertex"), "v").join(v.select(F.col("v").alias("seed"), F.col("uri").alias("root")), "seed").select(F.col("root").alias("seed"), "vertex", "dist")


add("neighbours_with_distance", neighbours_with_distance, oracle.with_(oracle.base("part", "part", replace(PART, t=0)), "SELECT seed, v AS vertex, dist FROM reach"))

# path features --------------------------------------------------------------------------------------

FEATURE_RUNS = {
    "part_features_k1": ("part", "part", replace(PART, k=1)),
    "part_features_k2": ("part", "part", replace(PART, k=2)),
    "part_features_k3": ("part", "part", PART),
    "part_features_k3_t0": ("part", "part", replace(PART, t=0)),
    "part_features_k3_t1": ("part", "part", replace(PART, t=1)),
    "part_features_same": ("part_same", "part", PART),
    "cust_features_k2": ("customer", "customer", CUST),
    "doc_features": ("doc", "doc", DOC),
    "page_features": ("page", "page", PAGE),
    "blacklist_pred": ("part_prov", "part", replace(PART, b_predicates=("rdf:*", "rdfs:*", "prov:*"))),
    "blacklist_exp": ("part", "part", replace(PART, b_exp_types=("cls:SupDebt",))),
    "blacklist_gen": ("part", "part", replace(PART, b_gen_types=("cls:Agent", "cls:NationOf/*"))),
    "features_l_max": ("part", "part", replace(PART, l_max=100)),
}
for _name, (_view, _seed, _p) in FEATURE_RUNS.items():
    add(_name, _features(_view, _seed, _p), oracle.features(_view, _seed, _p))

#: modes whose results SQL gives as well; the same features are asked of all that must agree
for _mode in baselines.MODES:
    if _mode not in ("method", "no_support_limits", "no_canonical_graph"):
        _p = replace(PART, k=2, **baselines.MODES[_mode])
        add(f"mode_{_mode}", _features("part", "part", _p), oracle.features("part", "part", _p))
_p = replace(PART, k=2, canonicalise=False, b_predicates=(*PART.b_predicates, PART.identity))
add("mode_no_canonical_graph", _features("part_same", "part", _p), oracle.features("part_same", "part", _p))
_p = replace(PART, k=2, l_min=0, kinds=frozenset(("neighbour",)))
add("mode_no_support_limits", _features("part", "part", _p), oracle.features("part", "part", _p))


def part_matrix(spark: SparkSession, d: str) -> DataFrame:
    return _result(spark, d, "part", "part", PART).named_matrix()


add("part_matrix_k3", part_matrix, oracle.with_(oracle.base("part", "part", PART) + oracle.mining(PART), f"SELECT seed, v AS feature FROM reach SEMI JOIN near USING (v) UNION ALL SELECT unnest(ul) AS seed, fid AS feature FROM (" + " UNION ALL ".join(f"SELECT fid, ul FROM c{h}" for h in (1, 2, 3)) + ") WHERE fid IN (SELECT feature FROM found)"))

#: the kinds of ATOMS by name in SQL: individuals of a class are its instances
LIKE = {"p": "(e LIKE 'supplier:%')", "g": "(e LIKE 'nation:%' OR e IN ('cls:Region', 'cls:Place'))", "m": "(e LIKE 'cls:NationOf/%')"}
M = ("none", "p", "g", "m", "pg", "pgm")


def kind_test(m: str) -> str:
    return " OR ".join(LIKE[c] for c in m) if m != "none" else "true"


def filtered_ctes(p: MiningParams, m: str) -> list[str]:
    """CTEs near_m and found_m: what passes a filter."""
    elems = " UNION ALL ".join(f"SELECT fid, es FROM c{h}" for h in range(1, p.k + 1))
    return [
        f"near_m AS (SELECT v, n FROM (SELECT *, v AS e FROM near) WHERE {kind_test(m)})",
        f"found_m AS (SELECT * FROM found WHERE feature IN (SELECT fid FROM (SELECT fid, unnest(es) AS e FROM ({elems})) WHERE {kind_test(m)}))",
    ]


def mined_with_m(view: str, seed: str, p: MiningParams, m: str) -> tuple[Query, str]:
    """The run with its fourth step, and its twin."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        r = _result(spark, d, view, seed, replace(p, m=m, atoms=ATOMS))
        return r.features().select("feature", "kind", F.col("n").alias("support"))

    body = "SELECT v AS feature, 'neighbour' AS kind, n AS support FROM near_m UNION ALL SELECT feature, kind, n FROM found_m"
    return run, oracle.with_(oracle.base(view, seed, p) + oracle.mining(p) + filtered_ctes(p, m), body)


for _m in M:

    def _filtered(spark: SparkSession, d: str, m: str = _m) -> DataFrame:
        r = _result(spark, d, "part", "part", PART)
        return r.filtered(domain.DomainFilter.parse(m, ATOMS)).select("feature", "kind", F.col("n").alias("support"))

    _run, _sql = mined_with_m("part", "part", PART, _m)
    add(f"filter_{_m}", _filtered, _sql)
    if _m != "none":
        add(f"mine_m_{_m}", _run, _sql)


def mine_m_matrix(spark: SparkSession, d: str) -> DataFrame:
    """The matrix of a run with the filter g."""
    return _result(spark, d, "part", "part", replace(PART, m="g", atoms=ATOMS)).named_matrix()


_cells = "SELECT unnest(ul) AS seed, fid AS feature FROM (" + " UNION ALL ".join(f"SELECT fid, ul FROM c{h}" for h in (1, 2, 3)) + ")"
add("mine_m_matrix", mine_m_matrix, oracle.with_(oracle.base("part", "part", PART) + oracle.mining(PART) + filtered_ctes(PART, "g"), f"SELECT seed, v AS feature FROM reach SEMI JOIN near_m USING (v) UNION ALL SELECT seed, feature FROM ({_cells}) WHERE feature IN (SELECT feature FROM found_m)"))

# measures -------------------------------------------------------------------------------------------



def _ladder(view: str, seed: str, p: MiningParams, m: str | None = None) -> tuple[Query, str]:
    p = replace(p, engine="faithful")
    asked = p if m is None else replace(p, m=m, atoms=ATOMS)
    sql = oracle.ladder(view, seed, p, filtered_ctes(p, m) if m else None)
    return (lambda spark, d: metrics.ladder(_result(spark, d, view, seed, asked))), sql


add("ladder_part", *_ladder("part", "part", PART))
add("ladder_cust", *_ladder("customer", "customer", replace(CUST, k=1)))
add("ladder_doc", *_ladder("doc", "doc", DOC))
#: the published grid, the largest k with t = 1 alone, on both seed sets; customers from k = 3 on have some
#: forty million patterns at the size of the comparison and are mined by the factorised engine alone
GRID = [("part", k, t) for k in (1, 2, 3) for t in (1, 2, 3)] + [("part", 4, 1)] + [("customer", k, t) for k in (1, 2) for t in (1, 2, 3)]
for _view, _k, _t in GRID:
    add(f"ladder_{_view[:4]}_k{_k}_t{_t}", *_ladder(_view, _view, replace(PART, k=_k, t=_t), "pgm"))

for _name, _view, _d in (("full_neighbourhood_d500", "star", 500), ("full_neighbourhood_dinf", "star", None), ("full_neighbourhood_chain", "conversation", 500)):
    _seed = "conversation" if _view == "conversation" else "customer"
    _p = replace(CUST, d=_d, t=None)
    add(
        _name,
        lambda spark, d, view=_view, seed=_seed, p=_p: baselines.full_neighbourhood(spark, kgview.triples(spark, d, view), kgview.seeds(spark, d, seed), p, p.d),
        oracle.with_(oracle.base(_view, _seed, _p, full=True), "SELECT 'neighbours' AS what, count(*) AS n FROM rv UNION ALL SELECT 'classes', count(DISTINCT cls) FROM lev UNION ALL SELECT 'k', max(d) FROM (SELECT min(dist) AS d FROM reach GROUP BY v) UNION ALL SELECT 't', max(l) FROM (SELECT min(level) AS l FROM lev GROUP BY cls)"),
    )


def seed_composition(spark: SparkSession, d: str) -> DataFrame:
    sql = "SELECT CASE WHEN l.quality = 0 THEN '+' ELSE '-' END AS label, d.source AS origin FROM {labels} l JOIN {documents} d ON l.doc_id = d.doc_id"
    return metrics.seed_composition(kgview.select(spark, d, sql))


add("seed_composition", seed_composition, "SELECT label, origin, count(*) AS n FROM (SELECT CASE WHEN l.quality = 0 THEN '+' ELSE '-' END AS label, d.source AS origin FROM labels l JOIN documents d ON l.doc_id = d.doc_id) GROUP BY ROLLUP (label, origin)")


def feature_counts(spark: SparkSession, d: str) -> DataFrame:
    """How many of a seed's paths each selected feature captures, of every length."""
    return extensions.counted_features(_result(spark, d, "part", "part", replace(PART, k=2)))


def counts_sql(p: MiningParams) -> str:
    each = " UNION ALL ".join(f"SELECT fid, pid, ss FROM x{h}" for h in range(1, p.k + 1))
    return oracle.with_(oracle.base("part", "part", p) + oracle.mining(p), f"SELECT seed, fid AS feature, count(DISTINCT pid) AS n FROM (SELECT fid, pid, unnest(ss) AS seed FROM ({each}) WHERE fid IN (SELECT feature FROM found)) GROUP BY ALL")


add("feature_counts", feature_counts, counts_sql(replace(PART, k=2)))


def generalisation_counts(spark: SparkSession, d: str) -> DataFrame:
    """S12 on paths of one to three arcs: how many patterns generalise each."""
    return extensions.generalisation_counts(spark, kgview.triples(spark, d, "part", False), kgview.seeds(spark, d, "part"), replace(PART, t=2))


_p = replace(PART, t=2, kinds=frozenset(("path",)), prune=False, c2=False, l_min=0)
_each = " UNION ALL ".join(f"SELECT fid, {h} AS len, es FROM c{h}" for h in (1, 2, 3))
add("generalisation_counts", generalisation_counts, oracle.with_(oracle.base("part", "part", _p) + oracle.mining(_p), f"SELECT fid AS path, len, (product(1 + coalesce(g, 0)) - 1)::BIGINT AS n FROM (SELECT fid, len, unnest(es) AS v FROM ({_each})) LEFT JOIN (SELECT v, count(*) AS g FROM lev GROUP BY v) USING (v) GROUP BY ALL"))


def recall_of_pruning(spark: SparkSession, d: str) -> DataFrame:
    """How many of the features that the exhaustive run would select are found."""
    p = replace(PART, k=2)
    found = _result(spark, d, "part", "part", p).path_features()
    every = _result(spark, d, "part", "part", replace(p, engine="faithful", type_filter=False, specificity="off", prune=False, drop_single=False)).path_features()
    return metrics.recall(found, every)


_p = replace(PART, k=2)
_q = replace(_p, type_filter=False, specificity="off", prune=False, drop_single=False)
add("recall_of_pruning", recall_of_pruning, f"SELECT count(b.feature) AS both, count(*) AS wanted FROM ({oracle.features('part', 'part', _q, near=False)}) a LEFT JOIN ({oracle.features('part', 'part', _p, near=False)}) b USING (feature)")


def storage_footprint(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of features repeated in every cell, and kept once under an integer."""
    return dictionary.footprint(_result(spark, d, "part", "part", replace(PART, k=2)).path_features())


_p = oracle.features("part", "part", replace(PART, k=2), near=False)
add("storage_footprint", storage_footprint, f"SELECT count(*) AS features, sum(support)::BIGINT AS cells, sum(strlen(feature) * support)::BIGINT AS bytes_lists, sum(strlen(feature) + 8 * support)::BIGINT AS bytes_ids FROM ({_p})")


def parameter_guidance(spark: SparkSession, d: str) -> DataFrame:
    ctx = _context(spark, d, "star", "part", replace(PART, d=None), found=False)
    return metrics.guidance(spark, ctx)


_p = replace(PART, d=None, t=None)
_q = " UNION ALL ".join(f"SELECT 'degree_p{name}', quantile_disc(n, {q}) FROM deg" for name, q in (("50", 0.5), ("90", 0.9), ("99", 0.99)))
add("parameter_guidance", parameter_guidance, oracle.with_(oracle.base("star", "part", _p, full=True), f"SELECT 'degree_max' AS what, max(n) AS n FROM deg UNION ALL {_q} UNION ALL SELECT 'k_full', max(d) FROM (SELECT min(dist) AS d FROM reach GROUP BY v) UNION ALL SELECT 't_full', max(l) FROM (SELECT min(level) AS l FROM lev GROUP BY cls)"))
