"""Driver queries of the remaining measures and of the optional steps; registered beside those of ``mining``."""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat import extensions
from kgfeat.api import mine
from kgfeat.operators import canon, degree, domain, reach
from kgfeat.params import MiningParams
from kgfeat.plans import metrics
from kgfeat.plans.context import prepare
from kgfeat.plans.state import Workspace
from kgfeat.queries import oracle
from kgfeat.queries.mining import ATOMS, CUST, DOC, ORACLES, PART, M, _context, _result, add
from kgfeat.sources import kgview

# measures -------------------------------------------------------------------------------------------


def class_extents(spark: SparkSession, d: str) -> DataFrame:
    """How many neighbours each class holds, another measure of generality."""
    ctx = _context(spark, d, "part", "part", PART)
    got, v = extensions.class_extents(ctx), ctx.vertex()
    return got.join(v, F.col("class") == F.col("v")).select(F.col("uri").alias("class"), "n")


add("class_extents", class_extents, oracle.with_(oracle.base("part", "part", PART), "SELECT cls AS class, count(*) AS n FROM lev GROUP BY 1"))


def features_by_length(spark: SparkSession, d: str) -> DataFrame:
    """Totals are marked 'all' and -1, so that no number is null."""
    got = metrics.by_kind_and_length(_result(spark, d, "part", "part", PART))
    return got.select(F.coalesce("kind", F.lit("all")).alias("kind"), F.coalesce("len", F.lit(-1)).alias("len"), "n")


add("features_by_length", features_by_length, f"SELECT coalesce(kind, 'all') AS kind, coalesce(len, -1) AS len, n FROM (SELECT kind, len, count(*) AS n FROM ({oracle.features('part', 'part', PART)}) GROUP BY ROLLUP (kind, len))")


def top_features(spark: SparkSession, d: str) -> DataFrame:
    return _result(spark, d, "part", "part", PART).top(20).select("feature", "kind", F.col("n").alias("support"))


add("top_features", top_features, f"SELECT feature, kind, support FROM ({oracle.features('part', 'part', PART)}) ORDER BY support DESC, feature LIMIT 20")


def filter_counts(spark: SparkSession, d: str) -> DataFrame:
    """What is left of each kind after each domain filter."""
    r = _result(spark, d, "part", "part", PART)
    out = None
    for m in M:
        one = r.filtered(domain.DomainFilter.parse(m, ATOMS)).groupBy("kind").agg(F.count("*").alias("n")).select(F.lit(m).alias("m"), "kind", "n")
        out = one if out is None else out.union(one)
    return out


add("filter_counts", filter_counts, " UNION ALL ".join(f"SELECT '{m}' AS m, kind, count(*) AS n FROM ({ORACLES[f'filter_{m}']}) GROUP BY kind" for m in M))

#: The reductions that the ladder shows
REDUCTIONS = (("neighbours_before", "neighbours_after"), ("classes_before", "classes_after"), ("generated", "selected"))


def ladder_ratios(spark: SparkSession, d: str) -> DataFrame:
    """Exact pairs of counts; their quotient is what ``metrics.ratios`` adds."""
    ws = Workspace(spark, "ratios")
    rows = ws.save(metrics.ladder(_result(spark, d, "part", "part", replace(PART, engine="faithful"))), "ladder")
    out = None
    for a, b in REDUCTIONS:
        one = metrics.ratios(rows, a, b).select(F.lit(f"{a}/{b}").alias("measure"), "over", "under")
        out = one if out is None else out.union(one)
    return out


_body = " UNION ALL ".join(f"SELECT '{a}/{b}' AS measure, max(n) FILTER (stage = '{a}') AS over, max(n) FILTER (stage = '{b}') AS under FROM x" for a, b in REDUCTIONS)
add("ladder_ratios", ladder_ratios, f"WITH x AS MATERIALIZED (SELECT * FROM ({ORACLES['ladder_part']})) " + _body)


def relative_feature_counts(spark: SparkSession, d: str) -> DataFrame:
    """A seed's paths by feature beside all its counted paths."""
    got = Workspace(spark, "counts").save(extensions.counted_features(_result(spark, d, "part", "part", replace(PART, k=2))), "counts")
    return extensions.relative_counts(got).select("seed", "feature", "n", "total")


add("relative_feature_counts", relative_feature_counts, f"SELECT seed, feature, n, (sum(n) OVER (PARTITION BY seed))::BIGINT AS total FROM ({ORACLES['feature_counts']})")


def full_to_k4(spark: SparkSession, d: str) -> DataFrame:
    """Neighbours of the full neighbourhood beside those within four arcs, with and without a degree limit."""
    t, s = kgview.triples(spark, d, "star", False), kgview.seeds(spark, d, "customer")
    ctx = prepare(spark, t, s, replace(CUST, d=None), around=math.inf)
    stop = ctx.ws.save(degree.hubs(ctx.arc, 500), "hubs")

    def counts(stop: DataFrame | None) -> tuple[int, int]:
        return tuple(reach.nearest(ctx.ws, ctx.arc, ctx.seeds, stop).agg(F.count("*"), F.count_if(F.col("dist") <= 4)).first())

    free = counts(None)
    limited = free if stop.isEmpty() else counts(stop)  # without hubs the limit changes nothing
    out = [("500", *limited), ("none", *free)]
    return spark.createDataFrame(out, "d string, full long, k4 long")


_sql = " UNION ALL ".join(f"SELECT '{x or 'none'}' AS d, (SELECT n FROM ({oracle.with_(oracle.base('star', 'customer', replace(CUST, d=x, t=0), full=True), 'SELECT count(*) AS n FROM rv')})) AS full, (SELECT n FROM ({oracle.with_(oracle.base('star', 'customer', replace(CUST, d=x, t=0), full=True), 'SELECT count(DISTINCT v) AS n FROM reach WHERE dist <= 4')})) AS k4" for x in (500, None))
add("full_to_k4", full_to_k4, _sql)


def run_cost(spark: SparkSession, d: str) -> DataFrame:
    """Wall time and memory of one run of the flagship; figures of this session, not for comparison."""
    with metrics.Cost(spark) as cost:
        _result(spark, d, "part", "part", PART).path_features().count()
    return spark.createDataFrame([(k, float(v)) for k, v in cost.values.items()], "measure string, value double")


add("run_cost", run_cost, None)


def cust_features_k3(spark: SparkSession, d: str) -> DataFrame:
    """Customers at k = 3 on the factorised engine: counts by kind and length (listing its paths one by one
    would take some forty million rows at the size of the comparison)."""
    r = _result(spark, d, "customer", "customer", replace(CUST, k=3, t=1))
    return r.mined.features.groupBy("kind", "len").agg(F.count("*").alias("n"), F.sum("n").alias("cells"))


add("cust_features_k3", cust_features_k3, None)

# optional steps on the graph ------------------------------------------------------------------------

#: predicates that a matcher may state alike, and a predicate hierarchy for the star
SAME_PREDICATE = (("fulfilledBy", "suppliedBy"),)
MORE_GENERAL = (("fulfilledBy", "suppliedFrom"), ("suppliedBy", "suppliedFrom"), ("livesIn", "locatedIn"), ("basedIn", "locatedIn"), ("inRegion", "locatedIn"), ("locatedIn", "related"))


def merged_predicates(spark: SparkSession, d: str) -> DataFrame:
    """Arcs of merged predicates, as a set."""
    alike = canon.canonical_map(spark, spark.createDataFrame(list(SAME_PREDICATE), "a string, b string"))
    got = canon.contract(kgview.triples(spark, d, kgview.STAR), spark.createDataFrame([], "v string, c string"), None, alike)
    return got.groupBy("p").agg(F.count("*").alias("n"))


_cases = " ".join(f"WHEN '{max(x)}' THEN '{min(x)}'" for x in SAME_PREDICATE)
add("merged_predicates", merged_predicates, f"SELECT p, count(*) AS n FROM (SELECT DISTINCT s, CASE p {_cases} ELSE p END AS p, o FROM ({kgview.duck_triples(kgview.STAR)})) GROUP BY p")


def predicate_hierarchy(spark: SparkSession, d: str) -> DataFrame:
    """Arcs by predicate once two levels of more general predicates are added."""
    up = spark.createDataFrame([(a, extensions.SUBPROPERTY, b) for a, b in MORE_GENERAL], "s string, p string, o string")
    got = extensions.generalise_predicates(Workspace(spark, "predicates"), kgview.triples(spark, d, kgview.STAR).union(up), 2)
    return got.groupBy("p").agg(F.count("*").alias("n"))


_values = ", ".join(f"('{a}', '{b}')" for a, b in MORE_GENERAL)
add(
    "predicate_hierarchy",
    predicate_hierarchy,
    f"WITH RECURSIVE up(a, b) AS (VALUES {_values}), t AS MATERIALIZED (SELECT s, p, o FROM ({kgview.duck_triples(kgview.STAR)}) UNION SELECT a, '{extensions.SUBPROPERTY}', b FROM up), "
    "climb AS (SELECT a AS p, b AS g, 1 AS l FROM up UNION SELECT c.p, up.b, l + 1 FROM climb c JOIN up ON c.g = up.a WHERE l < 2) "
    "SELECT p, count(*) AS n FROM (SELECT s, p, o FROM t UNION SELECT s, g, o FROM t JOIN climb USING (p)) GROUP BY p",
)


def _mined(spark: SparkSession, t: DataFrame, seeds: DataFrame, p: MiningParams, **how: object) -> DataFrame:
    return mine(spark, t, seeds, p, **how).features().select("feature", "kind", "len", F.col("n").alias("support"))


def _twin(p: MiningParams, view: str | tuple[str, ...], seed: str, general: tuple = (), **how: object) -> str:
    own = "SELECT v AS feature, 'neighbour' AS kind, 0 AS len, n AS support FROM near UNION ALL "
    return oracle.with_(oracle.base(view, seed, p, **how) + oracle.mining(p, general), own + "SELECT feature, kind, len, n AS support FROM found")


#: a matcher's statement for the mined view
ALIKE = (("basedIn", "inRegion"),)


def merged_predicates_mined(spark: SparkSession, d: str) -> DataFrame:
    """X1 carried into mining: features over merged predicates."""
    same = spark.createDataFrame(list(ALIKE), "a string, b string")
    return _mined(spark, kgview.triples(spark, d, "part", False), kgview.seeds(spark, d, "part"), PART, same_predicates=same)


add("merged_predicates_mined", merged_predicates_mined, _twin(PART, "part", "part", merged={max(x): min(x) for x in ALIKE}))

HIERARCHY = replace(PART, k=2, t=2, predicate_levels=2)


def predicate_hierarchy_mined(spark: SparkSession, d: str) -> DataFrame:
    """X2 carried into mining: patterns may name a more general predicate, and specificity compares predicates."""
    up = spark.createDataFrame([(a, extensions.SUBPROPERTY, b) for a, b in MORE_GENERAL], "s string, p string, o string")
    return _mined(spark, kgview.triples(spark, d, "part", False).union(up), kgview.seeds(spark, d, "part"), HIERARCHY)


add("predicate_hierarchy_mined", predicate_hierarchy_mined, _twin(HIERARCHY, "part", "part", MORE_GENERAL))

LITERAL_VIEW = (*kgview.VIEWS["star"], "balance")


def _balances(spark: SparkSession, d: str) -> DataFrame:
    return extensions.literal_vertices(kgview.select(spark, d, "SELECT 'customer:'||c_custkey AS s, 'balance' AS p, cast(c_acctbal AS string) AS value FROM {customer}"), 500.0)


def literal_buckets(spark: SparkSession, d: str) -> DataFrame:
    """customers' balances as shared vertices of 500 each."""
    return _balances(spark, d).groupBy("o").agg(F.count("*").alias("n"))


add("literal_buckets", literal_buckets, "SELECT 'num:balance/'||floor(c_acctbal / 500.0::DOUBLE)::BIGINT AS o, count(*) AS n FROM customer WHERE c_acctbal IS NOT NULL GROUP BY 1")


def literals_mined(spark: SparkSession, d: str) -> DataFrame:
    """X3 carried into mining: features with balances of customers."""
    t = kgview.triples(spark, d, "star", False).union(_balances(spark, d).select("s", "p", "o"))
    return _mined(spark, t, kgview.seeds(spark, d, "customer"), replace(CUST, k=1, l_min=3))


add("literals_mined", literals_mined, _twin(replace(CUST, k=1, l_min=3), LITERAL_VIEW, "customer"))


def extent_cut(spark: SparkSession, d: str) -> DataFrame:
    """X7 as a cut: of selected patterns with equal predicates and support sets the ones of least extent."""
    return extensions.least_extent(_result(spark, d, "part", "part", replace(PART, specificity="off"))).select("feature", "kind", "len", F.col("n").alias("support"))


_p = replace(PART, specificity="off")
_pats = " UNION ALL ".join(f"SELECT fid, ps, es, sup, isc FROM c{h} WHERE ispat" for h in (1, 2, 3))
add(
    "extent_cut",
    extent_cut,
    oracle.with_(
        oracle.base("part", "part", _p) + oracle.mining(_p) + [
            f"pat AS MATERIALIZED (SELECT fid, ps, es, sup FROM ({_pats}) WHERE fid IN (SELECT feature FROM found WHERE kind = 'pattern'))",
            "ext AS MATERIALIZED (SELECT cls AS e, count(*) AS n FROM lev GROUP BY 1)",
            "held AS MATERIALIZED (SELECT fid, ps, sup, sum(coalesce(ext.n, 1)) AS held FROM (SELECT fid, ps, sup, unnest(es) AS e FROM pat) LEFT JOIN ext USING (e) GROUP BY ALL)",
        ],
        "SELECT feature, kind, len, n AS support FROM found WHERE feature NOT IN (SELECT fid FROM (SELECT fid, held, min(held) OVER (PARTITION BY ps, sup) AS least FROM held) WHERE held > least)",
    ),
)


def dense_features(spark: SparkSession, d: str) -> DataFrame:
    """M4: the flagship with dense integers in place of hashes."""
    return _mined(spark, kgview.triples(spark, d, "part", False), kgview.seeds(spark, d, "part"), PART, ids="dense")


add("part_features_dense_ids", dense_features, ORACLES["part_features_k3"])


def transitive_next(spark: SparkSession, d: str) -> DataFrame:
    """Which turns follow which, at any distance."""
    return extensions.transitive(Workspace(spark, "transitive"), kgview.triples(spark, d, ("next",)), "next").select("s", "o")


add("transitive_next", transitive_next, f"WITH RECURSIVE e AS MATERIALIZED (SELECT s, o FROM ({kgview.duck_triples(('next',))})), r AS (SELECT s, o FROM e UNION SELECT r.s, e.o FROM r JOIN e ON r.o = e.s) SELECT s, o FROM r")


LABELS = "SELECT 'doc:'||doc_id AS uri, max(cast(quality = 0 AS int)) AS label FROM {labels} WHERE quality IS NOT NULL GROUP BY doc_id"


def _canonical_labels(spark: SparkSession, d: str, r) -> DataFrame:
    """(seed, uri, label, held_out): labels by the vertex that stands for a document, the highest of merged ones."""
    return kgview.select(spark, d, LABELS).join(r.context.vertex(), "uri").select(F.col("v").alias("seed"), "uri", "label").withColumn("held_out", extensions.held_out(F.col("uri")))


def seed_classifier(spark: SparkSession, d: str) -> DataFrame:
    """Labelled seeds with the class that a regression on the whole matrix gives; held-out seeds are not fitted."""
    r = _result(spark, d, "doc", "doc", DOC)
    model, data = extensions.classifier(r.context.ws, r.matrix(), _canonical_labels(spark, d, r))
    return model.transform(data).select(F.col("uri").alias("seed"), F.col("label").cast("int").alias("label"), "held_out", F.col("prediction").cast("int").alias("predicted"))


add("seed_classifier", seed_classifier, None)


def seed_classifier_folds(spark: SparkSession, d: str) -> DataFrame:
    """How many seeds of each label are fitted and held out."""
    got = kgview.select(spark, d, LABELS).withColumn("held_out", extensions.held_out(F.col("uri")))
    return got.groupBy("label", "held_out").agg(F.count("*").alias("n"))


add("seed_classifier_folds", seed_classifier_folds, "SELECT label, ('0x'||substr(md5(uri), 1, 8))::BIGINT % 5 = 0 AS held_out, count(*) AS n FROM (" + LABELS.replace("{labels}", "labels").replace("cast(quality = 0 AS int)", "cast(quality = 0 AS integer)") + ") GROUP BY ALL")


def classifier_influence(spark: SparkSession, d: str) -> DataFrame:
    """Seeds classified right, held out and fitted, by k, t and kinds of features."""
    labels = kgview.select(spark, d, LABELS)
    grid = [(1, 1, ("neighbour",)), (1, 1, ("path",)), (1, 1, ("pattern",)), (1, 1, ("neighbour", "path", "pattern")), (2, 1, ("neighbour", "path", "pattern"))]
    return extensions.influence(spark, kgview.triples(spark, d, "doc", False), kgview.seeds(spark, d, "doc"), labels, DOC, grid)


add("classifier_influence", classifier_influence, None)
