"""Optional steps around the method: predicate hierarchy as arcs, literals as vertices, transitive
predicates, counted features, class extents as a cut, and a classifier of seeds.

(Merged predicates are an argument of ``mine``, patterns over a predicate hierarchy its parameter
``predicate_levels``, neighbours with distances part of ``reach``, user-defined filters of ``operators.domain``.)
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgfeat.api import MiningResult, mine
from kgfeat.functions.render import render
from kgfeat.operators import types
from kgfeat.operators.dictionary import dense_ids
from kgfeat.params import MiningParams
from kgfeat.plans.context import SUBPROPERTY, Context
from kgfeat.plans.state import Workspace


def predicate_levels(ws: Workspace, triples: DataFrame, t: int | None) -> DataFrame:
    """(v, class, level): predicates and the more general ones up to t levels, as ``types.levels`` for classes."""
    sub = triples.filter(F.col("p") == SUBPROPERTY).select(F.col("s").alias("class"), F.col("o").alias("super"))
    own = triples.select(F.col("p").alias("v")).distinct()
    inst = sub.select(F.col("class").alias("v"), F.col("super").alias("class"))
    return types.levels(ws, own, inst, sub, t, use_top=False)


def generalise_predicates(ws: Workspace, triples: DataFrame, t: int | None = 1) -> DataFrame:
    """triples with an arc more for each more general predicate."""
    up = predicate_levels(ws, triples, t).select(F.col("v").alias("p"), F.col("class").cast("string").alias("general"))
    return triples.union(triples.join(up, "p").select("s", F.col("general").alias("p"), "o")).distinct()


def literal_vertices(literals: DataFrame, width: float) -> DataFrame:
    """Numeric literals (s, p, value) as arcs to shared vertices, one a bucket of the given width:
    one form for 1, 1.0 and '1'. What is no number is left out."""
    bucket = F.floor(F.expr("try_cast(value AS double)") / width).cast("long")
    return literals.select("s", "p", F.concat(F.lit("num:"), F.col("p"), F.lit("/"), bucket.cast("string")).alias("o")).filter("o is not null")


def transitive(ws: Workspace, triples: DataFrame, predicate: str) -> DataFrame:
    """triples with the closure of a transitive predicate; each round doubles the length of ways found."""
    seen = ws.save(triples.filter(F.col("p") == predicate).select("s", "o").distinct(), "closure")
    while True:
        far = seen.join(seen.select(F.col("s").alias("o"), F.col("o").alias("far")), "o").select("s", F.col("far").alias("o"))
        new = ws.save(far.join(seen, ["s", "o"], "left_anti").distinct(), "closure-new")
        if new.isEmpty():
            break
        seen = ws.save(seen.union(new), "closure")
    return triples.filter(F.col("p") != predicate).union(seen.select("s", F.lit(predicate).alias("p"), "o"))


def counted_features(result: MiningResult) -> DataFrame:
    """(seed, feature, n): how many of a seed's paths each selected path feature captures, of any length."""
    v = result.context.vertex().select(F.col("v").alias("seed"), "uri")
    return result.counted().join(result.path_features().select("fid", "feature"), "fid").join(v, "seed").select(F.col("uri").alias("seed"), "feature", "n")


def relative_counts(counted: DataFrame) -> DataFrame:
    """counted_features() with the share of all of a seed's counts."""
    total = counted.groupBy("seed").agg(F.sum("n").alias("total"))
    return counted.join(total, "seed").withColumn("share", F.col("n") / F.col("total"))


def generalisation_counts(spark, triples: DataFrame, seeds: DataFrame, params: MiningParams) -> DataFrame:
    """(path, len, n): patterns that generalise each path from a seed, of every length up to k: the product
    over its vertices of 1 and their usable classes (the top class is one), without the path itself."""
    r = mine(spark, triples, seeds, params, kinds=frozenset(("path",)), prune=False, c2=False, l_min=0, l_max=None, m=None)
    c = r.context
    g = c.inst_levels.groupBy("v").agg((F.count("*") + 1).alias("g"))
    steps = r.mined.features.select("fid", "len", F.explode("elems").alias("v")).join(g, "v", "left")
    n = steps.groupBy("fid", "len").agg((F.product(F.coalesce("g", F.lit(1))) - 1).cast("long").alias("n"))
    return n.join(render(r.mined.features, c.vertex(), c.predicate()), "fid").select(F.col("feature").alias("path"), "len", "n")


def class_extents(ctx: Context) -> DataFrame:
    """(class, n): direct and inherited instances among neighbours, another measure of how general a class is."""
    return ctx.inst_levels.groupBy("class").agg(F.count("*").alias("n"))


def least_extent(result: MiningResult) -> DataFrame:
    """Path features left by another cut for redundancy: of selected patterns with the same predicates and
    the same support set only those stay whose elements hold the fewest neighbours in all (an individual
    holds one), whether or not the hierarchy relates them. Columns of ``path_features``."""
    f, ext = result.mined.features, class_extents(result.context)
    steps = f.filter("kind = 'pattern'").select("fid", "preds", "sset", F.explode(F.arrays_zip("elems", "classes")).alias("x"))
    held = steps.select("fid", "preds", "sset", F.col("x.elems").alias("e"), F.col("x.classes").alias("is_class")).join(ext.select(F.col("class").alias("e"), F.col("n").alias("held")), "e", "left")
    size = held.groupBy("fid", "preds", "sset").agg(F.sum(F.when(F.col("is_class"), F.col("held")).otherwise(1)).alias("held"))
    least = size.groupBy("preds", "sset").agg(F.min("held").alias("least"))
    gone = size.join(least, ["preds", "sset"]).filter("held > least").select("fid")
    return result.path_features().join(gone, "fid", "left_anti")


def held_out(seed: Column, folds: int = 5) -> Column:
    """True for one in so many seeds, by a hash of the URI."""
    return F.conv(F.substring(F.md5(seed), 1, 8), 16, 10).cast("long") % folds == 0


def vectors(ws: Workspace, cells: DataFrame, seeds: DataFrame) -> tuple[DataFrame, int]:
    """(seed, ..., features): seeds with all columns of the matrix as sparse vectors, and their number."""
    from pyspark.ml.functions import array_to_vector  # noqa: F401  registers the vector type
    from pyspark.ml.linalg import Vectors, VectorUDT

    ids = ws.save(dense_ids(ws.spark, cells.select(F.col("fid").cast("string")), ws), "columns")
    width = max(1, ids.count())
    at = cells.withColumn("uri", F.col("fid").cast("string")).join(ids, "uri").groupBy("seed").agg(F.array_sort(F.collect_set("id")).alias("at"))
    sparse = F.udf(lambda x: Vectors.sparse(width, x or [], [1.0] * len(x or [])), VectorUDT())
    return seeds.join(at, "seed", "left").withColumn("features", sparse("at")).drop("at"), width


def classifier(ws: Workspace, cells: DataFrame, labels: DataFrame, iterations: int = 50):
    """Logistic regression on all features of the matrix: (model, data). labels: (seed, label 0/1, held_out);
    held-out seeds are not fitted."""
    from pyspark.ml.classification import LogisticRegression

    data = ws.save(vectors(ws, cells, labels.withColumn("label", F.col("label").cast("double")))[0], "vectors")
    return LogisticRegression(maxIter=iterations, regParam=0.01).fit(data.filter("not held_out")), data


def influence(spark, triples: DataFrame, seeds: DataFrame, labels: DataFrame, params: MiningParams, grid: list[tuple[int, int, tuple[str, ...]]]) -> DataFrame:
    """(k, t, kinds, fold, n, right): how many seeds the classifier gets right, held out and fitted, for each
    k, t and kinds of features. labels: (uri, label)."""
    out = []
    for k, t, kinds in grid:
        r = mine(spark, triples, seeds, params, k=k, t=t, kinds=frozenset(kinds))
        v = r.context.vertex().select(F.col("v").alias("seed"), "uri")
        known = labels.join(v, "uri").select("seed", "label", held_out(F.col("uri")).alias("held_out"))
        model, data = classifier(r.context.ws, r.matrix(), known)
        for x in model.transform(data).groupBy("held_out").agg(F.count("*").alias("n"), F.sum((F.col("prediction") == F.col("label")).cast("long")).alias("right")).collect():
            out.append((k, t, "+".join(kinds), "held out" if x["held_out"] else "fitted", x["n"], x["right"]))
    return spark.createDataFrame(out, "k int, t int, kinds string, fold string, n long, right long")
