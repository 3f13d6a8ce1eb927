"""Text forms of features."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def render(features: DataFrame, vertex: DataFrame, predicate: DataFrame) -> DataFrame:
    """(fid, feature): ``-[p]-> e -[p]-> e`` for each path feature."""
    steps = features.select("fid", F.posexplode(F.arrays_zip("preds", "elems")).alias("pos", "x")).select("fid", "pos", F.col("x.preds").alias("pred"), F.col("x.elems").alias("v"))
    named = steps.join(predicate, "pred").join(vertex, "v").select("fid", "pos", F.concat(F.lit("-["), "name", F.lit("]-> "), "uri").alias("s"))
    return named.groupBy("fid").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "s"))), lambda x: x["s"]), " ").alias("feature"))


def generalisations(classes_of_each: Column) -> Column:
    """Number of patterns that generalise a path, from the number of usable classes of each of its
    vertices, the top class among them: the product of 1 + classes, without the path itself."""
    return F.aggregate(classes_of_each, F.lit(1).cast("long"), lambda acc, c: acc * (c + 1)) - 1
