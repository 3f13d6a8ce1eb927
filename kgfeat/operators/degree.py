"""Degrees, hubs, and the arcs that a search may use."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def degrees(arc: DataFrame, u: bool = False) -> DataFrame:
    """(v, n): arcs out of v, or with u all arcs at v; a self loop counts once."""
    if not u:
        return arc.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("n"))
    ends = arc.select(F.explode(F.array_distinct(F.array("src", "dst"))).alias("v"))
    return ends.groupBy("v").agg(F.count("*").alias("n"))


def hubs(arc: DataFrame, d: int | None, u: bool = False) -> DataFrame | None:
    """(v) of degree strictly above d."""
    return None if d is None else degrees(arc, u).filter(F.col("n") > d).select("v")


def inverse(pred: str) -> Column:
    """The predicate of an arc that is followed against its direction."""
    return F.xxhash64(F.col(pred), F.lit("inverse"))


def both_ways(arc: DataFrame, direction_aware: bool = False) -> DataFrame:
    """Arcs and their inverses, not necessarily a set."""
    return arc.union(arc.select(F.col("dst").alias("src"), (inverse("pred") if direction_aware else F.col("pred")).alias("pred"), F.col("src").alias("dst")))


def allowed(arc: DataFrame, d: int | None, u: bool, banned: DataFrame | None, exempt: DataFrame | None = None, direction_aware: bool = False) -> DataFrame:
    """Arcs to traverse: both ways with u, not out of hubs (but out of ``exempt``), not into banned vertices.

    All limits are settled here, once, so that every round of a search is one join.
    """
    stop = hubs(arc, d, u)
    if u:
        arc = both_ways(arc, direction_aware).distinct()
    if stop is not None:
        if exempt is not None:
            stop = stop.join(exempt.select(F.col("seed").alias("v")), "v", "left_anti")
        arc = arc.join(stop.withColumnRenamed("v", "src"), "src", "left_anti")
    if banned is not None:
        arc = arc.join(banned.select(F.col("v").alias("dst")), "dst", "left_anti")
    return arc.select("src", "pred", "dst")


def drop_frequent_pairs(triples: DataFrame, max_sp: int, max_po: int) -> DataFrame:
    """The other way with hubs: drop arcs whose (source, predicate) or (predicate, target) is too frequent."""
    sp = triples.groupBy("s", "p").agg(F.count("*").alias("n")).filter(F.col("n") > max_sp).select("s", "p")
    po = triples.groupBy("p", "o").agg(F.count("*").alias("n")).filter(F.col("n") > max_po).select("p", "o")
    return triples.join(sp, ["s", "p"], "left_anti").join(po, ["p", "o"], "left_anti").select("s", "p", "o")
