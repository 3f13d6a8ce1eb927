"""Canonicalisation: components of the undirected identity graph, contraction of arcs and seeds.

``components`` needs no driver memory and no task that gathers a component: every round is a
pair of joins and grouped minima over a shrinking set of edges, with each round's result
committed as a table. Roots of large components are keys with very many edges: their few minima are
sent to the edges, which stay where they are (``_with_least``).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.plans.state import Workspace

SPREAD = 1000  # a key with over 1 / SPREAD of all edges is hot: there are fewer than SPREAD of them
SMALL = 1_000_000  # edges that one task may hold anyway
BROADCAST_MAP = 1_000_000  # rows of two longs sent to all tasks; longer maps are shuffled


def _both_ways(e: DataFrame) -> DataFrame:
    return e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))


def _with_least(edges: DataFrame, low: DataFrame, n: int) -> DataFrame:
    """edges joined with low (a, m, k: edges of a) on a; hot keys are not shuffled to one task."""
    if n <= SMALL:
        return edges.join(low.select("a", "m"), "a")
    hot = F.broadcast(low.filter(F.col("k") * SPREAD > n).select("a", "m"))
    return edges.join(hot, "a").union(edges.join(hot.select("a"), "a", "left_anti").join(low.select("a", "m"), "a"))


def _large_star(ws: Workspace, e: DataFrame, n: int) -> DataFrame:
    """Tie each vertex's larger neighbours to the least vertex around it (itself included)."""
    nb = _both_ways(e)
    low = ws.save(nb.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"), F.count("*").alias("k")), "low", 2 * n)
    return _with_least(nb.filter("b > a"), low, n).select(F.col("m").alias("a"), "b").filter("a <> b").distinct()


def _small_star(ws: Workspace, e: DataFrame, n: int) -> DataFrame:
    """Tie each vertex and its smaller neighbours to the least of them."""
    down = e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = ws.save(down.groupBy("a").agg(F.min("b").alias("m"), F.count("*").alias("k")), "low", n)
    return _with_least(down, low, n).select(F.col("m").alias("a"), "b").filter("a <> b").union(low.select(F.col("m").alias("a"), F.col("a").alias("b"))).distinct()


def components(spark: SparkSession, edges: DataFrame, a: str = "a", b: str = "b", method: str = "star", ws: Workspace | None = None) -> DataFrame:
    """(v, c): each vertex that has an edge to another, with the least vertex of its component.

    method 'star' alternates large and small stars, O(log V) rounds; 'minlabel' passes the least
    label along edges, O(diameter) rounds. Null ends and self loops are left out.
    """
    ws = ws or Workspace(spark, "components")
    e = ws.save(edges.select(F.col(a).alias("a"), F.col(b).alias("b")).filter("a is not null and b is not null and a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    if method == "minlabel":
        return _min_label(ws, e)
    if method != "star":
        raise ValueError(f"unknown method {method!r}")
    last, n = None, e.count()
    while True:
        e = ws.save(_small_star(ws, _large_star(ws, e, n), n), "star", n)  # no round adds edges
        # the total of (parent, child) pairs stands still only when every edge ends at a root
        now = e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == last:
            break
        last, n = now, max(n, now[0])
    return e.select(F.col("b").alias("v"), F.col("a").alias("c")).union(e.select(F.col("a").alias("v"), F.col("a").alias("c"))).distinct()


def _min_label(ws: Workspace, e: DataFrame) -> DataFrame:
    nb = ws.save(_both_ways(e), "both")
    lab = ws.save(nb.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("c")).select(F.col("a").alias("v"), "c"), "label")
    while True:
        around = nb.join(lab, nb.b == lab.v).groupBy(F.col("a").alias("v")).agg(F.min("c").alias("n"))
        new = ws.save(lab.join(around, "v").select("v", F.least("c", "n").alias("c"), (F.col("n") < F.col("c")).alias("moved")), "label")
        if new.filter("moved").isEmpty():
            return new.select("v", "c")
        lab = new.select("v", "c")


def canonical_map(spark: SparkSession, same: DataFrame, a: str = "a", b: str = "b", method: str = "star", ws: Workspace | None = None) -> DataFrame:
    """(v, c) for the merged vertices only; every other vertex stands for itself."""
    return components(spark, same, a, b, method, ws).filter("v <> c")


def named_map(ws: Workspace, same: DataFrame, vertex: DataFrame, method: str = "star") -> DataFrame:
    """canonical_map of integer arcs (src, dst); a component stands under its first URI by code point."""
    comp = ws.save(components(ws.spark, same, "src", "dst", method, ws), "components")
    first = comp.join(vertex, "v").groupBy("c").agg(F.min_by("v", "uri").alias("r"))
    return comp.join(first, "c").select("v", F.col("r").alias("c")).filter("v <> c")


def contract(triples: DataFrame, canon: DataFrame, identity: str | None = "owl:sameAs", pred_canon: DataFrame | None = None) -> DataFrame:
    """String triples over canonical vertices as a set; identity arcs go, self loops stay."""
    t = triples.filter(F.col("p") != identity) if identity else triples
    t = replaced(replaced(t, canon, "s"), canon, "o")
    if pred_canon is not None:
        t = replaced(t, pred_canon, "p")
    return t.select("s", "p", "o").distinct()


def replaced(rows: DataFrame, canon: DataFrame, col: str, few: bool = False) -> DataFrame:
    """rows with the vertices of a column replaced by the canonical ones; few: canon is known to be small."""
    m = canon.select(F.col("v").alias(col), F.col("c").alias("canonical one"))
    return rows.join(F.broadcast(m) if few else m, col, "left").withColumn(col, F.coalesce("canonical one", col)).drop("canonical one")


def contract_seeds(seeds: DataFrame, canon: DataFrame) -> DataFrame:
    """Distinct canonical seeds; the column is named ``seed``."""
    return replaced(seeds.select("seed"), canon, "seed").distinct()
