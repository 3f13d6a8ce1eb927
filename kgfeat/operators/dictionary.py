"""Integers for URIs.

``hash`` coding maps by a 64-bit hash: no join, equal in every run, checked for collisions. ``dense``
coding numbers distinct URIs 0, 1, 2 ... in order by distributed prefix sums, with no single-task sort.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.operators.prefix import prefix_sums
from kgfeat.params import TOP, TOP_NAME
from kgfeat.plans.state import Workspace


def code(uri: Column) -> Column:
    return F.xxhash64(uri)


def check_collisions(vertex: DataFrame, key: str = "v") -> None:
    """Raise if two URIs share an integer."""
    if not vertex.groupBy(key).agg(F.count("*").alias("n")).filter("n > 1").isEmpty():
        raise ValueError("two URIs have the same 64-bit hash; mine with ids='dense'")


@dataclass
class Coding:
    """vertex (v, uri) and predicate (pred, name) of a graph; ``dense``: ids are looked up, not computed."""

    vertex: DataFrame
    predicate: DataFrame
    dense: bool

    def of(self, uris: DataFrame, col: str) -> DataFrame:
        """uris with the column replaced by its integer; URIs that the graph does not have are left out if dense."""
        if not self.dense:
            return uris.withColumn(col, code(F.col(col)))
        at = self.vertex.select(F.col("v").alias("id of uri"), F.col("uri").alias(col))
        return uris.join(at, col).withColumn(col, F.col("id of uri")).drop("id of uri")

    def arcs(self, triples: DataFrame) -> DataFrame:
        """triples (s, p, o, ...) with s, p, o replaced by src, pred, dst."""
        t = triples.withColumnsRenamed({"s": "src", "o": "dst"})
        if not self.dense:
            return t.withColumns({"src": code(F.col("src")), "dst": code(F.col("dst")), "pred": code(F.col("p"))}).drop("p")
        return self.of(self.of(t, "src"), "dst").join(self.predicate.select("pred", F.col("name").alias("p")), "p").drop("p")


def ends(triples: DataFrame) -> DataFrame:
    """(uri), each once, at either end of string triples (s, p, o)."""
    return triples.select(F.explode(F.array("s", "o")).alias("uri")).filter("uri is not null").distinct()


def coding(ws: Workspace, triples: DataFrame, ids: str = "hash") -> Coding:
    """Integers for all URIs of string triples (s, p, o), committed; hashes are checked for collisions."""
    uris = ends(triples)
    names = triples.select(F.col("p").alias("name")).distinct()
    if ids == "dense":
        vertex = ws.save(dense_ids(ws.spark, uris, ws).select(F.col("id").alias("v"), "uri"), "vertex")
        return Coding(vertex, ws.save(dense_ids(ws.spark, names, ws).select(F.col("id").alias("pred"), F.col("uri").alias("name")), "predicate"), True)
    vertex = ws.save(uris.select(code(F.col("uri")).alias("v"), "uri"), "vertex")
    predicate = ws.save(names.select(code(F.col("name")).alias("pred"), "name"), "predicate")
    check_collisions(vertex)
    check_collisions(predicate, "pred")
    return Coding(vertex, predicate, False)


def with_top(vertex: DataFrame) -> DataFrame:
    """vertex with the class that all are instances of."""
    return vertex.union(vertex.sparkSession.createDataFrame([(TOP, TOP_NAME)], "v long, uri string"))


def dense_ids(spark: SparkSession, uris: DataFrame, ws: Workspace | None = None) -> DataFrame:
    """(uri, id): ids 0 .. n - 1 in code point order of the distinct non-null URIs."""
    ws = ws or Workspace(spark, "dictionary")
    one = uris.select(F.col(uris.columns[0]).alias("uri")).filter("uri is not null").distinct().withColumn("one", F.lit(1).cast("long"))
    return prefix_sums(ws, one, None, ["uri"], ["one"], "ids").select("uri", F.col("before_one").alias("id"))


def footprint(features: DataFrame, feature: str = "feature") -> DataFrame:
    """Bytes of features (fid, feature, n) kept as text in every cell of the matrix, and kept once with an
    8-byte integer in the cells, from the texts themselves: (features, cells, bytes_lists, bytes_ids)."""
    size = F.octet_length(feature)
    return features.agg(F.count("*").alias("features"), F.sum("n").alias("cells"), F.sum(size * F.col("n")).alias("bytes_lists"), F.sum(size + 8 * F.col("n")).alias("bytes_ids"))
