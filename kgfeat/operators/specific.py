"""Most specific patterns among those of one iteration, predicate sequence and support set.

Input rows: fid, sset, preds (array), elems (array), ancs (array of arrays: each element with all that
is above it). Pattern a is below b if every element of b is among the ancestors of a's element at that
place. Three ways with one result: an equi-join, a prefix tree per group, the whole hierarchy.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _below(elems: Column, ancs: Column) -> Column:
    return F.forall(F.zip_with(elems, ancs, lambda e, a: F.array_contains(a, e)), lambda x: x)


def dominated(pats: DataFrame, impl: str = "join") -> DataFrame:
    """(fid) of patterns with a more specific one of the same support set; on a cycle the least fid stays."""
    if impl == "join":
        return _by_join(pats)
    if impl == "hierarchy":
        return _by_hierarchy(pats)
    if impl == "trie":
        return _by_trie(pats)
    raise ValueError(impl)


def maximal(pats: DataFrame, impl: str = "join") -> DataFrame:
    return pats if impl == "off" else pats.join(dominated(pats, impl), "fid", "left_anti")


def _by_join(pats: DataFrame) -> DataFrame:
    """Ancestors of the last two elements are equi-join keys, so a pattern meets only those above both of
    its ends; the other positions are tested on the pairs that meet."""

    def at(col: str, place: int) -> Column:
        return F.when(F.size(col) >= -place, F.element_at(col, place))

    one = F.array(F.lit(0).cast("long"))  # patterns of one element: a key that all share
    a = pats.select(F.col("fid").alias("fa"), "sset", "preds", F.col("elems").alias("ea"), F.col("ancs").alias("aa"), F.explode(at("ancs", -1)).alias("last"))
    a = a.withColumn("before", F.explode(F.coalesce(at("aa", -2), one)))
    b = pats.select(F.col("fid").alias("fb"), "sset", "preds", F.col("elems").alias("eb"), F.col("ancs").alias("ab"), at("elems", -1).alias("last"), F.coalesce(at("elems", -2), F.lit(0)).alias("before"))
    both = a.join(b, ["sset", "preds", "last", "before"]).filter("fa <> fb").filter(_below(F.col("eb"), F.col("aa")))
    return both.filter(~_below(F.col("ea"), F.col("ab")) | (F.col("fa") < F.col("fb"))).select(F.col("fb").alias("fid")).distinct()


def _by_hierarchy(pats: DataFrame) -> DataFrame:
    """All generalisations of every pattern, looked up among the patterns: for small inputs only."""
    up = F.aggregate("ancs", F.array(F.array().cast("array<bigint>")), lambda acc, a: F.flatten(F.transform(acc, lambda p: F.transform(a, lambda x: F.array_append(p, x)))))
    a = pats.select(F.col("fid").alias("fa"), "sset", "preds", F.col("elems").alias("ea"), F.explode(up).alias("elems"))
    b = pats.select(F.col("fid").alias("fb"), "sset", "preds", "elems", F.col("ancs").alias("ab"))
    both = a.join(b, ["sset", "preds", "elems"]).filter("fa <> fb")
    return both.filter(~_below(F.col("ea"), F.col("ab")) | (F.col("fa") < F.col("fb"))).select(F.col("fb").alias("fid")).distinct()


class PrefixTree:
    """Patterns of one group by element after element; answers what lies above or below a pattern."""

    def __init__(self) -> None:
        self.root: dict = {}

    def add(self, elems: tuple, fid: int) -> None:
        at = self.root
        for e in elems[:-1]:
            at = at.setdefault(e, {})
        at[elems[-1]] = fid

    def remove(self, elems: tuple) -> None:
        trail, at = [], self.root
        for e in elems:
            trail.append((at, e))
            at = at[e]
        for node, e in reversed(trail):
            del node[e]
            if node:
                break

    def walk(self, steps: list) -> Iterator[tuple[tuple, int]]:
        """Leaves reached level by level; steps[i](node) gives the usable keys of a node at depth i."""
        front = [((), self.root)]
        for step in steps:
            front = [((*path, e), node[e]) for path, node in front for e in step(node)]
            if not front:
                return
        yield from front


def _by_trie(pats: DataFrame) -> DataFrame:
    """A tree for each predicate sequence and support set, built by one task: for groups that fit a task."""

    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        tree, above, out = PrefixTree(), {}, []
        for fid, elems, ancs in sorted(zip(pdf.fid, pdf.elems, pdf.ancs, strict=True), key=lambda r: r[0]):
            elems, sets = tuple(elems), [frozenset(a) for a in ancs]
            for e, s in zip(elems, sets, strict=True):
                above[e] = s
            down = [lambda node, e=e: [x for x in node if e in above[x]] for e in elems]
            if next(tree.walk(down), None):
                out.append(fid)
                continue
            up = [lambda node, s=s: [x for x in node if x in s] for s in sets]
            for path, old in list(tree.walk(up)):
                tree.remove(path)
                out.append(old)
            tree.add(elems, fid)
        return pd.DataFrame({"fid": pd.Series(out, dtype="int64")})

    return pats.groupBy("sset", "preds").applyInPandas(run, "fid long")
