"""Domain filters: keep features that mention at least one thing of a kind, or of one of several kinds."""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgfeat.operators.blacklist import matches


@dataclass(frozen=True)
class Atom:
    """A kind: individuals by URI or prefix or as instances, direct or inherited, of listed classes; and
    classes by URI or prefix (entries as in blacklists)."""

    individuals: tuple[str, ...] = ()
    classes: tuple[str, ...] = ()
    instances_of: tuple[str, ...] = ()

    def holds(self, uri: Column, is_class: Column) -> Column:
        """By name alone; ``instances_of`` needs the graph, see ``things``."""
        return F.when(is_class, matches(uri, self.classes)).otherwise(matches(uri, self.individuals))


@dataclass(frozen=True)
class DomainFilter:
    atoms: tuple[Atom, ...]

    @staticmethod
    def parse(m: str | None, known: Mapping[str, Atom]) -> DomainFilter | None:
        """'pg' means p or g; None and 'none' mean no filter. Atoms have names of one character."""
        if m is None or m == "none":
            return None
        if not isinstance(m, str) or not m:
            raise ValueError(f"not a filter: {m!r}")
        if missing := [c for c in m if c not in known]:
            raise ValueError(f"unknown kinds {missing}")
        return DomainFilter(tuple(known[c] for c in m))

    def holds(self, uri: Column, is_class: Column) -> Column:
        out = F.lit(False)
        for a in self.atoms:
            out = out | a.holds(uri, is_class)
        return out


def things(ctx, chosen: DomainFilter) -> DataFrame:
    """(v, is_class) of the vertices of a graph that are of a chosen kind, as individuals or as classes."""
    from kgfeat.operators import types

    named = ctx.vertex().select("v", "uri", F.explode(F.array(F.lit(False), F.lit(True))).alias("is_class"))
    out = named.filter(chosen.holds(F.col("uri"), F.col("is_class"))).select("v", "is_class")
    for a in chosen.atoms:
        if a.instances_of:
            under = types.instances_of(ctx.ws, ctx.inst, ctx.sub, ctx.classes_named(a.instances_of))
            out = out.union(under.select("v", F.lit(False).alias("is_class")))
    return out.distinct()


def apply(elements: DataFrame, features: DataFrame, chosen: DomainFilter | None) -> DataFrame:
    """features (fid, ...) with an element (fid, uri, is_class) of the kind; a neighbour is its own element."""
    if chosen is None:
        return features
    return features.join(elements.filter(chosen.holds(F.col("uri"), F.col("is_class"))).select("fid").distinct(), "fid", "left_semi")
