"""Configurations that the method is compared with, as runs of the same engine with steps switched off."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.api import MiningResult, mine
from kgfeat.params import MiningParams
from kgfeat.plans.context import Context, prepare, search
from kgfeat.plans.state import Workspace

#: name -> changes of parameters
MODES: dict[str, dict] = {
    "method": {},
    "faithful": {"engine": "faithful"},
    "no_support_limits": {"l_min": 0, "l_max": None, "kinds": frozenset(("neighbour",))},
    "exhaustive": {"engine": "faithful", "type_filter": False, "specificity": "off", "prune": False, "drop_single": False, "c2": False, "c3": False},
    "no_class_filter": {"type_filter": False},
    "whole_hierarchy": {"specificity": "hierarchy"},
    "prefix_tree": {"specificity": "trie"},
    "no_pruning": {"prune": False},
    "no_canonical_graph": {"canonicalise": False},
    "support_only": {"specificity": "off", "drop_single": False, "c2": False, "c3": False},
    "neighbours_only": {"kinds": frozenset(("neighbour",))},
    "paths_only": {"kinds": frozenset(("path",))},
    "patterns_only": {"kinds": frozenset(("pattern",))},
}


def run(spark: SparkSession, mode: str, triples: DataFrame, seeds: DataFrame, params: MiningParams, max_rows: float = 5e8) -> MiningResult:
    """Mine in a mode. The exhaustive mode first bounds its rows and refuses above max_rows."""
    p = replace(params, **MODES[mode])
    if mode == "exhaustive":
        n = estimate(search(prepare(spark, triples, seeds, p)))
        if n > max_rows:
            raise ValueError(f"about {n:.3g} path features; more than {max_rows:.3g}")
    return mine(spark, triples, seeds, p)


def estimate(ctx: Context) -> float:
    """An upper bound of exhaustive path features: walks by the mean out-degree times choices of elements."""
    p = ctx.params
    first = ctx.arc.join(ctx.seeds.select(F.col("seed").alias("src")), "src", "left_semi").select("pred", "dst").distinct().count()
    inside = ctx.reach.select(F.col("v").alias("src")).distinct()
    n_in = inside.count()
    out = ctx.arc.join(inside, "src", "left_semi").count() / max(1, n_in)
    g = 1 + ctx.inst_levels.count() / max(1, n_in)
    return sum(first * out ** (h - 1) * g**h for h in range(1, p.k + 1))


def full_neighbourhood(spark: SparkSession, triples: DataFrame, seeds: DataFrame, params: MiningParams, d: int | None, ws: Workspace | None = None) -> DataFrame:
    """(what, n) at the fixpoint, with or without a degree limit."""
    from kgfeat.plans.metrics import saturation

    return saturation(prepare(spark, triples, seeds, replace(params, d=d), ws))
