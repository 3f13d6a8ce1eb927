"""The paper's grid on the given tables: neighbours, classes and path features before and after limits.

python -m kgfeat.experiments /root/testdata/sf0.01 prints one row a configuration and stage, and the
reductions that the paper reports.
"""

from __future__ import annotations

import json
import sys
from dataclasses import replace

from pyspark.sql import SparkSession

from kgfeat.api import mine
from kgfeat.operators import domain
from kgfeat.params import MiningParams
from kgfeat.plans import baselines, metrics
from kgfeat.sources import kgview

#: (view, seeds, k, t): the paper's k from 1 to 4 and t from 1 to 3, the largest k with t = 1 alone; customers from k = 3 on by the factorised engine
GRID = [("part", "part", k, t) for k in (1, 2, 3) for t in (1, 2, 3)] + [("part", "part", 4, 1)] + [("customer", "customer", k, t) for k in (1, 2) for t in (1, 2, 3)] + [("customer", "customer", 3, 1)]


def grid(spark: SparkSession, sf_dir: str, configs: list[tuple[str, str, int, int]] = GRID, atoms: dict[str, domain.Atom] | None = None, m: str = "pgm") -> list[dict]:
    """One record a configuration: its counts before and after limits and filter, time and memory."""
    out = []
    for view, seed, k, t in configs:
        engine = "factorised" if view == "customer" and k > 2 else "faithful"
        with metrics.Cost(spark) as cost:
            r = mine(spark, kgview.triples(spark, sf_dir, view, False), kgview.seeds(spark, sf_dir, seed), MiningParams(k=k, t=t, d=500, l_min=5, engine=engine, m=m if atoms else None, atoms=atoms or {}))
            row = {"view": view, "k": k, "t": t, "engine": engine} | {x["stage"]: x["n"] for x in metrics.ladder(r).collect()}
        r.close()
        out.append(row | cost.values)
    return out


def reductions(row: dict) -> dict:
    """The paper's quotients of one configuration."""
    part = lambda a, b: round(row[a] / row[b], 2) if row.get(b) else None
    return {"neighbours": part("neighbours_before", "neighbours_after"), "classes": part("classes_before", "classes_after"), "path_features": part("generated", "selected")}


def full(spark: SparkSession, sf_dir: str, view: str = "star", seed: str = "customer") -> dict:
    """The full neighbourhood with and without a degree limit."""
    p = MiningParams(k=4, t=None, l_min=5)
    t, s = kgview.triples(spark, sf_dir, view), kgview.seeds(spark, sf_dir, seed)
    return {str(d): {r["what"]: r["n"] for r in baselines.full_neighbourhood(spark, t, s, replace(p, d=d), d).collect()} for d in (500, None)}


def main(sf_dir: str) -> None:
    from kgfeat.queries.mining import ATOMS

    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for row in grid(spark, sf_dir, atoms=ATOMS):
        print(json.dumps(row | {"reductions": reductions(row)}), flush=True)
    print(json.dumps({"full": full(spark, sf_dir)}))


if __name__ == "__main__":
    main(sys.argv[1])
