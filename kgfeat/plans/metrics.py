"""Measures of a run, as tidy rows."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.api import MiningResult
from kgfeat.operators import degree, reach, types
from kgfeat.plans.context import Context


def ladder(result: MiningResult) -> DataFrame:
    """(stage, n): vertices, classes and path features before and after limits, and after the domain filter
    if the run has one. ``generated`` counts every path feature only with the faithful engine."""
    c, all_ = result.context, result.unfiltered or result
    one = lambda stage, df: df.agg(F.count("*").alias("n")).select(F.lit(stage).alias("stage"), "n")
    rows = [
        one("neighbours_before", c.reach.select("v").distinct()),
        one("classes_before", c.inst_levels.select("class").distinct()),
        one("neighbours_after", all_.neighbours),
        one("classes_after", c.usable_types),
    ]
    if all_.mined is not None:
        rows += [c.spark.createDataFrame([("generated", sum(all_.mined.generated))], "stage string, n long"), one("selected", all_.mined.features)]
    if result.unfiltered is not None:
        rows.append(one("neighbours_after_m", result.neighbours))
        if result.mined is not None:
            rows.append(one("selected_after_m", result.mined.features))
    out = rows[0]
    for r in rows[1:]:
        out = out.union(r)
    return out


def by_kind_and_length(result: MiningResult) -> DataFrame:
    """Counts of selected features by kind and length, with totals."""
    return result.features().rollup("kind", "len").agg(F.count("*").alias("n"))


def ratios(rows: DataFrame, over: str, under: str) -> DataFrame:
    """(over, under, ratio) of two stages of a ladder."""
    n_of = lambda stage: F.max(F.when(F.col("stage") == stage, F.col("n")))
    return rows.agg(n_of(over).alias("over"), n_of(under).alias("under")).withColumn("ratio", F.when(F.col("under") > 0, F.col("over") / F.col("under")))


def saturation(ctx: Context) -> DataFrame:
    """(what, n): vertices and classes of the full neighbourhood and the k and t beyond which none is new."""
    full, k = reach.fixpoint(ctx.ws, ctx.arc, ctx.seeds)
    lev = ctx.ws.save(types.levels(ctx.ws, full.select("v"), ctx.inst, ctx.sub, None, ctx.unusable, ctx.params.use_top), "all-levels")
    t = lev.groupBy("class").agg(F.min("level").alias("l")).agg(F.max("l")).first()[0] or 0
    rows = [("neighbours", full.select("v").distinct().count()), ("classes", lev.select("class").distinct().count()), ("k", int(k)), ("t", int(t))]
    return ctx.spark.createDataFrame(rows, "what string, n long")


def seed_composition(labels: DataFrame) -> DataFrame:
    """(label, origin, n) of labelled seeds, with totals."""
    return labels.rollup("label", "origin").agg(F.count("*").alias("n"))


def recall(found: DataFrame, all_: DataFrame, on: str = "feature") -> DataFrame:
    """(both, wanted): how many of the exhaustive run's features were found."""
    return all_.select(on).distinct().join(found.select(on).distinct().withColumn("hit", F.lit(1)), on, "left").agg(F.count("hit").alias("both"), F.count("*").alias("wanted"))


def guidance(spark: SparkSession, ctx: Context) -> DataFrame:
    """(what, n): what helps to choose parameters: quantiles of degrees for d, depth of classes for t,
    hops to the full neighbourhood for k."""
    deg = degree.degrees(ctx.arc, ctx.params.u)
    at = [f"percentile_disc({x}) WITHIN GROUP (ORDER BY n)" for x in (0.5, 0.9, 0.99)]
    q = deg.agg(*(F.expr(x) for x in at), F.max("n")).first()
    sat = {r["what"]: r["n"] for r in saturation(ctx).collect()}
    rows = [*zip(("degree_p50", "degree_p90", "degree_p99", "degree_max"), (int(x or 0) for x in q), strict=True), ("k_full", sat["k"]), ("t_full", sat["t"])]
    return spark.createDataFrame(rows, "what string, n long")


class Cost:
    """What the jobs of a block of code used: wall seconds, and of all its stages the executors' CPU and run
    seconds, peak execution memory of a stage, spill, shuffled and written bytes. The figures are those that
    the session keeps of its stages (``spark.ui.retainedStages`` of them)."""

    def __init__(self, spark: SparkSession):
        sc = spark.sparkContext
        self.store, self.rest = sc._jsc.sc().statusStore(), (None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
        self.bus = sc._jsc.sc().listenerBus()
        self.values: dict[str, float] = {}

    def _stages(self) -> dict[tuple[int, int], object]:
        self.bus.waitUntilEmpty()
        rows = self.store.stageList(*self.rest)
        return {(r.stageId(), r.attemptId()): r for r in (rows.apply(i) for i in range(rows.size()))}

    def __enter__(self) -> Cost:
        self.before, self.start = set(self._stages()), time.perf_counter()
        return self

    def __exit__(self, *_: object) -> None:
        seconds = time.perf_counter() - self.start
        new = [r for k, r in self._stages().items() if k not in self.before]
        total = lambda name: sum(getattr(r, name)() for r in new)
        self.values = {
            "seconds": round(seconds, 2), "stages": len(new), "cpu_seconds": round(total("executorCpuTime") / 1e9, 2), "run_seconds": round(total("executorRunTime") / 1e3, 2),
            "peak_stage_memory_mb": round(max((r.peakExecutionMemory() for r in new), default=0) / 1e6, 2), "spill_mb": round((total("memoryBytesSpilled") + total("diskBytesSpilled")) / 1e6, 2),
            "shuffle_write_mb": round(total("shuffleWriteBytes") / 1e6, 2), "output_mb": round(total("outputBytes") / 1e6, 2),
        }
