"""Mixing sources to target weights: hash-random keys, a range sort within each source, distributed
prefix sums of token counts, and a cut at each source's exact budget, over several epochs if needed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, types as T
from pyspark.sql import functions as F

from kgfeat.operators.prefix import prefix_sums
from kgfeat.llm.text import given_back, key_of, neutral, word_count
from kgfeat.plans.state import Workspace

WEIGHTS = (3.0, 1.0, 2.0)  # by the sources' order, repeating
SHARE, MOST = 1.5, 2.0
BROADCAST_SOURCES = 100_000


def targets(sizes: list[int], weights: list[float], share: float = SHARE, most: float = MOST) -> list[float]:
    """share of all sizes, dealt by weight; none above most times its size, the excess reshared."""
    left, out, open_ = share * sum(sizes), [0.0] * len(sizes), [i for i, n in enumerate(sizes) if n > 0]
    while open_:
        unit = left / sum(weights[i] for i in open_)
        full = [i for i in open_ if weights[i] * unit > most * sizes[i]]
        if not full:
            for i in open_:
                out[i] = weights[i] * unit
            break
        for i in full:
            out[i] = most * sizes[i]
            left -= out[i]
        open_ = [i for i in open_ if i not in set(full)]
    return out


def random_key(ident: Column, seed: int) -> Column:
    """60 bits of MD5 over seed and id."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), key_of(ident))), 1, 15), 16, 10).cast("long")


def mix(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST, seed: int = 7, ws: Workspace | None = None) -> DataFrame:
    """(id, source, size, source_size, target, epochs, taken), one row per row of docs.

    Every document is taken ``epochs`` whole times; the words left of a source's budget after whole
    epochs are taken once more in the order of the hash-random keys, the last document in part, so
    that the words taken from a source equal its target rounded to whole words. Sources are ranked
    by code point, null last. Null and empty texts have size 0 and take 0. Equal rows get equal keys;
    which of them comes first does not change the set of rows. Driver memory: one row a source.
    """
    ws = ws or Workspace(spark, "mixing")
    narrow = docs.select(F.col(id_col).alias("id"), F.col(source_col).alias("source"), key_of(F.col(source_col)).alias("k"), word_count(F.col(text_col)).alias("size"), random_key(F.col(id_col), seed).alias("r"))
    run = prefix_sums(ws, narrow, "k", ["r", "id", "size"], ["size"], "keyed")
    tot = run.groupBy("k").agg(F.sum("size").alias("n")).collect()
    tot.sort(key=lambda r: r["k"])
    goal = targets([r["n"] for r in tot], [weights[i % len(weights)] for i in range(len(tot))], share, most)
    plan = [(r["k"], r["n"], g, round(g) // r["n"] if r["n"] else 0, round(g) % r["n"] if r["n"] else 0) for r, g in zip(tot, goal, strict=True)]
    table = spark.createDataFrame(plan, T.StructType([T.StructField("k", T.StringType()), T.StructField("source_size", T.LongType()), T.StructField("target", T.DoubleType()), T.StructField("epochs", T.LongType()), T.StructField("rest", T.LongType())]))
    part = F.least(F.col("size"), F.greatest(F.lit(0), F.col("rest") - F.col("before_size")))
    return run.join(F.broadcast(table) if len(plan) <= BROADCAST_SOURCES else table, "k").select("id", "source", "size", "source_size", "target", "epochs", part.alias("part"), (F.col("epochs") * F.col("size") + part).alias("taken"))


def mixed_documents(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = 7, ws: Workspace | None = None, **how: object) -> DataFrame:
    """The mix as rows of docs, all columns: each document as often as it is taken; the one at the cut is
    taken whole if at least half of it is, since a document is the unit of this table.

    The texts are not shuffled: each source's budget ends at one hash-random key, and a row compares
    its own key with it. Rows that share an id share the key and are taken equally often. A null source
    is a source of its own; null and empty texts come along with the whole epochs of their source. An
    empty table gives an empty result.
    """
    ws = ws or Workspace(spark, "mixing")
    plan = mix(spark, docs, id_col, text_col, source_col, seed=seed, ws=ws, **how)
    per = ws.save(plan.groupBy(key_of(F.col("source")).alias("k")).agg(F.max("epochs").alias("epochs"), F.max(F.when(2 * F.col("part") >= F.greatest(F.col("size"), F.lit(1)), random_key(F.col("id"), seed))).alias("upto")), "budgets")
    d, (i, s) = neutral(docs, id_col, source_col)
    few = per.count() <= BROADCAST_SOURCES  # one row a source; beyond that the join is left to the planner
    named = d.withColumns({"k": key_of(F.col(s)), "r": random_key(F.col(i), seed)}).join(F.broadcast(per) if few else per, "k")
    times = (F.col("epochs") + F.coalesce((F.col("r") <= F.col("upto")).cast("long"), F.lit(0))).cast("int")
    return given_back(named.filter(times > 0).withColumn("copy", F.explode(F.sequence(F.lit(1), times))), docs)
