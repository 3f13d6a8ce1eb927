"""Contiguous shards of near equal bytes from global prefix sums.

Documents are ordered by content (CRC-32, MD5 of the text, id), so equal texts lie side by side.
Prefix sums of sizes come from per-partition totals; cut j falls at the document edge nearest to
j/n of all bytes. Where such a cut would part a group of equal texts, it moves to the nearer end of
the group if that is within ``slack`` of a shard's size; larger groups are cut, so that sizes stay
near equal.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.llm.text import neutral
from kgfeat.operators.prefix import prefix_sums
from kgfeat.plans.state import Workspace


def assign(spark: SparkSession, docs: DataFrame, n: int = 16, id_col: str = "doc_id", text_col: str = "text", slack: float = 0.02, ws: Workspace | None = None) -> DataFrame:
    """(id, size, text_crc32, shard, slot): one row per row of docs; slots of a shard have no gaps.

    size: UTF-8 bytes plus 1; null text counts as empty. Rows alike in id and text are interchangeable.
    An empty table gives an empty result; with fewer documents than shards some shards stay empty.
    """
    run, firsts = _cut(ws or Workspace(spark, "sharding"), docs, n, id_col, text_col, slack)
    return _placed(run, F.col("before_one"), firsts).select("id", "size", "text_crc32", "shard", "slot")


def shard_documents(spark: SparkSession, docs: DataFrame, n: int = 16, id_col: str = "doc_id", text_col: str = "text", slack: float = 0.02, ws: Workspace | None = None) -> DataFrame:
    """The columns of docs with size, text_crc32, shard and slot, as ``assign`` gives them; columns of
    docs that have one of these four names are left out, all others stay whatever they are called.

    Cuts are found on ids and sizes alone, as row numbers in the common order; then the texts are
    sorted into that order once, and numbered by partition.
    """
    ws = ws or Workspace(spark, "sharding")
    _, firsts = _cut(ws, docs, n, id_col, text_col, slack)
    d, (i, x) = neutral(docs, id_col, text_col)
    t = F.coalesce(F.col(x), F.lit(""))
    full = d.withColumns({"size": (F.octet_length(t) + 1).cast("long"), "text_crc32": F.crc32(t), "h": F.md5(t)})
    keys = ["text_crc32", "h", i]
    full = ws.save(full.repartitionByRange(*keys).sortWithinPartitions(*keys).drop("h").withColumn("at", F.monotonically_increasing_id()), "sorted")
    part, row = F.shiftright("at", 33), F.col("at").bitwiseAND(F.lit((1 << 33) - 1))  # as that function is defined
    offsets, before = [], 0
    for r in sorted(full.groupBy(part.alias("part")).agg(F.count("*").alias("m")).collect()):  # one row a partition
        offsets.append((r["part"], before))
        before += r["m"]
    at = spark.createDataFrame(offsets, "part long, before long")
    numbered = full.withColumn("part", part).join(F.broadcast(at), "part")
    own = ("size", "text_crc32", "shard", "slot")
    keep = [F.col(f"c{k}").alias(c) for k, c in enumerate(docs.columns) if c.casefold() not in own]
    return _placed(numbered, F.col("before") + row, firsts).select(*keep, *own)


def _placed(rows: DataFrame, number: Column, firsts: list[int]) -> DataFrame:
    """rows with shard and slot, from a row's number in the order and the number of each shard's first row."""
    shard = F.lit(0)
    for c in firsts[1:]:
        shard = shard + (number >= F.lit(c)).cast("int")
    return rows.withColumn("shard", shard).withColumn("slot", number - F.element_at(F.array(*(F.lit(x).cast("long") for x in firsts)), F.col("shard") + 1))


def _cut(ws: Workspace, docs: DataFrame, n: int, id_col: str, text_col: str, slack: float) -> tuple[DataFrame, list[int]]:
    """Prefix sums over ids and sizes, and the row number at which each shard begins."""
    t = F.coalesce(F.col(text_col), F.lit(""))
    narrow = docs.select(F.col(id_col).alias("id"), (F.octet_length(t) + 1).cast("long").alias("size"), F.crc32(t).alias("text_crc32"), F.md5(t).alias("h"), F.lit(1).cast("long").alias("one"))
    run = prefix_sums(ws, narrow, None, ["text_crc32", "h", "id"], ["size", "one"], "ordered").drop("one")
    total = run.agg(F.max(F.col("before_size") + F.col("size"))).first()[0] or 0
    aims = [total * j / n for j in range(1, n)]
    if not total or not aims:
        return run, [0] * n
    end = F.col("before_size") + F.col("size")
    # the document in which an aim falls: at most n - 1 rows
    at = F.array(*(F.lit(float(a)) for a in aims))
    edge = run.filter(F.exists(at, lambda a: (F.col("before_size") <= a) & (a < end))).select("text_crc32", "h", F.col("before_size").alias("s"), end.alias("e")).collect()
    keys = F.lit(False)
    for c, h in {(r["text_crc32"], r["h"]) for r in edge}:
        keys = keys | ((F.col("text_crc32") == c) & (F.col("h") == h))
    spans = {(r["text_crc32"], r["h"]): (r["s"], r["e"]) for r in run.filter(keys).groupBy("text_crc32", "h").agg(F.min("before_size").alias("s"), F.max(end).alias("e")).collect()}
    cuts = []
    for a in aims:
        r = next(r for r in edge if r["s"] <= a < r["e"])
        nearer = lambda s, e, a=a: s if a - s <= e - a else e
        g = nearer(*spans[r["text_crc32"], r["h"]])
        cuts.append(g if abs(g - a) <= slack * total / n else nearer(r["s"], r["e"]))
    below = run.agg(*(F.sum((F.col("before_size") < c).cast("long")).alias(f"c{j}") for j, c in enumerate(cuts))).first()
    return run, [0, *below]


def write_shards(docs_with_shard: DataFrame, path: str, rows_a_file: int = 1_000_000) -> None:
    """One folder a shard. Ranges of (shard, slot) are written side by side, so a shard is many files
    whose rows, in the order of file names, are in slot order; no task writes a whole shard."""
    parts = docs_with_shard.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot")
    parts.write.option("maxRecordsPerFile", rows_a_file).partitionBy("shard").parquet(path)
