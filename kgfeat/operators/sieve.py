"""Semi-joins of very many rows with keys that few of them have.

A bitmap of the keys' hashes goes to all tasks, in segments of 32,768 bits, and discards nearly all rows
where they are read; what passes is joined, so the result is exact whatever the bitmap lets through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FEW = 50_000  # keys that are sent as they are
BITS_A_KEY = 32
MOST_BITS = 1 << 28  # 32 MB; beyond some ten million keys more rows pass


def sift(rows: DataFrame, key: str, keys: DataFrame, n: int) -> DataFrame:
    """rows without most of those whose key (a long) is not in keys, a table with that column of n distinct rows."""
    if n <= FEW:
        return rows.join(F.broadcast(keys.select(key)), key, "left_semi").select(*rows.columns)
    bits = min(MOST_BITS, 1 << (BITS_A_KEY * n - 1).bit_length())
    at = F.xxhash64(F.col(key), F.lit(7)).bitwiseAND(F.lit(bits - 1))
    ones = keys.select(at.alias("at")).select(F.shiftright("at", 6).alias("word"), F.expr("shiftleft(1L, cast(at & 63 AS int))").alias("bits"))
    blank = rows.sparkSession.range(0, bits >> 6, 1, 8).select(F.col("id").alias("word"), F.lit(0).cast("long").alias("bits"))
    words = ones.union(blank).groupBy("word").agg(F.bit_or("bits").alias("bits"))
    segment = words.groupBy(F.shiftright("word", 9).alias("its segment")).agg(F.transform(F.array_sort(F.collect_list(F.struct("word", "bits"))), lambda x: x["bits"]).alias("its words"))
    placed = rows.withColumn("its place", at)
    met = placed.join(F.broadcast(segment), F.shiftright("its place", 15) == F.col("its segment"))
    word = F.get("its words", F.shiftright("its place", 6).bitwiseAND(F.lit(511)).cast("int"))
    return met.filter(F.getbit(word, F.col("its place").bitwiseAND(F.lit(63)).cast("int")) == 1).select(*rows.columns)


def semi(rows: DataFrame, key: str, keys: DataFrame, n: int) -> DataFrame:
    """rows whose key is in keys (n distinct rows). The join is an inner one, for the optimizer moves a left
    semi join below the bitmap, and all rows would be shuffled."""
    out = sift(rows, key, keys, n)
    return out if n <= FEW else out.join(keys.select(key), key).select(*rows.columns)
