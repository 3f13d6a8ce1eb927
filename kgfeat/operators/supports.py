"""Support sets as rows of (set, seed): no row and no task ever holds a whole set.

A set's id is made of its members in any order: two exclusive-or sums of 64-bit hashes and the size.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def set_id(seed: Column | str) -> Column:
    """Aggregate: the id of the set of distinct seeds of a group."""
    s = F.col(seed) if isinstance(seed, str) else seed
    return F.concat_ws("-", F.hex(F.bit_xor(F.xxhash64(s))), F.hex(F.bit_xor(F.xxhash64(s, F.lit(1)))), F.count("*").cast("string"))


def counts(reach: DataFrame, key: str = "v") -> DataFrame:
    """(key, n) where a pair of seed and key stands once."""
    return reach.groupBy(key).agg(F.count("*").alias("n"))


def within(n: Column, l_min: int, l_max: int | None) -> Column:
    return (n >= l_min) if l_max is None else n.between(l_min, l_max)


def unions(member: DataFrame, sset: DataFrame, key: str = "fid") -> DataFrame:
    """(key, seed), each once: the union of the support sets (key, sset) of each key; sset: (sset, seed).

    A key of many sets is spread by seed before anything is gathered.
    """
    return member.select(key, "sset").distinct().join(sset, "sset").select(key, "seed").distinct()


def sized(union: DataFrame, key: str = "fid") -> DataFrame:
    """(key, sset, n) of rows (key, seed)."""
    return union.groupBy(key).agg(set_id("seed").alias("sset"), F.count("*").alias("n"))


def bitmaps(union: DataFrame, dense: DataFrame, key: str = "fid") -> DataFrame:
    """(key, bucket, bits): the sets as bitmaps of 32,768 seeds each, for exports of very large sets.
    dense: (seed, id) with small ids, see ``dictionary.dense_ids``; id 0 has a bucket of its own."""
    at = union.join(dense, "seed")
    return at.groupBy(key, F.bitmap_bucket_number("id").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("id")).alias("bits"))
