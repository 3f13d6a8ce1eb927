"""The Boolean matrix of seeds and features, kept as its true cells."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def build(features: DataFrame, sset: DataFrame) -> DataFrame:
    """(seed, fid): one row a true cell; features (fid, sset), sset (sset, seed)."""
    return features.select("fid", "sset").join(sset.select("sset", "seed"), "sset").select("seed", "fid")


def wide(cells: DataFrame, columns: list, max_cols: int = 1000) -> DataFrame:
    """One row a seed, one Boolean column a given feature."""
    if len(columns) > max_cols:
        raise ValueError(f"{len(columns)} columns asked for, {max_cols} allowed")
    names = [str(c) for c in columns]
    got = cells.withColumn("fid", F.col("fid").cast("string")).groupBy("seed").pivot("fid", names).agg(F.lit(True))
    return got.na.fill(False, names)


def csr(cells: DataFrame) -> DataFrame:
    """(seed, features): sorted feature ids of each seed, for seeds whose features fit a row."""
    return cells.groupBy("seed").agg(F.array_sort(F.collect_set("fid")).alias("features"))
