"""Reading triples and writing results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TRIPLE = "s string, p string, o string"
#: one line of N-Triples: subject, predicate, object, full stop
LINE = r"^\s*(<[^>]*>|_:\S+)\s+(<[^>]*>)\s+(<[^>]*>|_:\S+|\"(?:[^\"\\]|\\.)*\"(?:@[A-Za-z0-9-]+|\^\^<[^>]*>)?)\s*\.\s*(?:#.*)?$"


def read_ntriples(spark: SparkSession, path: str, keep_bad: bool = False) -> DataFrame:
    """(s, p, o, is_literal) of N-Triples text; with keep_bad also ``bad``, the lines that do not parse.

    Angle brackets are taken off; blank lines and comments are left out.
    """
    line = F.col("value")
    rows = spark.read.text(path).filter(~line.rlike(r"^\s*(#.*)?$"))
    got = [F.regexp_extract(line, LINE, i) for i in (1, 2, 3)]
    plain = [F.regexp_replace(g, r"^<|>$", "") for g in got]
    out = rows.select(*(F.when(got[0] != "", p).alias(n) for p, n in zip(plain, "spo", strict=True)), got[2].startswith('"').alias("is_literal"), F.when(got[0] == "", line).alias("bad"))
    return out if keep_bad else out.filter("bad is null").drop("bad")


def read_triples(spark: SparkSession, path: str, fmt: str = "parquet", **options: str) -> DataFrame:
    """Triples from Parquet, ORC, JSON or CSV with columns s, p, o (a set is made of them later)."""
    return spark.read.format(fmt).schema(TRIPLE).options(**options).load(path)


def drop_literals(triples: DataFrame, is_literal: str = "is_literal") -> DataFrame:
    """Arcs to vertices only."""
    return triples.filter(~F.coalesce(F.col(is_literal), F.lit(False))).select("s", "p", "o")


def write(result, path: str, fmt: str = "parquet") -> None:
    """Features by length, the matrix, and the vertices' names, below one folder."""
    result.features().write.format(fmt).partitionBy("len").save(f"{path}/features")
    result.matrix().write.format(fmt).save(f"{path}/matrix")
    result.context.vertex().write.format(fmt).save(f"{path}/vertices")


def write_sparse_text(result, path: str) -> None:
    """One line a seed: the seed and its sorted feature ids, as sparse-vector text."""
    cells = result.named_matrix().groupBy("seed").agg(F.array_sort(F.collect_set("feature")).alias("f"))
    cells.select(F.concat_ws(" ", F.col("seed"), F.array_join(F.transform("f", lambda x: F.concat(F.xxhash64(x).cast("string"), F.lit(":1"))), " "))).write.text(path)
