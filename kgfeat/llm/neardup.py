"""Near-duplicates by exact Jaccard similarity of word shingles: SimHash links first, then what they miss.

Texts are sets of hashed ``shingle``-word runs, lower-cased (A-Z). Rows with equal sets form a class; only
one text of a class takes part. A link is an exact Jaccard similarity of ``least`` or more. Pairs to
verify come from two searches:

1. SimHash fingerprints of the sets that differ in ``max_bits`` or fewer bits, through the pivot
   distance tables of ``simhash``. These are the closest pairs: at a Jaccard similarity of 0.8 a pair
   of 64-bit SimHash fingerprints differs in about ten bits, and no radius catches nearly all such
   pairs and leaves unrelated ones out. So this search alone cannot give the right groups.
2. Classes have ``BANDS`` keys, each made of ``ROWS`` minima of the set under fixed permutations, and meet
   in a cell where they share one. A pair of Jaccard 0.8 misses every cell with probability
   (1 - 0.8^4)^32 = 5e-8, more alike pairs less often. Cells whose classes are in one group already link
   nothing more. In the others the class of least key is compared with all that are not in its group,
   and in cells of several groups after that, every class not yet linked, as a spanning forest, cells
   above ``cell_rows`` in pairs of chunks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.llm import simhash
from kgfeat.llm.text import sent_if_few, words_of
from kgfeat.operators.canon import components
from kgfeat.plans.state import Workspace

SHINGLE, LEAST = 5, 0.8
BANDS, ROWS = 32, 4
#: odd multipliers, one a permutation
MULTIPLIERS = np.random.default_rng(42).integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_set(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of the shingles; a text of fewer words is one shingle, no words none."""
    w = words_of(text)
    if not w:
        return np.zeros(0, np.uint64)
    w = b" ".join(w).lower().split(b" ")
    h = xxhash.xxh64_intdigest
    grams = map(b" ".join, zip(*(w[k:] for k in range(shingle)), strict=False)) if len(w) >= shingle else [b" ".join(w)]
    return np.unique(np.fromiter((h(g, 42) for g in grams), np.uint64, count=max(1, len(w) - shingle + 1)))


def band_keys(s: np.ndarray) -> list[int]:
    """The fingerprints of a set as signed longs, none for the empty set."""
    if not len(s):
        return []
    least = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(s), 2048):  # very long texts: a slice at a time
        x = s[at : at + 2048, None] * MULTIPLIERS
        np.minimum(least, (x ^ (x >> np.uint64(32))).min(axis=0), out=least)
    part = least.reshape(BANDS, ROWS)
    return [xxhash.xxh64_intdigest(part[b].tobytes(), b) - (1 << 63) for b in range(BANDS)]


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / max(1, len(a) + len(b) - both)


def forest(sets: list[np.ndarray], least: float = LEAST) -> list[tuple[int, int]]:
    """Spanning forest of the links among the sets, as index pairs."""
    size = np.array([len(s) for s in sets])
    code = np.unique(np.concatenate(sets), return_inverse=True)[1]
    starts = np.concatenate(([0], np.cumsum(size)[:-1]))
    mark = np.zeros(int(code.max()) + 1, np.int64)
    rest, out = np.arange(len(sets)), []
    while len(rest) > 1:
        todo, rest = [int(rest[0])], rest[1:]
        while todo and len(rest):
            x = todo.pop()
            mine = code[starts[x] : starts[x] + size[x]]
            mark[mine] = 1
            both = np.add.reduceat(mark[code], starts)[rest]
            mark[mine] = 0
            hit = rest[both >= least * (size[x] + size[rest] - both)]
            out += [(x, int(y)) for y in hit]
            todo += hit.tolist()
            rest = np.setdiff1d(rest, hit, assume_unique=True)
    return out


def sketches(docs: DataFrame, id_col: str, text_col: str, shingle: int = SHINGLE) -> DataFrame:
    """(id, cls, fp, cells): the class of a row's shingle set, its SimHash fingerprint and its keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets = [shingle_set(t.as_py(), shingle) for t in b.column(1)]
            cls = pa.array([xxhash.xxh128_digest(s.tobytes()) for s in sets], pa.binary())
            fp = np.fromiter((simhash.majority(s) for s in sets), np.uint64, count=len(sets))
            yield pa.RecordBatch.from_arrays([b.column(0), cls, pa.array(fp.view(np.int64)), pa.array([band_keys(s) for s in sets], pa.list_(pa.int64()))], names=["id", "cls", "fp", "cells"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t")).mapInArrow(run, f"id {kind}, cls binary, fp long, cells array<long>")


def _groups(spark: SparkSession, ws: Workspace, classes: DataFrame, links: DataFrame) -> DataFrame:
    """(no, c): the group of each class."""
    comp = components(spark, links, ws=ws)
    return ws.save(classes.select("no").join(comp.withColumnRenamed("v", "no"), "no", "left").select("no", F.coalesce("c", "no").alias("c")), "groups")


def _verified(pairs: DataFrame, texts: DataFrame, least: float, shingle: int) -> DataFrame:
    """The pairs (a, b) whose texts are alike enough."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, last = None, np.zeros(0, np.uint64)
        for b in batches:
            keep = []
            for r, (a, ta, tb) in enumerate(zip(b.column(0), b.column(2), b.column(3), strict=True)):
                if a != held:
                    held, last = a, shingle_set(ta.as_py(), shingle)
                if jaccard(last, shingle_set(tb.as_py(), shingle)) >= least:
                    keep.append(r)
            yield b.select([0, 1]).take(pa.array(keep, pa.int64()))

    both = pairs.join(texts.select(F.col("no").alias("b"), F.col("t").alias("tb")), "b").join(texts.select(F.col("no").alias("a"), F.col("t").alias("ta")), "a")
    return both.select("a", "b", "ta", "tb").mapInArrow(compare, "a long, b long")


def near_duplicates(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = LEAST, shingle: int = SHINGLE, max_bits: int = 4, cell_rows: int = 4096, ws: Workspace | None = None) -> DataFrame:
    """(id, component_id): the least id reachable over links, the row itself included.

    Texts without words (null, empty) are one class. A null id takes part but is the least only of a group
    that has no other. Repeated rows give a row each; an empty table an empty result.
    """
    ws = ws or Workspace(spark, "neardup")
    rows = ws.save(sketches(docs, id_col, text_col, shingle), "sketches")
    classes = rows.groupBy("cls").agg(F.min("id").alias("id"), F.first("fp").alias("fp"), F.first("cells").alias("cells"))
    classes = ws.save(classes.withColumn("no", F.monotonically_increasing_id()), "classes")

    # closest pairs by SimHash: forest of the fingerprints' links, and classes of one fingerprint
    of_fp = ws.save(classes.groupBy("fp").agg(F.min("no").alias("rep")), "fingerprints")
    near = simhash.links(ws, of_fp.select("fp"), of_fp.count(), max_bits)
    ends = [of_fp.select(F.col("fp").alias(x), F.col("rep").alias(f"r{x}")) for x in "ab"]
    close = near.join(ends[0], "a").join(ends[1], "b").select(F.col("ra").alias("a"), F.col("rb").alias("b"))
    close = ws.save(close.union(classes.join(of_fp, "fp").filter("no <> rep").select(F.col("rep").alias("a"), F.col("no").alias("b"))), "close")
    texts = ws.save(_texts(ws, docs, id_col, text_col, classes, close.select("a").union(close.select("b"))), "texts")
    links = ws.save(_verified(close, texts, least, shingle), "links")
    ws.drop(texts)
    named = _groups(spark, ws, classes, links)

    # cells of several groups; those of the same classes link the same, and one of them stays
    cells = classes.select("no", "cells").join(named, "no").select("no", "c", F.explode("cells").alias("cell"))
    met = cells.groupBy("cell").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).filter("lo <> hi").select("cell")
    member = ws.save(cells.join(ws.save(met, "met"), "cell"), "met-members")
    one = member.groupBy("cell").agg(F.count("*").alias("m"), F.min("no").alias("top"), F.min_by("c", "no").alias("ctop"), F.bit_xor(F.xxhash64("no")).alias("x"))
    one = ws.save(one.groupBy("m", "top", "ctop", "x").agg(F.min("cell").alias("cell")).select("cell", "m", "top", "ctop"), "cells")
    member = ws.save(member.join(one, "cell"), "members")
    texts = ws.save(_texts(ws, docs, id_col, text_col, classes, member.select("no")), "texts")
    pairs = member.filter("c <> ctop").select(F.col("top").alias("a"), F.col("no").alias("b")).distinct()
    links = links.union(ws.save(_verified(pairs, texts, least, shingle), "more-links"))
    named = _groups(spark, ws, classes, links)
    # a cell of two is settled; one of several groups is not
    left = member.filter("m > 2").select("cell", "m", "no").join(named, "no")
    open_cells = ws.save(left.groupBy("cell").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).filter("lo <> hi").select("cell"), "open")
    if not open_cells.isEmpty():
        links = links.union(ws.save(_within(left.join(open_cells, "cell"), texts, least, shingle, cell_rows), "cell-links"))
        named = _groups(spark, ws, classes, links)
    ws.drop(texts)
    ws.drop(member)
    named = classes.select("cls", "no", "id").join(named, "no")
    table = ws.save(named.join(ws.save(named.groupBy("c").agg(F.min("id").alias("component_id")), "least"), "c").select("cls", "component_id"), "components")
    return rows.select("id", "cls").join(table, "cls", "left").select("id", "component_id")


def _texts(ws: Workspace, docs: DataFrame, id_col: str, text_col: str, classes: DataFrame, asked: DataFrame) -> DataFrame:
    """(no, t): one text of each class asked for (a column of their numbers)."""
    wanted = ws.save(classes.join(asked.toDF("no").distinct(), "no").select("no", F.col("id").alias("want")), "wanted")
    rows = docs.select(F.col(id_col).alias("own"), F.col(text_col).alias("t")).join(sent_if_few(wanted), F.col("own").eqNullSafe(F.col("want")))
    return rows.dropDuplicates(["no"]).select("no", "t")


def _within(member: DataFrame, texts: DataFrame, least: float, shingle: int, cell_rows: int) -> DataFrame:
    """(a, b): spanning forests of the links in each cell of (cell, m, no)."""
    chunks = F.ceil(F.col("m") / cell_rows).cast("int")
    part = member.select("cell", "no", chunks.alias("n"), F.pmod(F.xxhash64("no"), chunks).cast("int").alias("k"))
    part = part.select("cell", "no", "k", F.explode(F.sequence(F.lit(0), F.col("n") - 1)).alias("o"))
    part = part.select("cell", "no", F.least("k", "o").alias("i"), F.greatest("k", "o").alias("j")).join(texts, "no").select("cell", "i", "j", "no", "t")
    keys = ["cell", "i", "j"]

    def within(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rest = None
        for last, pdf in simhash._ends(batches):
            pdf = pdf if rest is None else pd.concat([rest, pdf], ignore_index=True)
            if not len(pdf):
                continue
            new = np.ones(len(pdf), bool)
            new[1:] = np.logical_or.reduce([pdf[k].values[1:] != pdf[k].values[:-1] for k in keys])
            starts = np.flatnonzero(new)
            if not last:  # the last cell may go on
                pdf, rest, starts = pdf.iloc[: starts[-1]], pdf.iloc[starts[-1] :], starts[:-1]
            a, b = [], []
            for s, e in zip(starts, np.append(starts[1:], len(pdf)), strict=True):
                no = pdf["no"].values[s:e]
                for x, y in forest([shingle_set(t, shingle) for t in pdf["t"].values[s:e]], least):
                    a.append(no[x])
                    b.append(no[y])
            yield pd.DataFrame({"a": pd.Series(a, dtype="int64"), "b": pd.Series(b, dtype="int64")})

    return part.repartition(*keys).sortWithinPartitions(*keys).mapInPandas(within, "a long, b long").distinct()


def one_of_each(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", ws: Workspace | None = None, **how: object) -> DataFrame:
    """``simhash.one_of_each`` with the groups of this module."""
    return simhash.one_of_each(spark, docs, id_col, text_col, ws or Workspace(spark, "neardup"), near_duplicates, **how)
