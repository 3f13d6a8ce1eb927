"""SimHash near-duplicates: pivot distance tables discard pairs, an exact count of bits verifies them.

Fingerprints: 64 bits over the XXH64 hashes (seed 42) of 4-word shingles. Two fingerprints link at
``max_bits`` or fewer differing bits. The pivot table holds the Hamming distances of each fingerprint
to pseudo-random reference fingerprints. By the triangle inequality the distances of a linked pair to
any reference differ by at most ``max_bits``, so a pair whose largest coordinate difference is greater
is discarded, and survivors are verified.

Distances of unrelated fingerprints to a reference crowd around 32 of 64 bits, so a reference discards
less than half of the pairs and the table by itself would have to be held against all pairs. Which
pairs it is held against is therefore settled by blocks of bits (no part of the pivot method): the
bits are dealt into ``blocks`` groups, a linked pair agrees on all bits of at least
``blocks - max_bits`` groups, so joining on every choice of that many groups brings every linked pair
into a cell. Groups are taken finer as the number of fingerprints grows, so that cells stay small.
README has the number of pairs after each step.

Only distinct fingerprints take part, cells emit a spanning forest of their links rather than all
pairs, and cells above ``cell_rows`` are cut into chunks whose pairs are separate tasks.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.llm.text import given_back, neutral, row_key, sent_if_few, words_of
from kgfeat.operators.canon import components
from kgfeat.plans.state import Workspace

BITS = 64


def fingerprint(text: str | None, shingle: int = 4, seed: int = 42) -> int:
    """SimHash of one text as an unsigned 64-bit number; no words: zero."""
    w = words_of(text)
    if not w:
        return 0
    w = b" ".join(w).lower().split(b" ")  # bytes.lower() changes A-Z alone
    n = len(w) - shingle + 1
    grams = map(b" ".join, zip(*(w[k:] for k in range(shingle)), strict=False)) if n > 0 else [b" ".join(w)]
    h = xxhash.xxh64_intdigest
    return majority(np.fromiter((h(g, seed) for g in grams), "<u8", count=max(n, 1)))


def majority(hashes: np.ndarray) -> int:
    """The bits set in over half of the hashes; no hashes: zero."""
    ones = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), 65536):  # very long texts: bits of a slice at a time
        part = hashes[at : at + 65536]
        ones += np.unpackbits(part.view(np.uint8).reshape(len(part), 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4, seed: int = 42) -> DataFrame:
    """(id, fp): the fingerprint as a signed long. A null text counts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.fromiter((fingerprint(t.as_py(), shingle, seed) for t in b.column(1)), np.uint64, count=b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fp.view(np.int64))], names=["id", "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t")).mapInArrow(run, f"id {kind}, fp long")


def spread_references(n: int = 16) -> np.ndarray:
    """Reference fingerprints by a rule: the first 8 bytes of SHA-256 of 'reference <i>'."""
    return np.array([int.from_bytes(hashlib.sha256(f"reference {i}".encode()).digest()[:8], "little") for i in range(n)], np.uint64)


def distance_table(fp: np.ndarray, refs: np.ndarray) -> np.ndarray:
    """Row i: the Hamming distances of fp[i] to every reference."""
    return np.bitwise_count(fp[:, None] ^ refs[None, :]).astype(np.int8)


def spanning_links(fp: np.ndarray, table: np.ndarray, max_bits: int) -> list[tuple[int, int]]:
    """Spanning forest of the links among one cell's distinct fingerprints, as index pairs."""
    rest, out = np.arange(len(fp)), []
    while len(rest) > 1:
        todo, rest = [rest[0]], rest[1:]
        while todo and len(rest):
            x = todo.pop()
            near = np.abs(table[rest] - table[x]).max(axis=1) <= max_bits
            cand = rest[near]
            hit = cand[np.bitwise_count(fp[cand] ^ fp[x]) <= max_bits]
            if len(hit):
                out += [(int(x), int(y)) for y in hit]
                todo += hit.tolist()
                rest = np.setdiff1d(rest, hit, assume_unique=True)
    return out


def block_count(n: int, max_bits: int, cell_target: int = 2) -> int:
    """The fewest groups of columns for which n random fingerprints put about cell_target into a cell."""
    for blocks in range(max_bits + 1, max_bits + 5):
        if n / 2.0 ** (BITS * (blocks - max_bits) // blocks) <= cell_target:
            return blocks
    return max_bits + 4


def cell_masks(blocks: int, max_bits: int) -> list[int]:
    """One 64-bit mask for each choice of blocks - max_bits groups; group g has the bits i with i % blocks == g."""
    group = [sum(1 << i for i in range(g, BITS, blocks)) for g in range(blocks)]
    return [sum(group[g] for g in c) for c in combinations(range(blocks), blocks - max_bits)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def links(ws: Workspace, distinct_fp: DataFrame, n: int, max_bits: int = 4, references: int = 16, cell_rows: int = 4096, blocks: int | None = None) -> DataFrame:
    """(a, b): links between distinct fingerprints that connect what all links would connect."""
    masks = cell_masks(blocks or block_count(n, max_bits), max_bits)
    cells = distinct_fp.select("fp", F.explode(F.array(*(F.struct(F.lit(k).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("cell")) for k, m in enumerate(masks)))).alias("x")).select("x.t", "x.cell", "fp")
    sizes = cells.groupBy("t", "cell").agg(F.count("*").alias("m")).filter(F.col("m") > cell_rows)
    hot = ws.save(sizes, "hot-cells")
    if not hot.isEmpty():
        chunks = F.ceil(F.col("m") / cell_rows).cast("int")
        mine = F.pmod(F.xxhash64("fp"), chunks).cast("int")
        joined = cells.join(hot, ["t", "cell"], "left")
        plain = joined.filter("m is null").select("t", "cell", F.lit(0).alias("i"), F.lit(0).alias("j"), "fp")
        split = joined.filter("m is not null").withColumn("k", mine).select("t", "cell", "fp", "k", F.explode(F.sequence(F.lit(0), chunks - 1)).alias("o"))
        cells = plain.union(split.select("t", "cell", F.least("k", "o").alias("i"), F.greatest("k", "o").alias("j"), "fp"))
    else:
        cells = cells.select("t", "cell", F.lit(0).alias("i"), F.lit(0).alias("j"), "fp")
    keys = ["t", "cell", "i", "j"]
    refs = spread_references(references)

    def pairs(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rest = None
        for last, pdf in _ends(batches):
            pdf = pdf if rest is None else pd.concat([rest, pdf], ignore_index=True)
            if not len(pdf):
                continue
            new = np.ones(len(pdf), bool)
            new[1:] = np.logical_or.reduce([pdf[k].values[1:] != pdf[k].values[:-1] for k in keys])
            starts = np.flatnonzero(new)
            if not last:  # the last cell may go on
                pdf, rest, starts = pdf.iloc[: starts[-1]], pdf.iloc[starts[-1] :], starts[:-1]
            ends = np.append(starts[1:], len(pdf))
            fp = pdf["fp"].values.view(np.uint64)
            two = starts[ends - starts == 2]
            a, b = fp[two], fp[two + 1]
            ta, tb = distance_table(a, refs), distance_table(b, refs)
            ok = (np.abs(ta - tb).max(axis=1, initial=0) <= max_bits) & (np.bitwise_count(a ^ b) <= max_bits)
            found = [(a[ok], b[ok])]
            for s, e in zip(starts[ends - starts > 2], ends[ends - starts > 2], strict=True):
                cell = fp[s:e]
                if link := spanning_links(cell, distance_table(cell, refs), max_bits):
                    x = np.array(link)
                    found.append((cell[x[:, 0]], cell[x[:, 1]]))
            yield pd.DataFrame({"a": np.concatenate([f[0] for f in found]).view(np.int64), "b": np.concatenate([f[1] for f in found]).view(np.int64)})

    return cells.repartition(*keys).sortWithinPartitions(*keys, "fp").mapInPandas(pairs, "a long, b long").distinct()


def _ends(batches: Iterator[pd.DataFrame]) -> Iterator[tuple[bool, pd.DataFrame]]:
    """Each batch with whether it is the last."""
    held = None
    for x in batches:
        if held is not None:
            yield False, held
        held = x
    if held is not None:
        yield True, held


def near_duplicates(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", max_bits: int = 4, shingle: int = 4, ws: Workspace | None = None, **how: object) -> DataFrame:
    """(id, fp, component_id): the least id reachable over links, the row itself included.

    Null and empty texts have fingerprint zero and link like any other. A null id takes part with
    its text but is never the least id unless its whole component has none. Repeated rows give one
    row each. An empty table gives an empty result.
    """
    ws = ws or Workspace(spark, "simhash")
    fps = ws.save(fingerprints(docs, id_col, text_col, shingle), "fingerprints")
    classes = ws.save(fps.groupBy("fp").agg(F.min("id").alias("least")), "classes")
    near = links(ws, classes.select("fp"), classes.count(), max_bits, **how)
    comp = components(spark, near, ws=ws)
    named = classes.join(comp.withColumnRenamed("v", "fp"), "fp", "left").select("fp", "least", F.coalesce("c", "fp").alias("c"))
    # a table of its own, so that the join may split a large component
    least = ws.save(named.groupBy("c").agg(F.min("least").alias("component_id")), "least")
    table = ws.save(named.join(least, "c").select("fp", "component_id"), "components")
    return fps.join(table, "fp", "left").select("id", "fp", "component_id")


def one_of_each(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", ws: Workspace | None = None, groups=near_duplicates, **how: object) -> DataFrame:
    """The rows of docs with the least id of their group, all columns. Rows that share an id are told
    apart by their text, the least hash first; rows alike in both count as one document, of which one
    stays. A null id comes last. ``groups`` (see near_duplicates) says what is one group."""
    ws = ws or Workspace(spark, "simhash")
    d, (i, t) = neutral(docs, id_col, text_col)
    keyed = d.withColumn("key", row_key(i, t))
    inner = Workspace(spark, "groups")
    group = ws.save(groups(spark, keyed, "key", t, ws=inner, **how).select("id", "component_id"), "rows")
    inner.close()  # all tables on the way to the groups
    gone = ws.save(group.filter(F.col("id") != F.col("component_id")).select(F.col("id").alias("gone")).distinct(), "gone")
    left = keyed.join(sent_if_few(gone), F.col("key") == F.col("gone"), "left_anti")
    rows = group.agg(F.count("*"), F.countDistinct("id")).first()
    return given_back(left if rows[0] == rows[1] else left.dropDuplicates(["key"]), docs)
