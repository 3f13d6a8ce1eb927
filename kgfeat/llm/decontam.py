"""Benchmark decontamination: rare word n-grams seed candidate pairs of a document and a test item,
Smith-Waterman alignment of the words scores them.

Words are runs of letters and digits, lower-cased. One pass over all documents looks every n-gram of
every item up, adds up how many documents hold it, and keeps around the hits on an item a window of
word numbers (no text), unless the words that window and item share are too few for the score asked,
whatever their order: that test loses nothing. An item's seeds are the rarest ``SHARE`` of its n-grams
found in documents. Windows with a seed are aligned with the item, and so are the others that passed
the test: copies whose own n-grams are commoner than the item's other ones have no seed, and leaving
them out would lose them. The score is the share of the best possible score.
An item of fewer than n words is one gram of its own length. Items are taken in blocks of bounded
size against all documents, so what is sent to executors never exceeds ``block_words`` words of items.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, types as T
from pyspark.sql import functions as F

from kgfeat.llm.text import given_back, neutral, row_key, sent_if_few
from kgfeat.plans.state import Workspace

WORD = re.compile(r"[^\W_]+")
MATCH, MISMATCH, GAP = 2, -1, -1
N, SCORE, SHARE, BLOCK_WORDS = 4, 0.5, 0.5, 250_000


def norm_words(text: str | None) -> list[str]:
    return WORD.findall(text.lower()) if text else []


class Items:
    """A block of test items with their n-grams; travels to the executors."""

    def __init__(self, rows: list[tuple[object, str | None]], n: int = N):
        self.rows = [(i, w) for i, t in rows if (w := norm_words(t))]
        self.vocab: dict[str, int] = {}
        self.ids = [np.array([self.vocab.setdefault(w, len(self.vocab) + 1) for w in words], np.int64) for _, words in self.rows]
        self.tables: list[tuple[int, np.ndarray, np.ndarray, int]] = []  # length, codes in order, their grams, number of the first
        places = []
        for size in range(1, n + 1):
            mine = [k for k, a in enumerate(self.ids) if min(len(a), n) == size]
            if not mine:
                continue
            all_ = np.concatenate([np.lib.stride_tricks.sliding_window_view(self.ids[k], size) for k in mine])
            keys, gram = np.unique(all_, axis=0, return_inverse=True)
            first = self.tables[-1][3] + len(self.tables[-1][1]) if self.tables else 0
            code = self.mixed([keys[:, j] for j in range(size)])
            order = np.argsort(code, kind="stable")
            self.tables.append((size, code[order], keys[order], first))
            rank = np.empty(len(order), np.int64)
            rank[order] = np.arange(len(order))
            item = np.concatenate([np.full(len(self.ids[k]) - size + 1, k) for k in mine])
            off = np.concatenate([np.arange(len(self.ids[k]) - size + 1) for k in mine])
            places.append(np.stack([first + rank[gram.ravel()], item, off], axis=1))
        at = np.concatenate(places) if places else np.zeros((0, 3), np.int64)
        at = at[np.argsort(at[:, 0], kind="stable")]
        self.where = at[:, 1:]  # (item, offset) of gram g: rows start[g] to start[g + 1]
        self.start = np.concatenate(([0], np.cumsum(np.bincount(at[:, 0])))) if len(at) else np.zeros(1, np.int64)

    @staticmethod
    def mixed(cols: list[np.ndarray]) -> np.ndarray:
        """64-bit code of the columns, to look n-grams up by; hits are compared in full."""
        h = np.zeros(len(cols[0]), np.uint64)
        for c in cols:
            h = (h ^ c.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(29)
        return h

    def word_ids(self, words: list[str]) -> np.ndarray:
        get = self.vocab.get
        return np.fromiter((get(w, 0) for w in words), np.int64, count=len(words))

    def hits(self, a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions of the words a at which an item's n-gram begins, and its number."""
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        known = a > 0
        for size, codes, keys, first in self.tables:
            m = len(a) - size + 1
            if m <= 0:
                continue
            run = known[:m].copy()
            for j in range(1, size):
                run &= known[j : m + j]
            pos = np.flatnonzero(run)
            if not len(pos):
                continue
            cols = [a[pos + j] for j in range(size)]
            code = self.mixed(cols)
            at = np.minimum(np.searchsorted(codes, code), len(codes) - 1)
            ok = codes[at] == code
            for j in range(size):
                ok &= keys[at, j] == cols[j]
            out.append((pos[ok], first + at[ok]))
        return np.concatenate([p for p, _ in out]), np.concatenate([g for _, g in out])

    def seeds(self, df: np.ndarray, share: float = SHARE) -> set[tuple[int, int]]:
        """(item, gram): of an item's grams found (df above 0) the rarest share, the lower numbers on ties."""
        gram = np.repeat(np.arange(len(self.start) - 1), np.diff(self.start))
        pairs = np.unique(np.stack([self.where[:, 0], gram], axis=1), axis=0)
        pairs = pairs[df[pairs[:, 1]] > 0]
        out = set()
        for mine in np.split(pairs, np.flatnonzero(np.diff(pairs[:, 0])) + 1) if len(pairs) else []:
            k, gs = int(mine[0, 0]), mine[:, 1]
            rarest = gs[np.argsort(df[gs], kind="stable")][: math.ceil(share * len(gs))]
            out |= {(k, g) for g in rarest.tolist()}
        return out


def align(a: np.ndarray, b: np.ndarray) -> tuple[int, int, int]:
    """Smith-Waterman local alignment with a linear gap: best score, and where in b it ends, begins.

    Rows are vectors: the running maximum of h + gap * j carries gaps along a row.
    """
    m = len(b)
    ramp = -GAP * np.arange(m + 1)
    h, beg = np.zeros(m + 1, np.int64), np.arange(m + 1)
    best, best_end, best_beg = 0, 0, 0
    for x in a:
        diag = h[:-1] + np.where(b == x, MATCH, MISMATCH)
        up = h[1:] + GAP
        take = diag >= up
        cur, cbeg = np.where(take, diag, up), np.where(take, beg[:-1], beg[1:])
        cur, cbeg = np.concatenate(([0], cur)), np.concatenate(([0], cbeg))
        fresh = cur <= 0
        cur[fresh], cbeg[fresh] = 0, np.flatnonzero(fresh)
        lifted = cur + ramp
        top = np.maximum.accumulate(lifted)
        src = np.maximum.accumulate(np.where(lifted == top, np.arange(m + 1), 0))
        h, beg = top - ramp, cbeg[src]
        j = int(h.argmax())
        if h[j] > best:
            best, best_end, best_beg = int(h[j]), j, int(beg[j])
    return best, best_end, best_beg


def within_reach(item: np.ndarray, part: np.ndarray, score: float) -> bool:
    """False if no alignment of the item with these words can have the score: matched words are in both."""
    return min(np.isin(part, item).sum(), np.isin(item, part).sum()) >= score * len(item)


def windows(items: Items, a: np.ndarray, pos: np.ndarray, gram: np.ndarray, score: float = SCORE) -> Iterator[tuple[int, list[int], list[list[int]], list[int]]]:
    """(item, beginnings, windows, grams hit) of the items that the hits (pos, gram) in the words a lead to
    and that some window may have the score with."""
    spots, grams = defaultdict(list), defaultdict(list)
    for p, g in zip(pos.tolist(), gram.tolist(), strict=True):
        for k, off in items.where[items.start[g] : items.start[g + 1]].tolist():
            spots[k].append(p - off)
            grams[k].append(g)
    for k, starts in spots.items():
        item, size = items.ids[k], len(items.ids[k])
        slack = size // 2 + 2 if size > 1 else 0
        starts.sort()
        lo = hi = None
        spans = []
        for s in starts:
            if hi is not None and s - slack <= hi and hi - lo <= 4 * size:
                hi = max(hi, s + size + slack)
            else:
                if hi is not None:
                    spans.append((lo, hi))
                lo, hi = s - slack, s + size + slack
        spans.append((lo, hi))
        spans = [(max(lo, 0), min(hi, len(a))) for lo, hi in spans]
        spans = [(lo, hi) for lo, hi in spans if within_reach(item, a[lo:hi], score)]
        if spans:
            yield k, [lo for lo, _ in spans], [a[lo:hi].tolist() for lo, hi in spans], grams[k]


def best_of(item: np.ndarray, los: list[int], parts: list[list[int]]) -> tuple[float, int, int]:
    """(score, first word, end word) of the best alignment, the first of equals."""
    found = (0.0, 0, 0)
    for lo, part in zip(los, parts, strict=True):
        got, end, beg = align(item, np.array(part, np.int64))
        found = max(found, (got / (MATCH * len(item)), -(lo + beg), lo + end))
    return found[0], -found[1], found[2]


def _blocks(spark: SparkSession, items: DataFrame, item_id: str, item_text: str, block_words: int) -> Iterator[list[tuple[object, str | None]]]:
    """The items in blocks of about block_words words; one block at a time is on the driver."""
    src = items.select(F.col(item_id).alias("i"), F.col(item_text).alias("t")).filter("t is not null").distinct()
    words = src.agg(F.sum(F.length("t"))).first()[0] or 0
    n = max(1, -(-words // (5 * block_words)))
    for b in range(n):
        rows = src.filter(F.pmod(F.xxhash64("i", "t"), F.lit(n)) == b).collect()
        yield sorted(((r["i"], r["t"]) for r in rows), key=lambda r: (str(r[0]), r[1]))


def leaks(spark: SparkSession, docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text", n: int = N, score: float = SCORE, block_words: int = BLOCK_WORDS, ws: Workspace | None = None) -> DataFrame:
    """(id, item_id, n_seeds, score, first_word, end_word): documents that hold a test item.

    Every document is read against every item. Null and empty texts match nothing, nor do items without
    a word; an item of fewer than n words matches where it stands whole. A null id is carried as it is.
    Rows with equal ids each give their own matches; equal item rows count once. Of several places of
    an item in a text the best alignment is given, the first of equals. Other columns play no part. No
    items or no documents: an empty result. Driver memory: a block of items and a count for each of its grams.
    """
    ws = ws or Workspace(spark, "decontam")
    src = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("t")).filter("t is not null")
    kind, ikind = src.schema["id"].dataType, items.schema[item_id].dataType
    schema = T.StructType([T.StructField("id", kind), T.StructField("item_id", ikind), T.StructField("n_seeds", T.IntegerType()), T.StructField("score", T.DoubleType()), T.StructField("first_word", T.IntegerType()), T.StructField("end_word", T.IntegerType())])
    found = T.StructType([T.StructField("id", kind), T.StructField("k", T.IntegerType()), T.StructField("los", T.ArrayType(T.IntegerType())), T.StructField("parts", T.ArrayType(T.ArrayType(T.IntegerType()))), T.StructField("grams", T.ArrayType(T.LongType()))])

    from pyspark.sql.pandas.types import to_arrow_schema

    out = None
    for rows in _blocks(spark, items, item_id, item_text, block_words):
        block = Items(rows, n)
        sent = spark.sparkContext.broadcast(block)

        def scan(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            """Windows of items in documents; at last rows of item -1 with the partition's counts of grams."""
            it, held, shape = sent.value, Counter(), to_arrow_schema(found)
            for b in batches:
                got = []
                for i, t in zip(b.column(0), b.column(1), strict=True):
                    a = it.word_ids(norm_words(t.as_py()))
                    pos, gram = it.hits(a)
                    if len(pos):
                        held.update(np.unique(gram).tolist())
                        ident = i.as_py()
                        got += [(ident, *w) for w in windows(it, a, pos, gram, score)]
                if got:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*got, strict=True), shape, strict=True)], schema=shape)
            if held:
                counts = [None, -1, [], [list(held.values())], list(held)]
                yield pa.RecordBatch.from_arrays([pa.array([c], f.type) for c, f in zip(counts, shape, strict=True)], schema=shape)

        hit = ws.save(src.mapInArrow(scan, found), "windows")
        each = hit.filter("k = -1").select(F.explode(F.arrays_zip("grams", F.col("parts")[0].alias("n"))).alias("x"))
        df = np.zeros(len(block.start) - 1, np.int64)
        for r in each.groupBy("x.grams").agg(F.sum("x.n").alias("n")).collect():  # at most the grams of the block
            df[r["grams"]] = r["n"]
        seeds = spark.sparkContext.broadcast(block.seeds(df))

        def score_all(batches: Iterator[pa.RecordBatch], sent=sent, seeds=seeds) -> Iterator[pa.RecordBatch]:
            it, sd, shape = sent.value, seeds.value, to_arrow_schema(schema)
            for b in batches:
                got = []
                for i, k, los, parts, grams in zip(*(c.to_pylist() for c in b.columns), strict=True):
                    s, first, end = best_of(it.ids[k], los, parts)
                    if s >= score:
                        got.append((i, it.rows[k][0], sum((k, g) in sd for g in grams), round(s, 6), first, end))
                if got:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*got, strict=True), shape, strict=True)], schema=shape)

        part = ws.save(hit.filter("k >= 0").mapInArrow(score_all, schema), "matches")
        ws.drop(hit)
        out = part if out is None else out.union(part)
    return out


def clean_documents(spark: SparkSession, docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", ws: Workspace | None = None, **how: object) -> DataFrame:
    """The rows of docs that have no match, all columns. Rows without text or id stay unless they match;
    of rows that share an id only those with a match go, and repeated rows stay or go together."""
    d, (i, t) = neutral(docs, id_col, text_col)
    keyed = d.withColumn("key", row_key(i, t))
    ws = ws or Workspace(spark, "decontam")
    bad = ws.save(leaks(spark, keyed, items, "key", t, ws=ws, **how).select(F.col("id").alias("bad")).distinct(), "bad")
    return given_back(keyed.join(sent_if_few(bad), F.col("key") == F.col("bad"), "left_anti"), docs)
