"""Risk-controlled quality thresholds.

Each rule rejects a text whose statistic exceeds a cutoff. Labelled rows are dealt into a tuning fold
(one in ``FOLDS``, by a hash of the id) and holdouts. The tuning fold, all strata together, only orders
the (rule, cutoff) steps, from those that reject fewest good texts on; a configuration is a beginning
of this path, and a text is rejected at the first step whose cutoff it exceeds. What is certified is
the verdict of all rules together: within a stratum (the language) the false rejections of a
configuration among the good holdouts are binomial, and it is certified if the exact binomial test
rejects "the false rejection rate is above alpha" at level delta / strata (Bonferroni over strata;
along the path the tests are in fixed sequence, which needs no further correction). So with
probability 1 - delta no stratum loses more than alpha of its good texts to the cutoffs. Strata with
too few good holdouts to certify even a configuration that rejects none of them are pooled, and the
bound then holds for the pool. Among certified configurations the one with the most bad texts rejected
less ``PRICE`` times the good ones is used, the laxest on ties, so no good text is given up for little.
Exact test: P(Bin(n, alpha) <= k) <= level, which is the Clopper-Pearson upper bound being <= alpha.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, types as T
from pyspark.sql import functions as F

from kgfeat.llm.text import given_back, neutral
from kgfeat.plans.state import Workspace

SYMBOLS = b"#*$%&|<>"  # fixed by the contract
WINDOW = 8
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
MORE = ("n_upper", "n_letters", "n_marks", "n_lines")
COUNTS = (*BASE, *MORE)
#: rule -> (numerator, denominator) of its statistic, in hundredths
RULES = {
    "symbols": ("n_symbols", "word_chars"),
    "upper": ("n_upper", "n_letters"),
    "marks": ("n_marks", "n_words"),
    "dup_lines": ("n_dup_lines", "n_lines"),
    "repeats": ("n_repeat_words", "n_words"),
}
#: cutoffs of every rule in hundredths, from the laxest
CUTOFFS = (90, 80, 70, 60, 50, 40, 30, 25, 20, 15, 10, 8, 6, 5, 4, 3, 2)
ALPHA, DELTA = 0.05, 0.05
FOLDS = 5  # one of so many labelled rows tunes, the others certify
PRICE = 10  # bad texts that must go for each good one given up


def repeated_words(words: list, window: int = WINDOW) -> int:
    """Words that lie in a window of that many words found twice or more (all its places count)."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    number: dict = {}
    rank = np.fromiter((number.setdefault(w, len(number)) for w in words), np.int64, count=len(words))
    if len(number) == len(words):
        return 0
    width = 1
    while width < window:  # ranks of runs of twice the words from ranks of halves: exact, no hashing
        step = min(width, window - width)
        pair = rank[: len(rank) - step] * (int(rank.max()) + 1) + rank[step:]
        rank, width = np.unique(pair, return_inverse=True)[1], width + step
    twice = np.bincount(rank)[rank] > 1
    if not twice.any():
        return 0
    edge = np.zeros(len(words) + 1, np.int64)
    at = np.flatnonzero(twice)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + window, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def text_counts(text: str | None) -> tuple[int, ...]:
    """COUNTS of one whole text; null counts as empty."""
    if not text:
        return (0,) * len(COUNTS)
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    squeezed = b"".join(words).decode("utf-8", "surrogatepass")
    seen, dup, lines = set(), 0, 0
    for line in raw.split(b"\n"):
        if line.split(None, 1):
            lines += 1
            dup += line in seen
            seen.add(line)
    upper = sum(map(str.isupper, squeezed)) if not squeezed.islower() else 0
    marks = len(raw) - len(raw.translate(None, b"!|"))
    symbols = len(raw) - len(raw.translate(None, SYMBOLS))
    letters = len(squeezed) - symbols - marks
    return len(words), len(squeezed), symbols, dup, repeated_words(words), upper, max(letters, 0), marks, lines


def with_counts(docs: DataFrame, text: str, keep: list[str] | None = None) -> DataFrame:
    """The columns of ``keep`` (all by default) of docs, see ``neutral``, and the COUNTS of the text, prefixed ``q_``."""
    keep = docs.columns if keep is None else keep
    docs = docs.select(*keep, *(c for c in (text,) if c not in keep))
    at, own = docs.columns.index(text), len(keep)
    schema = T.StructType([*docs.schema.fields[:own], *(T.StructField(f"q_{c}", T.LongType()) for c in COUNTS)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = np.array([text_counts(t.as_py()) for t in b.column(at)], np.int64).reshape(b.num_rows, len(COUNTS))
            yield pa.RecordBatch.from_arrays([*b.columns[:own], *(pa.array(rows[:, k]) for k in range(len(COUNTS)))], names=schema.names)

    return docs.mapInArrow(run, schema)


def base_failed() -> Column:
    return (F.col("q_n_words") < 20) | (100 * F.col("q_n_repeat_words") > 30 * F.col("q_n_words"))


def exceeds(rule: str, cutoff) -> Column:
    """The rule's statistic is above cutoff hundredths; integers only, so that no rounding decides."""
    num, den = RULES[rule]
    return 100 * F.col(f"q_{num}") > cutoff * F.col(f"q_{den}")


def binomial_tail(n: int, k: int, p: float) -> float:
    """P(Bin(n, p) <= k), summed exactly in logs."""
    if k >= n:
        return 1.0
    logs = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p) for i in range(k + 1)]
    top = max(logs)
    return min(1.0, math.exp(top) * math.fsum(math.exp(x - top) for x in logs))


def most_false(n_good: int, alpha: float, level: float) -> int:
    """The most false rejections among n_good that certify a rate of at most alpha; -1: none does."""
    low, high = -1, n_good  # the tail grows with k and is 1 at n_good
    while high - low > 1:
        mid = (low + high) // 2
        low, high = (mid, high) if binomial_tail(n_good, mid, alpha) <= level else (low, mid)
    return low


@dataclass(frozen=True)
class Threshold:
    """What one stratum uses: cutoffs by rule, with the counts of the group of strata that certified it."""

    stratum: str | None
    cutoffs: dict[str, int]  # a rule that is left out rejects nothing here
    pooled: bool
    n_good: int
    false_rejects: int
    bad_rejected: int


def tuning(ident: Column, folds: int = FOLDS) -> Column:
    """True for labelled rows that order the path and certify nothing."""
    return F.conv(F.substring(F.md5(ident.cast("string")), 1, 8), 16, 10).cast("long") % folds == 0


def ordered_steps(false_rejects: dict[tuple[str, int], int]) -> list[tuple[str, int]]:
    """The path: (rule, place among CUTOFFS), by false rejections in the tuning fold, the laxer first."""
    names = list(RULES)
    return sorted(false_rejects, key=lambda s: (false_rejects[s], s[1], names.index(s[0])))


def fit(counted: DataFrame, labels: DataFrame, ident: str, stratum: str, id_col: str = "doc_id", alpha: float = ALPHA, delta: float = DELTA) -> list[Threshold]:
    """Cutoffs of each labelled stratum, from all labelled rows that the base rules pass.

    counted: ident, stratum and q_ columns. labels: id and ``quality`` (1 good, 0 bad; null is left out;
    several labels of an id all count). Driver memory: a row a stratum and step of the path.
    """
    given = labels.filter("quality is not null").select(F.col(id_col).alias("l_id"), (F.col("quality") > 0).alias("good"))
    tall = counted.filter(~base_failed()).join(given, F.col(ident) == F.col("l_id"))
    cells = [F.sum((exceeds(r, F.lit(c)) & F.col("good")).cast("long")).alias(f"{r}_{i}") for r in RULES for i, c in enumerate(CUTOFFS)]
    first = tall.filter(tuning(F.col("l_id"))).agg(*cells).first()
    path = ordered_steps({(r, i): first[f"{r}_{i}"] or 0 for r in RULES for i in range(len(CUTOFFS))})
    at = F.least(*(F.when(exceeds(r, F.lit(CUTOFFS[i])), F.lit(k)) for k, (r, i) in enumerate(path)))
    rows = tall.filter(~tuning(F.col("l_id"))).groupBy(F.col(stratum).alias("s"), "good", at.alias("at")).agg(F.count("*").alias("n")).collect()
    strata = sorted({r["s"] for r in rows}, key=lambda s: (s is None, s))
    level = delta / max(1, len(strata))
    n_good = {s: sum(r["n"] for r in rows if r["s"] == s and r["good"]) for s in strata}
    small = [s for s in strata if most_false(n_good[s], alpha, level) < 0]
    out = []
    for group in [*([s] for s in strata if s not in small), small]:
        good, bad = [0] * len(path), [0] * len(path)
        for r in rows:
            if r["s"] in group and r["at"] is not None:
                (good if r["good"] else bad)[r["at"]] += r["n"]
        fr, hit = np.cumsum(good).tolist(), np.cumsum(bad).tolist()
        n = sum(n_good[s] for s in group)
        most = most_false(n, alpha, level)
        best = max((k for k in range(len(path)) if fr[k] <= most), key=lambda k: (hit[k] - PRICE * fr[k], -k), default=None)
        used: dict[str, int] = {}
        if best is not None and hit[best] > PRICE * fr[best]:
            used = {r: CUTOFFS[i] for r, i in path[: best + 1]}  # the strictest step of a rule comes last
        out += [Threshold(s, used, group is small, n, fr[best] if used else 0, hit[best] if used else 0) for s in group]
    return out


def verdict(thresholds: list[Threshold], stratum: str) -> Column:
    """True where neither the base rules nor the certified cutoffs of the row's stratum reject."""
    hit = F.lit(False)
    for t in thresholds:
        for rule, cutoff in t.cutoffs.items():
            hit = hit | (F.col(stratum).eqNullSafe(F.lit(t.stratum)) & exceeds(rule, F.lit(cutoff)))
    return ~base_failed() & ~F.coalesce(hit, F.lit(False))


def judge(spark: SparkSession, docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum: str = "lang", alpha: float = ALPHA, delta: float = DELTA, ws: Workspace | None = None) -> DataFrame:
    """One row per document: id, stratum, counts, base_failed, kept.

    Null text: no words, so the base rules reject it. A null id has no labels. Null stratum is a
    stratum; one without labels has no cutoffs. Repeated rows each get their row. An empty table or no
    labels: base rules alone. Columns of docs of other names play no part, whatever they are called.
    """
    counted, i, s, th = _fitted(ws or Workspace(spark, "quality"), docs, labels, id_col, text_col, stratum, alpha, delta)
    out = counted.withColumns({"base_failed": base_failed(), "kept": verdict(th, s)})
    return out.select(F.col(i).alias(id_col), F.col(s).alias(stratum), *(F.col(f"q_{c}").alias(c) for c in COUNTS), "base_failed", "kept")


def _fitted(ws: Workspace, docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, stratum: str, alpha: float, delta: float) -> tuple[DataFrame, str, str, list[Threshold]]:
    """Counts without texts, the names of id and stratum in them, the thresholds."""
    d, (i, t, s) = neutral(docs, id_col, text_col, stratum)
    counted = ws.save(with_counts(d, t, list(dict.fromkeys((i, s)))), "counts")
    return counted, i, s, fit(counted, labels, i, s, id_col, alpha, delta)


def keep_good(spark: SparkSession, docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum: str = "lang", alpha: float = ALPHA, delta: float = DELTA, ws: Workspace | None = None) -> DataFrame:
    """The rows of docs that are kept, all columns, as ``judge`` decides. A first pass keeps counts alone,
    to fit; the texts themselves are never shuffled: a second pass counts again and decides where it reads."""
    *_, s, th = _fitted(ws or Workspace(spark, "quality"), docs, labels, id_col, text_col, stratum, alpha, delta)
    d, (t,) = neutral(docs, text_col)
    return given_back(with_counts(d, t).filter(verdict(th, s)), docs)
