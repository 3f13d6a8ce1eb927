"""Toxicity: a Levenshtein automaton run over a lexicon trie catches misspelled terms, the window
around each hit tells quotation from abuse, a logistic model turns the hits into a score.

The lexicon is learned from labelled training rows. Its entries are words, and stems that take many
endings. What counts for a beginning of words is the number of different contexts (neighbouring
words) in toxic rows, so that a text copied many times does not make its words suspect, against its
occurrences in clean rows: the Wilson lower bound of the toxic share must reach ``share``.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.plans.state import Workspace

WORD = re.compile(r"[^\W_]+")
SPAN = 6  # words of context on either side
#: words that report speech, as a default for the context window
REPORTING = frozenset("said says quote quoted quotes wrote called reported according dijo dit sagte zitat cita citation".split())
PAIRS = {"“": "”", "«": "»", "„": "“", "‘": "’"}
FIT_ROWS = 20_000
BROADCAST_ROWS = 2_000_000  # of an id and a label each


STEM = "*"  # ends an entry that stands for all words that begin with it
SHORTEST, STEP = 3, 20  # beginnings of words are counted from SHORTEST characters on, STEP at first, then twice as far while any is frequent


def edit_budget(term: str) -> int:
    """Misspellings allowed: none in words of under 5 characters, 1 up to 8, then 2; 1 in stems from 7."""
    if term.endswith(STEM):
        return int(len(term) > 7)
    return 0 if len(term) < 5 else 1 if len(term) < 9 else 2


class LexiconAutomaton:
    """Product of the lexicon trie and the Levenshtein automata of its terms, made deterministic as
    words visit it. A state maps trie nodes to the fewest edits that reach them."""

    def __init__(self, terms: list[str], budget=edit_budget, states: int = 200_000):
        self.children: list[dict[str, int]] = [{}]
        self.term: list[str | None] = [None]
        self.slack: list[int] = [0]  # most edits any term below may still use
        self.states = states
        for t in sorted(set(terms)):
            at = 0
            for ch in t.removesuffix(STEM):
                self.slack[at] = max(self.slack[at], budget(t))
                nxt = self.children[at].get(ch)
                if nxt is None:
                    nxt = self.children[at][ch] = len(self.children)
                    self.children.append({})
                    self.term.append(None)
                    self.slack.append(0)
                at = nxt
            self.slack[at] = max(self.slack[at], budget(t))
            self.term[at] = t
        self.budget = {t: budget(t) for t in terms}
        self.alphabet = {ch: ch for c in self.children for ch in c}
        self._reset()

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("number", "sets", "step", "accept", "begun")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self._reset()

    def _reset(self) -> None:
        self.number: dict[tuple, int] = {}
        self.sets: list[tuple] = []
        self.step: list[dict[str, int]] = []
        self.accept: list[tuple[str, int] | None] = []
        self.begun: list[tuple[str, int] | None] = []  # a stem ends here, whatever follows
        self._state({0: 0})

    def _state(self, nodes: dict[int, int]) -> int:
        todo = list(nodes)
        while todo:  # terms' characters left out of the word
            n = todo.pop()
            for c in self.children[n].values():
                e = nodes[n] + 1
                if e <= self.slack[c] and e < nodes.get(c, 99):
                    nodes[c] = e
                    todo.append(c)
        key = tuple(sorted(nodes.items()))
        got = self.number.get(key)
        if got is None:
            got = self.number[key] = len(self.sets)
            self.sets.append(key)
            self.step.append({})
            ends = [(e, self.term[n]) for n, e in key if self.term[n] is not None and e <= self.budget[self.term[n]]]
            self.accept.append(min(ends)[::-1] if ends else None)
            stems = [x for x in ends if x[1].endswith(STEM)]
            self.begun.append(min(stems)[::-1] if stems else None)
        return got

    def find(self, word: str) -> tuple[str, int] | None:
        """(term, edits) of the nearest term within its budget, the first by code point on ties."""
        if len(self.sets) > self.states:
            self._reset()
        at, best = 0, None
        for ch in word:
            ch = self.alphabet.get(ch, "")  # all characters outside the lexicon act alike
            nxt = self.step[at].get(ch)
            if nxt is None:
                nodes: dict[int, int] = {}
                for n, e in self.sets[at]:
                    for c, child in self.children[n].items():
                        cost = e + (c != ch)
                        if cost <= self.slack[child] and cost < nodes.get(child, 99):
                            nodes[child] = cost
                    if e + 1 <= self.slack[n] and e + 1 < nodes.get(n, 99):
                        nodes[n] = e + 1
                nxt = self.step[at][ch] = self._state(nodes) if nodes else -1
            if nxt < 0:
                return best
            at = nxt
            if (stem := self.begun[at]) and (best is None or stem[1] < best[1]):
                best = stem
                if not stem[1]:
                    return best
        end = self.accept[at]
        return end if end and (best is None or end[1] <= best[1]) else best


class Quotation:
    """Whether a place of the text is inside quotation marks opened on its line; places are asked in order."""

    def __init__(self, text: str):
        self.text, self.at = text, 0
        self._line()

    def _line(self) -> None:
        self.odd, self.open = False, dict.fromkeys(PAIRS, False)

    def inside(self, start: int) -> bool:
        part, self.at = self.text[self.at : start], start
        if (k := part.rfind("\n")) >= 0:
            part = part[k + 1 :]
            self._line()
        self.odd ^= part.count('"') % 2 == 1
        for o, c in PAIRS.items():
            begun, ended = part.rfind(o), part.rfind(c)
            if begun != ended:
                self.open[o] = begun > ended
        return self.odd or any(self.open.values())


def context_weight(quoted: bool, before: list[str]) -> float:
    """1 for plain use, less for a hit inside quotation marks or after a word that reports speech."""
    weight = 0.4 if quoted else 1.0
    return weight * (0.5 if any(w in REPORTING for w in before) else 1.0)


@dataclass
class Model:
    automaton: LexiconAutomaton
    harmless: frozenset[str] = frozenset()  # misspelling-like words that clean training rows use
    weights: np.ndarray = field(default_factory=lambda: PRIOR.copy())
    trust: dict[str, float] = field(default_factory=dict)  # toxic share of an entry
    known: dict[str, tuple[str, int] | None] = field(default_factory=dict)

    def look(self, word: str) -> tuple[str, int] | None:
        if word in self.known:
            return self.known[word]
        if len(self.known) > 400_000:
            self.known.clear()
        hit = self.automaton.find(word)
        hit = None if hit and hit[1] and word in self.harmless else hit
        self.known[word] = hit
        return hit

    def hits(self, text: str | None) -> list[tuple[str, str, int, float]]:
        """(word, term, edits, context weight) of each hit in the whole text."""
        if not text:
            return []
        low = text.lower()
        look = self.look
        found = {w: h for w in set(WORD.findall(low)) if (h := look(w))}
        if not found:
            return []
        out, before, quotes = [], [], Quotation(low)
        for m in WORD.finditer(low):
            w = m.group()
            if h := found.get(w):
                out.append((w, h[0], h[1], context_weight(quotes.inside(m.start()), before[-SPAN:])))
            before.append(w)
            if len(before) > 4 * SPAN:
                del before[: -2 * SPAN]
        return out

    def features(self, text: str | None) -> np.ndarray:
        return self._features(self.hits(text), text)

    def _features(self, hits: list[tuple[str, str, int, float]], text: str | None) -> np.ndarray:
        """Constant; exact hits, misspelled hits, exact hits in a hundred words, all weighed by context
        and trust; the discount that context made."""
        exact = sum(h[3] * self.trust.get(h[1], 1.0) for h in hits if not h[2])
        near = sum(h[3] for h in hits if h[2])
        cut = sum(1 - h[3] for h in hits)
        dense = 100 * exact / max(20, text.count(" ")) if exact else 0.0
        return np.array([1.0, math.log1p(exact), math.log1p(near), math.log1p(dense), math.log1p(cut)])

    def judge(self, text: str | None) -> tuple[float, int]:
        """Score from 0 to 1, and the number of hits."""
        hits = self.hits(text)
        z = float(np.clip(self.weights @ self._features(hits, text), -30, 30))
        return 1 / (1 + math.exp(-z)), len(hits)


#: weights before any label is seen, and how firmly they are held (in units of inverse variance)
PRIOR, HOLD = np.array([-2.5, 4.0, 2.0, 1.0, 0.3]), np.array([0.02, 0.05, 0.3, 0.3, 1.0])


def fit_logistic(x: np.ndarray, y: np.ndarray, rounds: int = 40) -> np.ndarray:
    """Newton's method on the log-likelihood with a Gaussian prior around PRIOR."""
    w = PRIOR.copy()
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        grad = x.T @ (p - y) + HOLD * (w - PRIOR)
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(HOLD), grad)
        w = w - step * min(1.0, 2.0 / max(1e-9, float(np.abs(step).max())))
        if np.abs(step).max() < 1e-8:
            break
    return w


def wilson_low(k: Column, n: Column, z: float = 2.6) -> Column:
    """Lower bound of a share of k in n."""
    p = k / n
    return (p + z * z / (2 * n) - z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n))) / (1 + z * z / n)


def beginnings(w: str, low: int, high: int) -> Column:
    """The beginnings of a word of low to high characters."""
    return F.when(F.length(w) >= low, F.transform(F.sequence(F.lit(low), F.least(F.length(w), F.lit(high))), lambda k: F.substring(F.col(w), F.lit(1), k))).otherwise(F.array())


def frequent_beginnings(ws: Workspace, words: DataFrame, least: int) -> tuple[DataFrame, int]:
    """(p, bad): beginnings, and whole words with a closing mark, that words (w, n) have ``least`` times or
    more, and the length of the longest. A longer beginning is never more frequent than a shorter one, so
    longer ones are counted only for words whose beginning so far is frequent: no length is left out."""
    words = ws.save(words.filter(F.length("w") >= SHORTEST), "words")
    out = words.filter(F.col("n") >= least).select(F.concat("w", F.lit("$")).alias("p"), F.col("n").alias("bad"))
    low, high = SHORTEST, STEP
    while True:
        part = words.select("n", F.explode(beginnings("w", low, high)).alias("p")).groupBy("p").agg(F.sum("n").alias("bad")).filter(F.col("bad") >= least)
        part = ws.save(part, "beginnings")
        out = out.union(part)
        full = part.filter(F.length("p") == high).select(F.col("p").alias("start"))
        words = ws.save(words.filter(F.length("w") > high).withColumn("start", F.substring("w", 1, high)).join(full, "start", "left_semi").select("w", "n"), "words")
        if words.isEmpty():
            break
        low, high = high + 1, 2 * high
    longest = out.agg(F.max(F.length("p"))).first()[0]
    return out, longest or 0


def choose_entries(stats: dict[str, tuple[int, int]]) -> list[str]:
    """Lexicon entries from suspect beginnings {beginning: (toxic contexts, clean occurrences)}.

    From the shortest suspect beginning down: where its suspect continuations hold nearly all of its
    toxic contexts, and are few or leave out most of its clean ones, they stand in its place.
    """
    kids: dict[str, list[str]] = {}
    for p in stats:
        if p[:-1] in stats:
            kids.setdefault(p[:-1], []).append(p)
    out, todo = [], [p for p in stats if p[:-1] not in stats]
    while todo:
        p = todo.pop()
        bad, clean = stats[p]
        below = kids.get(p, [])
        held, left = sum(stats[k][0] for k in below), sum(stats[k][1] for k in below)
        if below and held >= 0.95 * bad and (len(below) <= 3 or 2 * left < clean):
            todo += below
        else:
            out.append(p[:-1] if p.endswith("$") else p + STEM)
    return sorted(out)


def held_out(ident: Column, folds: int = 5) -> Column:
    """Remainder 0 of the CRC-32 of the id as text; a null id counts as empty text."""
    return F.crc32(F.coalesce(ident.cast("string"), F.lit(""))) % folds == 0


def learn(spark: SparkSession, docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", contexts: int = 10, share: float = 0.6, fit_rows: int = FIT_ROWS, ws: Workspace | None = None) -> Model:
    """Lexicon and harmless look-alikes from all labelled training rows, weights from ``fit_rows`` of them
    at most (least hashes).

    A label of an id stands for all rows of that id; of several labels of an id the highest counts, null
    labels are left out. Null and empty texts have no words. Repeated rows count as often as they stand.
    No toxic label, or no documents: an empty lexicon and the prior weights. Driver memory: the lexicon
    and its look-alikes, both of words that toxic rows use in ``contexts`` contexts or that are within
    the edit budget of such words.
    """
    ws = ws or Workspace(spark, "toxicity")
    train = labels.filter("toxic is not null").filter(~held_out(F.col(id_col))).select(F.col(id_col).alias("i"), (F.col("toxic") > 0).cast("int").alias("y")).groupBy("i").agg(F.max("y").alias("y"))
    train = ws.save(train, "train")
    texts = docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).filter("t is not null")
    # ids and labels alone are sent to the texts while they are few; beyond that both sides are shuffled, once
    rows = texts.join(F.broadcast(train), "i") if train.count() <= BROADCAST_ROWS else ws.save(texts.join(train, "i"), "labelled")

    def in_context(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            w, c = [], []
            for t in b.column(0):
                x = WORD.findall(t.as_py().lower())
                for a, y, z in {(a, y, z) for a, y, z in zip(x, ["", *x[:-1]], [*x[1:], ""], strict=False)}:
                    w.append(a)
                    c.append(f"{y} {z}")
            yield pa.RecordBatch.from_arrays([pa.array(w, pa.string()), pa.array(c, pa.string())], names=["w", "c"])

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = Counter()
            for t in b.column(0):
                n.update(WORD.findall(t.as_py().lower()))
            yield pa.RecordBatch.from_arrays([pa.array(list(n), pa.string()), pa.array(list(n.values()), pa.int64())], names=["w", "n"])

    bad = rows.filter("y = 1").select("t").mapInArrow(in_context, "w string, c string").groupBy("w", F.xxhash64("c")).agg(F.lit(1)).groupBy("w").agg(F.count("*").alias("n"))
    cand, longest = frequent_beginnings(ws, bad, contexts)
    if not longest:
        return Model(LexiconAutomaton([]))
    clean = rows.filter("y = 0").select("t").mapInArrow(counted, "w string, n long").groupBy("w").agg(F.sum("n").alias("n"))
    parts = F.array_append(beginnings("w", SHORTEST, longest), F.concat("w", F.lit("$")))
    clean = clean.select("n", F.explode(parts).alias("p")).groupBy("p").agg(F.sum("n").alias("clean"))
    share_of = wilson_low(F.col("bad"), F.col("bad") + F.col("clean"))
    got = cand.join(clean, "p", "left").withColumn("clean", F.coalesce("clean", F.lit(0))).filter(share_of >= share).collect()
    stats = {r["p"]: (r["bad"], r["clean"]) for r in got}
    terms = choose_entries(stats)
    if not terms:
        return Model(LexiconAutomaton([]))
    of = {t: stats[t.removesuffix(STEM) if t.endswith(STEM) else t + "$"] for t in terms}
    model = Model(LexiconAutomaton(terms), trust={t: b / (b + c) for t, (b, c) in of.items()})
    picked = ws.save(train.orderBy(F.xxhash64("i"), "i").limit(fit_rows), "sample")  # ids, not texts
    sample = texts.join(F.broadcast(picked), "i")
    sent = spark.sparkContext.broadcast(model)

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for b in batches:
            f = [m.features(t.as_py()) for t in b.column(1)]
            near = [[w for w, _, e, _ in m.hits(t.as_py()) if e] if x[2] else [] for t, x in zip(b.column(1), f, strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x.tolist() for x in f], pa.list_(pa.float64())), pa.array(near, pa.list_(pa.string()))], names=["y", "x", "near"])

    def near_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for b in batches:
            y, w = [], []
            for label, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                near = [x for x in set(WORD.findall(t.as_py().lower())) if (h := m.look(x)) and h[1]]
                y += [label] * len(near)
                w += near
            yield pa.RecordBatch.from_arrays([pa.array(y, pa.int32()), pa.array(w, pa.string())], names=["y", "w"])

    tally = rows.select("y", "t").mapInArrow(near_words, "y int, w string").groupBy("w").agg(F.sum(1 - F.col("y")).alias("clean"), F.sum("y").alias("bad"))
    model.harmless = frozenset(r["w"] for r in tally.filter("clean > 0 and clean >= bad").select("w").collect())
    got = sample.select("y", "t").mapInArrow(describe, "y int, x array<double>, near array<string>").collect()
    calm = np.array([not any(w in model.harmless for w in r["near"]) for r in got])
    x, y = np.array([r["x"] for r in got]), np.array([r["y"] for r in got], float)
    model.weights = fit_logistic(x[calm], y[calm]) if calm.any() else PRIOR.copy()
    model.known = {}
    return model


def score_documents(spark: SparkSession, docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, held_out, score, predicted, n_hits), one row per row of docs; a null text counts as empty."""
    sent = spark.sparkContext.broadcast(model)
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for b in batches:
            got = [m.judge(t.as_py()) for t in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([g[0] for g in got], pa.float64()), pa.array([int(g[0] >= 0.5) for g in got], pa.int32()), pa.array([g[1] for g in got], pa.int32())], names=["id", "held_out", "score", "predicted", "n_hits"])

    return docs.select(F.col(id_col).alias("id"), held_out(F.col(id_col)).alias("h"), F.col(text_col).alias("t")).mapInArrow(run, f"id {kind}, held_out boolean, score double, predicted int, n_hits int")
