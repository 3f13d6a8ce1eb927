from __future__ import annotations

import re

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from kgfeat.llm import quality as q
from kgfeat.llm.text import words_of
from kgfeat.plans.state import Workspace

WS = re.compile(r"[^\x20\x09-\x0D]+")


def brute(text: str | None) -> tuple[int, int, int, int, int]:
    t = text or ""
    w = WS.findall(t)
    seen, dup = set(), 0
    for line in t.split("\n"):
        if WS.search(line):
            dup += line in seen
            seen.add(line)
    where = {}
    for i in range(len(w) - 7):
        where.setdefault(tuple(w[i : i + 8]), []).append(i)
    rep = {j for at in where.values() if len(at) > 1 for i in at for j in range(i, i + 8)}
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), dup, len(rep)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.sampled_from(["a", "b", "é#", " ", "\x1c", "|", "ß&"]), max_size=60), st.lists(st.sampled_from([" ", "\n", "\t", "\r\n", "\x0b"]), min_size=60, max_size=60))
def test_counts_match_brute_force(words, gaps):
    text = "".join(w + g for w, g in zip(words, gaps, strict=False))
    assert q.text_counts(text)[:5] == brute(text)


def test_edge_texts():
    assert q.text_counts(None) == q.text_counts("") == (0,) * len(q.COUNTS)
    long = "x " * 50_000
    assert q.text_counts(long)[:5] == (50_000, 50_000, 0, 0, 50_000)


def test_binomial_tail_is_the_clopper_pearson_bound():
    for n, k, p in [(600, 0, 0.01), (50, 3, 0.2), (10, 10, 0.5), (1000, 12, 0.02)]:
        pmf, total = (1 - p) ** n, 0.0
        for i in range(k + 1):
            total += pmf
            pmf *= (n - i) / (i + 1) * p / (1 - p)
        assert q.binomial_tail(n, k, p) == pytest.approx(min(1.0, total), rel=1e-9)


def test_most_false_rejections_that_certify():
    for n, alpha, level in [(0, 0.05, 0.01), (50, 0.05, 0.0125), (86, 0.05, 0.0125), (400, 0.05, 0.0125), (3000, 0.01, 0.05)]:
        k = q.most_false(n, alpha, level)
        assert k == max((i for i in range(n) if q.binomial_tail(n, i, alpha) <= level), default=-1)


def _labelled(rng, n, rates):
    """Rows that the base rules pass: good ones exceed some cutoffs at the given rates, bad ones often."""
    rows = []
    for i in range(n):
        good = rng.random() < 0.8
        word = [f"w{j}x" for j in range(100)]
        for at, rate in enumerate(rates):
            if rng.random() < (rate if good else 0.7):
                word[at::5] = [("$#" * (2 + at)) + str(j) for j in range(len(word[at::5]))] if at % 2 else [f"W{'X' * (3 + at)}{j}" for j in range(len(word[at::5]))]
        rows.append((i, " ".join(word), "en" if i % 3 else "de", int(good)))
    return rows


def test_false_rejection_of_all_rules_together_is_limited(spark):
    rng = np.random.default_rng(3)
    rows = _labelled(rng, 3000, [0.01, 0.03, 0.02, 0.05])
    docs = spark.createDataFrame([r[:3] for r in rows], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(r[0], r[3]) for r in rows[:1500]], "doc_id long, quality int")
    kept = {r["doc_id"]: r["kept"] for r in q.judge(spark, docs, labels).collect()}
    for lang in ("en", "de"):
        fresh = [r for r in rows[1500:] if r[2] == lang and r[3]]
        assert sum(not kept[r[0]] for r in fresh) / len(fresh) <= q.ALPHA + 0.02  # room for the chance of the fresh rows
    bad = [r for r in rows[1500:] if not r[3]]
    assert sum(not kept[r[0]] for r in bad) > 0.5 * len(bad)


@pytest.mark.parametrize("sf", ["sf0.01"])
def test_cutoffs_are_certified_and_used_on_the_given_tables(spark, sf):
    docs, labels = (spark.read.parquet(f"/root/testdata/{sf}/{t}.parquet") for t in ("documents", "labels"))
    got = q.judge(spark, docs, labels).join(labels, "doc_id").filter("not base_failed").groupBy("quality", "kept").count().collect()
    n = {(r["quality"], r["kept"]): r["count"] for r in got}
    assert n[0, False] > 5 * n.get((0, True), 0) and n.get((1, False), 0) <= q.ALPHA * n[1, True]
    *_, th = q._fitted(Workspace(spark, "quality"), docs, labels, "doc_id", "text", "lang", q.ALPHA, q.DELTA)
    assert {t.stratum for t in th} == {"en", "de", "es", "fr"} and all(t.cutoffs for t in th)
    assert [t.pooled for t in th if t.stratum == "en"] == [False] and any(t.pooled for t in th)


def test_judge_end_to_end(spark):
    good = " ".join(f"word{i}" for i in range(60))
    rows = [(i, good + f" tail{i}", "en") for i in range(1200)] + [(2000 + i, " ".join(f"w{j}$$$" for j in range(50)), "en") for i in range(200)]
    rows += [(9000, None, "en"), (9001, "", "en"), (9002, "few words only", None), (9003, good, None), (9003, good, None), (None, good, "en")]
    docs = spark.createDataFrame([(*r, "s", 1) for r in rows], "doc_id long, text string, lang string, kept string, quality int")
    labels = spark.createDataFrame([(r[0], int(r[0] < 2000), None) for r in rows[:1400]] + [(9003, None, None), (77777, 1, None)], "doc_id long, quality int, toxic int")
    got = {}
    for r in q.judge(spark, docs, labels).collect():
        got.setdefault(r["doc_id"], []).append((r["base_failed"], r["kept"]))
    assert all(got[i] == [(False, True)] for i in range(1200))
    assert all(got[2000 + i] == [(False, False)] for i in range(200))
    assert got[9000] == got[9001] == got[9002] == [(True, False)]
    assert got[9003] == [(False, True)] * 2 and got[None] == [(False, True)]
    kept = q.keep_good(spark, docs, labels)
    assert kept.columns == docs.columns and kept.count() == 1200 + 3


def test_too_few_labels_and_empty_tables(spark):
    docs = spark.createDataFrame([(1, " ".join(f"w{j}$$$" for j in range(50)), "en")], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(1, 0, 0)], "doc_id long, quality int, toxic int")
    assert q.judge(spark, docs, labels).first()["kept"]
    assert q.judge(spark, docs.limit(0), labels.limit(0)).count() == 0


def test_words_are_cut_at_six_characters():
    assert words_of("a b\x1cc d\te") == ["a b\x1cc".encode(), b"d", b"e"]
