from __future__ import annotations

import math
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from kgfeat.llm import toxicity as tx
from kgfeat.plans.state import Workspace

TERMS = ["idiot", "worthless", "disgustingly", "scum", "abcde*", "lowerstem*"]


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        prev, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            prev, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, prev + (x != y))
    return row[-1]


def brute(word):
    best = None
    for t in TERMS:
        k = tx.edit_budget(t)
        s = t.removesuffix("*")
        forms = [word] if s == t else [word[:n] for n in range(len(word) + 1)]
        d = min(distance(f, s) for f in forms)
        if d <= k and (best is None or d < best):
            best = d
    return best


@settings(max_examples=400, deadline=None)
@given(st.sampled_from([t.removesuffix("*") for t in TERMS]), st.lists(st.tuples(st.integers(0, 14), st.sampled_from("abciotx-")), max_size=3), st.sampled_from(["", "x", "ing"]))
def test_automaton_against_edit_distance(term, edits, tail):
    w = list(term)
    for at, ch in edits:
        at = min(at, len(w) - 1) if w else 0
        if ch == "-" and w:
            del w[at]
        elif len(w) > at and ch < "m":
            w[at] = ch
        else:
            w.insert(at, ch)
    word = "".join(w) + tail
    hit = AUTOMATON.find(word)
    assert (hit and hit[1]) == brute(word)


AUTOMATON = tx.LexiconAutomaton(TERMS)


def test_state_limit_does_not_change_results():
    small = tx.LexiconAutomaton(TERMS, states=3)
    for w in ("idiot", "idoit", "idi0t", "worthles", "wrthless", "abcdefg", "lowerstam", "clean", ""):
        assert small.find(w) == AUTOMATON.find(w)


def test_context_tells_quotation_from_abuse():
    m = tx.Model(AUTOMATON)
    plain = m.hits("you are an idiot and scum")
    quoted = m.hits('he said "you idiot" yesterday')
    assert [h[3] for h in plain] == [1.0, 1.0] and quoted[0][3] < 0.5
    assert m.judge("you are an idiot")[0] > m.judge('she said: "idiot"')[0] > m.judge("all is well")[0]


def test_entries_choose_words_and_stems():
    stats = {"tra": (137, 0), "tras": (137, 0), "trash": (137, 0), "trash$": (137, 0)}
    assert tx.choose_entries(stats) == ["trash"]
    many = {"low": (90, 0), "lowe": (90, 0), **{f"lowe{c}": (15, 0) for c in "abcdef"}}
    assert tx.choose_entries(many) == ["lowe*"]


def _corpus(seed=1, n=900):
    rng = random.Random(seed)
    syl = ["an", "er", "th", "on", "ha", "st", "re", "ti", "nd", "ou"]
    word = lambda: "".join(rng.choice(syl) for _ in range(rng.randrange(1, 4)))
    rows, labels = [], []
    for i in range(n):
        w = [word() for _ in range(rng.randrange(20, 120))]
        bad = i % 6 == 0
        if bad:
            for _ in range(rng.randrange(2, 5)):
                w[rng.randrange(len(w))] = rng.choice(["moron", "pathetic", "vile" + word()])
        rows.append((i, " ".join(w)))
        labels.append((i, int(bad)))
    return rows, labels


def test_held_out_accuracy_and_misspellings(spark):
    rows, labels = _corpus()
    docs = spark.createDataFrame([*rows, (9000, None), (9001, ""), (9002, "an er pathetlc th"), (9003, "x" * 200_000), (0, rows[0][1]), (None, "moron moron")], "doc_id long, text string")
    lab = spark.createDataFrame([*[(i, t, "q") for i, t in labels], (None, None, "q"), (1, None, "q")], "doc_id long, toxic int, text string")
    model = tx.learn(spark, docs, lab, fit_rows=400)
    got = tx.score_documents(spark, docs, model).collect()
    assert len(got) == len(rows) + 6
    want = dict(labels)
    out = [r for r in got if r["held_out"] and r["id"] in want]
    assert len(out) > 100 and sum(r["predicted"] == want[r["id"]] for r in out) / len(out) > 0.97
    assert all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in got)
    by = {r["id"]: r for r in got}
    assert by[9000]["score"] == by[9001]["score"] < 0.5 and by[9002]["n_hits"] == 1 and by[None]["predicted"] == 1


def test_no_labels(spark):
    docs = spark.createDataFrame([(1, "moron")], "doc_id long, text string")
    lab = spark.createDataFrame([], "doc_id long, toxic int")
    m = tx.learn(spark, docs, lab)
    assert tx.score_documents(spark, docs, m).first()["score"] == pytest.approx(m.judge("")[0])


def test_harmless_words_come_from_all_training_rows(spark):
    rows, labels = _corpus()
    rows = [(i, t + " morom" if i % 6 and i % 7 == 0 else t) for i, t in rows]
    docs, lab = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    few = tx.learn(spark, docs, lab, fit_rows=1)
    assert few.automaton.find("morom") == ("moron", 1)
    assert "morom" in few.harmless and not few.hits("a morom")
    assert few.harmless == tx.learn(spark, docs, lab).harmless


def test_quotation_in_lines_of_any_length():
    m, far = tx.Model(AUTOMATON), "word " * 2000
    weights = lambda text: [h[3] for h in m.hits(text)]
    assert weights(f'"{far} idiot" idiot') == [0.4, 1.0]
    assert weights(f'"{far}" {"word " * 10} idiot') == [1.0]
    assert weights(f"“{far} idiot {far} idiot” idiot\n idiot") == [0.4, 0.4, 1.0, 1.0]


def test_stems_of_any_length(spark):
    stem = "pseudointernationalistically"  # 28 characters
    rng = random.Random(2)
    rows = [(i, " ".join(rng.choice(["an", "on", "er", "th"]) + str(rng.randrange(999)) for _ in range(20)) + (f" {stem}{'abcdefgh'[i % 8]}{i % 16} x{i}" if i % 2 else "")) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i, _ in rows], "doc_id long, toxic int")
    m = tx.learn(spark, docs, labels)
    assert any(t.startswith(stem) for t in m.trust) or any(stem.startswith(t.removesuffix("*")) for t in m.trust)
    words = spark.createDataFrame([("a" * 50 + c, 6) for c in "bcd"] + [("b" * 45, 20), ("c" * 30, 3)], "w string, n long")
    got, longest = tx.frequent_beginnings(Workspace(spark, "t"), words, 10)
    have = {r["p"]: r["bad"] for r in got.collect()}
    assert have == {"a" * k: 18 for k in range(3, 51)} | {"b" * k: 20 for k in range(3, 46)} | {"b" * 45 + "$": 20} and longest == 50


def plain_score(m, text):
    """The score by edit distances to every entry and a look back along the line, word after word."""
    low = (text or "").lower()
    exact = near = cut = 0.0
    spots = list(tx.WORD.finditer(low))
    for n, x in enumerate(spots):
        w, best = x.group(), None
        for t in m.automaton.budget:
            s = t.removesuffix("*")
            forms = [w] if s == t else [w[:j] for j in range(len(w) + 1)]
            d = min(distance(f, s) for f in forms)
            if d <= tx.edit_budget(t):
                best = min(best or (9, ""), (d, t))
        if best is None or (best[0] and w in m.harmless):
            continue
        line = low[low.rfind("\n", 0, x.start()) + 1 : x.start()]
        quoted = line.count('"') % 2 == 1 or any(line.rfind(o) > line.rfind(c) for o, c in tx.PAIRS.items())
        weight = (0.4 if quoted else 1.0) * (0.5 if any(s.group() in tx.REPORTING for s in spots[max(0, n - tx.SPAN) : n]) else 1.0)
        cut += 1 - weight
        if best[0]:
            near += weight
        else:  # entries at no distance: the automaton names the first stem or the word
            exact += weight * m.trust.get(m.look(w)[0], 1.0)
    dense = 100 * exact / max(20, (text or "").count(" ")) if exact else 0.0
    z = sum(a * b for a, b in zip(m.weights, [1, math.log1p(exact), math.log1p(near), math.log1p(dense), math.log1p(cut)], strict=True))
    return 1 / (1 + math.exp(-max(-30, min(30, z))))


def test_query_against_plain_scores(spark):
    """Every row of a table of the given sizes, with the lexicon and weights of the query."""
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "labels"))
    m = tx.learn(spark, docs, labels, contexts=3, share=0.3)
    assert m.trust
    got = {r["id"]: r["score"] for r in tx.score_documents(spark, docs, m).collect()}
    rows = docs.select("doc_id", "text").collect()
    assert len(got) == len(rows)
    for r in rows:
        if len(r["text"] or "") < 6000:
            assert got[r["doc_id"]] == pytest.approx(plain_score(m, r["text"]), abs=1e-9)
    twice = tx.score_documents(spark, docs, tx.learn(spark, docs, labels, contexts=3, share=0.3))
    assert {r["id"]: r["score"] for r in twice.collect()} == got


def test_ties_repeats_and_empty_tables(spark):
    docs = spark.createDataFrame([(1, "an oaf"), (1, "an oaf"), (2, ""), (None, None)], "doc_id long, text string")
    lab = spark.createDataFrame([(1, 1), (1, 0), (2, 0)], "doc_id long, toxic int")
    m = tx.learn(spark, docs, lab)
    assert len(tx.score_documents(spark, docs, m).collect()) == 4
    assert tx.score_documents(spark, docs.limit(0), m).count() == 0
    assert not tx.learn(spark, docs.limit(0), lab).trust
