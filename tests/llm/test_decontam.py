from __future__ import annotations

import random

import numpy as np
import pytest

from kgfeat.llm import decontam as dc


def brute_align(a, b):
    h = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    best = 0
    for i, x in enumerate(a, 1):
        for j, y in enumerate(b, 1):
            h[i][j] = max(0, h[i - 1][j - 1] + (dc.MATCH if x == y else dc.MISMATCH), h[i - 1][j] + dc.GAP, h[i][j - 1] + dc.GAP)
            best = max(best, h[i][j])
    return best


@pytest.mark.parametrize("seed", range(40))
def test_alignment_score(seed):
    rng = random.Random(seed)
    a, b = ([rng.randrange(4) for _ in range(rng.randrange(1, 25))] for _ in range(2))
    got, end, beg = dc.align(np.array(a), np.array(b))
    assert got == brute_align(a, b)
    if got:
        assert brute_align(a, b[beg:end]) == got


def _words(rng, n):
    return ["".join(rng.choice("abcdefghij") for _ in range(5)) for _ in range(n)]


def test_leaks_exact_edited_and_clean(spark):
    rng = random.Random(4)
    items = [_words(rng, 40) for _ in range(30)]
    rows, want = [], set()
    for i in range(300):
        w = _words(rng, 200)
        if i % 5 == 0:
            k = rng.randrange(30)
            copy = list(items[k])
            if i % 10 == 0:  # edited: words replaced, dropped and put in
                for at in rng.sample(range(40), 5):
                    copy[at] = "other"
                del copy[rng.randrange(len(copy))]
                copy.insert(rng.randrange(len(copy)), "extra")
            at = rng.randrange(200)
            w[at:at] = copy
            want.add((i, k))
        rows.append((i, " ".join(w).upper() if i % 3 == 0 else ", ".join(w), "x"))
    rows += [(1000, None, "x"), (1001, "", "x"), (1002, " ".join(items[3]), "x"), (1002, " ".join(items[3]), "x"), (None, " ".join(items[4]), "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, item_id string")
    bench = spark.createDataFrame([(k, " ".join(w)) for k, w in enumerate(items)] + [(90, None), (91, "too short here"), (3, " ".join(items[3]))], "item_id long, text string")
    for block in (2_000_000, 100):
        got = [(r["id"], r["item_id"]) for r in dc.leaks(spark, docs, bench, block_words=block).collect()]
        assert sorted(got, key=str) == sorted([*want, (1002, 3), (1002, 3), (None, 4)], key=str)
    left = dc.clean_documents(spark, docs, bench)
    assert left.columns == docs.columns
    assert {r["doc_id"] for r in left.collect()} == {i for i, *_ in rows} - {i for i, _ in want} - {1002, None}


def test_empty_tables(spark):
    docs = spark.createDataFrame([(1, "a b c d e f g h i j")], "doc_id long, text string")
    bench = spark.createDataFrame([(1, "a b c d e f g h i j")], "item_id long, text string")
    assert dc.leaks(spark, docs.limit(0), bench).count() == 0
    assert dc.leaks(spark, docs, bench.limit(0)).count() == 0
    assert dc.leaks(spark, docs, bench).count() == 1


def test_seeds_are_the_rarer_grams_of_an_item():
    it = dc.Items([(0, "a b c d e f g h i j k l m n o p"), (1, "a b c d x y")])
    df = np.zeros(len(it.start) - 1, np.int64)
    assert it.seeds(df) == set()
    _, gram = it.hits(it.word_ids("a b c d e f g h i j k l m n o p".split()))
    df[gram] = [9, 1, 1, 2, 2, 2, 3, 3, 5, 1, 1, 8, 7]
    assert {g for k, g in it.seeds(df) if k == 0} == {int(g) for g in gram if 0 < df[g] <= 2}
    assert {g for k, g in it.seeds(df) if k == 1} == {int(gram[0])}  # its only gram found


def test_rarity_leaves_grams_out_on_the_given_tables(spark):
    import pandas as pd

    docs, bench = (pd.read_parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "benchmark"))
    it = dc.Items(list(zip(bench.item_id, bench.text, strict=True)))
    df = np.zeros(len(it.start) - 1, np.int64)
    for t in docs.text:
        df[np.unique(it.hits(it.word_ids(dc.norm_words(t)))[1])] += 1
    pairs = {(int(k), g) for g in range(len(df)) if df[g] for k in it.where[it.start[g] : it.start[g + 1], 0]}
    left_out = len(pairs) - len(it.seeds(df))
    assert 0 < left_out < 0.6 * len(pairs)


def _edited(rng, words, share):
    out = []
    for w in words:
        x = rng.random()
        if x < share / 3:
            continue
        out.append("sub" + rng.choice("abcdef") * 3 if x < 2 * share / 3 else w)
        if x > 1 - share / 3:
            out.append("put" + rng.choice("abcdef") * 3)
    return out


def test_recall_of_edited_copies_against_all_pairs(spark):
    rng = random.Random(11)
    common = _words(rng, 30)
    items = [[w if rng.random() < 0.7 else rng.choice(common) for w in _words(rng, rng.randrange(12, 45))] for _ in range(15)]
    rows = []
    for i in range(240):
        w = [rng.choice(common) for _ in range(rng.randrange(0, 80))]
        if i % 2:
            at = rng.randrange(len(w) + 1)
            w[at:at] = _edited(rng, items[i % 15], rng.choice([0.0, 0.1, 0.2, 0.3, 0.4]))
        rows.append((i, " ".join(w)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame([(k, " ".join(w)) for k, w in enumerate(items)], "item_id long, text string")
    got = {(r["id"], r["item_id"]): r["score"] for r in dc.leaks(spark, docs, bench).collect()}
    want = {}
    for i, t in rows:
        for k, w in enumerate(items):
            s = brute_align(w, t.split()) / (dc.MATCH * len(w))
            if s >= dc.SCORE:
                want[i, k] = round(s, 6)
    assert len(want) > 80 and set(got) <= set(want)
    assert all(got[x] == want[x] for x in got)
    assert len(got) / len(want) >= 0.9


def test_short_items_nulls_and_very_long_texts(spark):
    bench = spark.createDataFrame([(1, "alpha beta gamma", 1), (2, "solo", 1), (3, "--- ...", 1), (4, "", 1), (5, None, 1), (None, "null id item here", 1)], "item_id long, text string, id int")
    long = "word " * 300_000
    rows = [(1, "an Alpha, beta gamma!"), (2, "alpha beta"), (3, "so solo"), (4, long + "alpha beta gamma"), (5, None), (6, ""), (None, "a null id item here b"), (8, "alpha gamma beta")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r["id"], r["item_id"], r["score"], r["first_word"], r["end_word"]) for r in dc.leaks(spark, docs, bench).collect()), key=str)
    assert got == sorted([(1, 1, 1.0, 1, 4), (3, 2, 1.0, 1, 2), (4, 1, 1.0, 300_000, 300_003), (None, None, 1.0, 1, 5)], key=str)


def test_clean_documents_where_ids_repeat(spark):
    item = "one two three four five six seven eight nine ten eleven"
    docs = spark.createDataFrame([(1, f"start {item} end", 0), (1, "something else entirely", 1), (1, None, 2), (None, item, 3), (None, "clean words only", 4)], "doc_id long, text string, id int")
    bench = spark.createDataFrame([(7, item)], "item_id long, text string")
    left = dc.clean_documents(spark, docs, bench)
    assert left.columns == docs.columns
    assert sorted(r["id"] for r in left.collect()) == [1, 2, 4]


def test_edited_copies_whose_grams_are_commoner_than_the_item(spark):
    rng = random.Random(6)
    item = _words(rng, 40)
    copy = ["other" if at % 8 == 4 else w for at, w in enumerate(item)]
    rows = [(0, " ".join(item)), *((i, " ".join(copy)) for i in range(1, 31))]
    # one seed far from the copy does not stand for it
    rows += [(50, " ".join([*item[2:6], *_words(rng, 300), *copy])), (60, " ".join([*_words(rng, 50), *item[6:10], *_words(rng, 50)]))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = dc.leaks(spark, docs, spark.createDataFrame([(7, " ".join(item))], "item_id long, text string")).collect()
    assert sorted(r["id"] for r in got) == [*range(31), 50]


@pytest.mark.parametrize("seed", range(20))
def test_windows_out_of_reach_cannot_have_the_score(seed):
    rng = random.Random(seed)
    for _ in range(20):
        item, part = (np.array([rng.randrange(12) for _ in range(rng.randrange(4, 20))]) for _ in range(2))
        assert dc.within_reach(item, part, 0.5) or brute_align(item, part) < 0.5 * dc.MATCH * len(item)
