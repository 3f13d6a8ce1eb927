"""run() against brute force: plain Python and the DuckDB form of the quality rules, no operator of the package."""

from __future__ import annotations

import hashlib
import random
import re
import zlib
from collections import Counter

import duckdb
import pytest
from test_decontam import brute_align
from test_neardup import brute_left, brute_set
from test_sharding_mixing import brute_targets

import corpus_pipeline as cp
from kgfeat.llm import oracles

SF = "/root/testdata/sf0.001"
WS = re.compile(r"[^\x20\x09-\x0D]+")


def words(text):
    return re.findall(r"[^\W_]+", (text or "").lower())


def leaked(text, items):
    w = words(text)
    for it in items:
        n = len(it)
        grams = {tuple(it[i : i + 4]) for i in range(n - 3)}
        if any(tuple(w[i : i + 4]) in grams for i in range(len(w) - 3)) and brute_align(it, w) >= 0.5 * 2 * n:
            return True
    return False


def brute_run(folder):
    duck = duckdb.connect()
    for t in ("documents", "labels", "benchmark"):
        duck.sql(f"CREATE VIEW {t} AS SELECT DISTINCT * FROM '{folder}/{t}.parquet{'/*.parquet' if folder != SF else ''}'")
    kept = {i for i, k in duck.sql(f"SELECT doc_id, kept FROM ({oracles.quality_rules()})").fetchall() if k}
    rows = [r for r in duck.sql("SELECT doc_id, text, source FROM documents").fetchall() if r[0] in kept]
    left = set(brute_left([(i, t) for i, t, _ in rows]))
    items = [words(t) for (t,) in duck.sql("SELECT text FROM benchmark").fetchall() if words(t)]
    rows = [r for r in {r[0]: r for r in rows}.values() if r[0] in left and not leaked(r[1], items)]
    size = Counter()
    for _, t, s in rows:
        size[s] += len(WS.findall(t))
    order = sorted(size, key=lambda s: (s is None, s or ""))
    goal = brute_targets([size[s] for s in order], [(3, 1, 2)[k % 3] for k in range(len(order))], 1.5, 2) if order else []
    times = Counter()
    for s, g in zip(order, goal, strict=True):
        epochs, rest = divmod(round(g), size[s])
        mine = sorted((int(hashlib.md5(f"7|0{i}".encode()).hexdigest()[:15], 16), i, len(WS.findall(t))) for i, t, x in rows if x == s)
        before, last = 0, None
        for r, i, n in mine:
            if 2 * min(n, max(0, rest - before)) >= max(n, 1):
                last = r
            before += n
        for r, i, _ in mine:
            times[i] = epochs + (last is not None and r <= last)
    out = [(zlib.crc32(t.encode()), hashlib.md5(t.encode()).hexdigest(), i, len(t.encode()) + 1) for i, t, _ in rows for _ in range(times[i])]
    out.sort()
    total = sum(x[3] for x in out)
    ends, at = [], 0
    for x in out:
        ends.append((at, at + x[3]))
        at += x[3]
    cuts = []
    for j in range(1, 16):
        aim = total * j / 16
        k = next(k for k, (a, b) in enumerate(ends) if a <= aim < b)
        same = [e for e, x in zip(ends, out, strict=True) if x[:2] == out[k][:2]]
        near = lambda a, b, aim=aim: a if aim - a <= b - aim else b
        g = near(same[0][0], same[-1][1])
        cuts.append(g if abs(g - aim) <= 0.02 * total / 16 else near(*ends[k]))
    shard = [sum(a >= c for c in cuts) for a, _ in ends]
    slot, seen = [], Counter()
    for s in shard:
        slot.append(seen[s])
        seen[s] += 1
    return sorted((x[2], s, p) for x, s, p in zip(out, shard, slot, strict=True))


def check(spark, folder):
    out = cp.run(spark, folder)
    got = out.collect()
    # copies of one document are alike: which of them has which slot does not matter
    by = lambda rows: sorted((i, s, p) for i, s, p in rows)
    assert by((r["doc_id"], r["shard"], r["slot"]) for r in got) == brute_run(folder)
    assert set(spark.read.parquet(f"{folder}/documents.parquet").columns) <= set(out.columns)
    return got


def test_given_tables(spark):
    assert [n for n, _ in cp.STAGES] == ["quality rules", "simhash near-dedup", "benchmark decontamination", "mixing sources", "sharding"]
    assert len(check(spark, SF)) > 50


@pytest.mark.parametrize("seed", [1])
def test_nulls_repeats_copies_and_leaks(spark, tmp_path, seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefghijklm") for _ in range(6))
    items = [[word() for _ in range(rng.randrange(8, 30))] for _ in range(6)]
    rows = []
    for i in range(150):
        w = [word() for _ in range(rng.randrange(0, 120))]
        if i % 7 == 3 and rows:
            w = rng.choice(rows)[1].split()
            for _ in range(rng.randrange(0, 4)):
                w[rng.randrange(len(w) or 1) : 1] = [word()]
        if i % 11 == 5:
            it = list(rng.choice(items))
            it[rng.randrange(len(it))] = word()
            at = rng.randrange(len(w) + 1)
            w[at:at] = it
        rows.append((i, " ".join(w), rng.choice(["en", "de", None]), rng.choice(["a", "a", "b", None])))
    rows += [(500, None, "en", "a"), (501, "", None, None), (502, "few words", "en", "b"), rows[9], rows[9], (503, "x " * 20_000, "en", "a"), (504, " ".join(word() for _ in range(9000)), "de", "b")]
    extra = [(*r, f"size {len(r[1] or '')}", r[0] if r[0] % 2 else None) for r in rows]
    docs = spark.createDataFrame(extra, "doc_id long, text string, lang string, source string, key string, c0 long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    lab = [(i, int(rng.random() < 0.8), None) for i in range(0, 150, 2)] + [(None, 1, 1), (3, None, 0)]
    spark.createDataFrame(lab, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([*((k, " ".join(w)) for k, w in enumerate(items)), (90, None), (91, "")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = check(spark, str(tmp_path))
    assert got and brute_set(got[0]["text"])


def test_no_documents(spark, tmp_path):
    spark.read.parquet(f"{SF}/documents.parquet").limit(0).write.parquet(f"{tmp_path}/documents.parquet")
    for t in ("labels", "benchmark"):
        spark.read.parquet(f"{SF}/{t}.parquet").write.parquet(f"{tmp_path}/{t}.parquet")
    assert cp.run(spark, str(tmp_path)).count() == 0
