from __future__ import annotations

import random
import re
import zlib
from collections import Counter, defaultdict

import pytest

from kgfeat.llm import mixing, sharding
from kgfeat.llm.text import word_count

WS = re.compile(r"[^\x20\x09-\x0D]+")


def _docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, source string, size int, shard string, k int")


def _rows(seed=1, n=600):
    rng = random.Random(seed)
    out = [(i, " ".join("é" * rng.randrange(1, 6) for _ in range(rng.randrange(0, 40))), rng.choice(["a", "a", "a", "b", "É", None]), 0, "x", 1) for i in range(n)]
    out += [(n + i, "the same text " * 9, "a", 0, "x", 1) for i in range(200)]
    out += [(5000, None, "b", 0, "x", 1), (5001, "", None, 0, "x", 1), (5002, "w " * 3000, "b", 0, "x", 1), (5003, "twice", "c", 0, "x", 1), (5003, "twice", "c", 0, "x", 1), (None, "no id", "c", 0, "x", 1)]
    return out


def test_shards(spark):
    rows = _rows()
    full = sharding.shard_documents(spark, _docs(spark, rows), 16)
    assert full.columns == ["doc_id", "text", "source", "k", "size", "text_crc32", "shard", "slot"]
    got = full.collect()
    assert Counter((r["doc_id"], r["text"]) for r in got) == Counter((r[0], r[1]) for r in rows)
    size, slots, groups = Counter(), defaultdict(list), defaultdict(set)
    for r in got:
        raw = (r["text"] or "").encode()
        assert (r["size"], r["text_crc32"]) == (len(raw) + 1, zlib.crc32(raw))
        size[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
        groups[r["text"]].add(r["shard"])
    total = sum(size.values())
    biggest = max(r["size"] for r in got)
    assert all(abs(size[s] - total / 16) <= biggest + 0.04 * total / 16 for s in range(16))
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    same = sorted(groups["the same text " * 9])
    assert same == list(range(same[0], same[-1] + 1))  # contiguous
    again = sharding.assign(spark, _docs(spark, rows), 16).collect()
    assert Counter((r["id"], r["shard"], r["slot"]) for r in again if r["id"] != 5003) == Counter((r["doc_id"], r["shard"], r["slot"]) for r in got if r["doc_id"] != 5003)


@pytest.mark.parametrize("n", [0, 1, 5])
def test_few_documents(spark, n):
    got = sharding.assign(spark, _docs(spark, _rows()[:n]) if n else _docs(spark, _rows()).limit(0), 16).collect()
    assert len(got) == n and all(0 <= r["shard"] < 16 for r in got)
    assert all(r["shard"] == 0 for r in sharding.assign(spark, _docs(spark, _rows()[:5]), 1).collect())


def test_written_shards(spark, tmp_path):
    df = sharding.shard_documents(spark, _docs(spark, _rows()), 4)
    sharding.write_shards(df, f"{tmp_path}/out")
    back = spark.read.parquet(f"{tmp_path}/out")
    assert back.count() == len(_rows()) and back.select("shard").distinct().count() == 4


def brute_targets(sizes, weights, share, most):
    """Water level by bisection."""
    lo, hi = 0.0, 2 * most * sum(sizes) / min(weights) + 1
    for _ in range(200):
        mid = (lo + hi) / 2
        if sum(min(most * s, w * mid) for s, w in zip(sizes, weights, strict=True)) < share * sum(sizes):
            lo = mid
        else:
            hi = mid
    return [min(most * s, w * hi) for s, w in zip(sizes, weights, strict=True)]


@pytest.mark.parametrize("seed", range(20))
def test_targets(seed):
    rng = random.Random(seed)
    n = rng.randrange(1, 12)
    sizes, weights = [rng.randrange(1, 1000) for _ in range(n)], [(3, 1, 2)[i % 3] for i in range(n)]
    assert mixing.targets(sizes, weights) == pytest.approx(brute_targets(sizes, weights, 1.5, 2), rel=1e-6)
    assert mixing.targets([0, 0], [3, 1]) == [0, 0]


def test_mix(spark):
    rows = _rows()
    got = mixing.mix(spark, _docs(spark, rows)).collect()
    size = lambda t: len(WS.findall(t or ""))
    assert Counter((r["id"], r["size"]) for r in got) == Counter((r[0], size(r[1])) for r in rows)
    by = Counter()
    for r in rows:
        by[r[2]] += size(r[1])
    order = sorted(by, key=lambda s: (s is None, s or ""))
    want = dict(zip(order, brute_targets([by[s] for s in order], [(3, 1, 2)[i % 3] for i in range(len(order))], 1.5, 2), strict=True))
    taken = Counter()
    for r in got:
        assert 0 <= r["taken"] <= 2 * r["size"] and r["source_size"] == by[r["source"]]
        assert r["target"] == pytest.approx(want[r["source"]], rel=1e-6)
        taken[r["source"]] += r["taken"]
    assert all(abs(taken[s] - want[s]) <= 0.51 for s in order)
    again = mixing.mix(spark, _docs(spark, rows[::-1])).collect()
    assert Counter(map(tuple, again)) == Counter(map(tuple, got))


def test_mixed_documents(spark):
    rows = _rows()
    docs = _docs(spark, rows)
    out = mixing.mixed_documents(spark, docs)
    assert out.columns == docs.columns
    times = Counter(r["doc_id"] for r in out.collect())
    for r in mixing.mix(spark, docs).collect():
        if r["size"] and r["id"] != 5003:
            assert abs(times[r["id"]] - r["taken"] / r["size"]) <= 0.5 + 1e-9
    assert mixing.mixed_documents(spark, docs.limit(0)).count() == 0


def test_word_count(spark):
    texts = [None, "", " ", "a", " a  b\n", "a\x1cb c", "\t\x0b\x0c\rx", "a\u00a0b", "w " * 9999]
    df = spark.createDataFrame([(t,) for t in texts], "t string")
    assert [r[0] for r in df.select(word_count(df["t"])).collect()] == [len(WS.findall(t or "")) for t in texts]
