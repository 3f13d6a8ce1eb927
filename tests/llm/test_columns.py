"""Every operator and stage on tables whose further columns bear the names that the code uses inside,
with nulls in every column, empty and repeated rows."""

from __future__ import annotations

import re
from collections import Counter
from pathlib import Path

import pytest

import corpus_pipeline as cp
from kgfeat.llm import chat, decontam, mixing, neardup, pii, quality, sharding, simhash, toxicity, urlfilter, warc

FILES = [*Path(quality.__file__).parent.glob("*.py"), Path(quality.__file__).parents[1] / "operators/prefix.py", Path(quality.__file__).parents[1] / "operators/canon.py"]
FOUND = re.compile(r"(?:alias|withColumn|withColumnRenamed)\(\"(\w+)\"|withColumnRenamed\(\"\w+\", \"(\w+)\"|names=\[([^\]]*)\]|\"((?:\w+ \w+, )+\w+ \w+)\"|\{\"(\w+)\":")


def inside() -> list[str]:
    """Names of columns that the modules make."""
    out = {"_part", "_row", "_all", "_first", "_run_size", "_off_size", "before_size", "before_one", "row", "key", "c0", "c1", "c99", "q_n_words", "q_t", "kept", "base_failed", "good", "at", "copy"}
    for f in FILES:
        for m in FOUND.finditer(f.read_text()):
            if m[3]:
                out |= set(re.findall(r'"(\w+)"', m[3]))
            elif m[4]:
                out |= {x.split()[0] for x in m[4].split(", ")}
            else:
                out.add(m[1] or m[2] or m[5])
    return sorted({x.lower() for x in out if x})


LONG = "a very long text of many words " * 3000
TEXTS = [None, "", "   ", LONG, *(f"text number {i} has its own words w{i} x{i} y{i} z{i} and twenty more a{i} b{i} c{i} d{i} e{i} f{i} g{i} h{i} j{i} k{i}" for i in range(6))]


def table(spark, own: list[tuple], names: dict[str, str]):
    """The rows with a column of every inside name, null in some rows, and each row of even place twice."""
    more = [n for n in inside() if n not in names]
    rows = []
    for k, r in enumerate(own):
        full = (*r, *(None if k % 3 == 0 else f"{n}-{k}" for n in more))
        rows += [full] * (1 + (k % 2 == 0))
    return spark.createDataFrame(rows, ", ".join([*(f"`{n}` {t}" for n, t in names.items()), *(f"`{n}` string" for n in more)]))


@pytest.fixture(scope="module")
def docs(spark):
    own = [(i, t, ["en", None, "de"][i % 3], ["s", None, "r"][i % 3]) for i, t in enumerate(TEXTS)] + [(None, TEXTS[5], None, None), (None, None, None, None)]
    return table(spark, own, {"doc_id": "long", "text": "string", "lang": "string", "source": "string"})


@pytest.fixture(scope="module")
def labels(spark):
    return table(spark, [(i, i % 2, i % 2) for i in range(len(TEXTS))] + [(None, 1, 1), (4, None, None)], {"doc_id": "long", "quality": "int", "toxic": "int"})


@pytest.fixture(scope="module")
def bench(spark):
    return table(spark, [(1, TEXTS[6]), (None, "no such text"), (3, None), (4, "")], {"item_id": "long", "text": "string"})


def bag(df):
    return Counter(map(str, df.collect()))


def test_names_are_found():
    assert {"before_size", "times", "fp", "cells", "h", "size", "upto", "epochs", "made", "first", "shard", "slot"} - set(inside()) <= {"times"}


def test_filters_keep_rows_whole(spark, docs, labels, bench):
    every = bag(docs)
    for out, fewer in (
        (quality.keep_good(spark, docs, labels), True),
        (simhash.one_of_each(spark, docs), True),
        (neardup.one_of_each(spark, docs), True),
        (decontam.clean_documents(spark, docs, bench), True),
        (pii.pseudonymise(docs, "k"), False),
    ):
        assert out.columns == docs.columns
        got = bag(out)
        assert all(got[r] <= every[r] for r in got) and sum(got.values()) > 2
        assert (sum(got.values()) < sum(every.values())) == fewer
        assert out.limit(0).count() == 0


def test_mixing_and_sharding_keep_rows_whole(spark, docs):
    out = mixing.mixed_documents(spark, docs)
    assert out.columns == docs.columns and set(bag(out)) <= set(bag(docs))
    for none in (mixing.mixed_documents(spark, docs.limit(0)), sharding.shard_documents(spark, docs.limit(0), 4)):
        assert none.count() == 0
    full = sharding.shard_documents(spark, docs, 4)
    lost = {"size", "text_crc32", "shard", "slot"}
    assert full.columns == [c for c in docs.columns if c not in lost] + ["size", "text_crc32", "shard", "slot"]
    keep = [c for c in docs.columns if c not in lost]
    assert bag(full.select(*keep)) == bag(docs.select(*keep))


def test_tables_of_results(spark, docs, labels, bench):
    n = docs.count()
    assert quality.judge(spark, docs, labels).count() == n
    assert simhash.near_duplicates(spark, docs).count() == neardup.near_duplicates(spark, docs).count() == n
    assert sharding.assign(spark, docs, 4).count() == mixing.mix(spark, docs).count() == n
    model = toxicity.learn(spark, docs, labels)
    assert toxicity.score_documents(spark, docs, model).count() == n
    assert {r["id"] for r in decontam.leaks(spark, docs, bench).collect()} == {6}
    assert pii.pseudonymise(docs, "k", count_col="n").count() == n


def test_pages_and_turns(spark):
    urls = [None, "", "x://" + "h" * 70_000 + ".org/" + "p" * 70_000, "http://a.com/fr/x", "http://a.com/de/x", "http://b.net/q"]
    pages = table(spark, [(i, u, [None, "", "h" * 5000][i % 3]) for i, u in enumerate(urls)] + [(None, None, None)], {"page_id": "long", "url": "string", "html": "string"})
    n = pages.count()
    assert warc.round_trip(spark, pages).count() == urlfilter.judge(spark, pages).count() == n
    assert warc.round_trip(spark, pages.limit(0)).count() == urlfilter.judge(spark, pages.limit(0)).count() == 0
    turns = table(spark, [(1, 0, "a", "hi"), (1, 1, None, None), (1, 2, "unknown", LONG), (None, None, "a", ""), (2, 0, "system", "only")], {"conv_id": "long", "turn": "long", "role": "string", "text": "string"})
    assert chat.rotate(spark, turns).count() == 3 * 5 + 1 * 1  # rows of even place stand twice
    assert chat.rotate(spark, turns.limit(0)).count() == 0


@pytest.mark.parametrize("at", range(5))
def test_stages(spark, docs, labels, bench, tmp_path, at):
    for name, df in (("labels", labels), ("benchmark", bench)):
        df.write.parquet(f"{tmp_path}/{name}.parquet")
    name, stage = cp.STAGES[at]
    out = stage(spark, docs, str(tmp_path))
    lost = {"size", "text_crc32", "shard", "slot", "law"} if name == "sharding" else set()
    assert [c for c in out.columns if c not in lost] == [c for c in docs.columns if c not in lost]
    keep = [c for c in docs.columns if c not in lost]
    assert out.count() and set(bag(out.select(*keep))) <= set(bag(docs.select(*keep)))
    assert stage(spark, docs.limit(0), str(tmp_path)).count() == 0
