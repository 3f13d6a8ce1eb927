from __future__ import annotations

from kgfeat.params import MiningParams
from kgfeat.streaming import arcs

SF = "/root/testdata/sf0.001"


def _drain(query):
    try:
        query.processAllAvailable()
    finally:
        query.stop()


def _folder(spark, tmp_path, copies=2):
    ev = spark.read.parquet(f"{SF}/events.parquet").limit(300)
    for _ in range(copies):
        ev.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    return f"{tmp_path}/in", ev


def test_repeated_events_count_once(spark, tmp_path):
    folder, ev = _folder(spark, tmp_path)
    _drain(arcs.triples_from_events(arcs.read_events(spark, folder, 10)).writeStream.format("memory").queryName("arcs_once").start())
    got = spark.table("arcs_once")
    assert got.filter("p = 'did'").count() == ev.count() and got.count() == 2 * ev.count()


def test_activity_windows(spark, tmp_path):
    folder, ev = _folder(spark, tmp_path, 1)
    for kind in ("tumbling", "sliding", "session"):
        _drain(arcs.activity(arcs.read_events(spark, folder), kind).writeStream.outputMode("complete" if kind != "session" else "append").format("memory").queryName(f"act_{kind}").start())
    total = spark.table("act_tumbling").groupBy().sum("n").first()[0]
    assert total == ev.count() and spark.table("act_sliding").groupBy().sum("n").first()[0] == 4 * ev.count()


def test_mining_per_batch(spark, tmp_path):
    folder, _ = _folder(spark, tmp_path, 1)
    seen = []
    seeds = spark.createDataFrame([(f"user:{i}",) for i in range(100)], "seed string")
    stream = arcs.triples_from_events(arcs.read_events(spark, folder))
    _drain(arcs.remine(stream, f"{tmp_path}/store", seeds, MiningParams(k=1, t=1, l_min=2), lambda n, r: seen.append({x["feature"] for x in r.path_features().collect()})).start())
    assert seen and any("-[did]-> cls:Event/click" in s for s in seen)
