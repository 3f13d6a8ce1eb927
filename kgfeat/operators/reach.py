"""Breadth-first neighbourhoods of seeds, with distances."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfeat.operators import dictionary, sieve
from kgfeat.plans.state import Workspace


def bfs(ws: Workspace, arc: DataFrame, seeds: DataFrame, k: int | None) -> tuple[DataFrame, int]:
    """(seed, v, dist) for 1 <= dist <= k, and the last distance at which a pair was new.

    k None: on to the fixpoint. A seed is never its own neighbour, but may be another seed's.
    Each round joins the frontier with arcs, removes seen pairs, and is committed.
    """
    seen = seeds.select("seed", F.col("seed").alias("v"), F.lit(0).alias("dist"))
    levels, front, h = [], seen, 0
    while k is None or h < k:
        found = front.select("seed", F.col("v").alias("src")).join(arc.select("src", "dst"), "src").select("seed", F.col("dst").alias("v")).distinct()
        done = reduce(DataFrame.union, levels, seen).select("seed", "v")
        front = ws.save(found.join(done, ["seed", "v"], "left_anti").withColumn("dist", F.lit(h + 1)), f"reach-{h + 1}")
        if front.isEmpty():
            break
        levels.append(front)
        h += 1
    empty = seen.filter("false")
    return reduce(DataFrame.union, levels, empty), h


def fixpoint(ws: Workspace, arc: DataFrame, seeds: DataFrame) -> tuple[DataFrame, int]:
    """The full neighbourhood (seed, v, dist) and the k from which no vertex is new for any seed set."""
    reach, _ = bfs(ws, arc, seeds, None)
    first = reach.groupBy("v").agg(F.min("dist").alias("dist"))
    return reach, first.agg(F.max("dist")).first()[0] or 0


SENT = 48 << 20  # bytes of support sets that are sent to all tasks at once
PIECE = 1000  # members of a set in a row
MANY = 1_000_000  # sources of a vertex that stand in a row


def _sizes_of_unions(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(v, n) from rows (v, ids) with the rows of a vertex side by side: how many different ids it has."""
    stamp = np.zeros(0, np.int64)

    def size(ids: np.ndarray) -> int:
        """Each id keeps the last place where it stands; as many places find themselves kept as there are ids."""
        nonlocal stamp
        if (top := int(ids.max(initial=-1)) + 1) > len(stamp):
            stamp = np.zeros(max(top, 2 * len(stamp)), np.int64)
        place = np.arange(len(ids))
        stamp[ids] = place
        return int(np.count_nonzero(stamp[ids] == place))

    last, held, much = None, [], 0
    for b in batches:
        if not b.num_rows:
            continue
        v, ids = b.column(0).to_numpy(), b.column(1)
        flat, ends = ids.flatten().to_numpy(), np.cumsum(ids.value_lengths().to_numpy())
        first = np.flatnonzero(np.concatenate(([True], v[1:] != v[:-1])))
        cuts = np.concatenate(([0], ends[first[1:] - 1], ends[-1:]))
        vs, ns = [], []
        for i, x in enumerate(v[first].tolist()):
            if x != last:
                if last is not None:
                    vs.append(last)
                    ns.append(size(held[0] if len(held) == 1 else np.concatenate(held)))
                last, held, much = x, [], 0
            held.append(flat[cuts[i] : cuts[i + 1]])
            much += len(held[-1])
            if much > MANY and len(held) > 1:
                held = [np.unique(np.concatenate(held))]
                much = 0
        held = [np.array(x) for x in held]  # the batch may go
        if vs:
            yield pa.RecordBatch.from_pydict({"v": pa.array(vs, pa.int64()), "n": pa.array(ns, pa.int64())})
    if last is not None:
        yield pa.RecordBatch.from_pydict({"v": pa.array([last], pa.int64()), "n": pa.array([size(np.concatenate(held))], pa.int64())})


def support_counts(ws: Workspace, arc: DataFrame, seeds: DataFrame, k: int) -> DataFrame:
    """(v, n): how many seeds reach v within k arcs, as counted from ``bfs``, without the pairs of the last round.

    A vertex is reached by what reaches it or its sources within k - 1 arcs. These sets are sent to all tasks,
    a part of the seeds at a time, and of each union only the size is kept; sizes add up over the parts.
    """
    number = dictionary.dense_ids(ws.spark, seeds.select(F.col("seed").cast("string")), ws).select(F.col("uri").cast("long").alias("seed"), F.col("id").cast("int").alias("id"))
    number = ws.save(number, "seed-numbers")
    before = bfs(ws, arc, seeds, k - 1)[0].select("seed", "v").union(seeds.select("seed", F.col("seed").alias("v")))
    near = ws.save(before.join(number, "seed").select(F.col("v").alias("w"), "id"), "near")
    n, parts = number.count(), 1
    part = lambda: F.floor(F.col("id") * F.lit(parts) / F.lit(max(1, n)))
    while parts < n:
        most = near.groupBy(part().alias("part"), "w").agg(F.count("*").alias("n")).groupBy("part").agg(F.sum(4 * F.col("n") + 64 * F.ceil(F.col("n") / PIECE)).alias("b")).agg(F.max("b")).first()[0]
        if most <= SENT:
            break
        parts = max(parts + 1, min(n, -(-parts * most // SENT)))
    into = arc.select(F.col("dst").alias("v"), F.col("src").alias("w")).union(near.select(F.col("w").alias("v"), "w").distinct())
    heavy = ws.save(into.groupBy("v").agg(F.count("*").alias("n")).filter(F.col("n") > MANY).select("v"), "heavy")
    got = []
    if not heavy.isEmpty():
        pairs = into.join(F.broadcast(heavy), "v").distinct().join(near, "w").select("v", "id").distinct()
        got.append(ws.save(pairs.groupBy("v").agg(F.count("*").alias("n")), "counted"))
        into = into.join(F.broadcast(heavy), "v", "left_anti")
    rows = ws.save(into.groupBy("v").agg(F.collect_list("w").alias("ws")), "sources")
    for i in range(parts):
        sets = near.filter(part() == i).groupBy("w").agg(F.collect_list("id").alias("ids"))
        cut = F.transform(F.sequence(F.lit(0), F.floor((F.size("ids") - 1) / PIECE)), lambda j: F.slice("ids", (j * PIECE + 1).cast("int"), PIECE))
        met = rows.select("v", F.explode("ws").alias("w")).join(F.broadcast(sets.select("w", F.explode(cut).alias("ids"))), "w").select("v", "ids")
        got.append(ws.save(met.mapInArrow(_sizes_of_unions, "v long, n long"), "counted"))
    total = reduce(DataFrame.union, got).groupBy("v").agg(F.sum("n").alias("n"))
    own = seeds.select(F.col("seed").alias("v"), F.lit(1).alias("own"))  # a seed is not its own neighbour
    return total.join(own, "v", "left").select("v", (F.col("n") - F.coalesce("own", F.lit(0))).alias("n")).filter("n > 0")


def nearby_arcs(ws: Workspace, arc: DataFrame, seeds: DataFrame, hops: float, d: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(arcs (src, pred, dst) out of the vertices that seeds reach in fewer than hops steps, vertices (v) that
    seeds reach in so many, themselves included). arc, not necessarily a set, is read once a round and never
    shuffled as a whole; vertices with more than d arcs out of them are not walked through."""
    front = ws.save(seeds.select(F.col("seed").alias("v")).distinct(), "around-0")
    n, seen, levels, h = front.count(), front, [], 0
    while n:
        own = ws.save(sieve.semi(arc, "src", front.withColumnRenamed("v", "src"), n).select("src", "pred", "dst").distinct(), f"arcs-{h + 1}")
        levels.append(own)
        h += 1
        go = own
        if d is not None:
            stop = own.groupBy("src").agg(F.count("*").alias("n")).filter(F.col("n") > d).select("src")
            go = own.join(stop, "src", "left_anti")
        front = ws.save(go.select(F.col("dst").alias("v")).distinct().join(seen, "v", "left_anti"), f"around-{h}")
        n, seen = front.count(), seen.union(front)
        if h >= hops:
            break
    return reduce(DataFrame.union, levels) if levels else arc.select("src", "pred", "dst").filter("false"), seen


def nearest(ws: Workspace, arc: DataFrame, seeds: DataFrame, stop: DataFrame | None = None) -> DataFrame:
    """(v, dist): vertices of the full neighbourhood of all seeds with the least distance from a seed other
    than the vertex itself: the rows (v, min(dist)) of ``bfs``, without its pairs of seed and vertex. Vertices
    of stop (v) are reached, not walked through.

    Two seeds a vertex are enough: one that is not the vertex is among them, and where a seed is not kept
    two others that are as near go on in its place.
    """
    label = front = ws.save(seeds.select(F.col("seed").alias("v"), "seed", F.lit(0).alias("dist")).distinct(), "nearest-0")
    h = 0
    while True:
        h += 1
        go = front.select(F.col("v").alias("src"), "seed")
        if stop is not None:
            go = go.join(stop.withColumnRenamed("v", "src"), "src", "left_anti")
        own = go.select("src").distinct()
        met = go.join(sieve.sift(arc.select("src", "dst"), "src", own, own.count()), "src").groupBy(F.col("dst").alias("v")).agg(F.min("seed").alias("lo"), F.max("seed").alias("hi"))
        have = label.groupBy("v").agg(F.min("seed").alias("has"), F.count("*").alias("n"))
        new = met.join(have, "v", "left").filter("n is null or n < 2")
        both = F.when(F.col("has").isNull(), F.array_distinct(F.array("lo", "hi"))).when(F.col("lo") != F.col("has"), F.array("lo")).when(F.col("hi") != F.col("has"), F.array("hi")).otherwise(F.array().cast("array<bigint>"))
        front = ws.save(new.select("v", F.explode(both).alias("seed"), F.lit(h).alias("dist")), f"nearest-{h}")
        if front.isEmpty():
            break
        label = label.union(front)
    return ws.save(label.filter("seed <> v").groupBy("v").agg(F.min("dist").alias("dist")), "nearest")
