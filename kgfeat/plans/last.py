"""The last iteration: nothing grows from its features, so the vertices that they end in and the support sets
that they join are never listed as rows.

For each support set and each vertex that its paths end in, the steps from there are found once for all
features, as integers, a class of several vertices once. Rows with the same support set lie side by side, and
a task makes of them (``_combined``) the new features, each as parent and step, with their seeds, a seed of a feature once.
These go, packed and compressed (``_packed``), to the task that a hash of parent and step names, where
(``_found``) the sizes and the ids of the unions are read off. What grows from a path of too few seeds is
counted where it is made: a path has one support set, and so have its children, which is out of the limits.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from kgfeat.operators import dictionary, supports
from kgfeat.plans.context import Context

PIECE = 1000  # seeds of a set in a row
AT_ONCE = 2_000_000  # combinations that a task works on at once, as far as rows allow
FEW = 300_000  # rows that go to all tasks
HEAVY = 2_000_000  # combinations that one bucket gets on average, with those that are made several times
LISTED = 100_000  # rows to grow from, up to which the faithful engine lists the pairs of its last iteration

FOUND = "parent long, step int, size int, x long, y long, joined boolean"
PACKED = "bucket int, made long, rows binary"
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _ends(col: pa.Array) -> np.ndarray:
    """Offsets of the lists, from 0."""
    return np.concatenate(([0], np.cumsum(pc.list_value_length(col).to_numpy(zero_copy_only=False)))).astype(np.int64)


def _lists(col: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(values, offsets from 0)."""
    if isinstance(col, pa.ChunkedArray):
        col = col.chunk(0) if col.num_chunks == 1 else pa.concat_arrays(col.chunks)
    return col.flatten().to_numpy(zero_copy_only=False), _ends(col)


def _spread(at: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(which of at, place of the value) for every value of the lists at."""
    n = ends[at + 1] - ends[at]
    which = np.repeat(np.arange(len(at)), n)
    return which, np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + ends[at][which]


def _turned(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * _P2
    x = (x ^ (x >> np.uint64(29))) * _P3
    return x ^ (x >> np.uint64(32))


def _hashes(seed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """F.xxhash64(seed) and F.xxhash64(seed, F.lit(1)) of longs, of which ids of sets are made."""
    x = (np.uint64(42 + 8) + _P5) ^ (_turned(seed.astype(np.int64).view(np.uint64) * _P2, 31) * _P1)
    x = _mixed(_turned(x, 27) * _P1 + _P4)
    y = (x + _P5 + np.uint64(4)) ^ _P1
    y = _mixed(_turned(y, 23) * _P2 + _P3)
    return x.view(np.int64), y.view(np.int64)


def _packed(x: object) -> bytes:
    raw = pickle.dumps(x, protocol=5)
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def _unpacked(x: bytes) -> tuple:
    return pickle.loads(pa.decompress(x[8:], decompressed_size=int.from_bytes(x[:8], "little"), codec="zstd", asbytes=True))


def _narrow(x: np.ndarray) -> np.ndarray:
    return x.astype(np.min_scalar_type(int(x.max(initial=0))))


def _combined(child: np.ndarray, seed: np.ndarray, first: np.ndarray, much: np.ndarray, n_k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(new features, captured paths of each as far as 2, seeds of each, seeds) of combinations of a new feature and a
    seed. first: the one that stands for its paths, much: these are several."""
    both = ((child * n_k + seed) << 2) | (first.astype(np.int64) << 1) | (much & first)
    both.sort()
    pairs = both >> 2
    child = pairs // n_k
    start = np.flatnonzero(np.concatenate(([True], child[1:] != child[:-1])))
    paths = np.minimum(np.add.reduceat((both >> 1) & 1, start) + np.bitwise_or.reduceat(both & 1, start), 2)
    once = np.concatenate(([True], pairs[1:] != pairs[:-1]))
    n = np.add.reduceat(once.astype(np.int64), start)
    return child[start], paths, n, (pairs - child * n_k)[once]


def _made(batches: Iterator[pa.RecordBatch], buckets: int, l_min: int, l_max: int | None, at_once: int) -> Iterator[pa.RecordBatch]:
    """Rows of PACKED from rows (sset, size, leads, seeds, near, grown, to_v, to_steps); near: vertices that no seed
    of the set has at the new distance, grown: features that end here, to: vertices one arc on with their steps.
    A row without a bucket has how many children the paths of too few or too many seeds have."""

    def table(bucket: list[int | None], made: int, rows: list[bytes | None]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(bucket, pa.int32()), pa.array([made] * len(bucket), pa.int64()), pa.array(rows, pa.binary())], names=["bucket", "made", "rows"])

    made = 0
    for b in batches:
        if not b.num_rows:
            continue
        col = {n: b.column(i) for i, n in enumerate(b.schema.names)}
        near, near_at = _lists(col["near"])
        to, to_at = _lists(col["to_v"])
        owner = np.repeat(np.arange(b.num_rows), np.diff(to_at))
        _, v = np.unique(np.concatenate((near, to)), return_inverse=True)
        bad = np.repeat(np.arange(b.num_rows), np.diff(near_at)) * len(v) + v[: len(near)]
        ok = np.flatnonzero(~np.isin(owner * len(v) + v[len(near) :], bad))
        flat, at = _lists(col["to_steps"].flatten())
        which, place = _spread(ok, at)
        width = int(flat.max(initial=0)) + 1
        step, times = np.unique(owner[ok][which] * width + flat[place], return_counts=True)
        s_at = np.searchsorted(step // width, np.arange(b.num_rows + 1))
        step = step % width
        size, leads = col["size"].to_numpy(), col["leads"].to_numpy(zero_copy_only=False)
        seeds, k_at = _lists(col["seeds"])
        grown, own = col["grown"].flatten(), np.repeat(np.arange(b.num_rows), np.diff(_ends(col["grown"])))
        fids, ns, pats = (grown.field(k).to_numpy(zero_copy_only=False) for k in range(3))
        out = ~pats & ((size[own] < l_min) | ((size[own] > l_max) if l_max is not None else False))
        made += int((np.diff(s_at)[own] * leads[own])[out].sum())
        own, fids, ns, pats = (x[~out] for x in (own, fids, ns, pats))
        pairs = np.diff(s_at)[own]
        cost = np.concatenate(([0], np.cumsum(pairs * np.diff(k_at)[own])))
        at = 0
        while at < len(own):
            end = max(at + 1, int(np.searchsorted(cost, cost[at] + at_once, "right")) - 1)
            some, at = slice(at, end), end
            if not pairs[some].sum():
                continue
            f_of, f_first, f = np.unique(fids[some], return_index=True, return_inverse=True)
            r = own[some]
            g, sp = _spread(r, s_at)
            r = r[g]
            s_of, s = np.unique(step[sp], return_inverse=True)
            child = f[g] * len(s_of) + s
            much = (ns[some][g] * times[sp] > 1) & leads[r]
            wide = size[r] > 1
            big, big_size = child[wide], size[r][wide]
            lo, hi = k_at[own[some].min()], k_at[own[some].max() + 1]
            k_of, k = np.unique(seeds[lo:hi], return_inverse=True)
            if (np.diff(k_at)[r] == 1).all():
                seed, first = k[k_at[r] - lo], leads[r]
            else:
                pair, place = _spread(r, k_at)
                seed, first = k[place - lo], (place == k_at[r[pair]]) & leads[r[pair]]
                child, much = child[pair], much[pair]
            names = None
            if len(f_of) * len(s_of) * len(k_of) * 4 > 1 << 62:
                names, child = np.unique(child, return_inverse=True)
                big = np.searchsorted(names, big)
            name, paths, n, seed = _combined(child, seed, first, much, len(k_of))
            largest = np.ones(len(name), np.int64)
            np.maximum.at(largest, np.searchsorted(name, big), big_size)
            if names is not None:
                name = names[name]
            parent, s = name // len(s_of), s_of[name % len(s_of)]
            bucket = (_mixed(f_of.view(np.uint64)[parent] + s.astype(np.uint64) * _P1) % np.uint64(buckets)).astype(np.min_scalar_type(buckets))
            order = np.argsort(bucket, kind="stable")
            n_at = np.concatenate(([0], np.cumsum(n)))
            seed = seed[_spread(order, n_at)[1]]
            parent, s, paths, largest, n, bucket = (x[order] for x in (parent, s, paths, largest, n, bucket))
            n_at = np.concatenate(([0], np.cumsum(n)))
            cut = np.append(np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1]))), len(bucket))
            sent = []
            for lo, hi in zip(cut[:-1], cut[1:], strict=True):
                p_of, p = np.unique(parent[lo:hi], return_inverse=True)
                q_of, q = np.unique(seed[n_at[lo] : n_at[hi]], return_inverse=True)
                rows = (f_of[p_of], pats[some][f_first[p_of]], k_of[q_of], _narrow(p), np.diff(s[lo:hi], prepend=0).astype(np.int32), _narrow(paths[lo:hi]), _narrow(largest[lo:hi]), _narrow(n[lo:hi]), _narrow(q))
                sent.append(_packed(rows))
            yield table(bucket[cut[:-1]].tolist(), 0, sent)
    yield table([None], made, [None])


def _found(batches: Iterator[pa.RecordBatch], classes: bytes, l_min: int, l_max: int | None, drop_single: bool) -> Iterator[pa.RecordBatch]:
    """Rows of FOUND from rows of PACKED with those of a bucket side by side. A row without a parent
    has, as its x, how many features were made, those out of the limits included."""
    is_class_step, made = np.frombuffer(classes, bool), 0

    def table(got: dict) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.bool_())
        return pa.RecordBatch.from_arrays([pa.array(v, kind) for v, kind in zip(got.values(), kinds, strict=True)], names=list(got))

    def whole(held: list[bytes]) -> tuple[dict, int]:
        """The features of a bucket, and how many there are with those out of the limits."""
        rows = [_unpacked(x) for x in held]
        f_of, f_first, f = np.unique(np.concatenate([x[0] for x in rows]), return_index=True, return_inverse=True)
        pats = np.concatenate([x[1] for x in rows])[f_first]
        k_of, k = np.unique(np.concatenate([x[2] for x in rows]), return_inverse=True)
        f_lo, k_lo = (np.concatenate(([0], np.cumsum([len(x[i]) for x in rows]))) for i in (0, 2))
        parent = np.concatenate([f[lo + x[3].astype(np.int64)] for lo, x in zip(f_lo, rows, strict=False)])
        s_of, s = np.unique(np.concatenate([np.cumsum(x[4]) for x in rows]), return_inverse=True)
        seed = np.concatenate([k[lo + x[8].astype(np.int64)] for lo, x in zip(k_lo, rows, strict=False)])
        part_paths, part_largest, part_n = (np.concatenate([x[i].astype(np.int64) for x in rows]) for i in (5, 6, 7))
        name, child = np.unique(parent * len(s_of) + s, return_inverse=True)
        paths = np.bincount(child, part_paths, len(name))
        largest = np.zeros(len(name), np.int64)
        np.maximum.at(largest, child, part_largest)
        pairs = np.repeat(child, part_n) * len(k_of) + seed
        del rows, child, seed
        pairs.sort()
        pairs = pairs[np.concatenate(([True], pairs[1:] != pairs[:-1]))]
        child = pairs // len(k_of)
        start = np.searchsorted(child, np.arange(len(name)))
        n = np.diff(np.append(start, len(child)))
        parent, step = name // len(s_of), s_of[name % len(s_of)]
        ok = n >= l_min
        if l_max is not None:
            ok &= n <= l_max
        if drop_single:
            ok &= (paths > 1) | ~(pats[parent].astype(bool) | is_class_step[step])
        x, y = (np.bitwise_xor.reduceat(h[pairs - child * len(k_of)], start) for h in _hashes(k_of))
        return {"parent": f_of[parent[ok]], "step": step[ok], "size": n[ok], "x": x[ok], "y": y[ok], "joined": (n > largest)[ok]}, len(name)

    held, at = [], None
    for b in batches:
        for bucket, count, rows in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
            made += count
            if bucket is None:
                continue
            if held and bucket != at:
                got, n = whole(held)
                made, held = made + n, []
                yield table(got)
            at = bucket
            held.append(rows.as_py())
    if held:
        got, n = whole(held)
        made += n
        yield table(got)
    yield table({"parent": [None], "step": [None], "size": [None], "x": [made], "y": [None], "joined": [None]})


def grow(ctx: Context, alive: DataFrame, elements: DataFrame, sets: DataFrame, h: int) -> tuple[DataFrame, int]:
    """(features found, how many were made). Found: (parent, pred, elem, is_class, sset, size, joined), within the
    limits of support; joined: the set is larger than that of any captured path."""
    p, ws = ctx.params, ctx.ws
    code = sets.groupBy("sset").agg(F.count("*").alias("size")).withColumn("id", F.xxhash64("sset"))
    code = ws.save(code, "set-numbers")
    dictionary.check_collisions(code, "id")
    arc = ctx.arc.join(alive.select(F.col("last").alias("src")).distinct(), "src", "left_semi").select("src", "pred", F.col("dst").alias("v"))
    kinds = arc.select("pred", "v").distinct().join(elements, "v").select("pred", "elem", "is_class").distinct()
    name = F.concat_ws(" ", "pred", "elem", "is_class").alias("uri")
    number = dictionary.dense_ids(ctx.spark, kinds.select(name), ws).select("uri", F.col("id").cast("int").alias("step"))
    step = ws.save(kinds.withColumn("uri", name).join(number, "uri").drop("uri"), "steps")
    bits = np.zeros(max(1, step.count()), bool)
    bits[[r["step"] for r in step.filter("is_class").select("step").toLocalIterator()]] = True
    to = arc.join(elements, "v").join(step, ["pred", "elem", "is_class"]).groupBy("src", "pred", "v").agg(F.collect_list("step").alias("steps"))
    to = ws.save(to.groupBy(F.col("src").alias("last")).agg(F.collect_list("v").alias("to_v"), F.collect_list("steps").alias("to_steps")), "steps-of")
    paths = alive.select("last", F.xxhash64("sset").alias("id"), "size", F.struct("fid", "n", "is_pattern").alias("g"))
    weight = to.select("last", F.aggregate("to_steps", F.lit(0), lambda a, x: a + F.size(x)).cast("long").alias("w"))
    total = paths.groupBy("last").agg(F.sum("size").alias("size")).join(weight, "last").agg(F.sum(F.col("size") * F.col("w"))).first()[0] or 0
    buckets = 1 + total // HEAVY
    # vertices that no seed of a set has at distance h: all have them nearer by, or are them
    nearer = ctx.reach.filter(F.col("dist") < h).select("seed", "v").union(ctx.seeds.select("seed", F.col("seed").alias("v")))
    nearer = nearer.join(arc.select("v").distinct(), "v", "left_semi")
    mine = sets.withColumn("id", F.xxhash64("sset")).select("id", "seed")
    near = nearer.join(mine, "seed").groupBy("id", "v").agg(F.count("*").alias("n")).join(code.select("id", "size"), "id").filter(F.col("n") == F.col("size"))
    near = near.groupBy("id").agg(F.collect_list("v").alias("near"))
    cut = mine.join(code.select("id", "size"), "id").withColumn("piece", F.pmod(F.xxhash64("seed", F.lit(2)), F.ceil(F.col("size") / PIECE)))
    cut = cut.groupBy("id", "piece").agg(F.first("size").cast("int").alias("size"), F.collect_list("seed").alias("seeds"))
    leads = F.col("piece") == F.min("piece").over(Window.partitionBy("id"))
    members = cut.withColumn("leads", leads).join(near, "id", "left").select(F.col("id").alias("sset"), "size", "leads", "seeds", F.coalesce("near", F.array().cast("array<bigint>")).alias("near"))
    met = paths.groupBy("last", "id").agg(F.collect_list("g").alias("grown")).withColumnRenamed("id", "sset")
    rows = met.join(to, "last").join(members, "sset").select("sset", "size", "leads", "seeds", "near", "grown", "to_v", "to_steps")
    sent = rows.mapInArrow(partial(_made, buckets=buckets, l_min=p.l_min, l_max=p.l_max, at_once=AT_ONCE), PACKED)
    tasks = max(int(ctx.spark.conf.get("spark.sql.shuffle.partitions")), buckets // 16)
    sent = sent.repartition(tasks, "bucket").sortWithinPartitions("bucket")
    got = sent.mapInArrow(partial(_found, classes=bits.tobytes(), l_min=p.l_min, l_max=p.l_max, drop_single=p.drop_single), FOUND)
    got = ws.save(got, f"found-{h}")
    ws.sweep()
    made = got.filter("parent is null").agg(F.sum("x")).first()[0] or 0
    sset = F.concat_ws("-", F.hex("x"), F.hex("y"), F.col("size").cast("string"))
    return got.filter("parent is not null").join(F.broadcast(step) if len(bits) <= FEW else step, "step").select("parent", "pred", "elem", "is_class", sset.alias("sset"), F.col("size").cast("long").alias("size"), "joined"), made
