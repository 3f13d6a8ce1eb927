"""Steps before mining: canonical graph, static limits, reach, classes."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.operators import blacklist, canon, degree, dictionary, reach, sieve, types
from kgfeat.params import SUBCLASS, TYPE, MiningParams
from kgfeat.plans.state import Workspace

SUBPROPERTY = "rdfs:subPropertyOf"
#: what an arc's predicate makes it, besides an arc that may be traversed
PLAIN, OF_TYPE, OF_SUBCLASS, OF_IDENTITY = range(4)


@dataclass
class Context:
    spark: SparkSession
    ws: Workspace
    params: MiningParams
    coding: dictionary.Coding
    seeds: DataFrame  # seed long
    arc: DataFrame  # arcs to traverse
    inst: DataFrame  # v, class
    sub: DataFrame  # class, super
    unusable: DataFrame | None  # classes not to generalise to
    general: DataFrame | None  # pred, up: more general predicates, if they are mined
    reach: DataFrame | None = None
    depth: int = 0
    made: dict = field(default_factory=dict)

    def vertex(self) -> DataFrame:
        """(v, uri) with the top class."""
        return dictionary.with_top(self.coding.vertex)

    def predicate(self) -> DataFrame:
        p = self.coding.predicate
        if self.params.u and self.params.direction_aware:
            p = p.union(p.select(degree.inverse("pred").alias("pred"), F.concat(F.lit("^"), "name").alias("name")))
        return p

    # classes are worked out when first asked for: a search for neighbours alone does without

    @cached_property
    def climb(self) -> DataFrame:
        return types.climbs(self.ws, self.sub)

    @cached_property
    def inst_levels(self) -> DataFrame:
        p = self.params
        climb = self.climb if p.t is None or p.t > 1 else None
        return self.ws.save(types.levels(self.ws, self.reach.select("v"), self.inst, self.sub, p.t, self.unusable, p.use_top, climb), "class-levels")

    @cached_property
    def type_support(self) -> DataFrame:
        return self.ws.save(types.supports(self.reach, self.inst_levels), "class-supports")

    @property
    def usable_types(self) -> DataFrame:
        return types.frequent(self.type_support, self.params.l_min) if self.params.type_filter else self.inst_levels.select("class").distinct()

    def classes_named(self, entries: tuple[str, ...]) -> DataFrame:
        """(class) of the classes with a listed URI."""
        return _named(self.inst, self.sub, self.coding.vertex, entries)


def _named(inst: DataFrame, sub: DataFrame, vertex: DataFrame, entries: tuple[str, ...]) -> DataFrame:
    vocab = inst.select("class").union(sub.select("class")).union(sub.select("super")).distinct()
    listed = blacklist.match(vertex, entries).select(F.col("v").alias("class"))
    return vocab.join(listed, "class", "left_semi")


def seeds_of_class(triples: DataFrame, cls: str, ws: Workspace) -> DataFrame:
    """Seeds by intension: instances of a class, direct or inherited, as URIs."""
    inst = triples.filter(F.col("p") == TYPE).select(F.col("s").alias("v"), F.col("o").alias("class"))
    sub = triples.filter(F.col("p") == SUBCLASS).select(F.col("s").alias("class"), F.col("o").alias("super"))
    want = triples.sparkSession.createDataFrame([(cls,)], "class string")
    return types.instances_of(ws, inst, sub, want).select(F.col("v").alias("seed"))


def _merged(ws: Workspace, same: DataFrame, method: str) -> DataFrame:
    """canonical_map of identity triples by hashes."""
    ends = ws.save(dictionary.ends(same).select(dictionary.code(F.col("uri")).alias("v"), "uri"), "merged-vertex")
    dictionary.check_collisions(ends)
    arcs = same.select(dictionary.code(F.col("s")).alias("src"), dictionary.code(F.col("o")).alias("dst")).distinct()
    return ws.save(canon.named_map(ws, arcs, ends, method), "canon")


def _around(ws: Workspace, t: DataFrame, names: DataFrame, s: DataFrame, params: MiningParams, merged: DataFrame | None, hops: float) -> tuple[dictionary.Coding, DataFrame, DataFrame, DataFrame, DataFrame]:
    """(coding, arcs, instances, subclasses, seeds) as far as seeds reach in so many steps."""
    predicate = ws.save(names.select(F.col("p").alias("name")).distinct().select(dictionary.code(F.col("name")).alias("pred"), "name"), "predicate")
    dictionary.check_collisions(predicate, "pred")
    coding = dictionary.Coding(None, predicate, False)
    enc, s = coding.arcs(t).select("src", "pred", "dst", "kind", "banned"), coding.of(s, "seed").select("seed")
    if params.canonicalise:
        enc = enc.filter(F.col("kind") != OF_IDENTITY)
    if merged is not None:
        enc = canon.replaced(canon.replaced(enc, merged, "src", True), merged, "dst", True).select("src", "pred", "dst", "kind", "banned")
        s = canon.replaced(s, merged, "seed", True)
    s = ws.save(s.distinct(), "seeds")
    d = None if params.seed_hub_exempt else params.d
    arc = enc.filter("not banned").select("src", "pred", "dst")
    if params.u:
        arc = degree.both_ways(arc, params.direction_aware)
    arc, seen = reach.nearby_arcs(ws, arc, s, hops, d)
    sub = ws.save(enc.filter(F.col("kind") == OF_SUBCLASS).select(F.col("src").alias("class"), F.col("dst").alias("super")).distinct(), "subclasses")
    seen = ws.save(seen, "around")
    inst = enc.filter(F.col("kind") == OF_TYPE).select(F.col("src").alias("v"), F.col("dst").alias("class"))
    inst = ws.save(sieve.semi(inst, "v", seen, seen.count()).distinct(), "instances")
    # every URI with the integer of a vertex that is kept, so that no collision with one goes unseen
    kept = seen.union(inst.select("class")).union(sub.select("class")).union(sub.select("super"))
    if merged is not None:
        kept = kept.union(merged.select("v")).union(merged.select("c"))
    kept = ws.save(kept.distinct(), "kept")
    n = kept.count()
    uris = names.select(F.explode(F.array("s", "o")).alias("uri")).filter("uri is not null").select(dictionary.code(F.col("uri")).alias("v"), "uri")
    uris = sieve.sift(uris, "v", kept, n).distinct()
    coding.vertex = ws.save(uris if n <= sieve.FEW else uris.join(kept, "v").select("v", "uri"), "vertex")
    dictionary.check_collisions(coding.vertex)
    return coding, arc.withColumn("banned", F.lit(False)), inst, sub, s


def _whole(ws: Workspace, t: DataFrame, names: DataFrame, s: DataFrame, params: MiningParams, method: str) -> tuple[dictionary.Coding, DataFrame, DataFrame, DataFrame, DataFrame]:
    """(coding, arcs, instances, subclasses, seeds) of the whole graph."""
    coding = dictionary.coding(ws, names, params.ids)
    enc = coding.arcs(t).select("src", "pred", "dst", "kind", "banned").distinct()
    enc = ws.save(enc, "arcs")
    s = coding.of(s, "seed").select("seed").distinct()
    if params.canonicalise:
        same = enc.filter(F.col("kind") == OF_IDENTITY)
        enc = enc.filter(F.col("kind") != OF_IDENTITY)
        if not same.isEmpty():
            merged = ws.save(canon.named_map(ws, same, coding.vertex, method), "canon")
            few = merged.count() <= canon.BROADCAST_MAP
            enc = ws.save(canon.replaced(canon.replaced(enc, merged, "src", few), merged, "dst", few).select("src", "pred", "dst", "kind", "banned").distinct(), "canonical")
            s = canon.replaced(s, merged, "seed", few).distinct()
    s = ws.save(s, "seeds")
    inst = ws.save(enc.filter(F.col("kind") == OF_TYPE).select(F.col("src").alias("v"), F.col("dst").alias("class")), "instances")
    sub = ws.save(enc.filter(F.col("kind") == OF_SUBCLASS).select(F.col("src").alias("class"), F.col("dst").alias("super")), "subclasses")
    return coding, enc, inst, sub, s


def prepare(spark: SparkSession, triples: DataFrame, seeds: DataFrame, params: MiningParams, ws: Workspace | None = None, method: str = "star", pred_same: DataFrame | None = None, around: float | None = None) -> Context:
    """Encode, canonicalise, and settle every limit on traversal.

    triples (s, p, o) strings, not necessarily a set, rows with a null are left out; seeds (seed) URIs.
    pred_same (a, b): predicates that mean the same, merged like vertices. URIs become integers first;
    everything after that, contraction included, is joins of integers. around: keep only the part of the
    graph that seeds reach in so many steps (infinity: in any number), which is all that a search of that
    depth and mining on it use; triples are then read once a step and the whole graph is never stored.
    """
    ws = ws or Workspace(spark, "mine")
    t = triples.select("s", "p", "o").na.drop()
    s = seeds.select("seed").na.drop().distinct()
    if pred_same is not None:
        t = canon.replaced(t, ws.save(canon.canonical_map(spark, pred_same, ws=ws), "predicates"), "p")
    up = None
    if params.predicate_levels:
        up = ws.save(types.climb_predicates(ws, t.filter(F.col("p") == SUBPROPERTY), params.predicate_levels), "general")
        t = t.filter(F.col("p") != SUBPROPERTY)
    kind = F.when(F.col("p") == TYPE, OF_TYPE).when(F.col("p") == SUBCLASS, OF_SUBCLASS).when(F.col("p") == params.identity, OF_IDENTITY).otherwise(PLAIN).cast("tinyint")
    names = t if up is None else t.unionByName(up.select(F.lit(None).cast("string").alias("s"), F.col("up").alias("p"), F.lit(None).cast("string").alias("o")))
    marks = {"kind": kind, "banned": blacklist.matches(F.col("p"), params.b_predicates)}
    local = around is not None and params.ids == "hash" and (not params.u or params.d is None)  # arcs both ways do not give degrees
    merged = None
    if local:
        same = t.filter(F.col("p") == params.identity) if params.canonicalise else None
        merged = _merged(ws, same, method) if same is not None and not same.isEmpty() else None
        local = merged is None or merged.count() <= canon.BROADCAST_MAP
    if local:
        coding, enc, inst, sub, s = _around(ws, t.withColumns(marks), names, s, params, merged, around)
    else:
        coding, enc, inst, sub, s = _whole(ws, t.withColumns(marks), names, s, params, method)

    def listed(entries: tuple[str, ...]) -> DataFrame | None:
        return _named(inst, sub, coding.vertex, entries) if entries else None

    no_go = listed(params.b_exp_types)
    banned = ws.save(types.instances_of(ws, inst, sub, no_go), "banned") if no_go is not None else None
    turn = params.u and not local
    arc = degree.allowed(enc.filter("not banned").select("src", "pred", "dst"), params.d, turn, banned, s if params.seed_hub_exempt else None, params.direction_aware)
    if params.bucket_arcs:
        arc = ws.save_bucketed(arc, "arc", params.bucket_arcs, "src")
    elif params.d is not None or turn or banned is not None:
        arc = ws.save(arc, "arc")
    general = None
    if up is not None:
        code = coding.predicate
        general = up.join(code, up["p"] == code["name"]).select("pred", "up").join(code.select(F.col("pred").alias("g"), F.col("name").alias("up")), "up").select("pred", F.col("g").alias("up"))
        general = ws.save(general, "general-predicates")
    return Context(spark, ws, params, coding, s, arc, inst, sub, listed(params.b_gen_types), general)


def search(ctx: Context, full: bool = False) -> Context:
    """Fill in reach."""
    ctx.reach, ctx.depth = reach.fixpoint(ctx.ws, ctx.arc, ctx.seeds) if full else reach.bfs(ctx.ws, ctx.arc, ctx.seeds, ctx.params.k)
    return ctx
