"""Level-wise mining of paths and path patterns.

Two engines share selection. The factorised one keeps ``alive(fid, last, sset, size, n)``: features
with their captured paths grouped by last vertex and support set, which is all that expansion, support
and pruning depend on:

* growing a path leaves its support set as it was after its first arc, so the set's id is inherited and
  the members of all paths' sets are known after the first iteration;
* a pattern's set is the union of the distinct sets of its paths, however many paths there are, and patterns
  that join the same sets share one union, in this iteration and in later ones;
* paths of too little support matter only through the patterns that capture them.

The faithful engine lists every path and every (path, pattern) dependency, which gives the number of
path features generated; both find the same features. Of an iteration the captured paths, the unions
of support sets, the decisions and the rows to go on with are committed; what lies between is cached
and can be made again from these. Of the factorised engine's last iteration, and of the faithful one's if it
is large, only the features within the limits are committed (``last``); their captured paths and unions are made when they are asked for.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgfeat.operators import specific, supports, types
from kgfeat.plans import last
from kgfeat.plans.context import Context

#: what is kept of each iteration's decisions
DECIDED = ("fid", "preds", "elems", "classes", "is_pattern", "sset", "size", "joined", "joins", "chosen", "replaces")
FEATURE = "fid long, preds array<bigint>, elems array<bigint>, classes array<boolean>, len int, kind string, sset string, n long, joined boolean, joins string"


@dataclass
class Mined:
    """features: one row a path feature (see FEATURE; joined: its set is the union of several
    sets, and joins the id of these); sets (sset, seed): support sets of paths; unions (joins, seed): the unions;
    captured (fid, sset, n): paths that a feature captures, by support set; generated: path features made
    in each iteration before any was discarded."""

    features: DataFrame
    sets: DataFrame
    unions: DataFrame
    captured: DataFrame
    generated: list[int] = field(default_factory=list)

    def cells(self) -> DataFrame:
        """(seed, fid): true cells of the matrix."""
        own = self.features.filter("not joined").select("fid", "sset").join(self.sets, "sset").select("seed", "fid")
        return own.union(self.unions.join(self.features.filter("joined").select("fid", "joins"), "joins").select("seed", "fid"))

    def counts(self) -> DataFrame:
        """(seed, fid, n): how many paths from the seed a feature captures, features of any length."""
        rows = self.captured.join(self.features.select("fid"), "fid", "left_semi").groupBy("fid", "sset").agg(F.sum("n").alias("n"))
        return rows.join(self.sets, "sset").groupBy("seed", "fid").agg(F.sum("n").alias("n"))

    def only(self, fids: DataFrame, ws) -> Mined:
        """The same run with the features of fids (fid) alone."""
        return replace(self, features=ws.save(self.features.join(fids, "fid", "left_semi"), "kept"))


def _child() -> Column:
    """Id of the feature (parent, pred, elem); a step by a class or a more general predicate is another one."""
    return F.xxhash64("parent", "pred", "elem", F.col("is_class").cast("int") + 2 * F.col("is_up").cast("int"))


def _steps(ctx: Context, want_patterns: bool) -> tuple[DataFrame, DataFrame | None]:
    """elements (v, elem, is_class) that may stand for a vertex; and (pred, as_pred, is_up) that may stand
    for a predicate, if the predicate hierarchy is mined."""
    own = ctx.reach.select("v").distinct().select("v", F.col("v").alias("elem"), F.lit(False).alias("is_class"))
    if not want_patterns:
        return own, None
    usable = ctx.inst_levels.join(ctx.usable_types, "class", "left_semi")
    own = own.union(usable.select("v", F.col("class").alias("elem"), F.lit(True).alias("is_class")))
    if ctx.general is None:
        return own, None
    same = ctx.predicate().select("pred", F.col("pred").alias("as_pred"), F.lit(False).alias("is_up"))
    above = ctx.general.union(ctx.general.select("up", "up").distinct())  # a general predicate covers its own arcs too
    return own, same.union(above.select("pred", F.col("up").alias("as_pred"), F.lit(True).alias("is_up")))


def _stood_for(ext: DataFrame, elements: DataFrame, preds: DataFrame | None) -> DataFrame:
    """ext rows (pred, v, ...) with what may stand for the step: pred, elem, is_class, is_up."""
    rows = ext.join(elements, "v")
    if preds is None:
        return rows.withColumn("is_up", F.lit(False))
    return rows.join(preds, "pred").withColumn("pred", F.col("as_pred")).drop("as_pred")


def mine_path_features(ctx: Context) -> Mined:
    p, ws = ctx.params, ctx.ws
    faithful = p.engine == "faithful"
    want_patterns = "pattern" in p.kinds
    elements, stand = _steps(ctx, want_patterns)
    elements = ws.save(elements, "elements")
    ancs = types.ancestors(ws, ctx.reach.select("v"), ctx.inst, ctx.sub, ctx.climb) if want_patterns else elements.select(F.col("elem").alias("e"), F.array("elem").alias("ancs"))
    up = ancs.select(F.col("e").alias("elem"), F.col("ancs").alias("up"))

    # h = 1: the empty path of all seeds grows to every vertex at distance 1 of some seed
    near = ctx.reach.filter("dist = 1").select("v").distinct()
    first = ctx.arc.join(ctx.seeds.select(F.col("seed").alias("src")), "src", "left_semi").join(near.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "pred", "dst").distinct()
    ext = ws.save(first.groupBy("pred", F.col("dst").alias("v")).agg(supports.set_id("src").alias("sset"), F.count("*").alias("size")).withColumns({"fid": F.lit(0).cast("long"), "n": F.lit(1).cast("long")}), "paths-1")
    sets = ws.save(first.join(ext.select("pred", F.col("v").alias("dst"), "sset"), ["pred", "dst"]).select("sset", F.col("src").alias("seed")).distinct(), "sets")
    feats = ctx.spark.createDataFrame([(0, [], [], [], [], False, None, None, None)], "fid long, preds array<bigint>, elems array<bigint>, classes array<boolean>, ancs array<array<bigint>>, is_pattern boolean, sel long, sel_sset string, sel_class boolean")
    deps, generated = None, []
    chosen_in, unions_of, rows_of, known, at_last = [], [], [], None, None
    may_skip = want_patterns and ctx.general is None and p.d is not None and not p.seed_hub_exempt
    unlisted = False  # whether the last iteration goes without rows of captured paths

    for h in range(1, p.k + 1):
        if h > 1:
            if alive.isEmpty():  # noqa: F821
                break
            # to avoid loops: some seed of the path's set has the new vertex at distance h exactly
            step = ctx.arc.select(F.col("src").alias("last"), F.col("dst").alias("v")).distinct()
            pairs = alive.select("sset", "last").distinct().join(step, "last").select("sset", "v").distinct().join(sets, "sset")  # noqa: F821
            ok = pairs.join(ctx.reach.filter(F.col("dist") == h).select("seed", "v"), ["seed", "v"], "left_semi").select("sset", "v").distinct()
            ext = alive.join(ctx.arc, alive["last"] == ctx.arc["src"]).select("fid", "pred", F.col("dst").alias("v"), "sset", "size", "n", "is_pattern").join(ok, ["sset", "v"], "left_semi")  # noqa: F821
            if faithful:
                ext = ext if unlisted else ext.filter("not is_pattern")  # noqa: F821
            ext = ext.drop("is_pattern")
        if unlisted and h == p.k:
            found, made = last.grow(ctx, alive, elements, sets, h)  # noqa: F821
            generated.append(made)
            if made:
                paths = _stood_for(ext, elements, stand).withColumnRenamed("fid", "parent").select(_child().alias("fid"), "sset", "n")
                live, union = _decide_last(ctx, found.withColumn("is_up", F.lit(False)), large, up, paths, sets, known, h)  # noqa: F821
                at_last = live
                unions_of.append(union)
                rows_of.append(paths)
            break
        if faithful:
            rows, links = _generalise_each(ext, deps, elements, stand, h)
            if h < p.k:  # the last iteration's would only tell what to go on with
                links = ws.save(links, f"links-{h}")
        else:
            rows, links = _stood_for(ext, elements, stand).withColumnRenamed("fid", "parent").withColumn("fid", _child()), None
        made_of = ("parent", "pred", "elem", "is_class", "is_up")
        rows = rows.groupBy("fid", "v", "sset").agg(*(F.first(c).alias(c) for c in made_of), F.first("size").alias("size"), F.sum("n").alias("n"))
        rows = ws.save(rows, f"generated-{h}")
        ws.sweep()
        clash = (F.min("parent") != F.max("parent")) | (F.min("pred") != F.max("pred")) | (F.min("elem") != F.max("elem"))
        per = rows.groupBy("fid", "sset").agg(*(F.first(c).alias(c) for c in made_of), F.sum("n").alias("n"), F.first("size").alias("size"), clash.alias("mixed"))
        several = F.min("sset") != F.max("sset")
        per = per.groupBy("fid").agg(*(F.first(c).alias(c) for c in made_of), F.sum("n").alias("n_paths"), F.max("size").alias("largest"), F.sum("size").alias("most"), F.min("sset").alias("one"), several.alias("joined"), F.when(several, supports.set_id("sset")).alias("joins"), (clash | F.max("mixed")).alias("mixed"))
        old = feats.select(F.col("fid").alias("parent"), "preds", "elems", "classes", "ancs", F.col("is_pattern").alias("from_pattern"), "sel", "sel_sset", "sel_class")
        full = per.join(old, "parent").join(up, "elem")
        full = full.select("fid", F.array_append("preds", F.col("pred")).alias("preds"), F.array_append("elems", F.col("elem")).alias("elems"), F.array_append("classes", F.col("is_class")).alias("classes"), F.array_append("ancs", F.col("up")).alias("ancs"), (F.col("from_pattern") | F.col("is_class") | F.col("is_up")).alias("is_pattern"), "one", "joined", "joins", "mixed", "largest", "most", "n_paths", "is_class", "sel", "sel_sset", "sel_class").persist()
        count, mixed = full.agg(F.count("*"), F.max("mixed")).first()
        if mixed:
            raise ValueError("two path features have the same 64-bit id")
        generated.append(count)
        if not count:
            full.unpersist()
            break
        several = full.filter("joined")
        if p.prune:  # a union is no larger than the sum of its sets
            several = several.filter(F.col("most") >= p.l_min)
        several = several.groupBy("joins").agg(F.min("fid").alias("fid"))  # one of those that join the same sets
        if known is not None:
            several = several.join(known.select("joins"), "joins", "left_anti")
        union = ws.save(supports.unions(rows.select("fid", "sset").join(several, "fid").select("joins", "sset"), sets, "joins"), f"unions-{h}")
        fresh = ws.save(supports.sized(union, "joins").select("joins", F.col("sset").alias("u"), F.col("n").alias("un")), f"sizes-{h}")
        known = fresh if known is None else known.union(fresh)
        sized = full.join(known, "joins", "left").select(*full.columns, "u", "un")
        sized = sized.withColumns({"sset": F.when(F.col("joined"), F.col("u")).otherwise(F.col("one")), "size": F.when(F.col("joined"), F.coalesce("un", "most")).otherwise(F.col("largest"))}).drop("u", "un", "one", "most", "mixed")

        pats = sized.filter("is_pattern")
        if p.prune:
            pats = pats.filter(F.col("size") >= p.l_min)
        if p.drop_single:
            pats = pats.filter("n_paths > 1")
        pats = pats.persist()
        best = _most_specific(ctx, pats, p.specificity)
        paths = sized.filter("not is_pattern")
        live = paths.unionByName(best)
        again = F.coalesce(F.col("sel_sset") == F.col("sset"), F.lit(False)) if p.c2 else F.lit(False)
        fit = supports.within(F.col("size"), p.l_min, p.l_max) & (~again | (~F.col("is_class") & F.coalesce("sel_class", F.lit(False))))
        if p.c3:
            fit = fit & (~F.col("is_pattern") | (F.col("largest") < F.col("size")))
        live = ws.save(live.withColumns({"chosen": fit, "replaces": F.when(fit & again, F.col("sel"))}).drop("largest", "n_paths"), f"decided-{h}")
        full.unpersist()
        pats.unpersist()
        ws.sweep()
        chosen_in.append(live.select(*DECIDED))
        unions_of.append(union)
        rows_of.append(rows.select("fid", "sset", "n"))
        if h == p.k:
            break

        going = live if faithful or not p.prune else live.filter(F.col("is_pattern") | (F.col("size") >= p.l_min))
        if faithful:
            deps = links.join(live.filter("is_pattern").select("fid"), "fid", "left_semi")
            if p.prune:
                deps = ws.save(deps, f"dependencies-{h}")
                held = live.filter(~F.col("is_pattern") & (F.col("size") >= p.l_min)).select("fid").union(deps.select(F.col("path").alias("fid"))).distinct()
                going = live.filter("is_pattern").unionByName(live.filter("not is_pattern").join(held, "fid", "left_semi"))
        lost = live.filter("replaces is not null").select(F.col("replaces").alias("sel"), F.lit(True).alias("lost")).distinct()
        kept = lambda new, was: F.when(F.col("chosen"), F.col(new)).when(F.col("lost"), F.lit(None)).otherwise(F.col(was))
        feats, large = (x.join(lost, "sel", "left").select("fid", "preds", "elems", "classes", "ancs", "is_pattern", kept("fid", "sel").alias("sel"), kept("sset", "sel_sset").alias("sel_sset"), kept("is_class", "sel_class").alias("sel_class")) for x in (going, going.filter(F.col("size") >= p.l_min)))
        grow = going if may_skip and h + 1 == p.k or not faithful else going.filter("not is_pattern")
        alive = ws.save(rows.join(grow.select("fid", "is_pattern"), "fid").select("fid", F.col("v").alias("last"), "sset", "size", "n", "is_pattern"), f"alive-{h}")
        ws.sweep()
        unlisted = may_skip and h + 1 == p.k and (not faithful or alive.count() > last.LISTED)

    if not chosen_in:
        none = ctx.spark.createDataFrame([], FEATURE)
        return Mined(none, sets, none.select("joins", F.col("n").alias("seed")), none.select("fid", "sset", "n"), generated)
    all_ = reduce(DataFrame.unionByName, chosen_in)
    lost = (all_ if at_last is None else all_.unionByName(at_last)).filter("replaces is not null").select(F.col("replaces").alias("fid")).distinct()
    kind = F.when(F.col("is_pattern"), "pattern").otherwise("path")

    def named(rows: DataFrame) -> DataFrame:
        rows = rows.select("fid", "preds", "elems", "classes", F.size("elems").alias("len"), kind.alias("kind"), "sset", F.col("size").alias("n"), "joined", "joins")
        return rows.filter(F.col("kind").isin(*p.kinds)) if p.kinds & {"path", "pattern"} else rows.filter("false")

    found = ws.save(named(all_.filter("chosen").join(lost, "fid", "left_anti")), "selected")
    if at_last is not None:  # what was chosen last is replaced by nothing
        found = found.union(named(at_last))
    return Mined(found, sets, reduce(DataFrame.union, unions_of), reduce(DataFrame.union, rows_of), generated)


def _decide_last(ctx: Context, found: DataFrame, feats: DataFrame, up: DataFrame, paths: DataFrame, sets: DataFrame, known: DataFrame | None, h: int) -> tuple[DataFrame, DataFrame]:
    """(chosen features of the last iteration, unions (joins, seed) that are not among those known). found: see
    ``last.grow``; feats: the features they grow from; paths (fid, sset, n).

    A pattern is held only against patterns of the same predicates and support set, and only if it would be chosen.
    """
    p, ws = ctx.params, ctx.ws
    old = feats.select(F.col("fid").alias("parent"), "preds", "elems", "classes", "ancs", F.col("is_pattern").alias("from_pattern"), "sel", "sel_sset", "sel_class")
    brief = old.select("parent", F.xxhash64("preds").alias("before"), "from_pattern", "sel", "sel_sset", "sel_class")
    rows = found.withColumn("fid", _child()).join(F.broadcast(brief) if feats.count() <= last.FEW else brief, "parent")
    again = F.coalesce(F.col("sel_sset") == F.col("sset"), F.lit(False)) if p.c2 else F.lit(False)
    fit = ~again | (~F.col("is_class") & F.coalesce("sel_class", F.lit(False)))
    rows = rows.withColumn("is_pattern", F.col("from_pattern") | F.col("is_class"))
    if p.c3:
        fit = fit & (~F.col("is_pattern") | F.col("joined"))
    rows = rows.withColumns({"chosen": fit, "replaces": F.when(fit & again, F.col("sel")), "alike": F.xxhash64("sset", "before", "pred")})
    rows = ws.save(rows.select("fid", "parent", "pred", "elem", "is_class", "is_pattern", "sset", "size", "joined", "chosen", "replaces", "alike"), f"within-{h}")
    if not rows.groupBy("fid").agg(F.count("*").alias("n")).filter("n > 1").isEmpty():
        raise ValueError("two path features have the same 64-bit id")
    live = rows.filter("chosen")
    if p.specificity != "off":
        pats = rows.filter("is_pattern")
        several = pats.groupBy("alike").agg(F.count("*").alias("n"), F.max("chosen").alias("any")).filter("n > 1 and any")
        pats = pats.join(several, "alike", "left_semi").select("fid", "parent", "pred", "elem", "sset").join(old.select("parent", "preds", "elems", "ancs"), "parent").join(up, "elem")
        pats = pats.select("fid", "sset", F.array_append("preds", F.col("pred")).alias("preds"), F.array_append("elems", F.col("elem")).alias("elems"), F.array_append("ancs", F.col("up")).alias("ancs"))
        live = live.join(specific.dominated(ws.save(pats, f"alike-{h}"), p.specificity), "fid", "left_anti")
    live = live.drop("alike").join(old.select("parent", "preds", "elems", "classes"), "parent")
    live = live.withColumns({"preds": F.array_append("preds", F.col("pred")), "elems": F.array_append("elems", F.col("elem")), "classes": F.array_append("classes", F.col("is_class"))})
    own = F.concat(F.lit("last-"), F.col("sset"))
    if known is None:
        live = live.withColumn("as", F.lit(None).cast("string"))
    else:
        live = live.join(known.groupBy(F.col("u").alias("sset")).agg(F.min("joins").alias("as")), "sset", "left")
    live = ws.save(live.select(*(c for c in DECIDED if c != "joins"), "as"), f"decided-{h}")
    live = live.withColumn("joins", F.when(F.col("joined"), F.coalesce("as", own))).select(*DECIDED)
    fresh = live.filter(F.col("joined") & F.col("joins").startswith("last-")).groupBy("joins").agg(F.min("fid").alias("fid"))
    return live, supports.unions(paths.join(fresh, "fid").select("joins", "sset"), sets, "joins")


def _most_specific(ctx: Context, pats: DataFrame, impl: str) -> DataFrame:
    """The rows of pats without those that have a more specific one of the same support set.

    With a predicate hierarchy predicates are compared like elements, place by place.
    """
    if ctx.general is None or impl == "off":
        return specific.maximal(pats, impl)
    above = ctx.predicate().select("pred", F.col("pred").alias("up")).union(ctx.general).groupBy("pred").agg(F.collect_set("up").alias("ups"))
    named = pats.select("fid", F.posexplode("preds").alias("pos", "pred")).join(above, "pred").groupBy("fid").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "ups"))), lambda x: x["ups"]).alias("pa"))
    both = pats.join(named, "fid").select("fid", "sset", F.array().cast("array<bigint>").alias("preds"), F.concat("preds", "elems").alias("elems"), F.concat("pa", "ancs").alias("ancs"))
    return pats.join(specific.dominated(both, impl), "fid", "left_anti")


def _generalise_each(ext: DataFrame, deps: DataFrame | None, elements: DataFrame, stand: DataFrame | None, h: int) -> tuple[DataFrame, DataFrame]:
    """Every path and pattern with the path it captures: (rows, links (path, fid)).

    ext rows are paths to grow; deps (path, fid) are the surviving patterns of those paths.
    """
    new = ext.withColumnRenamed("fid", "old").withColumn("path", F.xxhash64("old", "pred", "v", F.lit(0)))
    each = _stood_for(new, elements, stand)
    cols = ["parent", "pred", "elem", "is_class", "is_up", "v", "sset", "size", "n", "path"]
    both = each.withColumnRenamed("old", "parent").select(*cols)
    if h > 1 and deps is not None:
        both = both.union(each.join(deps.select(F.col("path").alias("old"), F.col("fid").alias("parent")), "old").select(*cols))
    both = both.withColumn("fid", _child())
    return both.drop("path"), both.filter("fid <> path").select("path", "fid").distinct()
