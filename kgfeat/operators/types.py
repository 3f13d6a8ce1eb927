"""Classes of vertices: levels in the hierarchy, closures, blacklisted instances, interesting classes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgfeat.params import TOP
from kgfeat.plans.state import Workspace


def instances_of(ws: Workspace, inst: DataFrame, sub: DataFrame, classes: DataFrame) -> DataFrame:
    """(v) that are instances of the given classes (class) or of any class below them."""
    seen = front = ws.save(classes.select("class").distinct(), "banned-classes")
    while True:
        below = sub.join(front.select(F.col("class").alias("super")), "super", "left_semi").select("class").distinct()
        front = ws.save(below.join(seen, "class", "left_anti"), "banned-classes")
        if front.isEmpty():
            break
        seen = seen.union(front)
    return inst.join(seen, "class", "left_semi").select("v").distinct()


def climbs(ws: Workspace, sub: DataFrame) -> DataFrame:
    """(class, anc, steps): every class above a class with the fewest steps to it, itself not included
    unless the hierarchy has a cycle. The loop is over classes, never over their instances."""
    seen = front = ws.save(sub.select("class", F.col("super").alias("anc"), F.lit(1).alias("steps")).distinct(), "climb")
    steps = 1
    while True:
        up = front.select("class", "anc").join(sub.select(F.col("class").alias("anc"), "super"), "anc").select("class", F.col("super").alias("anc")).distinct()
        steps += 1
        front = ws.save(up.join(seen.select("class", "anc"), ["class", "anc"], "left_anti").withColumn("steps", F.lit(steps)), "climb")
        if front.isEmpty():
            return seen
        seen = seen.union(front)


def levels(ws: Workspace, vertices: DataFrame, inst: DataFrame, sub: DataFrame, t: int | None, unusable: DataFrame | None = None, use_top: bool = True, climb: DataFrame | None = None) -> DataFrame:
    """(v, class, level): a direct class has level 1, each step up the hierarchy one more, the shortest way
    counts; the top class has level 0. t None: no bound. ``unusable`` classes are climbed through, then left
    out. climb: the hierarchy's ``climbs``, if they are known."""
    own = vertices.select("v").distinct()
    top = own.select("v", F.lit(TOP).cast("long").alias("class"), F.lit(0).alias("level"))
    direct = inst.join(own, "v", "left_semi").select("v", "class", F.lit(1).alias("level"))
    out = direct.filter("false") if t == 0 else direct.distinct()
    if t is None or t > 1:
        far = climbs(ws, sub) if climb is None else climb
        if t is not None:
            far = far.filter(F.col("steps") < t)
        above = direct.select("v", "class").join(far, "class").select("v", F.col("anc").alias("class"), (F.col("steps") + 1).alias("level"))
        out = out.union(above).groupBy("v", "class").agg(F.min("level").alias("level"))
    if unusable is not None:
        out = out.join(unusable, "class", "left_anti").select("v", "class", "level")
    return out.union(top) if use_top else out


def ancestors(ws: Workspace, vertices: DataFrame, inst: DataFrame, sub: DataFrame, climb: DataFrame | None = None) -> DataFrame:
    """(e, ancs): for each vertex and each class, itself, all classes above it and the top class."""
    up = (climbs(ws, sub) if climb is None else climb).select("class", "anc")
    of_class = up.select(F.col("class").alias("e"), "anc")
    mine = inst.join(vertices.select("v").distinct(), "v", "left_semi").select(F.col("v").alias("e"), "class")
    of_vertex = mine.select("e", F.col("class").alias("anc")).union(mine.join(up, "class").select("e", "anc"))
    elems = vertices.select(F.col("v").alias("e")).union(inst.select("class")).union(sub.select("class")).union(sub.select("super")).distinct()
    rows = of_class.union(of_vertex).union(elems.select("e", F.col("e").alias("anc"))).union(elems.select("e", F.lit(TOP).cast("long")))
    rows = rows.union(vertices.sparkSession.createDataFrame([(TOP, TOP)], "e long, anc long"))
    return ws.save(rows.groupBy("e").agg(F.array_sort(F.collect_set("anc")).alias("ancs")), "ancestors")


def climb_predicates(ws: Workspace, sub: DataFrame, levels: int) -> DataFrame:
    """(p, up): predicates above a predicate by up to so many steps of triples (s, p, o) of a predicate hierarchy."""
    step = ws.save(sub.select(F.col("s").alias("p"), F.col("o").alias("up")).distinct(), "predicate-steps")
    seen = front = step
    for _ in range(levels - 1):
        front = front.join(step.select(F.col("p").alias("up"), F.col("up").alias("far")), "up").select("p", F.col("far").alias("up")).distinct()
        front = ws.save(front.join(seen, ["p", "up"], "left_anti"), "predicate-steps")
        if front.isEmpty():
            break
        seen = seen.union(front)
    return seen.filter("p <> up")


def supports(reach: DataFrame, inst: DataFrame) -> DataFrame:
    """(class, n): seeds with a neighbour of the class, over all neighbours."""
    return reach.select("seed", "v").join(inst.select("v", "class"), "v").select("class", "seed").distinct().groupBy("class").agg(F.count("*").alias("n"))


def frequent(support: DataFrame, l_min: int) -> DataFrame:
    """(class) with enough seeds; the upper bound of support is not applied to classes."""
    return support.filter(F.col("n") >= l_min).select("class")
