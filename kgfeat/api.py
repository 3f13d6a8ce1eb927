"""Entry points: triples and seeds in, features and matrix out."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.functions.render import render
from kgfeat.operators import domain, supports
from kgfeat.params import MiningParams
from kgfeat.plans.context import Context, prepare, search, seeds_of_class
from kgfeat.plans.miner import Mined, mine_path_features
from kgfeat.plans.state import Workspace

OUT = "fid long, kind string, len int, n long, feature string"


@dataclass
class MiningResult:
    """Features found and what they were made from; every table is lazy or committed, and lives until close()."""

    context: Context
    neighbours: DataFrame  # v, n within the limits
    mined: Mined | None
    unfiltered: MiningResult | None = None  # before the domain filter m, if there is one

    def path_features(self) -> DataFrame:
        """(fid, kind, len, n, feature) of paths and patterns."""
        c = self.context
        if self.mined is None:
            return c.spark.createDataFrame([], OUT)
        return self.mined.features.join(render(self.mined.features, c.vertex(), c.predicate()), "fid").select("fid", "kind", "len", "n", "feature")

    def neighbour_features(self) -> DataFrame:
        """The same columns for neighbours; a neighbour's feature id is its vertex."""
        return self.neighbours.join(self.context.vertex(), "v").select(F.col("v").alias("fid"), F.lit("neighbour").alias("kind"), F.lit(0).alias("len"), "n", F.col("uri").alias("feature"))

    def features(self) -> DataFrame:
        return self.neighbour_features().union(self.path_features())

    def matrix(self) -> DataFrame:
        """(seed, fid): true cells of all features."""
        near = self.context.reach.join(self.neighbours.select("v"), "v", "left_semi").select("seed", F.col("v").alias("fid"))
        return near if self.mined is None else near.union(self.mined.cells())

    def named_matrix(self) -> DataFrame:
        """(seed, feature) as text."""
        v = self.context.vertex()
        return self.matrix().join(self.features().select("fid", "feature"), "fid").join(v.select(F.col("v").alias("seed"), "uri"), "seed").select(F.col("uri").alias("seed"), "feature")

    def only(self, chosen: domain.DomainFilter | None) -> MiningResult:
        """The result with the features that mention a thing of the chosen kinds; a neighbour must be one."""
        if chosen is None:
            return self
        ws = self.context.ws
        things = ws.save(domain.things(self.context, chosen), "things")
        near = ws.save(self.neighbours.join(things.filter("not is_class").select("v"), "v", "left_semi"), "kept-neighbours")
        mined = self.mined
        if mined is not None:
            flat = mined.features.select("fid", F.explode(F.arrays_zip("elems", "classes")).alias("x")).select("fid", F.col("x.elems").alias("v"), F.col("x.classes").alias("is_class"))
            mined = mined.only(flat.join(things, ["v", "is_class"], "left_semi").select("fid").distinct(), ws)
        return MiningResult(self.context, near, mined, self)

    def filtered(self, chosen: domain.DomainFilter | None) -> DataFrame:
        """features() that mention a thing of the chosen kinds."""
        return self.only(chosen).features()

    def counted(self) -> DataFrame:
        """(seed, fid, n): how many of a seed's paths each path feature captures."""
        return self.mined.counts()

    def top(self, n: int) -> DataFrame:
        """The n features of largest support, by name on ties."""
        return self.features().orderBy(F.desc("n"), "feature").limit(n)

    def register_views(self, prefix: str = "kgfeat") -> None:
        self.features().createOrReplaceTempView(f"{prefix}_features")
        self.matrix().createOrReplaceTempView(f"{prefix}_matrix")

    def close(self) -> None:
        """Delete the run's tables; what was made from them can no longer be read."""
        self.context.ws.close()

    def __enter__(self) -> MiningResult:
        return self

    def __exit__(self, *_: object) -> None:
        self.close()


def mine(spark: SparkSession, triples: DataFrame, seeds: DataFrame, params: MiningParams | None = None, ws: Workspace | None = None, same_predicates: DataFrame | None = None, **changes: object) -> MiningResult:
    """All four steps. triples (s, p, o) and seeds (seed) are URIs; same_predicates (a, b) mean the same and
    are merged; changes override fields of params. With params.m the result has the features that pass it."""
    params = replace(params or MiningParams(), **changes)
    ctx = search(prepare(spark, triples, seeds, params, ws, pred_same=same_predicates, around=params.k))
    near = supports.counts(ctx.reach).filter(supports.within(F.col("n"), params.l_min, params.l_max))
    near = ctx.ws.save(near if "neighbour" in params.kinds else near.filter("false"), "neighbours")
    result = MiningResult(ctx, near, mine_path_features(ctx) if params.kinds & {"path", "pattern"} else None)
    return result.only(params.domain_filter())


def mine_sql(spark: SparkSession, triples: str, seeds: str, views: str = "kgfeat", **params: object) -> MiningResult:
    """mine() of two SQL queries, (s, p, o) and (seed); the result is left in the views <views>_features
    and <views>_matrix."""
    result = mine(spark, spark.sql(triples), spark.sql(seeds).toDF("seed"), **params)
    result.register_views(views)
    return result


class KnowledgeGraph:
    """Fluent form: KnowledgeGraph(triples).seeds(cls='...').mine(k=3)."""

    def __init__(self, triples: DataFrame):
        self.triples, self._seeds, self._canonical = triples, None, True
        self.ws = Workspace(triples.sparkSession, "graph")

    def canonicalise(self, on: bool = True) -> KnowledgeGraph:
        self._canonical = on
        return self

    def seeds(self, uris: list[str] | DataFrame | None = None, cls: str | None = None) -> KnowledgeGraph:
        if cls is not None:
            self._seeds = seeds_of_class(self.triples, cls, self.ws)
        elif isinstance(uris, DataFrame):
            self._seeds = uris.toDF("seed")
        else:
            self._seeds = self.triples.sparkSession.createDataFrame([(u,) for u in uris or []], "seed string")
        return self

    def mine(self, **params: object) -> MiningResult:
        if self._seeds is None:
            raise ValueError("choose seeds first")
        return mine(self.triples.sparkSession, self.triples, self._seeds, MiningParams(canonicalise=self._canonical), self.ws, **params)
