"""The standard configurations on the given tables, built once for each application and folder."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import cache, exchange, graph, partition, sampling
from ..operators.cache import CacheSpec
from ..operators.labels import planted
from ..plans.epoch import EpochPlan, Partitioned, SampleConfig, plan_epoch
from ..session import stage

ORACLE = CacheSpec(cs=500, ls=2, nc=128, d=1)
TIGHT = CacheSpec(cs=50, ls=3, nc=16, d=2)


class Workload:
    """The purchase graph with hash parts and one epoch's plan."""

    def __init__(self, spark: SparkSession, sf_dir: str, P: int = 4, sample: SampleConfig = SampleConfig((3, 3, 3), 64), spec: CacheSpec = ORACLE, train_share: float = 0.3, width: int = 4) -> None:
        self.spark, self.sf_dir, self.P, self.sample, self.spec, self.train_share, self.width = spark, sf_dir, P, sample, spec, train_share, width
        self.runs: dict = {}
        self.sample_two = SampleConfig((10, 3), 64)

    @cached_property
    def edges(self) -> DataFrame:
        return stage(graph.purchase(self.spark, self.sf_dir), "edges")

    @cached_property
    def vertices(self) -> DataFrame:
        return graph.purchase_vertices(self.spark, self.sf_dir)

    @cached_property
    def parts(self) -> DataFrame:
        return partition.by_hash(self.vertices, self.P)

    @cached_property
    def pg(self) -> Partitioned:
        return Partitioned.build(self.edges, self.parts, self.P)

    @cached_property
    def train(self) -> DataFrame:
        return graph.with_split(self.vertices, self.train_share).where("is_train").select("vid")

    @cached_property
    def plan(self) -> EpochPlan:
        return plan_epoch(self.pg, self.train, self.sample, self.spec)

    @cached_property
    def next_plan(self) -> EpochPlan:
        """The epoch after, whose caches go on from this one's."""
        return plan_epoch(self.pg, self.train, self.sample, self.spec, epoch=1, earlier=self.plan.push_plan)

    @cached_property
    def global_sample(self) -> tuple[DataFrame, DataFrame]:
        blocks, frontier = sampling.sample(self.plan.seeds, self.pg.placed, self.sample.fanouts, "global", seed=self.sample.seed, cut=stage)
        return stage(blocks), stage(frontier)

    @cached_property
    def eligible(self) -> DataFrame:
        return stage(exchange.eligible(self.plan.frontier, self.pg.directory))

    @cached_property
    def features(self) -> DataFrame:
        return stage(graph.hash_features(self.vertices, self.width))

    @cached_property
    def trained_features(self) -> DataFrame:
        """What models are trained on: the same in every epoch of every run, so stored once."""
        return stage(graph.hash_features(self.vertices, 16), "features")

    @cached_property
    def trained_labels(self) -> DataFrame:
        return stage(planted(self.edges, self.trained_features).join(self.train, "vid"), "labels")

    def pushes(self, spec: CacheSpec) -> DataFrame:
        return exchange.timeline(exchange.capped(self.eligible, self.pg.degrees, spec.nc, spec.by, spec.cap_mode), self.plan.rounds, spec.d)

    def hits(self, spec: CacheSpec) -> DataFrame:
        return cache.residency(cache.demand(self.plan.frontier), self.pushes(spec), spec, self.plan.rounds)


_BUILT: dict[tuple[str, str], Workload] = {}


def workload(spark: SparkSession, sf_dir: str) -> Workload:
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _BUILT:
        _BUILT[key] = Workload(spark, sf_dir)
    return _BUILT[key]


def inline(spark: SparkSession, schema: str, rows: list[tuple]) -> DataFrame:
    """A small table of constants."""
    return spark.createDataFrame(rows, schema).select(*[F.col(c.split()[0]) for c in schema.split(", ")])
