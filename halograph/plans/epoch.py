"""The plan of an epoch: samples, pushes and cache hits of all minibatches as six DataFrames, before any number is computed.

Nothing here depends on model values, so a whole epoch is planned by ordinary queries; only ids are moved. Each table is staged in shared
storage, because the next steps read it several times.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import cache, exchange, partition, sampling
from ..operators.cache import CacheSpec
from ..session import bucketed, stage


@dataclass(frozen=True)
class SampleConfig:
    """Fan-outs begin at the seeds; b seeds a minibatch."""

    fanouts: tuple[int, ...] = (5, 10, 15)
    b: int = 1000
    kind: str = "uniform"
    scope: str = "local"
    seed: int = 1
    #: draw by Spark's own hash instead of md5
    fast: bool = False
    #: ranks with fewer minibatches than the others run empty rounds (max), or all stop with the first (min)
    pad: str = "max"


@dataclass
class Partitioned:
    """A partitioned graph: edges with the parts of both ends, vertices' parts, halos, and who keeps whom as halo.

    The edges are stored in buckets of their destination, so a hop moves its frontier to them; they are exchanged once, here."""

    placed: DataFrame
    parts: DataFrame
    halos: DataFrame
    directory: DataFrame
    degrees: DataFrame
    P: int

    @staticmethod
    def build(edges: DataFrame, parts: DataFrame, P: int, cut: Callable[[DataFrame], DataFrame] = stage) -> Partitioned:
        placed = bucketed(partition.place(edges, parts), "dst") if cut is stage else cut(partition.place(edges, parts))
        halo = cut(partition.halos(placed))
        degrees = placed.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("deg"))
        return Partitioned(placed, parts, halo, cut(partition.directory(halo, parts)), cut(degrees), P)


@dataclass
class EpochPlan:
    seeds: DataFrame
    blocks: DataFrame
    frontier: DataFrame
    push_plan: DataFrame
    hit_plan: DataFrame
    exec_blocks: DataFrame
    rounds: int
    #: hits, and where the cache says so the rows that serve misses; like hit_plan
    serve_plan: DataFrame | None = None
    #: misses that are served as zeros, and misses whose features are fetched
    filled: DataFrame | None = None
    fetched: DataFrame | None = None
    extra: dict = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.serve_plan = self.hit_plan if self.serve_plan is None else self.serve_plan


def plan_epoch(pg: Partitioned, train: DataFrame, sample: SampleConfig, spec: CacheSpec, epoch: int = 0, earlier: DataFrame | None = None, cut: Callable[[DataFrame], DataFrame] = stage) -> EpochPlan:
    """earlier: pushes of the epochs before that may still be read (caches are never reset)."""
    seeds = cut(sampling.minibatches(train, pg.parts, sample.b, epoch, sample.seed, sample.fast))
    last = seeds.groupBy("rank").agg(F.max("it").alias("it")).agg(F.min("it") if sample.pad == "min" else F.max("it")).first()[0] or 0
    rounds = last + 1
    if sample.pad == "min":
        seeds = seeds.where(F.col("it") <= last)
    blocks, frontier = sampling.sample(seeds, pg.placed, sample.fanouts, sample.scope, sample.kind, sample.seed, cut, sample.fast)
    wanted = exchange.capped(exchange.eligible(frontier, pg.directory), pg.degrees, spec.nc, spec.by, spec.cap_mode, sample.seed, sample.fast)
    pushes = cut(exchange.timeline(wanted, rounds, spec.d))
    known = pushes if earlier is None else pushes.unionByName(earlier)
    hits = cut(cache.residency(cache.demand(frontier), known, spec, rounds))
    missed = cache.misses(hits)
    if spec.on_miss == "zero":
        return EpochPlan(seeds, blocks, frontier, pushes, hits, blocks, rounds, filled=missed)
    if spec.on_miss == "pull":
        return EpochPlan(seeds, blocks, frontier, pushes, hits, cut(sampling.prune(blocks, missed.where("layer > 0"))), rounds, fetched=missed.where("layer = 0"))
    served = hits
    if spec.on_miss == "stale":
        old = cache.stale(missed.drop("hit"), pushes, spec, rounds)
        served = cut(hits.where("hit").unionByName(old))
        missed = cache.misses(served)
    return EpochPlan(seeds, blocks, frontier, pushes, hits, cut(sampling.prune(blocks, missed)), rounds, served)


def sweep(plan: EpochPlan, pg: Partitioned, spec: CacheSpec, seed: int = 1, **values: list) -> DataFrame:
    """Hit rates per layer for each value of one setting of the cache, from the same samples: (value, layer, probes, hits)."""
    (name, settings), out = *values.items(), None
    wanted = exchange.eligible(plan.frontier, pg.directory)
    for v in settings:
        s = replace(spec, **{name: v})
        sent = exchange.timeline(exchange.capped(wanted, pg.degrees, s.nc, s.by, s.cap_mode, seed), plan.rounds, s.d)
        hits = cache.residency(cache.demand(plan.frontier), sent, s, plan.rounds)
        rows = hits.groupBy("layer").agg(F.count("*").alias("probes"), F.count_if("hit").alias("hits")).select(F.lit(-1 if v is None else v).alias("value"), "layer", "probes", "hits")
        out = rows if out is None else out.unionByName(rows)
    return out
