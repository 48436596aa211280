"""The stale-row cache as sets: what it holds and whom it serves follows from arrivals and demands alone.

A write makes a tag the newest, and the victim is always the oldest write. So the content at iteration k is the cs most recently written
tags of age at most ls, and residency is a ranking, not a simulation. Within one iteration smaller ids count as written later.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class CacheSpec:
    """cs lines per rank and layer (None: no bound), life ls (None: for ever; a tuple has one for each layer), push limit nc, delay d.

    clock: lives count iterations, or epochs. on_miss: drop (the halo is left out), zero (it is a row of zeros), stale (the last row that
    came this epoch, however old or whether it was evicted, else drop), or pull (features are fetched at layer 0, above it drop)."""

    cs: int | None = 500
    ls: int | None | tuple[int | None, ...] = 2
    nc: int | None = 128
    d: int = 1
    probe_in_warmup: bool = False
    by: str = "degree"
    cap_mode: str = "per_rank"
    clock: str = "iteration"
    on_miss: str = "drop"


def life(spec: CacheSpec, layer: int) -> int | None:
    return spec.ls[min(layer, len(spec.ls) - 1)] if isinstance(spec.ls, tuple) else spec.ls


def _in_rounds(ls: int | None, spec: CacheSpec, rounds: int) -> int:
    """A life in iterations. For ever is two epochs, as far back as rows are carried."""
    if ls is None:
        return 2 * rounds
    return ls if spec.clock == "iteration" else min(2, ls + 1) * rounds


def longest_life(spec: CacheSpec, rounds: int) -> int:
    """How many iterations back a probe may read."""
    layers = range(len(spec.ls)) if isinstance(spec.ls, tuple) else (0,)
    return max([_in_rounds(life(spec, k), spec, rounds) for k in layers] + [rounds] * (spec.on_miss == "stale"))


def _by_layer(spec: CacheSpec, value) -> Column:
    """value(life) for the row's layer."""
    if not isinstance(spec.ls, tuple):
        return F.lit(value(spec.ls))
    out = F.lit(value(spec.ls[-1]))
    for k, ls in enumerate(spec.ls[:-1]):
        out = F.when(F.col("layer") == k, F.lit(value(ls))).otherwise(out)
    return out


def demand(frontier: DataFrame) -> DataFrame:
    """Halos that minibatches ask for: (epoch, rank, it, layer, vid)."""
    return frontier.where("kind = 'halo'").select("epoch", "rank", "it", "layer", "vid")


def arrivals(pushes: DataFrame, rounds: int) -> DataFrame:
    """(rank, layer, vid, at): writes on the clock that runs on over epochs."""
    return pushes.select(F.col("to_rank").alias("rank"), "layer", "vid", (F.col("epoch") * rounds + F.col("arrive_it")).alias("at"))


def residency(wanted: DataFrame, pushes: DataFrame, spec: CacheSpec, rounds: int) -> DataFrame:
    """Demands with hit and version_it (the arrival that serves it, on its epoch's clock if it came in that epoch).

    The latest write no later than the demand is an as-of join: one exchange by (rank, layer, vid), and a running maximum."""
    keys = ["rank", "layer", "vid"]
    writes = arrivals(pushes, rounds).distinct()
    asked = wanted.withColumn("at", F.col("epoch") * rounds + F.col("it"))
    both = writes.select(*keys, "at", F.lit(0).alias("kind"), F.lit(None).cast("int").alias("epoch"), F.lit(None).cast("int").alias("it")).unionByName(
        asked.select(*keys, "at", F.lit(1).alias("kind"), "epoch", "it")
    )
    order = Window.partitionBy(*keys).orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)
    seen = both.withColumn("written", F.max(F.when(F.col("kind") == 0, F.col("at"))).over(order)).where("kind = 1")
    fresh = F.col("written").isNotNull()
    fresh &= _alive(F.col("at"), F.col("written"), spec, rounds)
    if not spec.probe_in_warmup:
        fresh &= F.col("it") >= spec.d
    seen = seen.withColumn("hit", fresh)
    if spec.cs is not None:
        seen = _held(seen, writes, spec, rounds)
    written = F.when(F.col("hit"), (F.col("written") - F.col("epoch") * rounds).cast("int"))
    return seen.select("epoch", "rank", "it", "layer", "vid", "hit", written.alias("version_it"))


def _alive(now: Column, written: Column, spec: CacheSpec, rounds: int) -> Column:
    """Whether a row written then may still be read now."""
    age = now - written if spec.clock == "iteration" else F.floor(now / rounds) - F.floor(written / rounds)
    return age <= _by_layer(spec, lambda ls: 2**31 - 1 if ls is None else ls)


def snapshots(writes: DataFrame, life: int | Column) -> DataFrame:
    """(rank, layer, now, vid, written): the lines that are alive at each iteration. Every write is alive for life + 1 iterations, so the
    rows are a small multiple of the writes, not a history; for ever is two epochs."""
    alive = writes.select("rank", "layer", "vid", F.col("at").alias("written"), F.explode(F.sequence(F.col("at"), (F.col("at") + life).cast(writes.schema["at"].dataType))).alias("now"))
    return alive.groupBy("rank", "layer", "now", "vid").agg(F.max("written").alias("written"))


def kept(lines: DataFrame, cs: int) -> DataFrame:
    """The cs newest lines of each (rank, layer, now)."""
    order = Window.partitionBy("rank", "layer", "now").orderBy(F.desc("written"), "vid")
    return lines.withColumn("n", F.row_number().over(order)).where(F.col("n") <= cs).drop("n")


def _held(seen: DataFrame, writes: DataFrame, spec: CacheSpec, rounds: int) -> DataFrame:
    lines = snapshots(writes, _by_layer(spec, lambda ls: _in_rounds(ls, spec, rounds)))
    if spec.clock == "epoch":
        lines = lines.where(_alive(F.col("now"), F.col("written"), spec, rounds))
    inside = kept(lines, spec.cs).select("rank", "layer", F.col("now").alias("at"), "vid", F.lit(True).alias("held"))
    return seen.join(inside, ["rank", "layer", "at", "vid"], "left").withColumn("hit", F.col("hit") & F.coalesce("held", F.lit(False))).drop("held")


def stale(wanted: DataFrame, pushes: DataFrame, spec: CacheSpec, rounds: int) -> DataFrame:
    """Demands with the last row that came this epoch, however old: what on_miss="stale" serves."""
    epoch = F.col("epoch")
    return residency(wanted, pushes.join(wanted.select("epoch").distinct(), "epoch", "left_semi"), replace(spec, cs=None, ls=None), rounds).withColumn("hit", F.col("hit") & epoch.isNotNull())


def misses(hits: DataFrame) -> DataFrame:
    return hits.where("NOT hit").select("epoch", "rank", "it", "layer", "vid")


# --- single steps on a table of lines (rank, layer, vid, written) ----------------------------------------------------------------


def admit(lines: DataFrame, coming: DataFrame, now: int, spec: CacheSpec) -> DataFrame:
    """Lines after the arrivals (rank, layer, vid) of iteration now: matching tags are overwritten, expired lines go, the oldest give way."""
    new = coming.select("rank", "layer", "vid", F.lit(now).alias("written"))
    merged = lines.select("rank", "layer", "vid", "written").union(new).groupBy("rank", "layer", "vid").agg(F.max("written").alias("written"))
    merged = expire(merged, now, spec)
    return merged if spec.cs is None else kept(merged.withColumn("now", F.lit(now)), spec.cs).drop("now")


def expire(lines: DataFrame, now: int, spec: CacheSpec) -> DataFrame:
    if spec.clock != "iteration":
        raise ValueError("single steps count lives in iterations")
    return lines.where(F.lit(now) - F.col("written") <= _by_layer(spec, lambda ls: 2**31 - 1 if ls is None else ls))


def probe(lines: DataFrame, asked: DataFrame) -> DataFrame:
    """asked (rank, layer, vid) with hit."""
    held = lines.select("rank", "layer", "vid", F.lit(True).alias("held"))
    return asked.join(held, ["rank", "layer", "vid"], "left").select("rank", "layer", "vid", F.coalesce("held", F.lit(False)).alias("hit"))


def fetch(lines: DataFrame, hits: DataFrame) -> DataFrame:
    """The rows of the hits; lines need a column row."""
    return hits.where("hit").select("rank", "layer", "vid").join(lines.select("rank", "layer", "vid", "row"), ["rank", "layer", "vid"])
