"""Seeds and layered neighbourhood samples of all minibatches of an epoch at once.

A minibatch is (epoch, rank, it). Frontier layer L holds its seeds; block l joins frontier l (sources) to frontier l + 1 (destinations).
Local sampling expands a rank's own vertices (solids) only; foreign ones (halos) end the recursion.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import RANGE, digest, draw, race

BATCH = ("epoch", "rank", "it")


def minibatches(train: DataFrame, parts: DataFrame, size: int, epoch: int = 0, seed: int = 1, fast: bool = False) -> DataFrame:
    """(epoch, rank, it, vid): each rank's training vertices in drawn order, cut into groups of size; the last may be short."""
    order = Window.partitionBy("rank").orderBy(digest(seed, "seed", epoch, F.col("vid"), fast=fast), "vid")
    mine = train.select("vid").join(parts, "vid").select(F.col("part").alias("rank"), "vid")
    it = F.floor((F.row_number().over(order) - 1) / size).cast("int")
    return mine.select(F.lit(epoch).alias("epoch"), "rank", it.alias("it"), "vid")


def hop_key(kind: str, layer: int, seed: int, fast: bool = False) -> Column:
    """The order in which a destination's candidates are taken."""
    about = (seed, "hop", F.col("epoch"), F.col("it"), layer, F.col("src"), F.col("dst"))
    if kind == "uniform":
        return digest(*about, fast=fast)
    return race(F.col("w") if kind == "weighted" else F.col("deg_src"), *about, fast=fast)


def hop(frontier: DataFrame, placed: DataFrame, fanout: int, layer: int, kind: str = "uniform", seed: int = 1, replace: bool = False, fast: bool = False) -> DataFrame:
    """In-neighbours of every frontier vertex, at most fanout of them: (epoch, rank, it, layer, src, dst, w, p_src).

    Edges that are stored in buckets of dst stay where they are: the frontier is brought to them, and as a destination's candidates then lie
    together, the limit is taken in the same task. The window's limit stands directly above it, so no more than fanout rows of a
    destination are kept while it sorts."""
    front = frontier.select(*BATCH, F.col("vid").alias("dst"))
    if replace:
        pos = F.row_number().over(Window.partitionBy("dst").orderBy("src")) - 1
        listed = placed.withColumn("pos", pos)
        deg = placed.groupBy("dst").agg(F.count("*").alias("deg"))
        draws = front.join(deg, "dst").withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(fanout - 1))))
        at = F.floor(draw(seed, "draw", F.col("epoch"), F.col("it"), layer, F.col("dst"), F.col("j"), fast=fast) * F.col("deg") / F.lit(float(RANGE))).cast("int")
        got = draws.withColumn("pos", at).join(listed, ["dst", "pos"])
        return got.select(*BATCH, F.lit(layer).alias("layer"), "src", "dst", "w", "p_src", "j")
    key = hop_key(kind, layer, seed, fast)
    order = Window.partitionBy("dst", *BATCH).orderBy("key", "src")  # as the join leaves it, so what is sorted are runs of one dst
    ranked = front.join(placed, "dst").withColumn("key", key).withColumn("n", F.row_number().over(order)).where(F.col("n") <= fanout)
    return ranked.select(*BATCH, F.lit(layer).alias("layer"), "src", "dst", "w", "p_src")


def sample(seeds: DataFrame, placed: DataFrame, fanouts: Sequence[int], scope: str = "local", kind: str = "uniform", seed: int = 1, cut: Callable[[DataFrame], DataFrame] = lambda df: df, fast: bool = False) -> tuple[DataFrame, DataFrame]:
    """(blocks, frontier) of all minibatches; fanouts begin at the seeds. cut stores a hop's result, so that later hops don't repeat it.
    scope local: solids are expanded; global: all vertices are, wherever they live."""
    top = len(fanouts)
    front = seeds.select(*BATCH, "vid", F.col("rank").alias("part"))
    fronts, blocks = [front.withColumn("layer", F.lit(top))], []
    for k, fanout in enumerate(fanouts):
        layer = top - 1 - k
        grown = front.where("part = rank") if scope == "local" else front
        block = cut(hop(grown, placed, fanout, layer, kind, seed, fast=fast))
        front = cut(grown.select(*BATCH, "vid", "part").union(block.select(*BATCH, "src", "p_src")).distinct())
        blocks.append(block)
        fronts.append(front.withColumn("layer", F.lit(layer)))
    union = lambda dfs: dfs[0] if len(dfs) == 1 else dfs[0].unionByName(union(dfs[1:]))
    kind_of = F.when(F.col("part") == F.col("rank"), F.lit("solid")).otherwise(F.lit("halo"))
    return union(blocks), union(fronts).withColumn("kind", kind_of)


def batch_ids(frontier: DataFrame, blocks: DataFrame) -> DataFrame:
    """Frontier with bid: dense per layer, destinations of the block above first, so that they are a prefix."""
    dst = blocks.select(*BATCH, "layer", F.col("dst").alias("vid"), F.lit(0).alias("tier")).distinct()
    tier = F.coalesce("tier", F.lit(1))
    order = Window.partitionBy(*BATCH, "layer").orderBy("tier", "vid")
    return frontier.join(dst, [*BATCH, "layer", "vid"], "left").withColumn("tier", tier).withColumn("bid", F.row_number().over(order) - 1).drop("tier")


def prune(blocks: DataFrame, misses: DataFrame) -> DataFrame:
    """Blocks without the edges out of halos that no cache served."""
    gone = misses.select(*BATCH, "layer", F.col("vid").alias("src"))
    return blocks.join(gone, [*BATCH, "layer", "src"], "left_anti")


def load_rows(frontier: DataFrame, features: DataFrame) -> DataFrame:
    """Input rows of the solids of layer 0."""
    return frontier.where("layer = 0 AND kind = 'solid'").select(*BATCH, "vid").join(features, "vid")
