"""What ranks send each other: delayed pushes, and the pull and naive baselines."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import digest, race


def eligible(frontier: DataFrame, directory: DataFrame) -> DataFrame:
    """Solids of each minibatch that are halos elsewhere, per layer below the seeds': (epoch, it, layer, from_rank, to_rank, vid). One join
    for all remote ranks."""
    top = frontier.agg(F.max("layer")).first()[0] or 0
    solid = frontier.where((F.col("kind") == "solid") & (F.col("layer") < top)).select("epoch", "it", "layer", F.col("rank").alias("from_rank"), "vid")
    d = directory.select(F.col("owner").alias("from_rank"), "vid", F.col("remote").alias("to_rank"))
    return solid.join(d, ["from_rank", "vid"]).select("epoch", "it", "layer", "from_rank", "to_rank", "vid")


def capped(wanted: DataFrame, degrees: DataFrame, limit: int | None, by: str = "degree", mode: str = "per_rank", seed: int = 1, fast: bool = False) -> DataFrame:
    """At most limit rows for each iteration, layer and pair of ranks (per_rank), or each sender (total, which is bounded however many
    ranks there are). by: degree (a race weighted by it), uniform, or top_degree."""
    if limit is None:
        return wanted
    about = (seed, "push", F.col("epoch"), F.col("it"), F.col("layer"), F.col("from_rank"), F.col("to_rank"), F.col("vid"))
    group = ["epoch", "it", "layer", "from_rank", *(["to_rank"] if mode == "per_rank" else [])]
    if by == "uniform":
        keys: list[Column] = [digest(*about, fast=fast)]
    elif by == "degree":
        keys = [race(F.col("deg"), *about, fast=fast)]
    else:
        keys = [F.desc("deg")]
    ranked = wanted.join(degrees.select("vid", "deg"), "vid").withColumn("n", F.row_number().over(Window.partitionBy(*group).orderBy(*keys, "vid", "to_rank")))
    return ranked.where(F.col("n") <= limit).select(*wanted.columns)


def timeline(wanted: DataFrame, rounds: int, delay: int) -> DataFrame:
    """Sends of iteration k arrive at k + delay; nothing is sent that would arrive after the epoch's last round."""
    return wanted.where(F.col("it") < rounds - delay).withColumnRenamed("it", "sent_it").withColumn("arrive_it", (F.col("sent_it") + delay).cast("int"))


def iteration_spine(seeds: DataFrame) -> DataFrame:
    """(rank, it, seeds): every rank runs as many rounds as the one with the most; rounds without seeds send empty lists."""
    rounds = seeds.agg(F.max("it").alias("last"))
    ranks = seeds.select("rank").distinct()
    spine = ranks.join(rounds).select("rank", F.explode(F.sequence(F.lit(0), F.col("last"))).alias("it"))
    return spine.join(seeds.groupBy("rank", "it").agg(F.count("*").alias("seeds")), ["rank", "it"], "left").na.fill(0)


def used_only(pushes: DataFrame, hits: DataFrame, rounds: int) -> DataFrame:
    """Dead-push elimination: the pushes whose row some later probe reads. Known before execution, as the plan is."""
    read = hits.where("hit").select(F.col("rank").alias("to_rank"), "layer", "vid", (F.col("epoch") * rounds + F.col("version_it")).alias("at")).distinct()
    clocked = pushes.withColumn("at", F.col("epoch") * rounds + F.col("arrive_it"))
    return clocked.join(read, ["to_rank", "layer", "vid", "at"], "left_semi").select(*pushes.columns)


def pulled(frontier: DataFrame) -> DataFrame:
    """Remote input rows that the pull baseline fetches before each minibatch: (epoch, rank, it, vid, owner)."""
    return frontier.where("layer = 0 AND part <> rank").select("epoch", "rank", "it", "vid", F.col("part").alias("owner")).distinct()


def volume(rows: DataFrame, width: int, *by: str) -> DataFrame:
    """Rows and bytes of float rows, by the given columns."""
    return rows.groupBy(*by).agg(F.count("*").alias("rows")).withColumn("bytes", F.col("rows") * 4 * width)
