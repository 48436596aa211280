"""Cost and accuracy measures over plans and logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def hit_rate(hits: DataFrame, *by: str) -> DataFrame:
    """Probed halos, hits and their share, by layer unless said otherwise."""
    got = hits.groupBy(*(by or ("layer",))).agg(F.count("*").alias("probes"), F.count_if("hit").alias("hits"))
    return got.withColumn("hit_rate", F.col("hits") / F.col("probes"))


def hit_rollup(hits: DataFrame) -> DataFrame:
    return hits.rollup("rank", "layer").agg(F.count("*").alias("probes"), F.count_if("hit").alias("hits"))


def staleness(hits: DataFrame) -> DataFrame:
    """How old the rows are that hits use."""
    age = hits.where("hit").withColumn("age", F.col("it") - F.col("version_it"))
    return age.groupBy("layer", "age").agg(F.count("*").alias("rows"))


def frontier_sizes(frontier: DataFrame) -> DataFrame:
    return frontier.groupBy("layer", "kind").agg(F.count("*").alias("rows"))


def minibatch_counts(seeds: DataFrame) -> DataFrame:
    per = seeds.groupBy("rank").agg((F.max("it") + 1).alias("n"))
    return per.agg(F.min("n").alias("least"), F.max("n").alias("most"), F.sum("n").alias("total"))


def load_imbalance(work: DataFrame, column: str = "rows") -> DataFrame:
    """(max - mean) / mean of the work of ranks."""
    return work.agg(F.max(column).alias("most"), F.avg(column).alias("mean")).withColumn("imbalance", (F.col("most") - F.col("mean")) / F.col("mean"))


def compute_volume(blocks: DataFrame) -> DataFrame:
    """Edges and destination rows that are aggregated, per layer."""
    return blocks.groupBy("layer").agg(F.count("*").alias("edges"), F.count_distinct("rank", "it", "dst").alias("rows"))


def naive_volume(frontier: DataFrame, width: int) -> DataFrame:
    """Rows and bytes if every halo row of every layer were fetched."""
    return frontier.where("kind = 'halo'").groupBy("layer").agg(F.count("*").alias("rows")).withColumn("bytes", F.col("rows") * 4 * width)


def accuracy(predicted: DataFrame) -> DataFrame:
    return predicted.agg(F.count("*").alias("n"), F.count_if(F.col("pred") == F.col("label")).alias("correct")).withColumn("accuracy", F.col("correct") / F.col("n"))


def confusion(predicted: DataFrame) -> DataFrame:
    return predicted.cube("label", "pred").agg(F.count("*").alias("n"))


def convergence_epoch(log: DataFrame, target: DataFrame, within: float = 0.01) -> DataFrame:
    """First epoch whose accuracy is less than a point below the target: (run, epoch)."""
    near = log.join(target, "run").where(F.col("target") - F.col("accuracy") < within)
    return near.groupBy("run").agg(F.min("epoch").alias("epoch"))


def speedup(times: DataFrame) -> DataFrame:
    """Against each series' smallest number of ranks: (series, ranks, speedup, efficiency)."""
    base = times.groupBy("series").agg(F.min(F.struct("ranks", "seconds")).alias("b")).select("series", F.col("b.ranks").alias("r0"), F.col("b.seconds").alias("s0"))
    s = F.col("s0") / F.col("seconds")
    return times.join(base, "series").select("series", "ranks", s.alias("speedup"), (s * F.col("r0") / F.col("ranks")).alias("efficiency"))


def gain(pairs: DataFrame) -> DataFrame:
    """(name, base, optimised) with the improvement as a share and as a factor."""
    return pairs.select("name", ((F.col("base") - F.col("optimised")) / F.col("base")).alias("share"), (F.col("base") / F.col("optimised")).alias("factor"))


def byte_op_ratio(width: int, bytes_per_value: int = 4) -> float:
    """Bytes moved per addition when one row is added to another: two are read and one is written."""
    return 3 * width * bytes_per_value / width


def loss_moving_average(log: DataFrame, span: int = 3) -> DataFrame:
    w = Window.partitionBy("run").orderBy("epoch").rowsBetween(1 - span, 0)
    return log.withColumn("smooth", F.avg("loss").over(w))


def epoch_parts(times: DataFrame) -> DataFrame:
    """(epoch, part, seconds): of every iteration the slowest rank's, added up; parts as the ranks timed them. Ranks wait for each other in
    the all-reduce, so there it is the fastest rank's time, which has nobody to wait for."""
    step = times.groupBy("epoch", "it", "part").agg(F.max("seconds").alias("most"), F.min("seconds").alias("least"))
    return step.groupBy("epoch", "part").agg(F.sum(F.when(F.col("part") == "allreduce", F.col("least")).otherwise(F.col("most"))).alias("seconds"))


def forward_with_remote(parts: DataFrame) -> DataFrame:
    """The four published components: forward takes in the gathering of pushes, waiting for them, and storing them. Sending is hidden."""
    name = F.when(F.col("part").isin("pre", "wait", "post"), F.lit("forward")).otherwise(F.col("part"))
    return parts.where("part <> 'send'").groupBy("epoch", name.alias("part")).agg(F.sum("seconds").alias("seconds"))


def waiting(times: DataFrame) -> DataFrame:
    """(epoch, send, wait): seconds that all ranks' pushes took to send, and seconds that ranks stood waiting for pushes. Iteration 0 is
    left out: there ranks also wait for each other to start. Without pushes both are 0."""
    later = [F.sum(F.when((F.col("part") == p) & (F.col("it") > 0), F.col("seconds")).otherwise(0.0)).alias(p) for p in ("send", "wait")]
    return times.groupBy("epoch").agg(*later)


def hidden(delayed: tuple[DataFrame, DataFrame], synchronous: tuple[DataFrame, DataFrame]) -> DataFrame:
    """(epoch, rows, rows_synchronous, wait, wait_synchronous, hidden) from (times, pushes carried out) of a run with a delay and of one
    without: the share of the waiting for a pushed row that the delay saves. Delayed runs push less, as nothing is sent that would
    arrive after the epoch, so waits are compared by row; null where either run pushes nothing or never waits without delay."""

    def one(run: tuple[DataFrame, DataFrame], tag: str) -> DataFrame:
        rows = run[1].where("arrive_it > 0").groupBy("epoch").agg(F.count("*").alias(f"rows{tag}"))
        return waiting(run[0]).select("epoch", F.col("wait").alias(f"wait{tag}")).join(rows, "epoch", "left").na.fill(0, [f"rows{tag}"])

    both = one(delayed, "").join(one(synchronous, "_synchronous"), "epoch")
    known = (F.col("rows") > 0) & (F.col("rows_synchronous") > 0) & (F.col("wait_synchronous") > 0)
    ratio = F.try_divide(F.col("wait") * F.col("rows_synchronous"), F.col("wait_synchronous") * F.col("rows"))
    return both.select("epoch", "rows", "rows_synchronous", "wait", "wait_synchronous", F.when(known, 1 - ratio).alias("hidden"))


def time_imbalance(times: DataFrame) -> DataFrame:
    """(epoch, imbalance): of the ranks' own work in a minibatch, (max - mean) / mean of its seconds over the epoch's iterations."""
    own = times.where("part IN ('minibatch', 'pre', 'forward', 'backward', 'post')").groupBy("epoch", "it", "rank").agg(F.sum("seconds").alias("s"))
    step = own.groupBy("epoch", "it").agg(F.max("s").alias("most"), F.avg("s").alias("mean"))
    return step.groupBy("epoch").agg(((F.sum("most") - F.sum("mean")) / F.sum("mean")).alias("imbalance"))
