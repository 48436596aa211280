"""Training on many small graphs: whole graphs are dealt into batches, so there are no halos and only gradients are exchanged."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import digest, draw


def graph_batches(graphs: DataFrame, size: int, seed: int = 1) -> DataFrame:
    """(graph_id, batch, ...): graphs in drawn order, size to a batch. Graphs are dealt by the high digits of their draw first, so that
    order is found within stretches and no task sorts all graphs."""
    order = digest(seed, "graph", F.col("graph_id"))
    drawn = graphs.withColumn("_k", order).withColumn("_s", F.floor(draw(seed, "graph", F.col("graph_id")) / (1 << 24)))
    counts = drawn.groupBy("_s").agg(F.count("*").alias("_n"))
    base = counts.select("_s", F.coalesce(F.sum("_n").over(Window.orderBy("_s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_b"))
    place = F.row_number().over(Window.partitionBy("_s").orderBy("_k", "graph_id")) - 1
    numbered = drawn.withColumn("_r", place).join(F.broadcast(base), "_s")  # at most 256 stretches
    return numbered.withColumn("batch", F.floor((F.col("_r") + F.col("_b")) / size).cast("int")).select("graph_id", "batch", *[c for c in graphs.columns if c != "graph_id"])


def train_small_graphs(graphs: DataFrame, edges: DataFrame, spec, epochs: int, rate: float, size: int = 8, seed: int = 1):
    """graphs: (graph_id, vid, x, label); edges: (graph_id, src, dst). Each epoch is one job: a batch of whole graphs gives one gradient
    row, and rows are summed by a query. Returns parameters and the loss of each epoch."""
    import numpy as np
    import pyarrow as pa

    from ..model.layers import Block, cross_entropy
    from ..model.network import Adam, backward, pack, unpack
    from ..session import ship_package, stage
    from .training import allreduce

    spark = graphs.sparkSession
    ship_package(spark)
    batch = graph_batches(graphs.select("graph_id").distinct(), size, seed)
    rows = graphs.select("graph_id", F.col("vid").alias("a"), F.lit(None).cast("long").alias("b"), "x", F.col("label").cast("long").alias("y"))
    ends = edges.select("graph_id", F.col("src").alias("a"), F.col("dst").alias("b"), F.lit(None).cast("array<double>").alias("x"), F.lit(None).cast("long").alias("y"))
    table = stage(rows.unionByName(ends).join(batch, "graph_id"))
    p, opt, losses = spec.init(seed), Adam(rate), []
    like = {k: np.zeros(s) for k, s in spec.shapes().items()}
    for _ in range(epochs):
        shared = spark.sparkContext.broadcast(p)

        def run(t: pa.Table) -> pa.Table:
            d = t.to_pandas()
            v, e = d[d["b"].isna()].sort_values(["graph_id", "a"]), d[d["b"].notna()].sort_values(["graph_id", "a", "b"])
            place = {k: i for i, k in enumerate(zip(v["graph_id"], v["a"], strict=True))}
            src, dst = (np.array([place[g, int(x)] for g, x in zip(e["graph_id"], e[c], strict=True)], np.int64) for c in "ab")
            block = Block(np.concatenate([src, dst]), np.concatenate([dst, src]), len(v), len(v))
            x, y = np.array(v["x"].tolist(), np.float64), v["y"].to_numpy(np.int64)
            out, layers, _ = spec.forward(shared.value, [block] * (len(spec.dims) - 1), lambda k, r: x if r is None else r)
            loss, dl = cross_entropy(out, y)
            return pa.table({"g": pa.array([[loss, float(len(y))] + pack(backward(layers, dl, [len(v)] * len(layers))).tolist()], pa.list_(pa.float64()))})

        total = allreduce(table.groupBy("batch").applyInArrow(run, "g array<double>"))
        losses.append(total[0] / total[1])
        p = opt.step(p, {k: g / total[1] for k, g in unpack(total[2:], like).items()})
        shared.unpersist()
    return p, losses
