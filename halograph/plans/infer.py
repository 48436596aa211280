"""Layer-wise inference over whole neighbourhoods, heads for the three tasks, and the full-batch reference."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.draws import draw
from ..functions.vectors import dot
from ..model.kernels import leaky, segment_extreme, segment_sum
from ..model.layers import Block, cross_entropy
from ..model.network import ModelSpec, backward
from ..operators import sampling
from ..session import batches_by_rows, release, ship_package, stage
from .epoch import Partitioned, SampleConfig
from .rank import RankEpoch, drive


_PART = "dst long, m array<double>, l array<double>, s array<double>, n long"


def _lists(rows: np.ndarray) -> pa.Array:
    flat = pa.array(np.ascontiguousarray(rows, np.float64).ravel())
    return pa.ListArray.from_arrays(pa.array(np.arange(0, rows.size + 1, rows.shape[1] if rows.shape[1] else 1, dtype=np.int32)[: len(rows) + 1]), flat)


def _array(column: pa.Array | pa.ChunkedArray, n: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return np.asarray(column.flatten(), np.float64).reshape(n, -1)


def _vertex_side(spec: ModelSpec, p: dict[str, np.ndarray], k: int):
    """What a vertex gives to its out-edges (u) and keeps for itself (v): for sage its row; for gat both transformed rows and the halves of
    the scores."""
    layer = spec.layer(p, k)

    def run(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if spec.kind == "sage":
            return x, x
        w, h = (lambda n: p[f"layer{k}.{n}"]), spec.heads
        zu, zv = x @ w("wu"), x @ w("wv")
        if layer.pre:
            zu, zv = zu + w("b"), zv + w("b")
            if layer.relu:
                zu, zv = np.maximum(zu, 0), np.maximum(zv, 0)
        score = lambda z, a: (z.reshape(len(z), h, -1) * w(a)).sum(-1)
        return np.concatenate([score(zu, "au"), zu], 1), np.concatenate([score(zv, "av"), zv], 1)

    return run


def _partial(spec: ModelSpec, p: dict[str, np.ndarray], k: int):
    """Of a batch of edges one row for each destination, which others can be added to: for sage a sum, for gat the greatest score, the sum
    of exponentials below it, and the sum of rows so weighed. A hub's in-edges thus become a row for each batch before they are exchanged."""
    layer, heads = spec.layer(p, k), spec.heads

    def run(dst: np.ndarray, u: np.ndarray, ev: np.ndarray | None):
        ids, place = np.unique(dst, return_inverse=True)
        n = np.bincount(place, minlength=len(ids))
        if spec.kind == "sage":
            if layer.op in ("max", "min"):
                s = segment_extreme(u, place, len(ids), np.maximum if layer.op == "max" else np.minimum)
            else:
                s = segment_sum(u, place, len(ids))
            return ids, np.zeros((len(ids), 1)), np.zeros((len(ids), 1)), s, n
        score = leaky(u[:, :heads] + ev, layer.slope)
        top = segment_extreme(score, place, len(ids), np.maximum)
        e = np.exp(score - top[place])
        z = u[:, heads:].reshape(len(u), heads, -1)
        return ids, top, segment_sum(e, place, len(ids)), segment_sum(z * e[..., None], place, len(ids)).reshape(len(ids), -1), n

    return run


def _finish(spec: ModelSpec, p: dict[str, np.ndarray], k: int):
    """The layer's output from a vertex's own side and the partial rows of its in-edges."""
    layer, heads = spec.layer(p, k), spec.heads
    w = lambda n: p[f"layer{k}.{n}"]

    def run(v: np.ndarray, at: np.ndarray, m: np.ndarray, l: np.ndarray, s: np.ndarray, n: np.ndarray) -> np.ndarray:
        count = np.bincount(at, weights=n, minlength=len(v))[:, None]
        if spec.kind == "sage":
            if layer.op in ("max", "min"):
                near = segment_extreme(s, at, len(v), np.maximum if layer.op == "max" else np.minimum)
            else:
                near = segment_sum(s, at, len(v))
                near = (near + v) / (count + 1) if layer.op == "gcn" else near / np.maximum(count, 1) if layer.op == "mean" else near
            out = near @ w("wn") + v @ w("ws") + w("b")
            return np.maximum(out, 0) if layer.relu else out
        top = segment_extreme(m, at, len(v), np.maximum)
        scale = np.exp(m - top[at])
        total = segment_sum(l * scale, at, len(v))
        rows = segment_sum(s.reshape(len(s), heads, -1) * scale[..., None], at, len(v))
        out = (rows / np.where(total > 0, total, 1)[..., None]).reshape(len(v), -1)
        if layer.op == "gcn":
            out = (out + v[:, heads:]) / (count + 1)
        if not layer.pre:
            out = out + w("b")
            out = np.maximum(out, 0) if layer.relu else out
        return out if layer.combine == "concat" else out.reshape(len(v), heads, -1).mean(1)

    return run


def full(edges: DataFrame, features: DataFrame, spec: ModelSpec, params: dict[str, np.ndarray], buckets: int | None = None) -> DataFrame:
    """(vid, logits) of all vertices, layer by layer. A layer joins rows to edges, adds up what a task has for a destination, and exchanges
    those sums; buckets of destinations are finished together, so that the products are matrix products."""
    spark = edges.sparkSession
    ship_package(spark)
    parts = buckets or int(spark.conf.get("spark.sql.shuffle.partitions")) * 4
    shared = spark.sparkContext.broadcast(params)
    rows = features.select("vid", F.col("x").cast("array<double>").alias("x"))
    for k in range(len(spec.dims) - 1):

        def sides(batches: Iterator[pa.RecordBatch], k: int = k) -> Iterator[pa.RecordBatch]:
            of = _vertex_side(spec, shared.value, k)
            for b in batches:
                u, v = of(_array(b.column(1), len(b)))
                yield pa.record_batch([b.column(0), _lists(u), _lists(v)], names=["vid", "u", "v"])

        made = stage(rows.mapInArrow(sides, "vid long, u array<double>, v array<double>"), "sides")
        joined = edges.select("src", "dst").join(made.select(F.col("vid").alias("src"), "u"), "src")
        if spec.kind == "gat":  # scalars of the destination
            joined = edges.select("src", "dst").join(made.select(F.col("vid").alias("dst"), F.slice("v", 1, spec.heads).alias("ev")), "dst").join(made.select(F.col("vid").alias("src"), "u"), "src")

        def partials(batches: Iterator[pa.RecordBatch], k: int = k) -> Iterator[pa.RecordBatch]:
            of = _partial(spec, shared.value, k)
            for b in batches:
                if len(b):
                    ids, m, l, s, n = of(b.column(0).to_numpy(), _array(b.column(1), len(b)), _array(b.column(2), len(b)) if spec.kind == "gat" else None)
                    yield pa.record_batch([pa.array(ids), _lists(m), _lists(l), _lists(s), pa.array(n)], names=["dst", "m", "l", "s", "n"])

        near = joined.select("dst", "u", *(["ev"] if spec.kind == "gat" else [])).mapInArrow(partials, _PART)
        none = F.lit(None).cast("array<double>")
        own = made.select(F.col("vid").alias("dst"), none.alias("m"), none.alias("l"), F.col("v").alias("s"), F.lit(-1).cast("long").alias("n"))
        both = near.unionByName(own).withColumn("bucket", F.pmod(F.xxhash64("dst"), F.lit(parts)))

        def finish(t: pa.Table) -> pa.Table:  # runs before k moves on, as the layer is staged
            dst, n = t.column("dst").to_numpy(), t.column("n").to_numpy()
            own, far = np.flatnonzero(n < 0), np.flatnonzero(n >= 0)
            own = own[np.argsort(dst[own])]
            ids = dst[own]
            if not len(ids):
                return pa.table({"vid": pa.array([], pa.int64()), "x": pa.array([], pa.list_(pa.float64()))})
            at = np.minimum(np.searchsorted(ids, dst[far]), len(ids) - 1)
            known = ids[at] == dst[far]
            far, at = far[known], at[known]
            order = np.argsort(at, kind="stable")
            far, at = far[order], at[order]
            take = lambda c, rows: _array(t.column(c).take(pa.array(rows)), len(rows)) if len(rows) else None
            v = take("s", own)
            empty = np.zeros((0, spec.heads)), np.zeros((0, spec.heads)), np.zeros((0, v.shape[1] - (spec.heads if spec.kind == "gat" else 0)))
            m, l, s = (take(c, far) for c in ("m", "l", "s")) if len(far) else empty
            return pa.table({"vid": pa.array(ids), "x": _lists(_finish(spec, shared.value, k)(v, at, m, l, s, n[far]))})

        rows = stage(both.groupBy("bucket").applyInArrow(finish, "vid long, x array<double>"))
    return rows.withColumnRenamed("x", "logits")


def sampled(pg: Partitioned, vertices: DataFrame, features: DataFrame, spec: ModelSpec, params: dict[str, np.ndarray], sample: SampleConfig = SampleConfig()) -> DataFrame:
    """(vid, logits) of the given vertices by the path that training takes: minibatches, sampled neighbourhoods over all ranks, one group
    for each minibatch. Features are exchanged with the vertices that need them: by their tables' size Spark may take drawn rows for a hundredth
    of what they are, and a broadcast would bring them all to the driver."""
    spark = pg.placed.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(params)
    seeds = stage(sampling.minibatches(vertices, pg.parts, sample.b, 0, sample.seed, sample.fast))
    blocks, frontier = sampling.sample(seeds, pg.placed, sample.fanouts, "global", sample.kind, sample.seed, stage, sample.fast)
    none = lambda t: F.lit(None).cast(t)
    row = lambda df, tag, a, b=None, x=None, layer="layer": df.select("rank", F.lit(tag).alias("tag"), "it", (F.col(layer) if layer else none("int")).alias("layer"), F.col(a).alias("a"), (F.col(b) if b else none("long")).alias("b"), (F.col(x).cast("array<float>") if x else none("array<float>")).alias("row"))
    x = features.select("vid", F.col("x").cast("array<float>").alias("x"))
    need = frontier.where("layer = 0").select("rank", "it", "vid").distinct().join(x.hint("merge"), "vid")
    rows = row(blocks, "e", "src", "dst").unionByName(row(frontier, "f", "vid")).unionByName(row(need, "x", "vid", x="x", layer=None))

    def run(t: pa.Table) -> pa.Table:
        steps = RankEpoch(t, spec, 0).steps(shared.value, t.column("it")[0].as_py(), train=False)
        got, _ = drive(steps, lambda k, sends: None)
        if "ids" not in got:
            return pa.table({"vid": pa.array([], pa.int64()), "logits": pa.array([], pa.list_(pa.float64()))})
        return pa.table({"vid": got["ids"], "logits": pa.array(list(got["logits"].astype(np.float64)), pa.list_(pa.float64()))})

    release(spark)
    with batches_by_rows(spark, 64 + 4 * spec.dims[0]):
        done = stage(rows.groupBy("rank", "it").applyInArrow(run, "vid long, logits array<double>"), "logits")
    release(spark)
    return done


def predict_nodes(logits: DataFrame) -> DataFrame:
    return logits.select("vid", (F.array_position("logits", F.array_max("logits")) - 1).cast("int").alias("pred"))


def link_scores(rows: DataFrame, pairs: DataFrame) -> DataFrame:
    """Inner products of both ends' rows."""
    a, b = (rows.select(F.col("vid").alias(v), F.col("x").alias(f"x_{v}")) for v in ("src", "dst"))
    return pairs.join(a, "src").join(b, "dst").select(*pairs.columns, dot(F.col("x_src"), F.col("x_dst")).alias("score"))


def negatives(pairs: DataFrame, low: int, count: int, seed: int = 1) -> DataFrame:
    """For every pair one with a drawn other end among count ids from low on."""
    return pairs.select("src", (F.floor(draw(seed, "neg", F.col("src"), F.col("dst")) * count / F.lit(float(1 << 32))) + low).cast("long").alias("dst"))


def graph_readout(rows: DataFrame, width: int) -> DataFrame:
    """Mean row of each small graph."""
    return rows.groupBy("graph_id").agg(F.count("*").alias("n"), F.array(*[F.avg(F.get("x", F.lit(k))) for k in range(width)]).alias("x"))


class WholeGraph:
    """A graph in one process: the exact reference for tests, and full-batch training."""

    def __init__(self, edges: DataFrame, features: DataFrame, labels: dict[int, int] | None = None) -> None:
        f = features.toPandas().sort_values("vid")
        self.ids = f["vid"].to_numpy()
        self.x = np.array(f["x"].tolist(), np.float64)
        e = edges.select("src", "dst").toPandas()
        self.src, self.dst = np.searchsorted(self.ids, e["src"]), np.searchsorted(self.ids, e["dst"])
        order = np.lexsort((self.src, self.dst))
        self.block = Block(self.src[order], self.dst[order], len(self.ids), len(self.ids))
        self.labels = labels or {}

    def logits(self, spec: ModelSpec, p: dict[str, np.ndarray], context: tuple[int, ...] | None = None):
        blocks = [self.block] * (len(spec.dims) - 1)
        return spec.forward(p, blocks, lambda k, rows: self.x if rows is None else rows, context, [self.ids] * (len(spec.dims)))

    def accuracy(self, spec: ModelSpec, p: dict[str, np.ndarray], test: np.ndarray, y: np.ndarray) -> float:
        return float((self.logits(spec, p)[0].argmax(1)[np.searchsorted(self.ids, test)] == y).mean())

    def train(self, spec: ModelSpec, ids: np.ndarray, y: np.ndarray, steps: int, opt, seed: int = 1) -> tuple[dict[str, np.ndarray], list[float]]:
        """Full batch: all vertices in every step."""
        p, at, losses = spec.init(seed), np.searchsorted(self.ids, ids), []
        for step in range(steps):
            out, layers, _ = self.logits(spec, p, (seed, 0, step))
            loss, d = cross_entropy(out[at], y)
            dout = np.zeros_like(out)
            np.add.at(dout, at, d / len(y))
            p = opt.step(p, backward(layers, dout, [len(self.ids)] * len(layers)))
            losses.append(loss / len(y))
        return p, losses
