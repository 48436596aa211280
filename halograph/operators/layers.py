"""Layers as queries: rows are (vid, x) with x an array of known width. A reduction is one sum for each position inside one aggregate, so
rows are never exploded into one for each dimension. The Arrow kernels compute the same for large widths."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import uniform
from ..functions.vectors import leaky_relu, relu
from ..session import ship_package

REDUCE = {"mean": F.avg, "sum": F.sum, "max": F.max, "min": F.min}


def _each(width: int, f) -> list[Column]:
    return [f(F.get("x", F.lit(k))) for k in range(width)]


def aggregate(edges: DataFrame, rows: DataFrame, width: int, op: str = "mean") -> DataFrame:
    """(vid, x): the sources' rows reduced by destination. gcn adds the own row, (sum + own) / (count + 1), so vertices without sources
    keep theirs; for the other reductions with_isolated() adds zero rows."""
    joined = edges.select("src", F.col("dst").alias("vid")).join(rows.select(F.col("vid").alias("src"), "x"), "src")
    if op != "gcn":
        return joined.groupBy("vid").agg(F.array(*_each(width, REDUCE[op])).alias("x"))
    summed = joined.groupBy("vid").agg(F.array(*_each(width, F.sum)).alias("s"), F.count("*").alias("n"))
    n = F.coalesce("n", F.lit(0))
    return rows.join(summed, "vid", "left").select("vid", F.array(*[(F.coalesce(F.get("s", F.lit(k)), F.lit(0.0)) + F.get("x", F.lit(k))) / (n + 1) for k in range(width)]).alias("x"))


def aggregate_edges(edges: DataFrame, value: str = "w") -> DataFrame:
    """Edge features reduced by destination."""
    return edges.groupBy(F.col("dst").alias("vid")).agg(F.sum(value).alias("total"), F.avg(value).alias("mean"))


def aggregate_scaled(edges: DataFrame, rows: DataFrame, width: int, coefs: Sequence[Column]) -> DataFrame:
    """Sum of rows times a scalar for each edge and head; the row is not repeated for the heads: one sum for each head and position."""
    joined = edges.join(rows.select(F.col("vid").alias("src"), "x"), "src")
    sums = [F.sum(c * F.get("x", F.lit(k))) for c in coefs for k in range(width)]
    return joined.groupBy(F.col("dst").alias("vid")).agg(F.array(*sums).alias("x"))


def aggregate_split(local: DataFrame, remote: DataFrame, rows: DataFrame, width: int) -> DataFrame:
    """The mean over local and remote edges from (sum, count) partials of either side."""

    def partial(e: DataFrame) -> DataFrame:
        joined = e.select("src", F.col("dst").alias("vid")).join(rows.select(F.col("vid").alias("src"), "x"), "src")
        return joined.groupBy("vid").agg(*[F.sum(F.get("x", F.lit(k))).alias(f"s{k}") for k in range(width)], F.count("*").alias("n"))

    both = partial(local).unionByName(partial(remote))
    return both.groupBy("vid").agg(F.array(*[F.sum(f"s{k}") / F.sum("n") for k in range(width)]).alias("x"))


def with_isolated(aggregated: DataFrame, vertices: DataFrame, width: int) -> DataFrame:
    """Vertices without neighbours get a zero row."""
    zero = F.array(*[F.lit(0.0)] * width)
    return vertices.select("vid").join(aggregated, "vid", "left").select("vid", F.coalesce("x", zero).alias("x"))


def affine(x: Column, w: np.ndarray, b: np.ndarray | None = None) -> list[Column]:
    """x W + b as one expression for each output; weights are literals, for narrow layers."""
    out = []
    for j in range(w.shape[1]):
        terms = [F.get(x, F.lit(k)) * F.lit(float(w[k, j])) for k in range(w.shape[0])]
        out.append(sum(terms, F.lit(0.0 if b is None else float(b[j]))))
    return out


def dropout(x: Column, width: int, rate: float, *about) -> Column:
    """Elements dropped by a hash of the context and the position, the others scaled up."""
    return F.array(*[F.when(uniform(*about, k) < rate, F.lit(0.0)).otherwise(F.get(x, F.lit(k)) / F.lit(1 - rate)) for k in range(width)])


def update(rows: DataFrame, w: np.ndarray, b: np.ndarray, act: bool = True) -> DataFrame:
    """affine and ReLU, in one projection."""
    return rows.select("vid", F.array(*[relu(c) if act else c for c in affine(F.col("x"), w, b)]).alias("x"))


def update_arrow(rows: DataFrame, w: np.ndarray, b: np.ndarray, act: bool = True, kernel: str = "fused") -> DataFrame:
    """The same by a NumPy kernel over Arrow batches: fused, unfused or blocked."""
    ship_package(rows.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from ..model.kernels import blocked_matmul, update_fused, update_unfused

        for batch in batches:
            x = np.asarray(batch.column(1).flatten()).reshape(len(batch), -1).astype(np.float64)
            if kernel == "blocked":
                y = blocked_matmul(x, w, 7, 2, 2) + b
                y = np.maximum(y, 0) if act else y
            else:
                y = (update_fused if kernel == "fused" else update_unfused)(x, w, b, act)
            ends = np.arange(0, y.size + 1, w.shape[1], dtype=np.int32)
            yield pa.record_batch([batch.column(0), pa.ListArray.from_arrays(pa.array(ends), pa.array(y.ravel()))], names=["vid", "x"])

    return rows.select("vid", "x").mapInArrow(run, "vid long, x array<double>")


def weight_grad(rows: DataFrame, left: str, right: str, n_left: int, n_right: int) -> DataFrame:
    """x' dout: each task adds its rows into a matrix of its own, and the matrices are then added. (i, j, g)."""
    ship_package(rows.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((n_left, n_right))
        for batch in batches:
            a, b = (np.asarray(batch.column(k).flatten()).reshape(len(batch), -1) for k in (0, 1))
            total += a.T @ b
        i, j = np.indices(total.shape)
        yield pa.record_batch([pa.array(i.ravel().astype(np.int32)), pa.array(j.ravel().astype(np.int32)), pa.array(total.ravel())], names=["i", "j", "g"])

    partial = rows.select(F.col(left), F.col(right)).mapInArrow(run, "i int, j int, g double")
    return partial.groupBy("i", "j").agg(F.sum("g").alias("g"))


def sage(edges: DataFrame, rows: DataFrame, p: dict[str, np.ndarray], op: str = "mean", act: bool = True) -> DataFrame:
    """One GraphSAGE layer; p has wn, ws and b. A vertex without sources has a zero row for its neighbours."""
    width = p["wn"].shape[0]
    near = aggregate(edges, rows, width, op).withColumnRenamed("x", "m")
    joined = rows.join(near, "vid", "left").withColumn("m", F.coalesce("m", F.array(*[F.lit(0.0)] * width)))
    out = [a + c for a, c in zip(affine(F.col("m"), p["wn"]), affine(F.col("x"), p["ws"], p["b"]), strict=True)]
    return joined.select("vid", F.array(*[relu(c) if act else c for c in out]).alias("x"))


def _ends(p: dict[str, np.ndarray], pre: bool) -> tuple[list[Column], list[Column]]:
    """A vertex's row transformed as a source and as a destination; both share the bias."""
    zu, zv = (affine(F.col("x"), p[w], p["b"] if pre else None) for w in ("wu", "wv"))
    return ([relu(c) for c in zu], [relu(c) for c in zv]) if pre else (zu, zv)


def attention_scores(edges: DataFrame, rows: DataFrame, p: dict[str, np.ndarray], heads: int, pre: bool = True) -> DataFrame:
    """Edges with zu (the source's transformed row) and score_h. The inner products are taken for each vertex; edges join scalars."""
    zu, zv = _ends(p, pre)
    d = len(zu) // heads
    inner = lambda z, a, h: sum((F.get(z, F.lit(h * d + k)) * F.lit(float(a[h, k])) for k in range(d)), F.lit(0.0))
    u = rows.select(F.col("vid").alias("src"), F.array(*zu).alias("zu")).select("src", "zu", *[inner("zu", p["au"], h).alias(f"u{h}") for h in range(heads)])
    v = rows.select(F.col("vid").alias("dst"), F.array(*zv).alias("zv")).select("dst", *[inner("zv", p["av"], h).alias(f"v{h}") for h in range(heads)])
    joined = edges.select("src", "dst").join(u, "src").join(v, "dst")
    return joined.select("src", "dst", "zu", *[leaky_relu(F.col(f"u{h}") + F.col(f"v{h}")).alias(f"score{h}") for h in range(heads)])


def edge_softmax(scored: DataFrame, heads: int) -> DataFrame:
    """alpha_h: softmax of score_h over each destination's edges, shifted by the maximum."""
    w = Window.partitionBy("dst")
    shifted = scored.withColumns({f"e{h}": F.exp(F.col(f"score{h}") - F.max(f"score{h}").over(w)) for h in range(heads)})
    return shifted.withColumns({f"alpha{h}": F.col(f"e{h}") / F.sum(f"e{h}").over(w) for h in range(heads)})


def gat(edges: DataFrame, rows: DataFrame, p: dict[str, np.ndarray], heads: int, pre: bool = True, combine: str = "concat", op: str = "gcn") -> DataFrame:
    """One attention layer. pre: bias and ReLU before the coefficients; else after the aggregation. op: gcn adds the own transformed row
    and divides by the number of sources and one; sum does neither. Every vertex of rows has a result."""
    width = p["wu"].shape[1]
    d = width // heads
    weighed = edge_softmax(attention_scores(edges, rows, p, heads, pre), heads)
    sums = [F.sum(F.col(f"alpha{h}") * F.get("zu", F.lit(h * d + k))) for h in range(heads) for k in range(d)]
    near = weighed.groupBy(F.col("dst").alias("vid")).agg(F.array(*sums).alias("s"), F.count("*").alias("n"))
    joined = rows.select("vid", F.array(*_ends(p, pre)[1]).alias("zv")).join(near, "vid", "left")
    out = [F.coalesce(F.get("s", F.lit(k)), F.lit(0.0)) for k in range(width)]
    if op == "gcn":
        out = [(s + F.get("zv", F.lit(k))) / (F.coalesce("n", F.lit(0)) + 1) for k, s in enumerate(out)]
    if not pre:
        out = [relu(s + F.lit(float(p["b"][k]))) for k, s in enumerate(out)]
    if combine == "mean":
        out = [sum((out[h * d + k] for h in range(heads)), F.lit(0.0)) / heads for k in range(d)]
    return joined.select("vid", F.array(*out).alias("x"))


def cross_entropy(logits: DataFrame, label: Column, classes: int) -> DataFrame:
    """(vid, loss): log of the summed exponentials minus the label's logit."""
    top = F.array_max("x")
    total = sum((F.exp(F.get("x", F.lit(k)) - top) for k in range(classes)), F.lit(0.0))
    return logits.select("vid", (F.log(total) + top - F.get("x", label)).alias("loss"))
