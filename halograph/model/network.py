"""Stacks of layers, their parameters, and optimisers."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..functions.vectors import dyadic_matrix
from .kernels import mask
from .layers import Block, GatLayer, SageLayer

#: learning rates for one rank and for many
RATES = {"sage": (0.003, 0.006), "gat": (0.001, 0.001)}


def rate_for(kind: str, ranks: int) -> float:
    return RATES[kind][ranks > 1]


@dataclass(frozen=True)
class ModelSpec:
    """dims: input, hidden, ..., classes. Hidden layers of GAT concatenate their heads, the last averages them. op: mean, sum or gcn; None
    is mean for sage and gcn for gat."""

    kind: str = "sage"
    dims: tuple[int, ...] = (100, 256, 256, 47)
    op: str | None = None
    heads: int = 4
    dropout: float = 0.5
    pre_activation: bool = True
    chunks: int = 1
    #: fused, or unfused with repeated scalars: the baseline of the single-node ladder
    kernel: str = "fused"

    def _last(self, k: int) -> bool:
        return k == len(self.dims) - 2

    def layer(self, p: dict[str, np.ndarray], k: int):
        name = f"layer{k}"
        if self.kind == "sage":
            return SageLayer(p, name, self.op or "mean", relu=not self._last(k), chunks=self.chunks, kernel=self.kernel)
        return GatLayer(p, name, self.heads, self.pre_activation, not self._last(k), "mean" if self._last(k) else "concat", chunks=self.chunks, op=self.op or "gcn", kernel=self.kernel)

    def shapes(self) -> dict[str, tuple[int, ...]]:
        out = {}
        for k, (a, b) in enumerate(zip(self.dims[:-1], self.dims[1:], strict=True)):
            s = SageLayer.shapes(a, b) if self.kind == "sage" else GatLayer.shapes(a, b, self.heads, "mean" if self._last(k) else "concat")
            out |= {f"layer{k}.{n}": v for n, v in s.items()}
        return out

    def init(self, seed: int = 1, how: str = "glorot") -> dict[str, np.ndarray]:
        """Reproducible parameters: uniform within Glorot's bound, biases zero; or dyadic ones for tests."""
        out = {}
        for k, (name, shape) in enumerate(sorted(self.shapes().items())):
            if how == "dyadic":
                two = shape if len(shape) == 2 else (1, shape[0])
                out[name] = dyadic_matrix(*two, salt=seed + k).reshape(shape)
            elif len(shape) == 1:
                out[name] = np.zeros(shape)
            else:
                bound = np.sqrt(6 / sum(shape))
                out[name] = np.random.Generator(np.random.PCG64([seed, k])).uniform(-bound, bound, shape)
        return out

    def apply(self, p: dict[str, np.ndarray], k: int, block: Block, rows: np.ndarray, context: tuple[int, ...] | None, ids: np.ndarray | None):
        """Layer k over its block: the layer, which keeps what its backward pass needs, and its output. context: seed, epoch and iteration
        for dropout while training; ids: the destinations."""
        drop = None
        if context is not None and self.dropout and not self._last(k):
            drop = mask(ids, self.dims[k + 1], self.dropout, *context, k).astype(rows.dtype)
        layer = self.layer(p, k)
        return layer, layer.forward(block, rows, drop)

    def forward(self, p: dict[str, np.ndarray], blocks: list[Block], inputs, context: tuple[int, ...] | None = None, ids: list[np.ndarray] | None = None):
        """inputs(k, rows) gives the source rows of block k from the previous output. Returns the logits, the layers, and each layer's
        source rows."""
        layers, sources, rows = [], [], None
        for k, block in enumerate(blocks):
            rows = inputs(k, rows)
            sources.append(rows)
            layer, rows = self.apply(p, k, block, rows, context, ids[k + 1] if ids is not None else None)
            layers.append(layer)
        return rows, layers, sources


def backward(layers: list, dlogits: np.ndarray, own: list[int]) -> dict[str, np.ndarray]:
    """Gradients of all parameters. own[k]: how many of layer k's source rows are outputs of the layer before; the others came from a
    cache and are constants."""
    grads: dict[str, np.ndarray] = {}
    d = dlogits
    for k in range(len(layers) - 1, -1, -1):
        d, g = layers[k].backward(d)
        grads |= g
        d = d[: own[k]]
    return grads


class Sgd:
    def __init__(self, rate: float) -> None:
        self.rate = rate

    def step(self, p: dict[str, np.ndarray], g: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        return {k: v - self.rate * g[k] for k, v in p.items()}


class Adam:
    def __init__(self, rate: float, b1: float = 0.9, b2: float = 0.999, eps: float = 1e-8) -> None:
        self.rate, self.b1, self.b2, self.eps, self.t, self.m, self.v = rate, b1, b2, eps, 0, {}, {}

    def step(self, p: dict[str, np.ndarray], g: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        self.t += 1
        out = {}
        for k, v in p.items():
            self.m[k] = self.b1 * self.m.get(k, 0) + (1 - self.b1) * g[k]
            self.v[k] = self.b2 * self.v.get(k, 0) + (1 - self.b2) * g[k] ** 2
            out[k] = v - self.rate * (self.m[k] / (1 - self.b1**self.t)) / (np.sqrt(self.v[k] / (1 - self.b2**self.t)) + self.eps)
        return out


def pack(p: dict[str, np.ndarray]) -> np.ndarray:
    return np.concatenate([p[k].ravel() for k in sorted(p)])


def unpack(flat: np.ndarray, like: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    out, at = {}, 0
    for k in sorted(like):
        n = like[k].size
        out[k] = flat[at : at + n].reshape(like[k].shape)
        at += n
    return out


def save(spark: SparkSession, p: dict[str, np.ndarray], path: str, version: int = 0) -> None:
    rows = [(version, k, list(v.shape), v.ravel().tolist()) for k, v in sorted(p.items())]
    spark.createDataFrame(rows, "version int, name string, shape array<int>, value array<double>").coalesce(1).write.mode("append").parquet(path)


def load(spark: SparkSession, path: str, version: int | None = None) -> dict[str, np.ndarray]:
    """The parameters of a version, the newest unless said otherwise."""
    df: DataFrame = spark.read.parquet(path)
    v = df.agg({"version": "max"}).first()[0] if version is None else version
    return {r.name: np.array(r.value).reshape(r["shape"]) for r in df.where(f"version = {v}").collect()}
