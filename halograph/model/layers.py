"""Layers over a block: sources (destinations are their prefix), edges as local positions. Each keeps what its backward pass needs."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .kernels import aggregate, edge_softmax, leaky, segment_sum, update_fused, update_unfused, weight_grad


@dataclass
class Block:
    """src and dst are positions; destinations are the first n_dst of n_src source rows."""

    src: np.ndarray
    dst: np.ndarray
    n_src: int
    n_dst: int


class SageLayer:
    """out = act(neighbours W_n + own W_s + b), the neighbours reduced by mean, sum or gcn. kernel: fused or unfused update."""

    def __init__(self, p: dict[str, np.ndarray], name: str, op: str = "mean", relu: bool = True, chunks: int = 1, kernel: str = "fused") -> None:
        self.p, self.name, self.op, self.relu, self.chunks, self.kernel = p, name, op, relu, chunks, kernel

    @staticmethod
    def shapes(n_in: int, n_out: int) -> dict[str, tuple[int, ...]]:
        return {"wn": (n_in, n_out), "ws": (n_in, n_out), "b": (n_out,)}

    def forward(self, block: Block, x: np.ndarray, drop: np.ndarray | None = None) -> np.ndarray:
        w = lambda k: self.p[f"{self.name}.{k}"]
        own = x[: block.n_dst]
        near = aggregate(x, block.src, block.dst, block.n_dst, self.op, own)
        # both products in one, with the bias: [near own] [W_n; W_s]
        both = np.concatenate([near, own], axis=1)
        out = (update_fused if self.kernel == "fused" else update_unfused)(both, np.concatenate([w("wn"), w("ws")]), w("b"), self.relu)
        self.kept = (block, both, out if drop is None else out.copy(), drop)
        return out if drop is None else np.multiply(out, drop, out=out)

    def backward(self, dout: np.ndarray) -> tuple[np.ndarray, dict[str, np.ndarray]]:
        block, both, out, drop = self.kept
        d = dout if drop is None else dout * drop
        if self.relu:
            d = d * (out > 0)
        n_in = both.shape[1] // 2
        dw = weight_grad(both, d, self.chunks)
        grads = {f"{self.name}.wn": dw[:n_in], f"{self.name}.ws": dw[n_in:], f"{self.name}.b": d.sum(0)}
        dnear = d @ self.p[f"{self.name}.wn"].T
        dx = np.zeros((block.n_src, n_in), dout.dtype)
        dx[: block.n_dst] = d @ self.p[f"{self.name}.ws"].T
        count = np.bincount(block.dst, minlength=block.n_dst).astype(d.dtype)[:, None]
        if self.op == "mean":
            dnear = dnear / np.maximum(count, 1)
        elif self.op == "gcn":
            dnear = dnear / (count + 1)
            dx[: block.n_dst] += dnear
        return dx + segment_sum(dnear[block.dst], block.src, block.n_src), grads


class GatLayer:
    """Additive attention with heads. pre: bias and ReLU come before the attention coefficients (the modified form); else after the
    aggregation (the original form). Both ends share the bias. op: sum of the weighed sources, or gcn, which adds the own transformed
    row and divides by the number of sources and one."""

    def __init__(self, p: dict[str, np.ndarray], name: str, heads: int = 4, pre: bool = True, relu: bool = True, combine: str = "concat", slope: float = 0.2, chunks: int = 1, op: str = "gcn", kernel: str = "fused") -> None:
        self.p, self.name, self.heads, self.pre, self.relu, self.combine, self.slope, self.chunks, self.op, self.kernel = p, name, heads, pre, relu, combine, slope, chunks, op, kernel

    @staticmethod
    def shapes(n_in: int, n_out: int, heads: int = 4, combine: str = "concat") -> dict[str, tuple[int, ...]]:
        width = n_out if combine == "concat" else n_out * heads
        return {"wu": (n_in, width), "wv": (n_in, width), "b": (width,), "au": (heads, width // heads), "av": (heads, width // heads)}

    def _w(self, k: str) -> np.ndarray:
        return self.p[f"{self.name}.{k}"]

    def forward(self, block: Block, x: np.ndarray, drop: np.ndarray | None = None) -> np.ndarray:
        own, shape = x[: block.n_dst], (-1, self.heads, self._w("au").shape[1])
        update = update_fused if self.kernel == "fused" else update_unfused
        bias = self._w("b") if self.pre else np.zeros(1, x.dtype)
        pu, pv = (update(rows, self._w(w), bias, self.pre and self.relu) for rows, w in ((x, "wu"), (own, "wv")))
        zu, zv = pu.reshape(shape), pv.reshape(shape)
        # a scalar for each vertex and head first; edges only add two scalars
        raw = (zu * self._w("au")).sum(-1)[block.src] + (zv * self._w("av")).sum(-1)[block.dst]
        alpha = edge_softmax(leaky(raw, self.slope), block.dst, block.n_dst)
        out = aggregate(zu, block.src, block.dst, block.n_dst, self.op, zv, coef=alpha, repeat=self.kernel != "fused")
        flat = out.reshape(len(out), -1)
        after = flat
        if not self.pre:
            after = flat + self._w("b")
            after = np.maximum(after, 0) if self.relu else after
        merged = after if self.combine == "concat" else after.reshape(shape).mean(1)
        self.kept = (block, x, zu, zv, raw, alpha, after, drop)
        return merged if drop is None else merged * drop

    def backward(self, dout: np.ndarray) -> tuple[np.ndarray, dict[str, np.ndarray]]:
        block, x, zu, zv, raw, alpha, after, drop = self.kept
        own, shape = x[: block.n_dst], zu.shape[1:]
        d = dout if drop is None else dout * drop
        if self.combine == "mean":
            d = np.repeat(d[:, None, :] / self.heads, self.heads, 1).reshape(len(d), -1)
        grads: dict[str, np.ndarray] = {}
        if not self.pre:
            d = d * (after > 0) if self.relu else d
            grads["b"] = d.sum(0)
        d = d.reshape(-1, *shape)
        if self.op == "gcn":
            d = d / (np.bincount(block.dst, minlength=block.n_dst).astype(d.dtype) + 1)[:, None, None]
        dz = segment_sum(alpha[..., None] * d[block.dst], block.src, block.n_src)
        dalpha = (d[block.dst] * zu[block.src]).sum(-1)
        mean = segment_sum(alpha * dalpha, block.dst, block.n_dst)
        draw = alpha * (dalpha - mean[block.dst]) * np.where(raw >= 0, 1, self.slope).astype(raw.dtype)
        du, dv = segment_sum(draw, block.src, block.n_src), segment_sum(draw, block.dst, block.n_dst)
        grads["au"], grads["av"] = (zu * du[..., None]).sum(0), (zv * dv[..., None]).sum(0)
        dzu, dzv = (dz + du[..., None] * self._w("au")).reshape(block.n_src, -1), (dv[..., None] * self._w("av") + (d if self.op == "gcn" else 0)).reshape(block.n_dst, -1)
        if self.pre:
            if self.relu:
                dzu, dzv = dzu * (zu.reshape(dzu.shape) > 0), dzv * (zv.reshape(dzv.shape) > 0)
            grads["b"] = dzu.sum(0) + dzv.sum(0)
        grads["wu"], grads["wv"] = weight_grad(x, dzu, self.chunks), weight_grad(own, dzv, self.chunks)
        dx = dzu @ self._w("wu").T
        dx[: block.n_dst] += dzv @ self._w("wv").T
        return dx, {f"{self.name}.{k}": g for k, g in grads.items()}


def log_softmax(x: np.ndarray) -> np.ndarray:
    x = x - x.max(1, keepdims=True)
    return x - np.log(np.exp(x).sum(1, keepdims=True))


def cross_entropy(logits: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
    """Summed loss, and its gradient; the caller divides by the number of seeds of the whole step."""
    logp = log_softmax(logits)
    d = np.exp(logp)
    d[np.arange(len(y)), y] -= 1
    return float(-logp[np.arange(len(y)), y].sum()), d
