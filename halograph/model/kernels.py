"""Segment reductions, fused and blocked updates, edge softmax."""

from __future__ import annotations

import numpy as np


def segments(index: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Order that sorts by index, the indices that occur, and where each begins in that order."""
    order = np.argsort(index, kind="stable")
    count = np.bincount(index, minlength=n)
    present = np.flatnonzero(count)
    return order, present, (np.cumsum(count) - count)[present]


def segment_sum(values: np.ndarray, index: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros((n, *values.shape[1:]), values.dtype)
    if len(index):
        order, present, begin = segments(index, n)
        out[present] = np.add.reduceat(values[order], begin, axis=0)
    return out


def segment_extreme(values: np.ndarray, index: np.ndarray, n: int, op: np.ufunc) -> np.ndarray:
    """np.maximum or np.minimum by segment; zero where a segment is empty."""
    out = np.zeros((n, *values.shape[1:]), values.dtype)
    if len(index):
        order, present, begin = segments(index, n)
        out[present] = op.reduceat(values[order], begin, axis=0)
    return out


def aggregate(rows: np.ndarray, src: np.ndarray, dst: np.ndarray, n: int, op: str = "mean", own: np.ndarray | None = None, coef: np.ndarray | None = None, repeat: bool = False) -> np.ndarray:
    """Rows of the sources reduced by destination. coef: a scalar for each edge (or edge and head) that is broadcast over the row's last
    axis; repeat: written out along it first, as a baseline. own: the destinations' rows, for gcn."""
    taken = rows[src]
    if coef is not None and repeat:
        taken = taken * np.repeat(coef[..., None], rows.shape[-1], -1)
    elif coef is not None:
        np.multiply(taken, coef[..., None], out=taken)
    if op in ("max", "min"):
        return segment_extreme(taken, dst, n, np.maximum if op == "max" else np.minimum)
    total = segment_sum(taken, dst, n)
    if op == "sum":
        return total
    count = np.bincount(dst, minlength=n).astype(rows.dtype).reshape(-1, *[1] * (rows.ndim - 1))
    return (total + own) / (count + 1) if op == "gcn" else total / np.maximum(count, 1)


def merge_partials(parts: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """The mean from (sum, count) partials of local and remote rows; means are never averaged."""
    total, count = (sum(x) for x in zip(*parts, strict=True))
    return total / np.maximum(count, 1)[:, None]


def mask(ids: np.ndarray, width: int, rate: float, *about: int) -> np.ndarray:
    """Reproducible dropout factors: 0 with probability rate, else 1 / (1 - rate), by a mixing hash of the vertex, column and context."""
    with np.errstate(over="ignore"):
        x = ids.astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(width, dtype=np.uint64) * np.uint64(0xBF58476D1CE4E5B9)
        for k in about:
            x = x ^ np.uint64(k * 0x94D049BB133111EB % (1 << 64))
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(31)
    keep = (x >> np.uint64(11)).astype(np.float64) / (1 << 53) >= rate
    return keep / (1 - rate)


def update_fused(x: np.ndarray, w: np.ndarray, b: np.ndarray, relu: bool = True, drop: np.ndarray | None = None) -> np.ndarray:
    """Affine, ReLU and dropout in one buffer."""
    out = np.empty((len(x), w.shape[1]), np.result_type(x, w))
    np.matmul(x, w, out=out)
    out += b
    if relu:
        np.maximum(out, 0, out=out)
    if drop is not None:
        out *= drop
    return out


def update_unfused(x: np.ndarray, w: np.ndarray, b: np.ndarray, relu: bool = True, drop: np.ndarray | None = None) -> np.ndarray:
    """The same with a new array for every step."""
    out = x @ w
    out = out + b
    out = np.where(out > 0, out, 0) if relu else out
    return out * drop if drop is not None else out


def blocked_matmul(x: np.ndarray, w: np.ndarray, bn: int = 256, bc: int = 64, bk: int = 64) -> np.ndarray:
    """Product by tiles. A tail of rows is a smaller tile; a width that its tile does not divide is one tile."""
    n, c = x.shape
    k = w.shape[1]
    bc, bk = bc if c % bc == 0 else c, bk if k % bk == 0 else k
    out = np.zeros((n, k), np.result_type(x, w))
    for i in range(0, n, bn):
        for j in range(0, k, bk):
            acc = out[i : i + bn, j : j + bk]
            for m in range(0, c, bc):
                acc += x[i : i + bn, m : m + bc] @ w[m : m + bc, j : j + bk]
    return out


def weight_grad(x: np.ndarray, dout: np.ndarray, chunks: int = 1) -> np.ndarray:
    """x' dout, each chunk of rows into a copy of its own; copies are then added."""
    cuts = np.linspace(0, len(x), chunks + 1).astype(int)
    return sum(x[a:b].T @ dout[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True))


def leaky(x: np.ndarray, slope: float = 0.2) -> np.ndarray:
    return np.where(x >= 0, x, x.dtype.type(slope) * x)


def edge_softmax(score: np.ndarray, dst: np.ndarray, n: int) -> np.ndarray:
    """Softmax of edge scores over each destination's edges."""
    top = segment_extreme(score, dst, n, np.maximum)
    e = np.exp(score - top[dst])
    return e / segment_sum(e, dst, n)[dst]
