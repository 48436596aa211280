"""What one rank does in an epoch, whichever engine runs it: its minibatches, its inbox, and a step of forward and backward."""

from __future__ import annotations

import os
import tempfile
import time
from collections import defaultdict
from collections.abc import Callable, Generator, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from ..model.layers import Block, cross_entropy
from ..model.network import ModelSpec, backward

#: rows by which plans reach ranks. tag: e edge (a src, b dst), f solid of a frontier (a vid), h served halo (a vid, b version), z halo that is
#: served as zeros (a vid), u halo whose row was fetched (a vid), p push (a vid, b rank), x features (a vid), y label (a vid, b class), m message
#: of an earlier epoch or step (it its arrival, a vid)
SCHEMA = "rank int, tag string, it int, layer int, a long, b long, row array<float>"
ROWS = pa.schema(list(zip((f.split()[0] for f in SCHEMA.split(", ")), (pa.int32(), pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.float32())), strict=True)))

#: a push: receiving rank, layer, ids, rows
Send = tuple[int, int, np.ndarray, np.ndarray]
#: parts of a step that are timed here; engines add allreduce, wait, post and send
PARTS = ("minibatch", "pre", "forward", "backward", "allreduce", "wait", "post", "send")


def _whole(column: pa.ChunkedArray) -> np.ndarray:
    """64-bit whole numbers, -1 for null."""
    return pc.fill_null(column.cast(pa.int64()), -1).to_numpy()


def _rows(column: pa.ChunkedArray, at: np.ndarray, dtype: str) -> np.ndarray:
    if not len(at):
        return np.zeros((0, 0), dtype)
    return np.asarray(column.take(pa.array(at)).combine_chunks().flatten(), dtype).reshape(len(at), -1)


class Turns:
    """A rank's rows in order of it, nulls first, from batches that are read no sooner than they are due."""

    def __init__(self, batches: Iterator[pa.RecordBatch]) -> None:
        self.batches, self.rest = batches, None

    def each(self, it: int) -> Iterator[pa.RecordBatch]:
        """The rows of iterations before it that have not been taken yet, batch by batch; those without an iteration come with the first."""
        while True:
            b, self.rest = self.rest if self.rest is not None else next(self.batches, None), None
            if b is None:
                break
            n = int(np.searchsorted(pc.fill_null(b.column(2), -(2**31)).to_numpy(zero_copy_only=False), it))
            if n < len(b):
                self.rest = b.slice(n)
            if n:
                yield b.slice(0, n)
            if n < len(b):
                break

    def before(self, it: int) -> pa.Table:
        got = list(self.each(it))
        return pa.Table.from_batches(got) if got else ROWS.empty_table()


class Mapped:
    """Rows by id in files that are mapped, so a rank's features take no memory but what the system can take back at any time. The files have
    no name, and end with the task. Ids come in ascending order; of equal ones the first counts."""

    def __init__(self, width: int, dtype: str) -> None:
        at = os.environ.get("SPARK_LOCAL_DIRS", "").split(",")[0] or None  # the executor's own disk
        self.files = [tempfile.TemporaryFile(dir=at) for _ in range(2)]
        self.width, self.dtype, self.n, self.last = width, np.dtype(dtype), 0, None

    def add(self, ids: np.ndarray, rows: np.ndarray) -> None:
        if not len(ids):
            return
        new = np.diff(ids, prepend=ids[0] - 1 if self.last is None else self.last)
        if (new < 0).any():
            raise ValueError("ids out of order")
        ids, rows = ids[new > 0], rows[new > 0]
        for f, values, dtype in zip(self.files, (ids, rows), (np.dtype(np.int64), self.dtype), strict=True):
            f.write(np.ascontiguousarray(values, dtype).data.cast("B") if len(ids) else b"")
        self.n, self.last = self.n + len(ids), ids[-1] if len(ids) else self.last

    def arrays(self) -> tuple[np.ndarray, np.ndarray]:
        shapes = ((self.n,), np.int64), ((self.n, self.width), self.dtype)
        if not self.n:
            return tuple(np.zeros(*s) for s in shapes)
        for f in self.files:
            f.flush()
        return tuple(np.asarray(np.memmap(f, dtype, "r", shape=shape)) for f, (shape, dtype) in zip(self.files, shapes, strict=True))


class RankEpoch:
    """One rank's part of an epoch's plan, or of one iteration of it."""

    def __init__(self, table: pa.Table, spec: ModelSpec, epoch: int, seed: int = 1, dtype: str = "f4") -> None:
        self.spec, self.epoch, self.seed, self.dtype = spec, epoch, seed, np.dtype(dtype)
        self.top = len(spec.dims) - 1
        self._none = (np.zeros(0, np.int64), np.zeros(0, np.int64))
        it, layer, a, b, where = self._columns(table)
        self._plan(table, it, layer, a, b, where)
        self.x_ids, self.x = self._distinct(where("x"), a, table, spec.dims[0])
        self.inbox: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]] = {}
        self._carry(table, layer, a, where)

    def _carry(self, table: pa.Table, layer: np.ndarray, a: np.ndarray, where: Callable[[str], np.ndarray]) -> None:
        arrived = table.column("it").to_numpy(zero_copy_only=False)
        old = where("m")
        for v, k in sorted({(int(arrived[i]), int(layer[i])) for i in old}):
            at = old[(arrived[old] == v) & (layer[old] == k)]
            self.receive(v, k, a[at], _rows(table.column("row"), at, self.dtype.str))

    def take(self, batches: Iterator[pa.RecordBatch]) -> None:
        """What is kept for the whole epoch, batch by batch: features in order of their ids, and messages of earlier epochs."""
        kept = Mapped(self.spec.dims[0], self.dtype.str)
        for b in batches:
            table = pa.Table.from_batches([b])
            _, layer, a, _, where = self._columns(table)
            at = where("x")
            kept.add(a[at], _rows(table.column("row"), at, self.dtype.str).reshape(-1, self.spec.dims[0]))
            self._carry(table, layer, a, where)
        self.x_ids, self.x = kept.arrays()

    @staticmethod
    def _columns(table: pa.Table):
        tag = table.column("tag").combine_chunks().dictionary_encode()
        kinds = tag.dictionary.to_pylist()
        code = tag.indices.to_numpy()
        where = lambda t: np.flatnonzero(code == kinds.index(t)) if t in kinds else np.zeros(0, np.int64)
        return *(_whole(table.column(c)) for c in ("it", "layer", "a", "b")), where

    def _plan(self, table: pa.Table, it: np.ndarray, layer: np.ndarray, a: np.ndarray, b: np.ndarray, where: Callable[[str], np.ndarray]) -> None:
        self.parts: dict[tuple, tuple[np.ndarray, np.ndarray]] = {}
        for t in "efhpz":
            at = where(t)
            at = at[np.lexsort((b[at], a[at], layer[at], it[at]))]  # a fixed order, whatever the shuffle gave
            key = it[at] * 64 + layer[at]
            cut = np.flatnonzero(np.diff(key, prepend=-1, append=-1))
            for lo, hi in zip(cut[:-1], cut[1:], strict=True):
                self.parts[t, int(key[lo]) // 64, int(key[lo]) % 64] = (a[at[lo:hi]], b[at[lo:hi]])
        at = where("y")
        self.y_ids, first = np.unique(a[at], return_index=True)
        self.y = b[at][first]
        self.pulled_ids, self.pulled = self._distinct(where("u"), a, table, self.spec.dims[0])
        self.pulled_at = {int(k): np.unique(a[where("u")][it[where("u")] == k]) for k in np.unique(it[where("u")])}

    def turn(self, table: pa.Table) -> None:
        """The plan of the next iteration in place of the one that is held, for engines that bring it when it is due."""
        self._plan(table, *self._columns(table))

    def _distinct(self, at: np.ndarray, a: np.ndarray, table: pa.Table, width: int) -> tuple[np.ndarray, np.ndarray]:
        ids, first = np.unique(a[at], return_index=True)
        return ids, _rows(table.column("row"), at[first], self.dtype.str).reshape(-1, width)

    def _part(self, tag: str, it: int, layer: int) -> tuple[np.ndarray, np.ndarray]:
        return self.parts.get((tag, it, layer), self._none)

    def features_of(self, ids: np.ndarray) -> np.ndarray:
        at = np.searchsorted(self.x_ids, ids)
        if len(ids) and (at.max() >= len(self.x_ids) or (self.x_ids[at] != ids).any()):
            raise ValueError("a vertex without features")
        return self.x[at]

    def receive(self, version: int, layer: int, ids: np.ndarray, rows: np.ndarray) -> None:
        if not len(ids):
            return
        rows = rows.astype(self.dtype, copy=False)
        old = self.inbox.get((version, layer))
        if old is not None:
            ids, rows = np.concatenate([old[0], ids]), np.concatenate([old[1], rows])
        order = np.argsort(ids, kind="stable")
        self.inbox[version, layer] = (ids[order], rows[order])

    def forget(self, before: int) -> None:
        for key in [k for k in self.inbox if k[0] < before]:
            del self.inbox[key]

    def _halo_ids(self, it: int, layer: int) -> np.ndarray:
        pulled = self.pulled_at.get(it, self._none[0]) if layer == 0 else self._none[0]
        return np.concatenate([self._part("h", it, layer)[0], self._part("z", it, layer)[0], pulled])

    def _halo_rows(self, it: int, layer: int) -> np.ndarray:
        """Rows of the halos, in the order of their ids: from the cache, zeros, and fetched ones."""
        ids, versions = self._part("h", it, layer)
        all_ids = self._halo_ids(it, layer)
        rows = np.zeros((len(all_ids), self.spec.dims[layer]), self.dtype)
        for v in np.unique(versions):
            which = np.flatnonzero(versions == v)
            have, stored = self.inbox[int(v), layer]
            rows[which] = stored[np.searchsorted(have, ids[which])]
        if layer == 0 and it in self.pulled_at:
            rows[len(all_ids) - len(self.pulled_at[it]) :] = self.pulled[np.searchsorted(self.pulled_ids, self.pulled_at[it])]
        return rows

    def steps(self, p: dict[str, np.ndarray], it: int, train: bool = True) -> Generator[tuple[int, list[Send]], None, tuple[dict[str, np.ndarray], dict[str, float]]]:
        """One iteration. Yields the pushes of each layer as soon as its rows exist, so they can travel while the rest is computed;
        without delay, whoever runs this brings the other ranks' before going on. Returns gradients (of the summed loss) and measures;
        out of training the logits in place of the gradients."""
        clock = time.perf_counter
        began = clock()
        measures = {"seeds": 0.0, "loss": 0.0, "correct": 0.0, "edges": 0.0} | {f"{k}_seconds": 0.0 for k in PARTS}
        solids = [self._part("f", it, k)[0] for k in range(self.top + 1)]
        seeds = solids[self.top]
        measures["seeds"] = float(len(seeds))
        if not len(seeds):
            for k in range(self.top):
                yield k, []
            return {k: np.zeros(s, self.dtype) for k, s in self.spec.shapes().items()}, measures
        # destinations of block k are the solids of layer k + 1, which come first among the solids of layer k
        order = [seeds]
        for k in range(self.top - 1, -1, -1):
            order.insert(0, np.concatenate([order[0], np.setdiff1d(solids[k], order[0], assume_unique=True)]))
        blocks, places = [], []
        for k in range(self.top):
            src, dst = self._part("e", it, k)
            names = np.concatenate([order[k], self._halo_ids(it, k)])
            by = np.argsort(names, kind="stable")
            places.append((by, names))
            head = order[k + 1]
            to = np.argsort(head, kind="stable")
            blocks.append(Block(by[np.searchsorted(names, src, sorter=by)] if len(src) else src, to[np.searchsorted(head, dst, sorter=to)] if len(dst) else dst, len(names), len(head)))
            measures["edges"] += len(src)
        rows = self.features_of(order[0])
        measures["minibatch_seconds"] = clock() - began
        context = (self.seed, self.epoch, it) if train else None
        layers = []
        for k, block in enumerate(blocks):
            at = clock()
            ids, to = self._part("p", it, k)
            by, names = places[k]
            sends = [(int(r), k, ids[to == r], rows[by[np.searchsorted(names, ids[to == r], sorter=by)]]) for r in np.unique(to)]
            measures["pre_seconds"] += clock() - at
            yield k, sends
            at = clock()
            rows = np.concatenate([rows, self._halo_rows(it, k)])
            layer, rows = self.spec.apply(p, k, block, rows, context, order[k + 1])
            layers.append(layer)
            measures["forward_seconds"] += clock() - at
        if not train:
            return {"ids": seeds, "logits": rows}, measures
        at = clock()
        y = self.y[np.searchsorted(self.y_ids, seeds)]
        loss, d = cross_entropy(rows, y)
        measures |= {"loss": loss, "correct": float((rows.argmax(1) == y).sum())}
        grads = backward(layers, d, [len(o) for o in order[:-1]])
        measures["backward_seconds"] = clock() - at
        return grads, measures


def drive(steps: Generator, on_push: Callable[[int, list[Send]], None]):
    """Run an iteration to its end, handing each layer's pushes to on_push."""
    while True:
        try:
            k, sends = next(steps)
        except StopIteration as e:
            return e.value
        on_push(k, sends)


def merged(parts: list[tuple[dict[str, np.ndarray], dict[str, float]]]) -> tuple[dict[str, np.ndarray], dict[str, float]]:
    """All-reduce: gradients over the seeds of all ranks, which is the gradient of the whole step's batch."""
    total: dict[str, float] = defaultdict(float)
    for _, m in parts:
        for k, v in m.items():
            total[k] += v
    n = parts[0][0][next(iter(parts[0][0]))].dtype.type(max(1.0, total["seeds"]))
    return {k: sum(g[k] for g, _ in parts) / n for k in parts[0][0]}, dict(total)
