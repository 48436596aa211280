"""The cache as a stateful streaming operator: a state for each rank and layer, which is one cache of at most cs lines, keyed by vertex;
the iteration is the clock."""

from __future__ import annotations

import sys
from collections.abc import Iterator

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..operators.cache import CacheSpec
from ..session import ship_package

#: what the stream carries: kind 0 a write, kind 1 a probe
TRACE = "rank int, layer int, vid long, it int, kind int"
OUT = "rank int, it int, layer int, vid long, hit boolean, version_it int"


class CacheLines(StatefulProcessor):
    """Rows must come in order of iterations; within one, writes are stored before probes are answered."""

    def __init__(self, cs: int | None, ls: int | tuple | None, d: int, probe_in_warmup: bool) -> None:
        self.cs, self.ls, self.d, self.probe_in_warmup = cs, ls, d, probe_in_warmup

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.lines = handle.getMapState("lines", "vid long", "written int")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer) -> Iterator[pd.DataFrame]:
        rank, layer = int(key[0]), int(key[1])
        trace = pd.concat(list(rows)).sort_values(["it", "kind", "vid"])
        held = {int(k[0]): int(v[0]) for k, v in self.lines.iterator()}
        before = dict(held)
        out: list[tuple] = []
        for it, part in trace.groupby("it", sort=True):
            for vid in part.loc[part.kind == 0, "vid"]:
                held[int(vid)] = int(it)
            self._shrink(held, int(it), layer)
            for vid in part.loc[part.kind == 1, "vid"]:
                written = held.get(int(vid))
                hit = written is not None and (self.probe_in_warmup or it >= self.d)
                out.append((rank, int(it), layer, int(vid), hit, written if hit else None))
        for k in before.keys() - held.keys():
            self.lines.removeKey((k,))
        for k, v in held.items():
            if before.get(k) != v:
                self.lines.updateValue((k,), (v,))
        frame = pd.DataFrame(out, columns=["rank", "it", "layer", "vid", "hit", "version_it"])
        frame["version_it"] = frame["version_it"].astype("Int32")
        yield frame

    def _shrink(self, held: dict[int, int], now: int, layer: int) -> None:
        """Expired lines go; if there are too many the oldest do, larger ids first among equals."""
        ls = self.ls[min(layer, len(self.ls) - 1)] if isinstance(self.ls, tuple) else self.ls
        if ls is not None:
            for k in [k for k, v in held.items() if now - v > ls]:
                del held[k]
        if self.cs is not None and len(held) > self.cs:
            for _, k in sorted((-v, k) for k, v in held.items())[self.cs :]:
                del held[k]

    def close(self) -> None:
        pass


def cache_hits(trace: DataFrame, spec: CacheSpec) -> DataFrame:
    """Answers to the probes of a stream of TRACE rows."""
    ship_package(trace.sparkSession)
    # the worker that checks the state's schema gets no files from the session, so the class travels by value
    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    lines = CacheLines(spec.cs, spec.ls, spec.d, spec.probe_in_warmup)
    return trace.groupBy("rank", "layer").transformWithStateInPandas(statefulProcessor=lines, outputStructType=OUT, outputMode="Append", timeMode="None")
