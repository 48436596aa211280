"""Multilevel minimum-edge-cut partitioning with balanced sizes and balanced training vertices.

Vertices propose their heaviest edge; mutual proposals are contracted by one aggregate, until the graph is small. The small graph is cut
on the driver by greedy growing under both capacities; its size is bounded by `small`, not by the data. Parts are then projected back and
refined level by level: vertices of one parity ask for the part that pulls them most, and parts admit the largest gains they have room for.
Where contraction stalls above the bound, label propagation on that level takes the place of the cut on the driver.
"""

from __future__ import annotations

import heapq
from collections import defaultdict

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.draws import digest
from ..session import stage
from .partition import by_label_propagation
from .ranking import running


def match(edges: DataFrame, seed: int, level: int, rounds: int = 2) -> DataFrame:
    """(vid, to): both ends of matched edges go to the smaller id."""
    free, found = edges, None
    for k in range(rounds):
        order = F.struct("w", digest(seed, level, k, F.least("src", "dst"), F.greatest("src", "dst")).alias("h"), "dst")
        best = free.groupBy("src").agg(F.max(order).alias("b")).select("src", F.col("b.dst").alias("dst"))
        mutual = best.join(best.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"])
        pairs = stage(mutual.select(F.col("src").alias("vid"), F.least("src", "dst").alias("to")))
        found = pairs if found is None else found.union(pairs)
        if k + 1 < rounds:
            done = pairs.select("vid")
            free = stage(free.join(done.withColumnRenamed("vid", "src"), "src", "left_anti").join(done.withColumnRenamed("vid", "dst"), "dst", "left_anti").select("src", "dst", "w"))
    return found


def contract(vertices: DataFrame, edges: DataFrame, pairs: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(map, vertices, edges) of the coarser graph; weights of what is merged are added."""
    to = stage(vertices.select("vid").join(pairs, "vid", "left").select("vid", F.coalesce("to", "vid").alias("to")))
    v = vertices.join(to, "vid").groupBy("to").agg(F.sum("size").alias("size"), F.sum("ntrain").alias("ntrain")).withColumnRenamed("to", "vid")
    e = edges.join(to.select(F.col("vid").alias("src"), F.col("to").alias("a")), "src").join(to.select(F.col("vid").alias("dst"), F.col("to").alias("b")), "dst")
    e = e.where("a <> b").groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum("w").alias("w"))
    return to, stage(v), stage(e)


def grow(ids: np.ndarray, size: np.ndarray, ntrain: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, parts: int, slack: float, balance_train: bool, tries: int = 4) -> np.ndarray:
    """Greedy growing: each part takes the vertex that it pulls most until it is full; the best of several starts is kept."""
    n = len(ids)
    near: list[list[tuple[int, float]]] = [[] for _ in range(n)]
    for a, b, x in zip(np.searchsorted(ids, src), np.searchsorted(ids, dst), w, strict=True):
        near[b].append((int(a), float(x)))
    cap, tcap = (1 + slack) * size.sum() / parts, max(1.0, (1 + slack) * ntrain.sum() / parts)
    best, best_cut = None, np.inf
    for t in range(tries):
        rng = np.random.Generator(np.random.PCG64([7, t]))
        part, order = np.full(n, -1), rng.permutation(n)
        load, tload = np.zeros(parts), np.zeros(parts)
        target = size.sum() / parts
        at = 0
        for p in range(parts):
            queue: list[tuple[float, int]] = []
            pull: dict[int, float] = defaultdict(float)
            while load[p] < target:
                v = -1
                while queue:
                    g, u = heapq.heappop(queue)
                    if part[u] < 0 and -g == pull[u]:
                        v = u
                        break
                if v < 0:
                    while at < n and part[order[at]] >= 0:
                        at += 1
                    if at == n:
                        break
                    v = int(order[at])
                if load[p] + size[v] > cap or (balance_train and tload[p] + ntrain[v] > tcap):
                    if not queue:
                        break
                    continue
                part[v] = p
                load[p] += size[v]
                tload[p] += ntrain[v]
                for u, x in near[v]:
                    if part[u] < 0:
                        pull[u] += x
                        heapq.heappush(queue, (-pull[u], u))
        for v in np.flatnonzero(part < 0):
            over = np.maximum(load + size[v] - cap, 0) + (np.maximum(tload + ntrain[v] - tcap, 0) * (size.sum() / max(1, ntrain.sum())) if balance_train else 0)
            p = int(np.lexsort((load, over))[0])
            part[v] = p
            load[p] += size[v]
            tload[p] += ntrain[v]
        cut = sum(x for v in range(n) for u, x in near[v] if part[u] != part[v])
        if cut < best_cut:
            best, best_cut = part, cut
    return best


def refine(vertices: DataFrame, edges: DataFrame, parts: DataFrame, P: int, slack: float, balance_train: bool, rounds: int, seed: int) -> DataFrame:
    total = vertices.agg(F.sum("size"), F.sum("ntrain")).first()
    cap, tcap = (1 + slack) * total[0] / P, max(1.0, (1 + slack) * total[1] / P)
    weights = vertices.join(parts, "vid")
    for turn in range(rounds):
        near = edges.join(weights.select(F.col("vid").alias("src"), "part"), "src").groupBy(F.col("dst").alias("vid"), "part").agg(F.sum("w").alias("pull"))
        best = near.groupBy("vid").agg(F.max(F.struct("pull", (-F.col("part")).alias("n"))).alias("b")).select("vid", F.col("b.pull").alias("pull"), (-F.col("b.n")).cast("int").alias("to"))
        here = near.select("vid", "part", F.col("pull").alias("held"))
        wish = weights.join(best, "vid").join(here, ["vid", "part"], "left").withColumn("gain", F.col("pull") - F.coalesce("held", F.lit(0)))
        wish = wish.where((F.col("to") != F.col("part")) & (F.col("gain") > 0) & (F.pmod(F.xxhash64("vid"), F.lit(2)) == turn % 2))
        room = weights.groupBy(F.col("part").alias("to")).agg((F.lit(cap) - F.sum("size")).alias("room"), (F.lit(tcap) - F.sum("ntrain")).alias("troom"))
        wish = wish.select("vid", "to", "gain", "size", "ntrain", digest(seed, turn, F.col("vid")).alias("draw"))
        ok = F.col("s") <= F.col("room")
        if balance_train:
            ok &= (F.col("t") <= F.col("troom")) | (F.col("ntrain") == 0)
        ranked = running(wish, "to", [("gain", True), ("draw", False), ("vid", False)], s=F.col("size"), t=F.col("ntrain"))
        moved = ranked.join(room, "to").where(ok).select("vid", "to")
        weights = stage(weights.join(moved, "vid", "left").select("vid", "size", "ntrain", F.coalesce("to", "part").cast("int").alias("part")))
    return weights.select("vid", "part")


def by_multilevel(edges: DataFrame, vertices: DataFrame, train: DataFrame, P: int, slack: float = 0.05, balance_train: bool = True, small: int = 2_000, rounds: int = 4, seed: int = 1) -> DataFrame:
    """(vid, part). balance_train=False is the plain minimum edge cut."""
    v = stage(vertices.select("vid").join(train.select("vid", F.lit(1).alias("t")), "vid", "left").select("vid", F.lit(1).cast("long").alias("size"), F.coalesce("t", F.lit(0)).cast("long").alias("ntrain")))
    levels, e, n = [], edges.select("src", "dst", "w"), v.count()
    while n > small:
        to, cv, ce = contract(v, e, match(e, seed, len(levels)))
        m = cv.count()
        if m > 0.9 * n:
            break
        levels.append((to, v, e))
        v, e, n = cv, ce, m
    if n <= small:
        a, b = v.orderBy("vid").toPandas(), e.toPandas()
        part = grow(a.vid.to_numpy(), a["size"].to_numpy(float), a.ntrain.to_numpy(float), b.src.to_numpy(), b.dst.to_numpy(), b.w.to_numpy(float), P, slack, balance_train)
        parts = stage(edges.sparkSession.createDataFrame(list(zip(a.vid.tolist(), part.tolist(), strict=True)), "vid long, part int"))
    else:
        parts = by_label_propagation(e, v, P, slack=slack, seed=seed)
    parts = refine(v, e, parts, P, slack, balance_train, rounds, seed)
    for to, fv, fe in reversed(levels):
        fine = stage(to.join(parts.withColumnRenamed("vid", "to"), "to").select("vid", "part"))
        parts = refine(fv, fe, fine, P, slack, balance_train, rounds, seed)
    return parts
