"""The experiments on the given tables. python experiments.py [NAME...] prints tables; counts are exact, seconds are this machine's.

ladder      one rank's epoch: the library's way, with the fused update and broadcast, with the sampler in step; and single kernels
scaling     2 to 16 ranks: rows pushed, used and pulled, edges computed, hit rates, imbalance, with hash and multilevel parts
hits        hit rate per layer against the share of a part that a minibatch covers
sweeps      hit rate per layer against cs, ls, nc and d
partition   edge cut, halos and training balance of the partitioners
epochs      epoch time by component, speedup, efficiency, overlap and imbalance of push and pull, measured in the ranks
overlap     time that ranks wait for pushes with and without delay
converge    accuracy of one rank, push, pull and no remote rows, on languages and on the planted label
target      epochs until push comes within a point of one rank, on languages, with multilevel parts, for three seeds
"""

from __future__ import annotations

import json
import os
import sys
import time

import numpy as np
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from halograph import measures
from halograph.model import kernels
from halograph.model.network import ModelSpec
from halograph.operators import exchange, graph, partition
from halograph.operators.cache import CacheSpec
from halograph.operators.labels import planted
from halograph.operators.multilevel import by_multilevel
from halograph.plans.epoch import Partitioned, SampleConfig, plan_epoch, sweep
from halograph.plans.infer import WholeGraph
from halograph.plans import single
from halograph.plans.training import TrainConfig, plan_for, sent, train
from halograph.session import local_session, stage

SF = os.environ.get("EXP_SF_DIR", "/root/testdata/sf0.1")
SMALL = os.environ.get("EXP_SMALL_DIR", "/root/testdata/sf0.01")


def show(title: str, rows: list[dict]) -> None:
    print(f"\n### {title}\n")
    names = list(dict.fromkeys(k for r in rows for k in r))
    print("| " + " | ".join(names) + " |\n|" + "---|" * len(names))
    for r in rows:
        print("| " + " | ".join(f"{r.get(k, ''):.3g}" if isinstance(r.get(k), float) else f"{r.get(k, '')}" for k in names) + " |")
    sys.stdout.flush()


def best(f, n: int = 5) -> float:
    out = []
    for _ in range(n):
        began = time.perf_counter()
        f()
        out.append(time.perf_counter() - began)
    return min(out)


def ladder(spark) -> None:
    rows = []
    for name, edges, x, y, classes in (
        ("documents", stage(graph.documents(spark, SF)), graph.trigram_features(spark, SF), graph.language_labels(spark, SF), 4),
        ("purchase", stage(graph.purchase(spark, SF)), graph.hash_features(graph.purchase_vertices(spark, SF), 64), None, 6),
    ):
        v = stage(vertices_of(edges))
        x = stage(x.join(v, "vid"))
        y = stage((planted(edges, x) if y is None else y).join(v, "vid"))
        whole, labels = WholeGraph(edges, x), graph.with_split(y, 0.3).where("is_train").toPandas()
        g = single.Csr(whole.block.src, whole.block.dst, len(whole.ids))
        feats, seeds = whole.x.astype(np.float32), np.searchsorted(whole.ids, labels.vid.to_numpy())
        for kind in ("sage", "gat"):
            base = None
            for rung, kernel, sampler, beside in single.LADDER:
                _, log = single.train_single(g, feats, seeds, labels.label.to_numpy(), ModelSpec(kind, (64, 256, 256, classes), dropout=0.5), (5, 10, 15), 256, 3, kernel=kernel, sampler=sampler, beside=beside)
                one = min(log, key=lambda m: m["seconds"])
                base = base or one["seconds"]
                rows.append({"graph": name, "model": kind, "rung": rung, "epoch_s": one["seconds"], "of which waiting for or making minibatches": one["minibatch_seconds"], "factor": base / one["seconds"]})
    show("Single-node ladder, one epoch (b = 256, fan-outs 5,10,15, hidden 256, best of three epochs)", rows)
    kernels_alone()


def kernels_alone() -> None:
    rng = np.random.default_rng(0)
    rows = []
    for n in (5_000, 50_000):
        x, w, b = rng.normal(size=(n, 256)).astype(np.float32), rng.normal(size=(256, 256)).astype(np.float32), np.zeros(256, np.float32)
        drop = kernels.mask(np.arange(n), 256, 0.5, 1).astype(np.float32)
        base = best(lambda x=x, drop=drop: kernels.update_unfused(x, w, b, True, drop))
        fused = best(lambda x=x, drop=drop: kernels.update_fused(x, w, b, True, drop))
        rows.append({"part": "update", "rows": n, "base_ms": base * 1e3, "optimised_ms": fused * 1e3, "factor": base / fused})
        e, heads = n * 3, 4
        z, alpha = rng.normal(size=(n, heads, 64)).astype(np.float32), rng.random((e, heads)).astype(np.float32)
        src, dst = rng.integers(0, n, e), np.sort(rng.integers(0, n // 5, e))
        run = lambda repeat, z=z, alpha=alpha, src=src, dst=dst, n=n: kernels.aggregate(z, src, dst, n // 5, "sum", coef=alpha, repeat=repeat)
        repeated, broadcast = best(lambda run=run: run(True), 3), best(lambda run=run: run(False), 3)
        rows.append({"part": "broadcast", "rows": e, "base_ms": repeated * 1e3, "optimised_ms": broadcast * 1e3, "factor": repeated / broadcast})
    show("Kernels alone", rows)


def graphs(spark, sf: str):
    return {"purchase": (stage(graph.purchase(spark, sf)), graph.purchase_vertices(spark, sf).select("vid")), "supply": (stage(graph.supply(spark, sf)), None)}


def vertices_of(edges):
    return edges.selectExpr("src AS vid").distinct()


def _parts(how: str, edges, v, train_ids, P: int):
    return partition.by_hash(v, P) if how == "hash" or P == 1 else stage(by_multilevel(edges, v, train_ids, P))


def scaling(spark) -> None:
    rows = []
    for name, edges, how in (("purchase", stage(graph.purchase(spark, SF)), "hash"), ("documents", stage(graph.documents(spark, SF)), "hash"), ("documents", stage(graph.documents(spark, SF)), "multilevel")):
        v = stage(vertices_of(edges))
        n = v.count()
        train_ids = stage(graph.with_split(v, 0.3).where("is_train").select("vid"))
        for P in (2, 4, 8, 16):
            pg = Partitioned.build(edges, _parts(how, edges, v, train_ids, P), P)
            spec = CacheSpec(cs=int(0.58 * n / P), ls=2, nc=512, d=1)
            sample = SampleConfig((5, 10, 15), 64, fast=True)
            plan = plan_epoch(pg, train_ids, sample, spec)
            pull = plan_for(pg, train_ids, TrainConfig(ModelSpec(), sample, spec, "pull"), 0, None)
            hits = {f"hit{r['layer']}": round(r["hit_rate"], 3) for r in measures.hit_rate(plan.hit_plan).collect()}
            per = plan.exec_blocks.groupBy("rank").count()
            rows.append({
                "graph": name, "parts": how, "P": P, "rounds": plan.rounds, "pushed": plan.push_plan.count(), "carried out": sent(plan, spec, True).count(), "pulled": exchange.pulled(pull.frontier).count(),
                "edges_push": plan.exec_blocks.count(), "edges_pull": pull.blocks.count(), **dict(sorted(hits.items())), "imbalance": float(measures.load_imbalance(per, "count").first()["imbalance"]),
            })
    show("Scaling over ranks (fan-outs 5,10,15, b=64, nc=512, ls=2, d=1, cs=0.58 V/P, 30 % training vertices)", rows)


def hits(spark) -> None:
    rows, P = [], 4
    for name, edges in (("documents", stage(graph.documents(spark, SF))), ("supply", stage(graph.supply(spark, SF)))):
        v = stage(vertices_of(edges))
        n = v.count()
        train_ids = stage(graph.with_split(v, 0.5).where("is_train").select("vid"))
        for how in ("hash", "multilevel"):
            pg = Partitioned.build(edges, _parts(how, edges, v, train_ids, P), P)
            for b in (16, 64, 256):
                plan = plan_epoch(pg, train_ids, SampleConfig((5, 10, 15), b, fast=True), CacheSpec(cs=int(0.58 * n / P), ls=2, nc=4 * b, d=1))
                solids = plan.frontier.where("kind = 'solid' AND layer = 0").groupBy("rank", "it").count().agg({"count": "avg"}).first()[0]
                got = {f"hit{r['layer']}": round(r["hit_rate"], 3) for r in measures.hit_rate(plan.hit_plan).collect()}
                rows.append({"graph": name, "parts": how, "b": b, "rounds": plan.rounds, "minibatch covers of its part": float(solids) * P / n, **dict(sorted(got.items()))})
    show(f"Hit rate per layer, {P} ranks, fan-outs 5,10,15, nc = 4 b", rows)


def epochs(spark) -> None:
    rows, times = [], []
    for name, edges, how, share in (("documents", stage(graph.documents(spark, SF)), "multilevel", 0.5), ("purchase", stage(graph.purchase(spark, SF)), "hash", 0.3)):
        v = stage(vertices_of(edges))
        n, width, classes = v.count(), 64, 4 if name == "documents" else 6
        x = stage(graph.trigram_features(spark, SF).join(v, "vid") if name == "documents" else graph.hash_features(v, 16).select("vid", F.concat(*["x"] * 4).alias("x")))
        y = graph.language_labels(spark, SF).join(v, "vid") if name == "documents" else planted(edges, graph.hash_features(v, 16))
        train_set = stage(graph.with_split(y, share).where("is_train").select("vid", "label"))
        for P in (1, 2, 4, 8):
            pg = Partitioned.build(edges, _parts(how, edges, v, train_set.select("vid"), P), P)
            for kind in ("sage", "gat"):
                for mode in ("push", "pull") if P > 1 else ("push",):
                    cfg = TrainConfig(ModelSpec(kind, (width, 64, 64, classes)), SampleConfig((5, 10, 15), 128, fast=True), CacheSpec(cs=int(0.58 * n / P), ls=2, nc=512, d=1), mode, 2, engine="barrier")
                    r = train(pg, x, train_set, cfg)
                    part = {p.part: p.seconds for p in measures.forward_with_remote(measures.epoch_parts(r.times)).where("epoch = 1").collect()}
                    off = {o.epoch: o.imbalance for o in measures.time_imbalance(r.times).collect()}[1]
                    total = sum(part.values())
                    times.append((f"{name} {kind} {mode}", P, total))
                    hit = {h.layer: round(h.hit_rate, 2) for h in measures.hit_rate(r.plans[-1].hit_plan).collect()} if mode == "push" and P > 1 else {}
                    rows.append({"graph": name, "model": kind, "mode": mode, "P": P, "epoch_s": total, **{k: part.get(k, 0.0) for k in ("minibatch", "forward", "backward", "allreduce")}, "imbalance": float(off), "hits": "/".join(str(hit[k]) for k in sorted(hit)), "edges": int(r.log[-1]["edges"]), "run_s": r.log[-1]["run_seconds"], "plan_s": r.log[-1]["plan_seconds"]})
    show("Epoch time in the ranks by component (second epoch; b = 128, fan-outs 5,10,15, hidden 64)", rows)
    show("Speedup and efficiency against the smallest number of ranks", [r.asDict() for r in measures.speedup(spark.createDataFrame(times, "series string, ranks int, seconds double")).orderBy("series", "ranks").collect()])


def sweeps(spark) -> None:
    edges, _ = graphs(spark, SF)["supply"]
    v = stage(vertices_of(edges))
    train_ids = graph.with_split(v, 0.3).where("is_train").select("vid")
    pg = Partitioned.build(edges, partition.by_hash(v, 4), 4)
    spec = CacheSpec(cs=5_000, ls=2, nc=128, d=1)
    plan = plan_epoch(pg, train_ids, SampleConfig((3, 3, 3), 64), spec)
    rows = []
    for name, values in (("cs", [10, 50, 250, 5000]), ("ls", [0, 1, 2, 4, 8]), ("nc", [0, 32, 64, 128, None]), ("d", [0, 1, 2, 3])):
        got = {}
        for r in sweep(plan, pg, spec, **{name: values}).collect():
            got.setdefault(r["value"], {})[r["layer"]] = r["hits"] / r["probes"]
        rows += [{"setting": name, "value": "all" if k == -1 else k, **{f"layer{x}": got[k].get(x, 0.0) for x in (0, 1, 2)}} for k in [-1 if x is None else x for x in values]]
    show("Hit rate per layer on the supply graph, 4 ranks", rows)


def partitions(spark) -> None:
    rows = []
    doc = stage(graph.documents(spark, SMALL))
    for name, edges in (("documents (sf0.01)", doc), ("supply (sf0.01)", stage(graph.supply(spark, SMALL)))):
        v = stage(vertices_of(edges))
        train_ids = stage(graph.with_split(v, 0.3).where("is_train").select("vid"))
        made = {"hash": lambda v=v: partition.by_hash(v, 4), "range": lambda v=v: partition.by_range(v, 4), "labels": lambda v=v, e=edges: partition.by_label_propagation(e, v, 4), "multilevel": lambda v=v, e=edges, t=train_ids: by_multilevel(e, v, t, 4), "multilevel, sizes only": lambda v=v, e=edges, t=train_ids: by_multilevel(e, v, t, 4, balance_train=False)}
        for how, f in made.items():
            parts = stage(f())
            q = {r["part"]: r for r in partition.quality(partition.place(edges, parts), train_ids, parts).collect()}
            own = [q[p] for p in q if p is not None]
            rows.append({"graph": name, "partitioner": how, "cut": q[None]["cut"] / q[None]["edges"], "halos": q[None]["halos"], "largest": max(r["vertices"] for r in own) * len(own) / q[None]["vertices"], "train": max(r["train"] for r in own) * len(own) / q[None]["train"]})
    show("Partitioners, 4 parts: share of cut edges, halos, largest part and most training vertices against the mean", rows)


def overlap(spark) -> None:
    """What a delay hides: the same pushes, all of them carried out, waited for at once (d = 0) and one or two iterations later. On one
    machine rows travel over the loopback, so the seconds say little about a network."""
    edges, P, rows = stage(graph.documents(spark, SF)), 8, []
    v = stage(vertices_of(edges))
    n = v.count()
    x = stage(graph.trigram_features(spark, SF).join(v, "vid"))
    y = stage(graph.with_split(graph.language_labels(spark, SF).join(v, "vid"), 0.5).where("is_train").select("vid", "label"))
    pg = Partitioned.build(edges, _parts("multilevel", edges, v, y.select("vid"), P), P)
    for hidden in (64, 256):
        base = None
        for d in (0, 1, 2):
            cfg = TrainConfig(ModelSpec("sage", (64, hidden, hidden, 4)), SampleConfig((5, 10, 15), 64, fast=True), CacheSpec(cs=int(0.58 * n / P), ls=2, nc=None, d=d), "push", 2, engine="barrier", used_only=False)
            r = train(pg, x, y, cfg)
            spent = {o.epoch: o for o in measures.waiting(r.times).collect()}[1]
            total = sum(p.seconds for p in measures.forward_with_remote(measures.epoch_parts(r.times)).where("epoch = 1").collect())
            plan = r.plans[1].push_plan.where("arrive_it > 0")
            base = base or (r.times, plan)
            share = {m.epoch: m.hidden for m in measures.hidden((r.times, plan), base).collect()}.get(1)
            mb = sum(p["count"] * 4 * (64 if p.layer == 0 else hidden) for p in plan.groupBy("layer").count().collect()) / 1e6
            rows.append({"hidden size": hidden, "d": d, "rounds": r.plans[1].rounds, "MB pushed": mb, "all ranks waited, s": float(spent.wait), "sending, s": float(spent.send), "epoch in the ranks, s": total, "share of d=0's wait per row saved": share if d else ""})
    show("What the delay hides: documents, 8 ranks, all pushes carried out (second epoch)", rows)


def converge(spark) -> None:
    doc = stage(graph.documents(spark, SMALL))
    linked = stage(vertices_of(doc))
    tasks = {
        "languages": (doc, stage(graph.trigram_features(spark, SMALL).join(linked, "vid")), stage(graph.language_labels(spark, SMALL).join(linked, "vid")), 64, 4, (3, 3), 0.08, 8),
    }
    edges, v = stage(graph.purchase(spark, SMALL)), graph.purchase_vertices(spark, SMALL)
    x = stage(graph.hash_features(v, 16))
    tasks["planted"] = (edges, x, stage(planted(edges, x)), 16, 6, (30, 3), 0.3, 12)
    rows = []
    for name, (edges, x, y, width, classes, fan, share, epochs) in tasks.items():
        s = graph.with_split(y, share)
        train_set = stage(s.where("is_train").select("vid", "label"))
        test = s.where("NOT is_train").select("vid", "label").toPandas()
        whole = WholeGraph(edges, x)
        v = y.select("vid")
        n = y.count()
        runs = [("sage", "push", 1), ("sage", "push", 4), ("sage", "pull", 4), ("sage", "none", 4)] + ([("gat", "push", 1), ("gat", "push", 4)] if name == "languages" else [])
        target: dict[str, float] = {}
        for kind, mode, P in runs:
            pg = Partitioned.build(edges, partition.by_hash(v, P), P)
            model = ModelSpec(kind, (width, 32, classes), dropout=0.0)
            b = 16 if name == "languages" else 32
            spec = CacheSpec(cs=max(1, int(0.58 * n / P)), ls=2, nc=2 * b, d=1)
            cfg = TrainConfig(model, SampleConfig(fan, b), spec, mode, epochs, rate=0.01, engine="local")
            began = time.perf_counter()
            r = train(pg, x, train_set, cfg, evaluate=lambda p, m=model: whole.accuracy(m, p, test.vid.to_numpy(), test.label.to_numpy()))
            acc = [m["accuracy"] for m in r.log]
            if P == 1:
                target[kind] = max(acc)
            near = next((k + 1 for k, a in enumerate(acc) if target[kind] - a < 0.01), None)
            rate = measures.hit_rate(r.plans[-1].hit_plan, "layer").agg({"hits": "sum", "probes": "sum"}).first() if mode == "push" and P > 1 else None
            rows.append({"task": name, "model": kind, "mode": mode, "P": P, "best": max(acc), "last": acc[-1], "epochs_to_target": near or f"> {epochs}", "hit_rate": rate[0] / rate[1] if rate and rate[1] else "", "edges": int(r.log[-1]["edges"]), "seconds": time.perf_counter() - began})
    show("Convergence to within a point of one rank", rows)


def target(spark) -> None:
    """The rule of convergence: best one-rank accuracy minus accuracy is below a point."""
    edges = stage(graph.documents(spark, SMALL))
    v = stage(vertices_of(edges))
    x, y = stage(graph.trigram_features(spark, SMALL).join(v, "vid")), stage(graph.language_labels(spark, SMALL).join(v, "vid"))
    s = graph.with_split(y, 0.3)
    train_set, test = stage(s.where("is_train").select("vid", "label")), s.where("NOT is_train").select("vid", "label").toPandas()
    whole, n, rows = WholeGraph(edges, x), y.count(), []
    for seed in (1, 2, 3):
        for kind in ("sage", "gat"):
            goal = None
            for P, n_epochs in ((1, 6), (2, 8), (4, 12)):
                parts = partition.by_hash(v, 1) if P == 1 else stage(by_multilevel(edges, v, train_set, P, seed=seed))
                pg = Partitioned.build(edges, parts, P)
                model = ModelSpec(kind, (64, 32, 4), dropout=0.0)
                cfg = TrainConfig(model, SampleConfig((3, 3), 16, fast=True, seed=seed), CacheSpec(cs=max(1, int(0.58 * n / P)), ls=2, nc=32, d=1), "push", n_epochs, rate=0.01, engine="local", seed=seed)
                r = train(pg, x, train_set, cfg, evaluate=lambda p, m=model: whole.accuracy(m, p, test.vid.to_numpy(), test.label.to_numpy()))
                acc = [m["accuracy"] for m in r.log]
                goal = goal or max(acc)
                hit = measures.hit_rate(r.plans[-1].hit_plan).agg({"hits": "sum", "probes": "sum"}).first() if P > 1 else None
                rows.append({"seed": seed, "model": kind, "P": P, "epochs": n_epochs, "best": max(acc), "epochs_to_target": next((k + 1 for k, a in enumerate(acc) if goal - a < 0.01), f"> {n_epochs}"), "hit_rate": hit[0] / hit[1] if hit and hit[1] else ""})
    show("Epochs to within a point of one rank: languages, multilevel parts, 30 % training vertices, b = 16", rows)


ALL = {"ladder": ladder, "scaling": scaling, "hits": hits, "epochs": epochs, "overlap": overlap, "sweeps": sweeps, "partition": partitions, "converge": converge, "target": target}

if __name__ == "__main__":
    session = local_session(8, 8, **{"spark.driver.memory": "12g"})
    session.sparkContext.setLogLevel("ERROR")
    for which in sys.argv[1:] or ALL:
        t = time.perf_counter()
        ALL[which](session)
        print(json.dumps({"experiment": which, "seconds": round(time.perf_counter() - t, 1)}))
