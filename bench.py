"""Headline queries, one after another, on $BENCH_SF_DIR with local[$BENCH_CPUS]. Prints one line of JSON."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from halograph.session import local_session, ship_package

    spark = local_session(CPUS, 16, **{"spark.driver.memory": "12g"})
    spark.sparkContext.setLogLevel("ERROR")
    ship_package(spark)
    times: dict[str, float] = {}
    facts: dict[str, float] = {}

    def timed(name: str, run):
        began = time.perf_counter()
        out = run()
        times[name] = round(time.perf_counter() - began, 3)
        return out

    import numpy as np
    from pyspark.sql import functions as F

    from halograph import measures
    from halograph.model.kernels import blocked_matmul, update_fused, update_unfused
    from halograph.model.layers import Block, GatLayer, SageLayer
    from halograph.model.network import ModelSpec
    from halograph.operators import exchange, graph, layers, partition
    from halograph.operators.cache import CacheSpec
    from halograph.operators.labels import planted
    from halograph.operators.multilevel import by_multilevel
    from halograph.plans.epoch import Partitioned, SampleConfig, plan_epoch
    from halograph.plans.training import TrainConfig, train
    from halograph.session import stage

    sink = lambda df: df.write.format("noop").mode("overwrite").save()
    sink(graph.purchase(spark, SF_DIR))  # the first query also starts the engine
    edges = timed("graph_purchase", lambda: stage(graph.purchase(spark, SF_DIR)))
    v = graph.purchase_vertices(spark, SF_DIR)
    n = v.count()
    x = timed("features", lambda: stage(graph.hash_features(v, 16)))
    labels = timed("planted_labels", lambda: stage(planted(edges, x)))
    seeds = graph.with_split(v, 0.08).where("is_train").select("vid")
    for op in ("mean", "max", "gcn"):
        timed(f"aggregate_{op}", lambda op=op: sink(layers.aggregate(edges, x, 16, op)))
    small = graph.hash_features(v, 4)
    g = {k: np.ones(s) for k, s in GatLayer.shapes(4, 4, 2).items()}
    timed("gat_layer_sql", lambda: sink(layers.gat(edges, small, g, 2)))

    # scaling over ranks: what is planned, sent, hit and computed, and how evenly
    sample = SampleConfig((5, 10, 15), 64, fast=True)
    for P in (2, 4, 8, 16):
        spec = CacheSpec(cs=int(0.58 * n / P), ls=2, nc=128, d=1)
        pg = Partitioned.build(edges, partition.by_hash(v, P), P)
        plan = timed(f"plan_epoch_{P}", lambda pg=pg, spec=spec: plan_epoch(pg, seeds, sample, spec))
        facts[f"pushed_rows_{P}"] = plan.push_plan.count()
        facts[f"computed_edges_{P}"] = plan.exec_blocks.count()
        for r in measures.hit_rate(plan.hit_plan).collect():
            facts[f"hit_rate_{P}_layer{r['layer']}"] = round(r["hit_rate"], 4)
        facts[f"imbalance_{P}"] = round(measures.load_imbalance(plan.exec_blocks.groupBy("rank").count(), "count").first()["imbalance"], 4)
        facts[f"used_pushes_{P}"] = exchange.used_only(plan.push_plan, plan.hit_plan, plan.rounds).count()

    def measured(name: str, r) -> None:
        """Seconds in the ranks by component (sampling and fetched features are in the plan, not here), and imbalance of the last epoch."""
        last = r.log[-1]["epoch"]
        for p in measures.forward_with_remote(measures.epoch_parts(r.times)).where(F.col("epoch") == last).collect():
            facts[f"{name}_{p.part}_seconds"] = round(p.seconds, 3)
        facts[f"{name}_epoch_seconds"] = round(sum(v for k, v in facts.items() if k in {f"{name}_{c}_seconds" for c in ("minibatch", "forward", "backward", "allreduce")}), 3)
        facts[f"{name}_waited_seconds"] = round(measures.waiting(r.times).where(F.col("epoch") == last).first().wait, 4)
        facts[f"{name}_imbalance"] = round(measures.time_imbalance(r.times).where(F.col("epoch") == last).first().imbalance, 3)

    # push against pull: the same graph, seeds and model
    for kind in ("sage", "gat"):
        for mode in ("push", "pull"):
            pg = Partitioned.build(edges, partition.by_hash(v, 4), 4)
            model = ModelSpec(kind, (16, 32, 32, 6), dropout=0.0)
            cfg = TrainConfig(model, SampleConfig((5, 5, 5), 256, fast=True), CacheSpec(cs=20_000, ls=2, nc=512, d=1), mode, 1, rate=0.01, engine="barrier")
            r = timed(f"train_{mode}_{kind}", lambda pg=pg, cfg=cfg: train(pg, x, labels.join(seeds, "vid"), cfg))
            facts[f"{mode}_{kind}_edges"] = r.log[0]["edges"]
            facts[f"{mode}_{kind}_run_seconds"] = round(r.log[0]["run_seconds"], 3)
            measured(f"{mode}_{kind}", r)

    # the document graph on parts of few cut edges, at two numbers of ranks
    doc = timed("graph_documents", lambda: stage(graph.documents(spark, SF_DIR)))
    linked = stage(doc.selectExpr("src AS vid").distinct())
    dx = stage(graph.trigram_features(spark, SF_DIR).join(linked, "vid"))
    dy = stage(graph.with_split(graph.language_labels(spark, SF_DIR).join(linked, "vid"), 0.5).where("is_train").select("vid", "label"))
    size = linked.count()
    for P in (4, 8):
        parts = timed(f"multilevel_{P}", lambda P=P: stage(by_multilevel(doc, linked, dy, P)))
        pg = Partitioned.build(doc, parts, P)
        facts[f"documents_cut_{P}"] = round(partition.cut_edges(pg.placed).count() / pg.placed.count(), 4)
        for kind in ("sage", "gat") if P == 8 else ("sage",):
            for mode in ("push", "pull"):
                spec = CacheSpec(cs=int(0.58 * size / P), ls=2, nc=512, d=1)
                cfg = TrainConfig(ModelSpec(kind, (64, 64, 64, 4)), SampleConfig((5, 10, 15), 128, fast=True), spec, mode, 1, engine="barrier")
                r = timed(f"documents_{mode}_{kind}_{P}", lambda pg=pg, cfg=cfg: train(pg, dx, dy, cfg))
                measured(f"documents_{mode}_{kind}_{P}", r)
                if mode == "push":
                    for h in measures.hit_rate(r.plans[0].hit_plan).collect():
                        facts[f"documents_{kind}_{P}_hit_rate_layer{h.layer}"] = round(h.hit_rate, 4)

    # single-node ladder on one block of the paper's shape
    rng = np.random.default_rng(0)
    rows = rng.normal(size=(50_000, 128)).astype(np.float32)
    w, b = rng.normal(size=(128, 256)).astype(np.float32), np.zeros(256, np.float32)
    for name, f in (("update_unfused", update_unfused), ("update_fused", update_fused)):
        timed(f"kernel_{name}", lambda f=f: [f(rows, w, b) for _ in range(5)])
    timed("kernel_blocked", lambda: blocked_matmul(rows, w, 4096, 128, 256))
    dst = np.sort(rng.integers(0, 5_000, 50_000))
    block = Block(rng.integers(0, 50_000, 50_000), dst, 50_000, 5_000)
    p = {f"l.{k}": rng.normal(size=s).astype(np.float32) for k, s in SageLayer.shapes(128, 256).items()}
    timed("kernel_sage_layer", lambda: SageLayer(p, "l").forward(block, rows))

    try:  # the operators for training data may be absent
        from halograph.llm import queries as llm
    except ModuleNotFoundError:
        llm = None
    if llm is not None:
        for name, q in llm.queries().items():
            timed(name, lambda q=q: sink(q(spark, SF_DIR)))
    total = round(sum(times.values()), 3)
    print(json.dumps({"metric": "total_seconds", "value": total, "unit": "sec", "queries": times, "facts": facts, "sf": SF_DIR}))


if __name__ == "__main__":
    main()
