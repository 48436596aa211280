"""Kernels, gradients, engines, limiting cases and convergence."""

import os
import sys
import threading
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pytest
from pyspark import cloudpickle
from pyspark.sql import functions as F

from halograph import measures
from halograph.model import kernels
from halograph.model.layers import Block, GatLayer, SageLayer, cross_entropy
from halograph.model.network import Adam, ModelSpec, Sgd, backward, load, pack, rate_for, save, unpack
from halograph.operators import cache, graph, layers, partition, sampling
from halograph.operators.cache import CacheSpec
from halograph.operators.labels import planted
from halograph.plans.epoch import Partitioned, SampleConfig, plan_epoch
from halograph.plans.infer import WholeGraph, full, sampled
from halograph.plans import single
from halograph.plans.peers import PUSH, Peers
from halograph.plans.rank import PARTS, RankEpoch, drive
from halograph.plans.training import TrainConfig, train
from halograph.session import fresh_path, stage

from .conftest import SF

RNG = np.random.default_rng(0)
BLOCK = Block(np.array([0, 3, 4, 1, 2, 4, 5]), np.array([0, 0, 0, 1, 2, 2, 2]), 6, 4)  # destination 3 has no edges


def numeric(f, x, eps=1e-6):
    g = np.zeros_like(x)
    for i in np.ndindex(x.shape):
        old = x[i]
        x[i] = old + eps
        a = f()
        x[i] = old - eps
        g[i] = (a - f()) / (2 * eps)
        x[i] = old
    return g


LAYERS = {f"sage-{op}": lambda p, op=op: SageLayer(p, "l", op) for op in ("mean", "sum", "gcn")} | {
    f"gat-{'new' if pre else 'old'}-{h}-{c}-{op}": lambda p, pre=pre, h=h, c=c, op=op: GatLayer(p, "l", h, pre, combine=c, op=op)
    for pre in (True, False) for h in (1, 4) for c in ("concat", "mean") for op in ("sum", "gcn")
}


@pytest.mark.parametrize("name", LAYERS)
def test_gradients(name):
    heads, combine = (int(name.split("-")[2]), name.split("-")[3]) if name.startswith("gat") else (0, "")
    shapes = GatLayer.shapes(4, 8, heads, combine) if heads else SageLayer.shapes(4, 8)
    p = {f"l.{k}": RNG.normal(size=s) for k, s in shapes.items()}
    x, drop = RNG.normal(size=(6, 4)), kernels.mask(np.arange(4), 8, 0.3, 1)
    weigh = RNG.normal(size=(4, 8))
    loss = lambda: float((LAYERS[name](p).forward(BLOCK, x, drop) * weigh).sum())
    layer = LAYERS[name](p)
    layer.forward(BLOCK, x, drop)
    dx, grads = layer.backward(weigh)
    for got, at in [(dx, x), *[(grads[k], p[k]) for k in p]]:
        want = numeric(loss, at)
        assert np.abs(got - want).max() <= 1e-5 * max(1, np.abs(want).max()), name


def test_network_gradient_with_constant_cached_rows():
    spec = ModelSpec("sage", (4, 5, 3), dropout=0.0)
    p = spec.init(3)
    blocks = [Block(np.array([0, 1, 2, 3]), np.array([0, 1, 2, 2]), 4, 3), Block(np.array([1, 2, 3]), np.array([0, 0, 1]), 4, 2)]
    x, cached, y = RNG.normal(size=(4, 4)), RNG.normal(size=(1, 5)), np.array([0, 2])
    inputs = lambda k, rows: x if k == 0 else np.concatenate([rows, cached])
    loss = lambda: cross_entropy(spec.forward(p, blocks, inputs)[0], y)[0]
    logits, made, _ = spec.forward(p, blocks, inputs)
    grads = backward(made, cross_entropy(logits, y)[1], [4, 3])
    for k in p:
        want = numeric(loss, p[k])
        assert np.abs(grads[k] - want).max() < 1e-5 * max(1, np.abs(want).max())


def test_kernels_agree():
    x, w, b = RNG.normal(size=(53, 12)), RNG.normal(size=(12, 10)), RNG.normal(size=10)
    want = kernels.update_unfused(x, w, b)
    assert np.allclose(kernels.update_fused(x, w, b), want)
    for tiles in ((7, 4, 5), (16, 5, 3), (64, 12, 10), (1, 1, 1)):
        assert np.allclose(kernels.blocked_matmul(x, w, *tiles), x @ w)
    d = RNG.normal(size=(53, 10))
    assert np.allclose(kernels.weight_grad(x, d, 6), x.T @ d)
    alpha = kernels.edge_softmax(RNG.normal(size=(7, 2)), BLOCK.dst, 4)
    assert np.allclose(kernels.segment_sum(alpha, BLOCK.dst, 4)[:3], 1)
    keep = kernels.mask(np.arange(4000), 8, 0.5, 1, 2)
    assert abs((keep > 0).mean() - 0.5) < 0.02 and set(np.unique(keep)) == {0.0, 2.0}
    rows = RNG.normal(size=(6, 3))
    near = lambda sel: (kernels.segment_sum(rows[BLOCK.src[sel]], BLOCK.dst[sel], 4), np.bincount(BLOCK.dst[sel], minlength=4))
    half = np.arange(7) % 2 == 0
    assert np.allclose(kernels.merge_partials([near(half), near(~half)]), kernels.aggregate(rows, BLOCK.src, BLOCK.dst, 4))


def test_sql_layers_equal_kernels(spark):
    n, width = 12, 4
    x = RNG.integers(-8, 8, (n, width)) / 16
    src, dst = RNG.integers(0, n, 60), RNG.integers(0, n - 3, 60)  # three vertices have no sources
    src, dst = np.unique(np.stack([src, dst]), axis=1)
    rows = spark.createDataFrame([(i, x[i].tolist()) for i in range(n)], "vid long, x array<double>")
    edges = spark.createDataFrame([(int(a), int(b), 1) for a, b in zip(src, dst)], "src long, dst long, w long")
    block = Block(src, dst, n, n)
    of = lambda df: np.array([r.x for r in df.orderBy("vid").collect()])
    p = {k: RNG.normal(size=s) for k, s in SageLayer.shapes(4, 3).items()}
    for op in ("mean", "sum", "gcn"):
        assert np.allclose(of(layers.sage(edges, rows, p, op)), SageLayer({f"l.{k}": v for k, v in p.items()}, "l", op).forward(block, x))
    g = {k: RNG.normal(size=s) for k, s in GatLayer.shapes(4, 4, 2).items()}
    for pre in (True, False):
        for combine in ("concat", "mean"):
            for op in ("sum", "gcn"):
                got = of(layers.gat(edges, rows, g, 2, pre, combine, op))
                assert len(got) == n and np.allclose(got, GatLayer({f"l.{k}": v for k, v in g.items()}, "l", 2, pre, combine=combine, op=op).forward(block, x))


@pytest.fixture(scope="module")
def task(spark):
    """The planted task on the small purchase graph."""
    edges, v = stage(graph.purchase(spark, SF)), graph.purchase_vertices(spark, SF)
    x = stage(graph.hash_features(v, 16))
    y = stage(planted(edges, x))
    s = graph.with_split(v, 0.5)
    whole = WholeGraph(edges, x)
    test = y.join(s.where("NOT is_train").select("vid"), "vid").toPandas()
    return edges, v, x, stage(y.join(s.where("is_train").select("vid"), "vid")), whole, test


def run(task, mode="push", P=2, engine="local", epochs=2, spec=CacheSpec(cs=400, ls=2, nc=64, d=1), kind="sage", dropout=0.0, **more):
    edges, v, x, y, whole, test = task
    pg = Partitioned.build(edges, partition.by_hash(v, P), P)
    cfg = TrainConfig(ModelSpec(kind, (16, 16, 6), dropout=dropout), SampleConfig((10, 3), 16), spec, mode, epochs, rate=0.01, engine=engine, **({"dtype": "f8"} | more))
    return train(pg, x, y, cfg, evaluate=lambda p: whole.accuracy(cfg.model, p, test.vid.to_numpy(), test.label.to_numpy())), cfg


def same(a, b, tol=0.0):
    return all(np.abs(a.params[k] - b.params[k]).max() <= tol for k in a.params)


def test_engines_take_the_same_steps(task):
    a, _ = run(task, dropout=0.2)
    assert any(p.hit_plan.where("hit").count() for p in a.plans)
    assert same(a, run(task, engine="barrier", dropout=0.2)[0], 1e-9)
    assert same(a, run(task, engine="step", dropout=0.2)[0], 1e-6)
    assert same(a, run(task, dropout=0.2, prefetch=True)[0], 0)
    assert same(a, run(task, dropout=0.2, used_only=False)[0], 0)
    assert same(a, run(task, dropout=0.2, dtype="f4")[0], 1e-3) and not same(a, run(task, dropout=0.2, dtype="f4")[0])


def test_three_ranks_and_longer_delays(task):
    spec = CacheSpec(cs=100, ls=3, nc=16, d=2)
    a = run(task, P=3, spec=spec)[0]
    b, cfg = run(task, P=3, spec=spec, engine="barrier")
    assert same(a, b, 1e-9)
    rows = b.times.toPandas()
    assert set(rows.part) == set(PARTS) and set(rows["rank"]) == {0, 1, 2} and (rows.seconds >= 0).all()
    assert rows.groupby(["epoch", "it"]).size().eq(3 * len(PARTS)).all()
    parts = {(r.epoch, r.part): r.seconds for r in measures.epoch_parts(b.times).collect()}
    step = rows.groupby(["epoch", "it", "part"]).seconds.agg(["max", "min"]).reset_index()
    for (e, part), seconds in parts.items():
        mine = step[(step.epoch == e) & (step.part == part)]
        assert abs(seconds - mine["min" if part == "allreduce" else "max"].sum()) < 1e-6
    four = {(r.epoch, r.part): r.seconds for r in measures.forward_with_remote(measures.epoch_parts(b.times)).collect()}
    assert abs(four[0, "forward"] - sum(parts[0, p] for p in ("pre", "wait", "post", "forward"))) < 1e-6
    spent = {r.epoch: r for r in measures.waiting(b.times).collect()}
    assert spent[0].send > 0 and abs(spent[0].send - rows[(rows.epoch == 0) & (rows.part == "send") & (rows.it > 0)].seconds.sum()) < 1e-6
    pushes = b.plans[0].push_plan
    slower = b.times.withColumn("seconds", F.col("seconds") * 8)
    got = measures.hidden((b.times, pushes), (slower, pushes.unionByName(pushes))).where("epoch = 0").first()  # twice the rows, eight times the wait
    assert got.rows == pushes.where("arrive_it > 0").count() > 0 and abs(got.hidden - 0.75) < 1e-6
    assert measures.hidden((b.times, pushes.where("false")), (slower, pushes)).first().hidden is None  # nothing pushed tells nothing
    quiet = run(task, "pull", P=2, epochs=1, engine="barrier")[0]
    assert measures.waiting(quiet.times).first().send == 0 and measures.waiting(quiet.times).first().wait == 0  # nothing is pushed, nothing is timed
    assert all(r.imbalance >= 0 for r in measures.time_imbalance(b.times).collect())


def test_without_delay_rows_are_fresh(task):
    """d = 0: all engines agree, and a halo that is hit has this iteration's row."""
    spec = CacheSpec(cs=None, ls=0, nc=None, d=0)
    a = run(task, spec=spec)[0]
    assert same(a, run(task, spec=spec, engine="barrier")[0], 1e-9)
    assert same(a, run(task, spec=spec, engine="step")[0], 1e-6)
    assert not same(a, run(task, spec=replace(spec, d=1, ls=1))[0])
    assert a.plans[0].hit_plan.where("hit AND version_it <> it").count() == 0


@dataclass(frozen=True)
class FailsOnce(ModelSpec):
    """Fails in the third iteration of one rank, until a file is there."""

    marker: str = ""

    def apply(self, p, k, block, rows, context, ids):
        if context and context[-1] == 2 and len(ids) % 2 == 0 and not os.path.exists(self.marker):
            open(self.marker, "w").close()
            raise RuntimeError("lost")
        return super().apply(p, k, block, rows, context, ids)


def test_an_epoch_runs_again_when_a_task_fails(task, tmp_path):
    cloudpickle.register_pickle_by_value(sys.modules[__name__])
    edges, v, x, y, *_ = task
    pg = Partitioned.build(edges, partition.by_hash(v, 2), 2)
    out = []
    for marker in (tmp_path / "first", tmp_path / "first"):
        model = FailsOnce("sage", (16, 16, 6), dropout=0.0, marker=str(marker))
        out.append(train(pg, x, y, TrainConfig(model, SampleConfig((5, 3), 16), CacheSpec(cs=400, ls=2, nc=64, d=1), "push", 1, rate=0.01, engine="barrier", dtype="f8")))
    assert (tmp_path / "first").exists() and same(*out, 1e-9)


def test_what_a_miss_can_do(task):
    base = CacheSpec(cs=50, ls=1, nc=16, d=1)
    runs = {m: run(task, spec=replace(base, on_miss=m))[0] for m in ("drop", "zero", "stale", "pull")}
    assert all(not same(runs[a], runs[b]) for a in runs for b in runs if a < b)
    edges = {m: r.plans[0].exec_blocks.count() for m, r in runs.items()}
    blocks = runs["drop"].plans[0].blocks.count()
    assert edges["drop"] < edges["stale"] < edges["zero"] == blocks and edges["drop"] < edges["pull"] <= blocks
    for m in ("zero", "stale", "pull"):
        assert same(runs[m], run(task, spec=replace(base, on_miss=m), engine="barrier")[0], 1e-9)


def test_caches_that_are_emptied_and_rounds_that_end_with_the_first_rank(task):
    spec = CacheSpec(cs=400, ls=4, nc=64, d=1)
    kept, emptied = run(task, spec=spec)[0], run(task, spec=spec, reset=True)[0]
    assert not same(kept, emptied)
    first = emptied.plans[1].hit_plan.where("hit AND version_it < 0").count()
    assert first == 0 and kept.plans[1].hit_plan.where("hit AND version_it < 0").count() > 0
    assert same(emptied, run(task, spec=spec, reset=True, engine="barrier")[0], 1e-9)
    assert same(kept, run(task, spec=spec, engine="step")[0], 1e-6)
    edges, v, x, y, *_ = task
    pg = Partitioned.build(edges, partition.by_range(v, 3), 3)
    most, least = (plan_epoch(pg, y, SampleConfig((3, 3), 16, pad=pad), spec) for pad in ("max", "min"))
    per = [r.n for r in most.seeds.groupBy("rank").agg(F.max("it").alias("n")).collect()]
    assert most.rounds == max(per) + 1 and least.rounds == min(per) + 1 and least.seeds.where(f"it > {min(per)}").count() == 0


def test_lives_by_layer_and_by_epoch(task):
    edges, v, x, y, *_ = task
    pg = Partitioned.build(edges, partition.by_hash(v, 2), 2)
    spec = CacheSpec(cs=None, ls=2, nc=32, d=1)
    plan = plan_epoch(pg, y, SampleConfig((3, 3), 8), spec)
    rate = lambda s: {r.layer: r.hits for r in measures.hit_rate(cache.residency(cache.demand(plan.frontier), plan.push_plan, s, plan.rounds)).collect()}
    two, zero, ever = rate(spec), rate(replace(spec, ls=0)), rate(replace(spec, ls=None))
    assert rate(replace(spec, ls=(None, 0))) == {0: ever[0], 1: zero[1]} and rate(replace(spec, ls=(0, 2))) == {0: zero[0], 1: two[1]}
    assert rate(replace(spec, ls=(None, 2), cs=10**6)) == {0: ever[0], 1: two[1]}
    assert rate(replace(spec, ls=0, clock="epoch")) == ever == rate(replace(spec, ls=0, clock="epoch", cs=10**6))


def test_ids_are_whole_numbers_of_64_bits():
    big = 2**53
    rows = [(0, "f", 0, 1, big + 1, None, None), (0, "f", 0, 0, big + 1, None, None), (0, "f", 0, 0, big, None, None), (0, "e", 0, 0, big, big + 1, None)]
    rows += [(0, "x", None, None, big + k, None, [float(k), 1.0]) for k in (0, 1)] + [(0, "y", None, None, big + 1, 1, None)]
    kinds = (pa.int32(), pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.float32()))
    t = pa.table([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["rank", "tag", "it", "layer", "a", "b", "row"])
    rank = RankEpoch(t, ModelSpec("sage", (2, 3), dropout=0.0), 0)
    assert rank.x_ids.tolist() == [big, big + 1] and rank.features_of(np.array([big + 1])).tolist() == [[1.0, 1.0]]
    grads, m = drive(rank.steps(ModelSpec("sage", (2, 3)).init(1), 0), lambda k, sends: None)
    assert m["edges"] == 1 and m["seeds"] == 1


def test_peers_add_up_and_fail_together():
    for n in (1, 2, 3, 5, 8):
        ports: dict[int, str] = {}
        ready = threading.Barrier(n)
        out = {}

        def gather(me, s):
            ports[me] = s
            ready.wait(20)
            return [ports[k] for k in range(n)]

        def go(me):
            p = Peers(me, ["127.0.0.1"] * n, lambda s: gather(me, s), b"0" * 16)
            for it in range(3):
                for o in range(n):
                    if o != me:
                        p.push(o, it, 0, np.array([me]), np.full((1, 2), me + it, np.float32))
                got = [p.get(PUSH, it, 0, o)[1].tolist() for o in range(n) if o != me]
                total, counts = p.allreduce(it, np.array([1.0, me]), np.array([me]))
                out[me, it] = (got, total.tolist(), counts.tolist())
            ready.wait(20)
            p.close()

        threads = [threading.Thread(target=go, args=(k,)) for k in range(n)]
        for t in threads:
            t.start()
        for t in threads:
            t.join(60)
        for me in range(n):
            for it in range(3):
                assert out[me, it] == ([[[o + it] * 2] for o in range(n) if o != me], [n, n * (n - 1) / 2], [n * (n - 1) // 2])


def test_a_hop_leaves_the_edges_where_they_are(spark, task):
    edges, v, x, y, *_ = task
    pg = Partitioned.build(edges, partition.by_hash(v, 2), 2)
    seeds = sampling.minibatches(y, pg.parts, 16)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        plan = sampling.hop(stage(seeds), pg.placed, 3, 1)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.conf.unset("spark.sql.adaptive.enabled")
    assert plan.count("Exchange") == 1 and "WindowGroupLimit" in plan, plan


def test_limiting_cases(task):
    none = run(task, "none", epochs=1)[0]
    assert same(none, run(task, spec=CacheSpec(cs=0, ls=2, nc=64, d=1), epochs=1)[0])
    assert same(none, run(task, spec=CacheSpec(cs=400, ls=2, nc=64, d=99), epochs=1)[0])
    assert not same(none, run(task, epochs=1)[0])
    assert same(run(task, P=1, epochs=1)[0], run(task, "pull", P=1, epochs=1)[0])


def test_half_precision_rows_change_little(task):
    a, b = run(task, epochs=1)[0], run(task, epochs=1, row_dtype="f2")[0]
    assert not same(a, b) and same(a, b, 0.02)


def test_attention_trains(task):
    r, _ = run(task, kind="gat", epochs=3)
    assert r.log[-1]["loss"] < r.log[0]["loss"]


def test_inference_over_whole_neighbourhoods(task):
    edges, v, x, y, whole, _ = task
    for kind in ("sage", "gat"):
        spec = ModelSpec(kind, (16, 8, 6), dropout=0.0)
        p = spec.init(2)
        got = np.array(full(edges, x, spec, p).toPandas().sort_values("vid")["logits"].tolist())
        assert np.allclose(got, whole.logits(spec, p)[0])


def test_inference_by_samples(task):
    """With fan-outs above every degree, sampled inference is inference over whole neighbourhoods."""
    edges, v, x, y, whole, _ = task
    pg = Partitioned.build(edges, partition.by_hash(v, 2), 2)
    for kind in ("sage", "gat"):
        spec = ModelSpec(kind, (16, 8, 6), dropout=0.0)
        p = spec.init(2)
        got = {r.vid: r.logits for r in sampled(pg, v, x, spec, p, SampleConfig((1000, 1000), 40)).collect()}
        want = whole.logits(spec, p)[0]
        assert len(got) == len(whole.ids) and all(np.allclose(got[i], want[k], atol=1e-4) for k, i in enumerate(whole.ids.tolist()))


def test_wide_samples_on_one_rank_are_full_batch(task):
    """With a fan-out above every degree and one minibatch, a step's gradient is that of the full batch."""
    edges, v, x, y, whole, _ = task
    pg = Partitioned.build(edges, partition.by_hash(v, 1), 1)
    model = ModelSpec("sage", (16, 8, 6), dropout=0.0)
    cfg = TrainConfig(model, SampleConfig((1000, 1000), 10_000), CacheSpec(), "push", 1, "sgd", 0.1, engine="local", dtype="f8")
    got = train(pg, x, y, cfg).params
    labels = y.toPandas()
    want, _ = whole.train(model, labels.vid.to_numpy(), labels.label.to_numpy(), 1, Sgd(0.1), seed=1)
    assert all(np.allclose(got[k], want[k], atol=1e-6) for k in got)


def test_the_ladder_trains_the_same_model(task):
    """Rungs differ in speed, not in what they learn; a wide sample gives every neighbour."""
    _, _, _, y, whole, _ = task
    graph_ = single.Csr(whole.block.src, whole.block.dst, len(whole.ids))
    labels = y.toPandas()
    seeds, x = np.searchsorted(whole.ids, labels.vid.to_numpy()), whole.x
    rng = np.random.default_rng(0)
    for how in ("at once", "one by one"):
        blocks, ids = graph_.minibatch(seeds[:20], (3, 2), rng, how)
        assert all(len(np.unique(i)) == len(i) for i in ids) and (ids[1][:20] == seeds[:20]).all()
        assert np.bincount(blocks[1].dst).max() <= 3 and np.bincount(blocks[0].dst).max() <= 2
        edges = set(zip(whole.block.src.tolist(), whole.block.dst.tolist(), strict=True))
        assert all((int(ids[0][a]), int(ids[1][b])) in edges for a, b in zip(blocks[0].src, blocks[0].dst, strict=True))
        pairs = list(zip(blocks[0].src.tolist(), blocks[0].dst.tolist(), strict=True))
        assert len(set(pairs)) == len(pairs)
    for kind in ("sage", "gat"):
        out = [single.train_single(graph_, x, seeds, labels.label.to_numpy(), ModelSpec(kind, (16, 8, 6), dropout=0.2), (1000, 1000), 40, 2, kernel=k, sampler=s, beside=n) for _, k, s, n in single.LADDER]
        assert all(np.allclose(out[0][0][k], o[0][k], atol=1e-8) for o in out[1:] for k in o[0])
        assert out[0][1][1]["loss"] < out[0][1][0]["loss"]


def test_held_out_links_are_told_from_others(spark):
    """Every fifth link is kept for the test; the model never sees it, neither as a pair nor as an edge."""
    sf = SF.replace("sf0.001", "sf0.01")
    edges = stage(graph.documents(spark, sf))
    x = graph.trigram_features(spark, sf).join(edges.select(F.col("src").alias("vid")).distinct(), "vid")
    whole = WholeGraph(edges, x)
    pairs = np.stack([whole.block.src, whole.block.dst], 1)
    pairs = pairs[pairs[:, 0] < pairs[:, 1]]
    held = np.random.default_rng(0).random(len(pairs)) < 0.2
    seen, test = pairs[~held], pairs[held]
    g = single.Csr(np.concatenate(seen.T), np.concatenate(seen.T[::-1]), len(whole.ids))
    spec = ModelSpec("sage", (64, 32, 16), dropout=0.0)
    p, losses = single.train_links(g, whole.x, seen, spec, (5, 5), 256, 4, 0.01)
    assert losses[-1] < losses[0]
    whole.block = Block(np.concatenate(seen.T), np.concatenate(seen.T[::-1]), len(whole.ids), len(whole.ids))
    h = whole.logits(spec, p)[0]
    rng = np.random.default_rng(1)
    false = np.stack([test[:, 0], rng.integers(0, len(whole.ids), len(test))], 1)
    score = lambda e: (h[e[:, 0]] * h[e[:, 1]]).sum(1)
    assert single.area_under_curve(score(test), score(false)) > 0.65  # 0.5 is chance
    assert single.area_under_curve(np.array([3.0, 1.0]), np.array([2.0, 1.0])) == 0.625


def test_full_batch_learns(task):
    edges, v, x, y, whole, test = task
    labels = y.toPandas()
    p, losses = whole.train(ModelSpec("sage", (16, 32, 6), dropout=0.0), labels.vid.to_numpy(), labels.label.to_numpy(), 60, Adam(0.02))
    assert losses[-1] < 0.5 * losses[0]


def test_parameters_survive_storage(spark):
    spec = ModelSpec("gat", (5, 8, 3))
    p, path = spec.init(4), fresh_path(spark, "params")
    save(spark, p, path, 0)
    save(spark, {k: v + 1 for k, v in p.items()}, path, 1)
    assert all(np.array_equal(load(spark, path)[k], p[k] + 1) and np.array_equal(load(spark, path, 0)[k], p[k]) for k in p)
    assert all(np.array_equal(v, p[k]) for k, v in unpack(pack(p), p).items())
    assert rate_for("sage", 1) == 0.003 and rate_for("sage", 8) == 0.006


def test_parameter_counts_of_the_published_models():
    n = lambda dims: sum(int(np.prod(s)) for s in ModelSpec("sage", dims).shapes().values())
    assert n((100, 256, 256, 47)) == 206_895 and n((128, 256, 256, 172)) == 285_356


def test_small_graphs(spark):
    from halograph.plans.small import train_small_graphs

    rng = np.random.default_rng(3)
    rows, ends = [], []
    for g in range(20):
        x = rng.normal(size=(6, 4))
        rows += [(g, i, x[i].tolist(), int(x[i, 0] + x[max(0, i - 1), 1] > 0)) for i in range(6)]
        ends += [(g, i, i + 1) for i in range(5)]
    v = spark.createDataFrame(rows, "graph_id long, vid long, x array<double>, label int")
    e = spark.createDataFrame(ends, "graph_id long, src long, dst long")
    _, losses = train_small_graphs(v, e, ModelSpec("sage", (4, 8, 2), dropout=0.0), 6, 0.05)
    assert losses[-1] < losses[0]

def test_a_rank_holds_one_iteration_of_its_plan():
    """Rows come in order of their iteration and are read when it is due, whatever batches cut them."""
    from halograph.plans.rank import ROWS, Turns

    its = [None, None, -1, 0, 0, 1, 3, 3, 3]
    rows = [(0, "f", it, 0, k, None, None) for k, it in enumerate(its)]
    for size in (1, 2, 4, 9):
        batches = [pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows[i : i + size], strict=True), ROWS.types, strict=True)], names=ROWS.names) for i in range(0, len(rows), size)]
        read = []
        turns = Turns(read.append(b) or b for b in batches)
        got = [turns.before(it).column("a").to_pylist() for it in range(5)]
        assert got == [[0, 1, 2], [3, 4], [5], [], [6, 7, 8]]
        turns, read[:] = Turns(read.append(b) or b for b in batches), []
        turns.before(0)
        assert len(read) == 3 // size + 1  # no further than the first row that is not due


def test_a_rank_maps_its_features():
    """They come in order of id, batch by batch, and none of their memory is the process's own."""
    from halograph.plans.rank import ROWS, Turns

    n, width, spec = 40_000, 32, ModelSpec("sage", (32, 3), dropout=0.0)
    x = RNG.random((n, width), np.float32)
    held = []

    def batches():
        for lo in range(0, n, 1000):
            held.append(pa.total_allocated_bytes())
            ids = np.repeat(np.arange(lo, lo + 1000) * 3, 2)  # each comes twice
            yield pa.record_batch([pa.array(np.zeros(2000), pa.int32()), pa.array(["x"] * 2000), pa.nulls(2000, pa.int32()), pa.nulls(2000, pa.int32()), pa.array(ids), pa.nulls(2000, pa.int64()), pa.array(list(np.repeat(x[lo : lo + 1000], 2, 0)), pa.list_(pa.float32()))], names=ROWS.names)
        yield pa.record_batch([pa.array(c, t) for c, t in zip(zip((0, "m", -1, 0, 7, None, [1.0] * width), (0, "f", 0, 0, 9, None, None), strict=True), ROWS.types, strict=True)], names=ROWS.names)

    turns, rank = Turns(batches()), RankEpoch(ROWS.empty_table(), spec, 0)
    rank.take(turns.each(0))
    assert max(held) - held[0] < x.nbytes / 4 and all(isinstance(a.base, np.memmap) for a in (rank.x, rank.x_ids))
    at = RNG.permutation(n)[:500]
    assert (rank.features_of(at * 3) == x[at]).all() and rank.inbox[-1, 0][0].tolist() == [7]
    with pytest.raises(ValueError):
        rank.features_of(np.array([1]))
    assert turns.before(1).column("a").to_pylist() == [9]
    with pytest.raises(ValueError):
        rank.take(iter([pa.record_batch([pa.array(c, t) for c, t in zip(zip(*[(0, "x", None, None, k, None, [1.0] * width) for k in (2, 1)], strict=True), ROWS.types, strict=True)], names=ROWS.names)]))


def test_step_engine_lists_few_folders(monkeypatch, spark, work):
    """Iterations share folders, which the driver lists one at a time, and the run is that of one process."""
    from pathlib import Path

    from halograph.plans import training

    made = []
    monkeypatch.setattr(training, "fresh_path", lambda s, name: made.append(fresh_path(s, name)) or made[-1])
    monkeypatch.setattr(training, "ITERATIONS_A_FOLDER", 2)
    x = graph.hash_features(work.vertices, 4)
    labels = planted(work.edges, x, 4).join(work.train, "vid")
    cfg = TrainConfig(ModelSpec("sage", (4, 6), dropout=0.0), SampleConfig((3,), 10), replace(work.spec, d=1), "push", 1, rate=0.01, engine="step")
    got = train(work.pg, x, labels, cfg)
    rounds = got.log[0]["rounds"]
    assert rounds > 2 and len(list(Path(made[0].removeprefix("file://")).glob("*=*"))) == -(-rounds // 2)
    want = train(work.pg, x, labels, replace(cfg, engine="local"))
    assert all(np.allclose(got.params[k], want.params[k], atol=1e-5) for k in want.params)
    assert got.times.select("rank", "it").distinct().count() == want.times.select("rank", "it").distinct().count()
