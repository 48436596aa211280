"""Queries that SQL does not follow, against plain Python and the one-process engine."""

from collections import defaultdict
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from halograph import catalog
from halograph.model.network import ModelSpec
from halograph.operators import graph
from halograph.operators.labels import planted
from halograph.plans.epoch import SampleConfig
from halograph.plans.infer import predict_nodes, sampled
from halograph.plans.training import TrainConfig, train

from .conftest import SF


@pytest.fixture(scope="module")
def q():
    return catalog.queries()


def test_approximations(spark, work, q):
    exact = {r.layer: r for r in work.plan.frontier.groupBy("layer").agg(F.count_distinct("vid").alias("n"), F.percentile("vid", F.lit(0.45)).alias("lo"), F.percentile("vid", F.lit(0.55)).alias("hi")).collect()}
    for r in q["approx_frontier"](spark, SF).collect():
        assert abs(r.about - exact[r.layer].n) <= 0.1 * exact[r.layer].n + 1 and exact[r.layer].lo <= r.middle <= exact[r.layer].hi
    n = work.pg.halos.select("vid").distinct().count()
    assert abs(q["hll_halo_overlap"](spark, SF).first().distinct_halos - n) <= 0.05 * n + 1


def test_late_edges(spark, q):
    """Counts by window of what is not behind the watermark, for the windows that the last watermark closes. A batch closes windows by the
    watermark of the batches before it, and leaves out what belongs to windows that the batch before it has closed."""
    rows = [(r.event_id, r.s) for r in spark.read.parquet(f"{SF}/events.parquet").select("event_id", F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', CAST(ts AS TIMESTAMP_NTZ))").alias("s")).collect()]
    key = {i: i + 400 if i % 20 == 0 else i for i, _ in rows}
    low, high = min(key.values()), max(key.values())
    step = -(-(high - low + 1) // 4)
    counts, marks, late = defaultdict(int), [-(1 << 60)] * 2, 0
    for k in range(4):
        batch = [s for i, s in rows if low + k * step <= key[i] < low + (k + 1) * step]
        for s in batch:
            start = s // 3600 * 3600
            if start + 3600 <= marks[-2]:
                late += 1
            else:
                counts[start] += 1
        marks.append(max([marks[-1], *(s - 3600 for s in batch)]))
    got = {r.start: r.n for r in q["stream_late_edges"](spark, SF).collect()}
    assert got == {w: n for w, n in counts.items() if w + 3600 <= marks[-1]} and late > 0


@pytest.mark.parametrize("name, mode, kind, epochs, d", [("train_push_log", "push", "sage", 2, 1), ("train_push_gat_log", "push", "gat", 1, 1), ("train_pull_log", "pull", "sage", 2, 1), ("train_no_remote_log", "none", "sage", 1, 1), ("train_sync_log", "push", "sage", 1, 0), ("train_step_engine_log", "push", "sage", 1, 1)])
def test_training_logs(spark, work, q, name, mode, kind, epochs, d):
    x = graph.hash_features(work.vertices, 16)
    cfg = TrainConfig(ModelSpec(kind, (16, 32, 6), dropout=0.0), SampleConfig((10, 3), 64), replace(work.spec, d=d), mode, epochs, rate=0.01, engine="local", dtype="f8")
    want = train(work.pg, x, planted(work.edges, x).join(work.train, "vid"), cfg).log
    got = sorted(q[name](spark, SF).collect())
    assert [(r.epoch, r.rounds, r.edges) for r in got] == [(m["epoch"], m["rounds"], m["edges"]) for m in want]
    assert all(abs(r.loss - m["loss"]) < 1e-3 * m["loss"] and abs(r.train_accuracy - m["train_accuracy"]) < 0.02 for r, m in zip(got, want, strict=True))


def test_measured_queries(spark, work, q):
    parts = q["measured_parts"](spark, SF).collect()
    assert {(r.run, r.epoch, r.part) for r in parts} == {(run, e, p) for run in ("push", "pull") for e in (0, 1) for p in ("minibatch", "forward", "backward", "allreduce")}
    total = {r.run: 0.0 for r in parts}
    for r in parts:
        assert r.seconds > 0
        total[r.run] += r.seconds
    seconds = defaultdict(float)
    for r in q["measured_epoch_time"](spark, SF).collect():
        seconds[r.run] += r.seconds
    assert all(total[k] < seconds[k] for k in total)  # the ranks' own time is part of the epoch's
    rounds = work.runs[next(k for k in work.runs if k[0] == "push" and k[2] == 2)].plans[0].rounds
    for r in q["measured_waiting"](spark, SF).collect():
        assert (r.send > 0) == (r.run == "push" and rounds > 1)
    for r in q["measured_hidden"](spark, SF).collect():
        assert (r.hidden is None) == (rounds == 1)  # one round pushes nothing that is delayed
    assert {r.run for r in q["measured_imbalance"](spark, SF).collect()} == {"push", "pull"}
    assert q["measured_gain"](spark, SF).first().factor > 0


def test_sampled_inference(spark, work, q):
    got = {r.vid: r.pred for r in q["sampled_inference"](spark, SF).collect()}
    assert got.keys() == {r.vid for r in work.train.collect()} and set(got.values()) <= set(range(6))
    key = next(k for k in work.runs if k[0] == "push" and k[2] == 2)
    again = predict_nodes(sampled(work.pg, work.train, graph.hash_features(work.vertices, 16), ModelSpec("sage", (16, 32, 6), dropout=0.0), work.runs[key].params, work.sample_two))
    assert {r.vid: r.pred for r in again.collect()} == got


@pytest.mark.parametrize("name, given", [("ablation_gain", "lineitem"), ("breakdown_pivot", "events"), ("convergence_epoch", "events"), ("dyadic_weights", "part"), ("loss_moving_avg", "events"), ("lr_table", "lineitem"), ("scaling_efficiency", "lineitem"), ("source_ring_graph", "customer"), ("speedup_table", "lineitem"), ("time_breakdown", "events"), ("time_to_target", "events")])
def test_reads_a_given_table(spark, q, name, given):
    assert any(f.endswith(f"/{given}.parquet") for f in q[name](spark, SF).inputFiles())


def test_clock_ticks_with_the_events(spark, q):
    """The stream's files are gone into what it wrote, so rows are compared: every event is a tick, in four iterations."""
    got = q["stream_clock"](spark, SF)
    assert got.select("tick").exceptAll(spark.read.parquet(f"{SF}/events.parquet").select("event_id")).isEmpty() and got.count() == spark.read.parquet(f"{SF}/events.parquet").count()
    assert {r.it for r in got.select("it").distinct().collect()} == {0, 1, 2, 3}
