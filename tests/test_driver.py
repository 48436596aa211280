"""What a run leaves in the driver: it must not grow with the run's length."""

from __future__ import annotations

from dataclasses import replace
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pytest

from halograph import catalog, session
from halograph.model.network import ModelSpec, Sgd
from halograph.plans import infer, training
from halograph.plans.epoch import SampleConfig
from halograph.plans.training import TrainConfig, train
from halograph.queries import numeric
from halograph.queries.workload import workload

SF = "/root/testdata/sf0.001"


def test_epochs_give_the_drivers_heap_back(spark):
    w, heap = workload(spark, SF), spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
    cfg = TrainConfig(ModelSpec("sage", (16, 32, 6), dropout=0.0), SampleConfig((10, 3), 64), replace(w.spec, d=1), "none", 1, rate=0.01, engine="local")
    x, y = w.trained_features, w.trained_labels
    _ = w.pg
    for _ in range(8):
        spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.byte, 60_000_000)
    grown = heap.totalMemory()
    train(w.pg, x, y, cfg)
    assert heap.totalMemory() < 0.8 * grown


def test_models_are_trained_on_stored_rows(spark):
    """Features and labels are drawn and counted once, not in every epoch."""
    w = workload(spark, SF)
    for df in (w.trained_features, w.trained_labels):
        assert not any("testdata" in f for f in df.inputFiles()) and "md5" not in df._jdf.queryExecution().toString()


LIMITS = ("spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch")


def test_ranks_batches_are_not_weighed_with_every_row(spark, monkeypatch):
    """A limit of bytes makes Spark weigh the batch with each row, which was nine tenths of the ranks' stage. The stage itself is not run here."""
    before, seen = [spark.conf.get(k, None) for k in LIMITS], []

    def look(df, name):
        seen.append([spark.conf.get(k, None) for k in LIMITS])
        raise InterruptedError

    monkeypatch.setattr(training, "stage", look)
    rows = spark.createDataFrame([(0, "f", 0, 0, 1, None, None)], training.SCHEMA)
    with pytest.raises(InterruptedError):
        training._run_barrier(rows, None, TrainConfig(ModelSpec("sage", (16, 32, 6))), 0, 1, {}, None)
    assert seen == [["10000", str(2**31 - 1)]]
    assert [spark.conf.get(k, None) for k in LIMITS] == before


def test_batches_by_rows_keep_wide_rows_to_the_bytes(spark):
    def sizes(batches):
        yield from (pa.record_batch([pa.array([len(b)], pa.int64())], names=["n"]) for b in batches)

    with session.batches_by_rows(spark, session.BATCH_BYTES // 100):
        got = [r.n for r in spark.range(0, 1050, 1, 1).mapInArrow(sizes, "n long").collect()]
    assert max(got) == 100 and sum(got) == 1050


@pytest.mark.parametrize("d", [1, 0])
def test_an_iteration_of_the_step_engine_is_one_job(spark, monkeypatch, d):
    """Without delay one for each layer besides. Queries, their exchanges and listings took most of an epoch of thousands of iterations."""
    w, sc = workload(spark, SF), spark.sparkContext
    cfg = TrainConfig(ModelSpec("sage", (16, 8, 6), dropout=0.0), SampleConfig((3, 2), 6), replace(w.spec, d=d), "push", 1, rate=0.01, dtype="f8")
    plan = training.plan_for(w.pg, w.trained_labels, cfg, 0, None)
    rows = session.stage(training.epoch_rows(plan, w.trained_features, w.trained_labels, spec=cfg.cache, by_iteration=True))
    add, seen, start = training.allreduce, [], cfg.model.init(1)

    def counted(*a):
        out = add(*a)
        sc._jsc.sc().listenerBus().waitUntilEmpty(30_000)
        seen.append(len(sc.statusTracker().getJobIdsForGroup(f"steps-{d}")))
        return out

    monkeypatch.setattr(training, "allreduce", counted)
    sc.setJobGroup(f"steps-{d}", "")
    got = training._run_step(rows, None, cfg, 0, plan.rounds, start, Sgd(0.01))
    sc.setJobGroup("", "")
    assert plan.rounds > 2 and len(seen) == plan.rounds * (1 if d else 3) and seen[-1] - seen[0] == len(seen) - 1
    want = training._run_local(rows, None, cfg, 0, plan.rounds, start, Sgd(0.01))
    assert all(np.allclose(got.params[k], want.params[k], atol=1e-6) for k in want.params) and plan.hit_plan.where("hit").count() > 0
    assert [m["edges"] for m in got.log] == [m["edges"] for m in want.log]
    assert sorted(got.rows.where("tag = 't'").select("rank", "it").collect()) == sorted(want.rows.where("tag = 't'").select("rank", "it").collect())


def test_inference_brings_no_features_to_the_driver(spark, monkeypatch):
    """They are read as they are stored, and neither end of their join is broadcast; batches are not weighed with every row."""
    plans = []

    def look(df, name="stage"):
        plans.append((df._jdf.queryExecution().toString(), [spark.conf.get(k, None) for k in LIMITS]))
        return session.stage(df, name)

    monkeypatch.setattr(infer, "stage", look)
    monkeypatch.setattr(numeric, "trained", lambda w, mode: SimpleNamespace(params=ModelSpec("sage", (16, 32, 6)).init(1)))
    df = catalog.queries()["sampled_inference"](spark, SF)
    plans.append((df._jdf.queryExecution().toString(), None))
    plan, limits = next(p for p in plans if "FlatMapGroupsInArrow" in p[0])
    assert "BroadcastExchange" not in plan and "md5" not in plan and limits == ["10000", str(2**31 - 1)]
    assert df.count() == workload(spark, SF).train.count()
