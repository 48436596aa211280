"""Training over an epoch's plan: delayed push, pull baseline, no remote rows, one rank; and the engines that run the steps.

Only numbers flow here: which rows are sent, arrive and serve was settled by the plan. Engines differ in where steps run.

barrier  one stage for an epoch, a task for each rank, which keeps its features and cache. Pushes go straight from executor to executor in
         the background and are waited for d iterations later; gradients are summed over a tree. It needs a slot for every rank.
step     one job for an iteration, messages in shared storage, gradients summed in two levels by the same job. It needs no slots at once, and
         what an iteration has written outlives lost executors.
local    all ranks in this process, one after another: the reference for tests.
auto     barrier where there are slots for all ranks, else step.

All compute the same steps. With a delay of 0 a layer's rows are brought to the other ranks before the layer is computed.
"""

from __future__ import annotations

import operator
import os
import pickle
import time
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from functools import partial

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.parquet as pq
from pyarrow import fs as pafs
from pyspark import RDD, BarrierTaskContext, TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.network import Adam, ModelSpec, Sgd, pack, rate_for, unpack
from ..operators import cache, exchange, sampling
from ..operators.cache import CacheSpec
from ..session import batches_by_rows, fresh_path, release, ship_package, stage, store
from .epoch import EpochPlan, Partitioned, SampleConfig, plan_epoch
from .peers import PUSH, Peers
from .rank import PARTS, ROWS, SCHEMA, RankEpoch, Turns, drive, merged


@dataclass(frozen=True)
class TrainConfig:
    model: ModelSpec
    sample: SampleConfig = SampleConfig()
    cache: CacheSpec = CacheSpec()
    mode: str = "push"  # push, pull, or none (no remote rows)
    epochs: int = 5
    optimizer: str = "adam"
    rate: float | None = None
    engine: str = "auto"
    seed: int = 1
    #: plan the next epoch while this one runs
    prefetch: bool = False
    #: how rows travel, and how numbers are computed
    row_dtype: str = "f4"
    dtype: str = "f4"
    #: begin every epoch with empty caches
    reset: bool = False
    #: send only rows that a later probe reads, which the plan knows
    used_only: bool = True


#: of the step engine's rows
ITERATIONS_A_FOLDER = 16
#: of a row group of them, before it is compressed
GROUP_BYTES = 1 << 20
_PLAIN = pa.schema([f for f in ROWS if f.name != "rank"])

TIMES = "epoch int, rank int, it int, part string, seconds double"


@dataclass
class TrainResult:
    params: dict[str, np.ndarray]
    log: list[dict] = field(default_factory=list)
    plans: list[EpochPlan] = field(default_factory=list)
    #: TIMES, a row for each part of each rank's iterations
    times: DataFrame | None = None


def plan_for(pg: Partitioned, labels: DataFrame, cfg: TrainConfig, epoch: int, earlier: DataFrame | None) -> EpochPlan:
    """The plan of the configured mode. Pull samples across ranks, so it has neither pushes nor hits; its blocks are complete."""
    spec = replace(cfg.cache, nc=0) if cfg.mode == "none" else cfg.cache
    if cfg.mode != "pull":
        return plan_epoch(pg, labels, cfg.sample, spec, epoch, earlier if cfg.mode == "push" else None)
    seeds = stage(sampling.minibatches(labels, pg.parts, cfg.sample.b, epoch, cfg.sample.seed, cfg.sample.fast))
    rounds = (seeds.agg(F.max("it")).first()[0] or 0) + 1
    blocks, frontier = sampling.sample(seeds, pg.placed, cfg.sample.fanouts, "global", cfg.sample.kind, cfg.sample.seed, stage, cfg.sample.fast)
    nobody = stage(exchange.timeline(frontier.where("false").select("epoch", "it", "layer", F.col("rank").alias("from_rank"), F.col("rank").alias("to_rank"), "vid"), rounds, spec.d))
    hits = frontier.where("false").select("epoch", "rank", "it", "layer", "vid", F.lit(True).alias("hit"), F.col("it").alias("version_it"))
    return EpochPlan(seeds, blocks, frontier, nobody, hits, blocks, rounds)


def sent(plan: EpochPlan, spec: CacheSpec, used_only: bool) -> DataFrame:
    """The pushes that are carried out. Those that no probe of this epoch reads are left out, unless the next epoch may read them."""
    if not used_only or spec.on_miss == "stale":
        return plan.push_plan
    late = F.col("arrive_it") >= plan.rounds - 1 - cache.longest_life(spec, plan.rounds)
    read = exchange.used_only(plan.push_plan.where(~late), plan.serve_plan, plan.rounds)
    return read.unionByName(plan.push_plan.where(late))


def epoch_rows(plan: EpochPlan, features: DataFrame, labels: DataFrame, whole: bool = False, spec: CacheSpec = CacheSpec(), used_only: bool = True, by_iteration: bool = False) -> DataFrame:
    """The plan as SCHEMA rows, keyed by rank. whole: foreign vertices are computed here as well, from fetched rows (pull).

    Features join once for each rank and vertex, not for each minibatch; by_iteration: for each minibatch, as a rank that does not keep
    them needs them."""
    none = lambda t: F.lit(None).cast(t)

    def rows(df: DataFrame, tag: str, it="it", layer="layer", a="vid", b=None, row=None) -> DataFrame:
        as_col = lambda x, t: none(t) if x is None else F.col(x).cast(t)
        return df.select(F.col("rank").cast("int").alias("rank"), F.lit(tag).alias("tag"), as_col(it, "int").alias("it"), as_col(layer, "int").alias("layer"), as_col(a, "long").alias("a"), as_col(b, "long").alias("b"), as_col(row, "array<float>").alias("row"))

    mine = plan.frontier if whole else plan.frontier.where("kind = 'solid'")
    when = ["it"] if by_iteration else []
    it = "it" if by_iteration else None
    need = mine.where("layer = 0").select("rank", *when, "vid").distinct().join(features, "vid")
    top = plan.seeds.join(labels, "vid").select("rank", "it", "vid", "label").distinct()
    pushes = sent(plan, spec, used_only).select(F.col("from_rank").alias("rank"), F.col("sent_it").alias("it"), "layer", "vid", "to_rank")
    out = rows(plan.exec_blocks, "e", a="src", b="dst").unionByName(rows(mine, "f"))
    out = out.unionByName(rows(need, "x", it=it, layer=None, row="x")).unionByName(rows(top, "y", layer=None, b="label"))
    out = out.unionByName(rows(pushes, "p", b="to_rank")).unionByName(rows(plan.serve_plan.where("hit"), "h", b="version_it"))
    if plan.filled is not None:
        out = out.unionByName(rows(plan.filled, "z"))
    if plan.fetched is not None:
        out = out.unionByName(rows(plan.fetched.join(features, "vid"), "u", layer=None, row="x"))
    return out


def _by_rank(table: pa.Table) -> dict[int, pa.Table]:
    rank = table.column("rank").to_numpy()
    return {int(r): table.take(pa.array(np.flatnonzero(rank == r))) for r in np.unique(rank)}


def _message_rows(inbox: dict, rank: int, shift: int, before: int) -> list[tuple]:
    """What later epochs may still read, on their clock."""
    return [(rank, "m", v - shift, k, int(i), None, row.astype(np.float32)) for (v, k), (ids, rows) in inbox.items() if v >= before for i, row in zip(ids, rows, strict=True)]


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    columns = zip(*rows, strict=True) if rows else [()] * len(ROWS)
    return pa.record_batch([pa.array(c, k) for c, k in zip(columns, ROWS.types, strict=True)], names=ROWS.names)


def _time_row(rank: int, it: int, m: dict[str, float]) -> tuple:
    return (rank, "t", it, None, None, None, np.array([m[f"{k}_seconds"] for k in PARTS], np.float32))


def times_of(rows: DataFrame, epoch: int) -> DataFrame:
    """TIMES from an engine's rows of tag t."""
    part = F.posexplode("row").alias("k", "s")
    t = rows.where("tag = 't'").select("rank", "it", part)
    return t.select(F.lit(epoch).alias("epoch"), "rank", "it", F.get(F.array(*map(F.lit, PARTS)), "k").alias("part"), F.col("s").cast("double").alias("seconds"))


@dataclass
class _Epoch:
    """What an engine gives back: parameters, measures by iteration, messages that later epochs may read, and times."""

    params: dict[str, np.ndarray]
    log: list[dict]
    carried: DataFrame | None
    rows: DataFrame


def _back_to(before: CacheSpec, rounds: int) -> int:
    return rounds - 1 - cache.longest_life(before, rounds)


# --- engines --------------------------------------------------------------------------------------------------------------------


def _run_local(rows: DataFrame, carried: DataFrame | None, cfg: TrainConfig, epoch: int, rounds: int, p, opt) -> _Epoch:
    spark = rows.sparkSession
    table = (rows if carried is None else rows.unionByName(carried)).toArrow()
    ranks = {r: RankEpoch(t, cfg.model, epoch, cfg.seed, cfg.dtype) for r, t in _by_rank(table).items()}
    log, flight, out = [], [], []
    for it in range(rounds):
        for m in flight:
            if m[0] == it:
                ranks[m[1]].receive(it, *m[2:])
        flight = [m for m in flight if m[0] > it]
        running, parts, seconds = {r: rank.steps(p, it) for r, rank in ranks.items()}, {}, {r: 0.0 for r in ranks}
        while running:
            swapped = []
            for r in list(running):
                began = time.perf_counter()
                try:
                    _, sends = next(running[r])
                    swapped += [(it + cfg.cache.d, to, k, ids, x.astype(cfg.row_dtype)) for to, k, ids, x in sends if to in ranks]
                except StopIteration as e:
                    parts[r] = e.value
                    del running[r]
                seconds[r] += time.perf_counter() - began
            if cfg.cache.d == 0:
                for _, to, k, ids, x in swapped:
                    ranks[to].receive(it, k, ids, x)
            else:
                flight += swapped
        grads, total = merged([parts[r] for r in ranks])
        p = opt.step(p, grads)
        out += [_time_row(r, it, m) for r, (_, m) in parts.items()]
        log.append(total | {"it": it, "slowest": max(seconds.values()), "mean": float(np.mean(list(seconds.values())))})
    left = [m for r, rank in ranks.items() for m in _message_rows(rank.inbox, r, rounds, _back_to(cfg.cache, rounds))]
    done = spark.createDataFrame(pa.Table.from_batches([_batch(out + left)]), SCHEMA)
    return _Epoch(p, log, done.where("tag = 'm'") if left else None, done)


def _run_barrier(rows: DataFrame, carried: DataFrame | None, cfg: TrainConfig, epoch: int, rounds: int, p, opt) -> _Epoch:
    """One barrier stage, a task for each rank. The driver gets parameters and measures of one task; messages for later epochs go from the
    tasks into shared storage. A rank's rows come in order of their iteration and are read when it is due; its features, which come first and in
    order of id, go to mapped files. So a task holds the messages that are alive and one iteration's plan, however long the epoch and however
    many its vertices are."""
    spark = rows.sparkSession
    # every rank has a frontier, and of the union only that branch is read; as many rows as ranks
    ranks = [r[0] for r in rows.where("tag = 'f'").select("rank").distinct().orderBy("rank").collect()]
    rows = rows if carried is None else rows.unionByName(carried)
    start = spark.sparkContext.broadcast((p, opt))
    place = F.array_position(F.array(*map(F.lit, ranks)), F.col("rank")).cast("int") - 1
    token, d = os.urandom(16), cfg.cache.d
    talk = cfg.mode == "push" and cfg.cache.nc != 0  # else nothing is ever pushed, and no messages are exchanged
    back = _back_to(cfg.cache, rounds)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        context = BarrierTaskContext.get()
        turns = Turns(batches)
        p, opt = start.value
        rank = RankEpoch(ROWS.empty_table(), cfg.model, epoch, cfg.seed, cfg.dtype)
        rank.take(turns.each(0))
        me, n = context.partitionId(), len(ranks)
        name = ranks[me]
        peers = Peers(me, [i.address.rsplit(":", 1)[0] for i in context.getTaskInfos()], context.allGather, token)
        others = [r for r in range(n) if r != me]
        number = {r: k for k, r in enumerate(ranks)}
        out, log = [], []

        def arrivals(sent_it: int, layers, m: dict[str, float]) -> None:
            for k in layers:
                for o in others:
                    began = time.perf_counter()
                    ids, x = peers.get(PUSH, sent_it, k, o)
                    came = time.perf_counter()
                    rank.receive(sent_it + d, k, ids, x)
                    m["wait_seconds"] += came - began
                    m["post_seconds"] += time.perf_counter() - came

        for it in range(rounds):
            rank.turn(turns.before(it + 1))
            extra = {"wait_seconds": 0.0, "post_seconds": 0.0}
            if talk and d and it >= d:
                arrivals(it - d, range(rank.top), extra)
            rank.forget(min(back, it - cache.longest_life(cfg.cache, rounds)))

            def on_push(k: int, sends: list) -> None:
                if not talk or it >= rounds - d:
                    return
                mine = {number[to]: (ids, x.astype(cfg.row_dtype)) for to, _, ids, x in sends if to in number}
                for o in others:
                    peers.push(o, it, k, *mine.get(o, (np.zeros(0, np.int64), np.zeros((0, cfg.model.dims[k]), cfg.row_dtype))))
                if not d:
                    arrivals(it, [k], extra)

            began = time.perf_counter()
            grads, m = drive(rank.steps(p, it), on_push)
            busy = time.perf_counter() - began - (0.0 if d else extra["wait_seconds"])
            for key, seconds in extra.items():
                m[key] += seconds
            at = time.perf_counter()
            flat = np.concatenate([pack(grads), np.array([m["loss"], busy], cfg.dtype)])
            total, counts = peers.allreduce(it, flat, np.array([m["seeds"], m["correct"], m["edges"]], np.int64))
            m["allreduce_seconds"] = time.perf_counter() - at
            m["send_seconds"] = peers.take_send_seconds()
            seeds = counts[0]
            p = opt.step(p, unpack(total[:-2] / total.dtype.type(max(1, seeds)), grads))
            out.append(_time_row(name, it, m))
            log.append({"it": it, "seeds": float(seeds), "correct": float(counts[1]), "edges": float(counts[2]), "loss": float(total[-2])})
        out += _message_rows(rank.inbox, name, rounds, back)
        if me == 0:
            out.append((name, pickle.dumps((pack(p), opt, log)).hex(), None, None, None, None, None))
        context.barrier()
        peers.close()
        yield _batch(out)

    # the exchange makes the barrier stage one that Spark can run again as a whole if a task or an executor is lost
    dealt = rows.repartitionById(len(ranks), place).sortWithinPartitions(F.asc_nulls_first("it"), "a")
    with batches_by_rows(spark, 64 + 4 * max(cfg.model.dims)):  # SCHEMA's other columns, and a row of the widest layer
        done = stage(dealt.mapInArrow(run, SCHEMA, barrier=True).repartition(len(ranks), "rank"), "barrier")
    flat, opt2, log = pickle.loads(bytes.fromhex(done.where("tag NOT IN ('m', 't')").first().tag))
    opt.__dict__.update(opt2.__dict__)
    return _Epoch(unpack(flat, p), log, done.where("tag = 'm'"), done)


def allreduce(grads: DataFrame | RDD, how: str = "tree"):
    """Sum of gradient rows (column g), or of an RDD's values, which are made and added in one job. tree: groups of rows are added on executors,
    and as many sums as a group has rows reach the driver; sql: by position, in a query."""
    if isinstance(grads, RDD):
        if how != "tree":
            raise ValueError(how)
        return grads.treeReduce(operator.add, depth=2)
    if how == "sql":
        summed = grads.select(F.posexplode("g").alias("i", "v")).groupBy("i").agg(F.sum("v").alias("v")).orderBy("i")
        return np.array([r.v for r in summed.collect()])  # one row for each parameter
    if how == "tree":
        kind = grads.schema["g"].dataType.elementType
        width = max(1, int(np.sqrt(grads.count())))

        def add(t: pa.Table) -> pa.Table:
            g = np.asarray(t.column("g").combine_chunks().flatten()).reshape(t.num_rows, -1)
            return pa.table({"g": pa.array([g.sum(0)])})

        spread = grads.select(F.pmod(F.monotonically_increasing_id() + F.spark_partition_id(), F.lit(width)).alias("k"), "g")
        return sum(np.array(r.g) for r in spread.groupBy("k").applyInArrow(add, f"g array<{kind.simpleString()}>").collect())
    raise ValueError(how)


@dataclass
class _Sent:
    """What tasks of an iteration give back: the sum of their measures and gradients, (file, receiving ranks) of the messages that they have
    written, and their rows of times."""

    g: np.ndarray
    files: list[tuple[str, list[int]]]
    times: list[tuple]

    def __add__(self, other: _Sent) -> _Sent:
        return _Sent(self.g + other.g, self.files + other.files, self.times + other.times)


#: measures that are added up with the gradients
_SUMMED = ("correct", "edges", "loss", "seeds")


def _read_rows(file: str, column: str, low: int, high: int) -> pa.Table:
    """The rows of a Parquet file with column in [low, high]; of its row groups only those are read that can have some."""
    fs, place = store(file)
    with fs.open_input_file(place) as raw, pq.ParquetFile(raw) as f:
        at = f.schema_arrow.get_field_index(column)
        stats = [f.metadata.row_group(k).column(at).statistics for k in range(f.num_row_groups)]
        some = [k for k, s in enumerate(stats) if s is None or not s.has_min_max or (s.min <= high and s.max >= low)]
        table = f.read_row_groups(some, columns=_PLAIN.names + ["rank"] * (column == "rank"))
    values = pc.and_(pc.greater_equal(table.column(column), low), pc.less_equal(table.column(column), high))
    return table.filter(values).select(_PLAIN.names).cast(_PLAIN)


def _files(folder: str) -> list[str]:
    """The Parquet files of a folder, none if there is no such folder."""
    fs, place = store(folder)
    found = fs.get_file_info(pafs.FileSelector(place, allow_not_found=True))
    return sorted(f"{folder}/{x.base_name}" for x in found if x.base_name.endswith(".parquet") and x.is_file)


def _write_rows(batches: list[pa.RecordBatch], file: str) -> str:
    """Each batch is a row group."""
    fs, place = store(file)
    fs.create_dir(place.rpartition("/")[0], recursive=True)
    with fs.open_output_stream(place) as raw, pq.ParquetWriter(raw, ROWS) as out:
        for b in batches:
            out.write_batch(b)
    return file


def _messages(to: int, arrival: int, layer: int, ids: np.ndarray, rows: np.ndarray) -> pa.RecordBatch:
    n, width = rows.shape
    same = lambda v, t: pa.array(np.full(n, v), t)
    listed = pa.ListArray.from_arrays(pa.array(np.arange(0, n * width + 1, width, dtype=np.int32)), pa.array(rows.astype(np.float32).ravel()))
    return pa.record_batch([same(to, pa.int32()), pa.array(["m"] * n), same(arrival, pa.int32()), same(layer, pa.int32()), pa.array(ids, pa.int64()), pa.nulls(n, pa.int64()), listed.cast(ROWS.field("row").type)], schema=ROWS)


def _step_of(me: int, cfg: TrainConfig, epoch: int, rounds: int, it: int, upto: int | None, p: dict[str, np.ndarray], plan: str, old: str | None, inbox: dict[int, list[str]], to: str) -> _Sent:
    """An iteration of one rank, in a task: from its plan and messages in shared storage to its gradients and its own messages there. upto: it
    ends with that layer's rows."""
    d, life = cfg.cache.d, cache.longest_life(cfg.cache, rounds)
    tables = [ROWS.empty_table().select(_PLAIN.names)]
    tables += [_read_rows(f, "it", it, it) for f in _files(f"{plan}/turn={it // ITERATIONS_A_FOLDER}/rank={me}")]
    if old is not None and it <= life:
        tables += [_read_rows(f, "it", it - life, -1) for f in _files(f"{old}/rank={me}")]
    tables += [_read_rows(f, "rank", me, me) for f in inbox.get(me, [])]
    steps = RankEpoch(pa.concat_tables(tables), cfg.model, epoch, cfg.seed, cfg.dtype).steps(p, it)
    out: dict[int, list[pa.RecordBatch]] = {}

    def on_push(k: int, sends: list) -> None:
        if it < rounds - d and (d or k == upto):
            for r, _, ids, x in sends:
                if len(ids):
                    out.setdefault(r, []).append(_messages(r, it + d, k, ids, x.astype(cfg.row_dtype)))

    if upto is None:
        grads, m = drive(steps, on_push)
        g, times = np.concatenate([[m[n] for n in _SUMMED], pack(grads)]).astype(np.float64), [_time_row(me, it, m)]
    else:
        for _ in range(upto + 1):
            on_push(*next(steps))
        g, times = np.zeros(0), []
    # a task that is run again writes a file of its own, and only that of the one whose result counts is read
    files = [(_write_rows([b for r in sorted(out) for b in out[r]], f"{to}/{me}-{TaskContext.get().taskAttemptId()}.parquet"), sorted(out))] if out else []
    return _Sent(g, files, times)


def _run_step(rows: DataFrame, carried: DataFrame | None, cfg: TrainConfig, epoch: int, rounds: int, p, opt) -> _Epoch:
    """One job for an iteration, a task for each rank, which reads its own rows and the messages to it that are alive. Without delay there is a
    job for each layer before, which computes up to that layer and sends its rows. A job is no query: nothing is planned, exchanged or
    listed by the driver for it, since an epoch has thousands. The driver is told which files have messages for whom, and times."""
    spark, d, top = rows.sparkSession, cfg.cache.d, len(cfg.model.dims) - 1
    path, made = fresh_path(spark, "steps"), fresh_path(spark, "iterations")
    # a folder holds several iterations in their order, a file of it one rank's, in row groups of which a task reads those with its iteration
    turns = rows.withColumn("turn", F.floor(F.col("it") / ITERATIONS_A_FOLDER))
    turns.repartition("turn", "rank").sortWithinPartitions("turn", "rank", "it").write.option("parquet.block.size", str(GROUP_BYTES)).partitionBy("turn", "rank").parquet(path)
    old = None
    if carried is not None:
        old = fresh_path(spark, "carried")
        carried.where("rank IS NOT NULL").repartition("rank").write.partitionBy("rank").parquet(old)
    # every rank has a frontier, and of the union only that branch is read; as many rows as ranks
    ranks = [r[0] for r in rows.where("tag = 'f'").select("rank").distinct().orderBy("rank").collect()]
    tasks = spark.sparkContext.parallelize(ranks, len(ranks))
    inbox: dict[int, list[tuple[str, list[int]]]] = {}
    log, times, like = [], [], {k: np.zeros(s) for k, s in cfg.model.shapes().items()}
    life = cache.longest_life(cfg.cache, rounds)
    for it in range(rounds):
        inbox.pop(it - life - 1, None)
        for upto in ([*range(top), None] if d == 0 else [None]):
            alive: dict[int, list[str]] = {}
            for v in range(max(0, it - life), it + 1):
                for file, receivers in inbox.get(v, []):
                    for r in receivers:
                        alive.setdefault(r, []).append(file)
            step = partial(_step_of, cfg=cfg, epoch=epoch, rounds=rounds, it=it, upto=upto, p=p, plan=path, old=old, inbox=alive, to=f"{made}/{it}-{upto}")
            done = allreduce(tasks.map(step))
            if done.files:
                inbox.setdefault(it + d, []).extend(done.files)
        m = dict(zip(_SUMMED, done.g[: len(_SUMMED)].tolist(), strict=True))
        n = np.dtype(cfg.dtype).type(max(1.0, m["seeds"]))
        p = opt.step(p, {k: (v.astype(cfg.dtype) / n) for k, v in unpack(done.g[len(_SUMMED) :], like).items()})
        log.append(m | {"it": it})
        times += done.times
        if (it + 1) % ITERATIONS_A_FOLDER == 0 or it + 1 == rounds:  # so no more are held than a folder's ranks have iterations
            _write_rows([_batch(times)], f"{made}/times/{it}.parquet")
            times = []
    later = sorted({file for v, files in inbox.items() if v >= _back_to(cfg.cache, rounds) for file, _ in files})
    left = None
    if later:
        left = stage(spark.read.schema(SCHEMA).parquet(*later).withColumn("it", (F.col("it") - rounds).cast("int")), "carried")
    return _Epoch(p, log, left, spark.read.schema(SCHEMA).parquet(f"{made}/times"))


ENGINES = {"local": _run_local, "barrier": _run_barrier, "step": _run_step}


def engine_for(spark: SparkSession, cfg: TrainConfig, P: int):
    name = cfg.engine if cfg.engine != "auto" else "barrier" if spark.sparkContext.defaultParallelism >= P else "step"
    return name, ENGINES[name]


def train(pg: Partitioned, features: DataFrame, labels: DataFrame, cfg: TrainConfig, params: dict[str, np.ndarray] | None = None, evaluate=None) -> TrainResult:
    """labels: (vid, label) of the training vertices. evaluate(params) gives the accuracy that is logged for each epoch.

    Parameters may come from a saved run; the plan of an epoch depends only on its number, so training resumes where it stopped."""
    spark = pg.placed.sparkSession
    ship_package(spark)
    name, engine = engine_for(spark, cfg, pg.P)
    p = {k: v.astype(cfg.dtype) for k, v in (params or cfg.model.init(cfg.seed)).items()}
    rate = cfg.rate if cfg.rate is not None else rate_for(cfg.model.kind, pg.P)
    opt = Adam(rate) if cfg.optimizer == "adam" else Sgd(rate)
    result, earlier, carried = TrainResult(p), None, None
    ahead = None
    for epoch in range(cfg.epochs):
        began = time.perf_counter()
        plan = ahead.result() if ahead is not None else plan_for(pg, labels, cfg, epoch, earlier)
        planned = time.perf_counter()
        release(spark)
        earlier = None if cfg.reset else plan.push_plan
        ahead = _ahead(pg, labels, cfg, epoch + 1, earlier) if cfg.prefetch and epoch + 1 < cfg.epochs else None
        rows = epoch_rows(plan, features, labels, cfg.mode == "pull", cfg.cache, cfg.used_only, by_iteration=name == "step")
        done = engine(rows, carried, cfg, epoch, plan.rounds, p, opt)
        p, carried = done.params, None if cfg.reset else done.carried
        ended = time.perf_counter()
        release(spark)
        times = times_of(done.rows, epoch)
        result.times = times if result.times is None else result.times.unionByName(times)
        seeds = max(1.0, sum(m["seeds"] for m in done.log))
        row = {"epoch": epoch, "loss": sum(m["loss"] for m in done.log) / seeds, "train_accuracy": sum(m["correct"] for m in done.log) / seeds, "rounds": plan.rounds, "edges": sum(m["edges"] for m in done.log), "plan_seconds": planned - began, "run_seconds": ended - planned, "engine": name}
        if evaluate is not None:
            row["accuracy"] = evaluate(p)
        result.log.append(row)
        result.plans.append(plan)
    result.params = p
    return result


def _ahead(pg, labels, cfg, epoch, earlier):
    """The next epoch's plan in another thread: asynchronous sampling."""
    from concurrent.futures import Future

    from pyspark import InheritableThread

    out: Future = Future()

    def run() -> None:
        try:
            out.set_result(plan_for(pg, labels, cfg, epoch, earlier))
        except BaseException as e:  # noqa: BLE001 - handed to whoever waits
            out.set_exception(e)

    InheritableThread(target=run).start()
    return out
