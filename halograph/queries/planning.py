"""Graphs, partitions, samples, pushes, caches and their measures."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import measures
from ..operators import cache, exchange, graph, partition, sampling
from ..operators.cache import CacheSpec
from ..plans.epoch import sweep
from .registry import ORACLES, add
from .sql import ABOUT, CS, D, FANOUTS, LS, NC, P, TOP, VIEWS, capped, draw, held, hits, md5, pushed, race, sql
from .workload import ORACLE, TIGHT, workload

# --- graphs ------------------------------------------------------------------------------------------------------------------

add("symmetric_edges", lambda w: graph.purchase(w.spark, w.sf_dir), sql("SELECT * FROM v_edges"))
add("degrees", lambda w: graph.degrees(w.edges), sql("SELECT * FROM v_deg"))
add(
    "degree_hist",
    lambda w: graph.degrees(w.edges).groupBy("deg").agg(F.count("*").alias("n"), F.max_by("vid", "vid").alias("last_vid")),
    sql("SELECT deg, count(*) AS n, max(vid) AS last_vid FROM v_deg GROUP BY deg"),
)
add(
    "supply_edges", lambda w: graph.supply(w.spark, w.sf_dir),
    """WITH p AS (SELECT l_partkey AS a, l_suppkey + (SELECT count(*) FROM part) AS b, count(*) AS w FROM lineitem GROUP BY 1, 2)
    SELECT src, dst, CAST(sum(w) AS BIGINT) AS w FROM (SELECT a AS src, b AS dst, w FROM p UNION ALL SELECT b, a, w FROM p) WHERE src <> dst GROUP BY src, dst""",
)
add(
    "trade_edges", lambda w: graph.trade(w.spark, w.sf_dir),
    sql("""SELECT least(src, dst) + flip * abs(src - dst) AS src, greatest(src, dst) - flip * abs(src - dst) AS dst, CAST(sum(w) AS BIGINT) AS w FROM (SELECT a AS src, b AS dst, w FROM (
        SELECT a, b, w FROM v_pairs
        UNION ALL SELECT l_partkey + (SELECT count(*) FROM customer), l_suppkey + (SELECT count(*) FROM customer) + (SELECT count(*) FROM part), count(*) FROM lineitem GROUP BY 1, 2
        UNION ALL SELECT c_custkey, c_nationkey + (SELECT count(*) FROM customer) + (SELECT count(*) FROM part) + (SELECT count(*) FROM supplier), 1 FROM customer
        UNION ALL SELECT s_suppkey + (SELECT count(*) FROM customer) + (SELECT count(*) FROM part), s_nationkey + (SELECT count(*) FROM customer) + (SELECT count(*) FROM part) + (SELECT count(*) FROM supplier), 1 FROM supplier)
    ) CROSS JOIN (VALUES (0), (1)) AS f(flip) WHERE src <> dst GROUP BY 1, 2"""),
)
add(
    "dataset_summary",
    lambda w: w.edges.agg(F.count("*").alias("edges"), F.count_distinct("src").alias("connected")).join(
        graph.with_split(w.vertices, w.train_share).agg(F.count("*").alias("vertices"), F.count_if("is_train").alias("train"), F.count_if(~F.col("is_train")).alias("test"), F.count_distinct("label").alias("classes"))
    ),
    sql("""SELECT (SELECT count(*) FROM v_edges) AS edges, (SELECT count(DISTINCT src) FROM v_edges) AS connected, (SELECT count(*) FROM v_verts) AS vertices,
      (SELECT count(*) FROM v_train) AS train, (SELECT count(*) FROM v_verts) - (SELECT count(*) FROM v_train) AS test,
      (SELECT count(DISTINCT x) FROM (SELECT c_mktsegment AS x FROM customer UNION SELECT p_type FROM part)) AS classes"""),
)
add(
    "document_edges", lambda w: graph.documents(w.spark, w.sf_dir),
    r"""WITH t AS (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(coalesce(text, '')), '[^ \t\n\r\f\v.,;:!?]{5,}')) AS token FROM documents),
      r AS (SELECT doc_id, token FROM t WHERE token IN (SELECT token FROM t GROUP BY token HAVING count(*) BETWEEN 2 AND 8))
      SELECT a.doc_id AS src, b.doc_id AS dst, count(*) AS w FROM r a JOIN r b ON a.token = b.token AND a.doc_id <> b.doc_id GROUP BY ALL""",
)
add("train_vertices", lambda w: w.train, sql("SELECT vid FROM v_train"))
add(
    "page_degrees", lambda w: graph.same_host_degrees(w.spark, w.sf_dir),
    """WITH h AS (SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host FROM pages)
    SELECT a.page_id AS vid, count(*) AS deg FROM h a JOIN h b ON a.host = b.host AND a.page_id <> b.page_id GROUP BY a.page_id""",
)
for _name, _of, _sql in (("supply", graph.supply, "supply_edges"), ("trade", graph.trade, "trade_edges"), ("documents", graph.documents, "document_edges")):
    add(
        f"dataset_summary_{_name}", lambda w, of=_of: of(w.spark, w.sf_dir).agg(F.count("*").alias("edges"), F.count_distinct("src").alias("connected"), F.max("w").alias("heaviest")),
        f"SELECT count(*) AS edges, count(DISTINCT src) AS connected, max(w) AS heaviest FROM ({ORACLES[_sql]})",
    )

# --- partitions ----------------------------------------------------------------------------------------------------------------

add("partition_hash", lambda w: w.parts, sql("SELECT * FROM v_parts"))
add(
    "partition_range", lambda w: partition.by_range(w.vertices, P),
    sql(f"SELECT vid, CAST(floor((vid - (SELECT min(vid) FROM v_verts)) * {P} / (SELECT max(vid) - min(vid) + 1 FROM v_verts)) AS INTEGER) AS part FROM v_verts"),
)
add("cut_edges", lambda w: partition.cut_edges(w.pg.placed).select("src", "dst", "p_src", "p_dst"), sql("SELECT src, dst, p_src, p_dst FROM v_placed WHERE p_src <> p_dst"))
add("halo_vertices", lambda w: w.pg.halos, sql("SELECT * FROM v_halo"))
CATALOG = f"""SELECT part, CAST(row_number() OVER (PARTITION BY part ORDER BY kind DESC, vid) - 1 AS INTEGER) AS pid, vid, kind, coalesce(g.deg, 0) AS deg
  FROM (SELECT part, vid, 'solid' AS kind FROM v_parts UNION ALL SELECT part, vid, 'halo' FROM v_halo) LEFT JOIN v_deg g USING (vid)"""  # fmt: skip
add("vertex_catalog", lambda w: partition.catalog(w.parts, w.pg.halos, w.pg.placed), sql(CATALOG))
add("partition_ids", lambda w: partition.catalog(w.parts, w.pg.halos, w.pg.placed).groupBy("part", "kind").agg(F.min("pid").alias("first"), F.max("pid").alias("last"), F.count("*").alias("n")), sql(f"SELECT part, kind, min(pid) AS first, max(pid) AS last, count(*) AS n FROM ({CATALOG}) GROUP BY part, kind"))
add("halo_directory", lambda w: w.pg.directory, sql(f"SELECT CAST(vid % {P} AS INTEGER) AS owner, vid, part AS remote FROM v_halo"))
add(
    "partition_quality", lambda w: partition.quality(w.pg.placed, w.train, w.parts),
    sql("""WITH q AS (SELECT part, count(*) AS vertices, count(t.vid) AS train FROM v_parts LEFT JOIN v_train t USING (vid) GROUP BY part),
      e AS (SELECT p_dst AS part, count(*) AS edges, count(*) FILTER (p_src <> p_dst) AS cut FROM v_placed GROUP BY 1), h AS (SELECT part, count(*) AS halos FROM v_halo GROUP BY 1)
      SELECT part, CAST(sum(vertices) AS BIGINT) AS vertices, CAST(sum(train) AS BIGINT) AS train, CAST(sum(edges) AS BIGINT) AS edges, CAST(sum(cut) AS BIGINT) AS cut, CAST(sum(halos) AS BIGINT) AS halos
      FROM q JOIN e USING (part) JOIN h USING (part) GROUP BY GROUPING SETS ((part), ())""".replace("WITH q AS", "SELECT * FROM (WITH q AS") + ")"),
)
add(
    "train_balance", lambda w: w.train.join(w.parts, "vid").groupBy("part").agg(F.count("*").alias("train")).agg(F.min("train").alias("least"), F.max("train").alias("most"), (F.max("train") / F.avg("train")).alias("imbalance")),
    sql(f"SELECT min(n) AS least, max(n) AS most, max(n) / avg(n) AS imbalance FROM (SELECT count(*) AS n FROM v_train GROUP BY vid % {P})"),
)
add(
    "vertex_cut_replicas", lambda w: partition.vertex_cut(w.edges, P).groupBy("part").agg(F.count("*").alias("copies"), F.sum("vid").alias("vid_sum")),
    sql(f"""SELECT part, count(*) AS copies, CAST(sum(vid) AS BIGINT) AS vid_sum FROM (SELECT DISTINCT unnest([src, dst]) AS vid, part FROM (
      SELECT src, dst, CAST((CASE WHEN a.deg <= b.deg THEN src ELSE dst END) % {P} AS INTEGER) AS part FROM v_edges JOIN v_deg a ON a.vid = src JOIN v_deg b ON b.vid = dst WHERE src < dst)) GROUP BY part"""),
)
add(
    "labelprop_round", lambda w: partition.labelprop_round(w.edges, w.parts, 1000),
    sql(f"""SELECT v.vid, coalesce(m.target, v.part) AS part FROM v_parts v LEFT JOIN (
      SELECT vid, target FROM (SELECT z.vid, z.target, row_number() OVER (PARTITION BY z.target ORDER BY z.gain DESC, {md5(1, 0, 'z.vid')}) AS n FROM (
        SELECT y.vid, y.part AS target, y.pull - coalesce(o.pull, 0) AS gain FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY pull DESC, part) AS r FROM (SELECT dst AS vid, p_src AS part, sum(w) AS pull FROM v_placed GROUP BY 1, 2)) y
        LEFT JOIN (SELECT dst AS vid, sum(w) AS pull FROM v_placed WHERE p_src = p_dst GROUP BY 1) o USING (vid) WHERE r = 1 AND y.part <> y.vid % {P} AND y.vid % 2 = 0) z WHERE z.gain > 0) q
      WHERE n <= greatest(0, 1000 - (SELECT count(*) FROM v_parts c WHERE c.part = q.target))) m USING (vid)"""),
)

# --- samples ---------------------------------------------------------------------------------------------------------------------

add("minibatches", lambda w: w.plan.seeds, sql("SELECT * FROM v_seeds"))
add("sample_hop1", lambda w: w.plan.blocks.where(F.col("layer") == TOP - 1), sql(f"SELECT * FROM lo_b{TOP - 1}"))
add("sample_blocks", lambda w: w.plan.blocks, sql("SELECT * FROM lo_blocks"))
add("sample_local", lambda w: w.plan.frontier, sql("SELECT * FROM lo_frontier"))
add("sample_global", lambda w: w.global_sample[1], sql("SELECT * FROM gl_frontier"))


def _hop(order: str) -> str:
    return (
        f"SELECT epoch, rank, it, {TOP - 1} AS layer, src, dst, w, p_src FROM (SELECT f.epoch, f.rank, f.it, p.*, row_number() OVER (PARTITION BY f.rank, f.it, p.dst ORDER BY {order}, p.src) AS n"
        f" FROM v_seeds f JOIN v_placed p ON p.dst = f.vid) WHERE n <= {FANOUTS[0]}"
    )


HOP_ABOUT = (1, "'hop'", "f.epoch", "f.it", TOP - 1, "p.src", "p.dst")
for _kind, _weight in (("weighted", "p.w"), ("importance", "p.deg_src")):
    add(f"sample_{_kind}", lambda w, kind=_kind: sampling.hop(w.plan.seeds, w.pg.placed, FANOUTS[0], TOP - 1, kind), sql(_hop(race(_weight, *HOP_ABOUT))))
add(
    "sample_replace", lambda w: sampling.hop(w.plan.seeds, w.pg.placed, FANOUTS[0], TOP - 1, replace=True),
    sql(f"""SELECT q.epoch, q.rank, q.it, {TOP - 1} AS layer, a.src, a.dst, a.w, a.p_src, CAST(q.j AS INTEGER) AS j FROM (
      SELECT f.*, k.j, CAST(floor({draw(1, "'draw'", 'f.epoch', 'f.it', TOP - 1, 'f.vid', 'k.j')} * g.deg / 4294967296::DOUBLE) AS BIGINT) AS pos
      FROM v_seeds f JOIN v_deg g ON g.vid = f.vid, (SELECT unnest(range(0, {FANOUTS[0]})) AS j) k) q
      JOIN (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY src) - 1 AS pos FROM v_placed) a ON a.dst = q.vid AND a.pos = q.pos"""),
)
add(
    "block_ids", lambda w: sampling.batch_ids(w.plan.frontier, w.plan.blocks).select("epoch", "rank", "it", "layer", "vid", "bid"),
    sql("""SELECT f.epoch, f.rank, f.it, f.layer, f.vid, CAST(row_number() OVER (PARTITION BY f.epoch, f.rank, f.it, f.layer ORDER BY b.vid IS NULL, f.vid) - 1 AS INTEGER) AS bid
      FROM lo_frontier f LEFT JOIN (SELECT DISTINCT epoch, rank, it, layer, dst AS vid FROM lo_blocks) b ON b.epoch = f.epoch AND b.rank = f.rank AND b.it = f.it AND b.layer = f.layer AND b.vid = f.vid"""),
)
add("mb_solid_halo", lambda w: w.plan.frontier.groupBy("rank", "it", "layer").agg(F.count_if(F.col("kind") == "solid").alias("solids"), F.count_if(F.col("kind") == "halo").alias("halos")), sql(f"SELECT rank, it, layer, count(*) FILTER (vid % {P} = rank) AS solids, count(*) FILTER (vid % {P} <> rank) AS halos FROM lo_frontier GROUP BY rank, it, layer"))
add(
    "load_features", lambda w: sampling.load_rows(w.plan.frontier, w.features).select("epoch", "rank", "it", "vid", *[F.get("x", F.lit(k)).alias(f"x{k}") for k in range(4)]),
    sql("SELECT f.epoch, f.rank, f.it, x.* FROM lo_f0 f JOIN v_x x USING (vid) WHERE f.part = f.rank"),
)
add("iteration_spine", lambda w: exchange.iteration_spine(w.plan.seeds), sql(f"SELECT CAST(r.r AS INTEGER) AS rank, CAST(k.k AS INTEGER) AS it, count(s.vid) AS seeds FROM (SELECT unnest(range(0, {P})) AS r) r, (SELECT unnest(range(0, (SELECT m FROM v_rounds))) AS k) k LEFT JOIN v_seeds s ON s.rank = r.r AND s.it = k.k GROUP BY r.r, k.k"))
add("small_graph_batches", lambda w: _small_batches(w), f"""SELECT graph_id, CAST(floor((row_number() OVER (ORDER BY {md5(1, "'graph'", 'graph_id')}, graph_id) - 1) / 8) AS INTEGER) AS batch, turns FROM (SELECT conv_id AS graph_id, count(*) AS turns FROM conversations GROUP BY conv_id)""")


def _small_batches(w):
    from ..plans.small import graph_batches

    t = w.spark.read.parquet(f"{w.sf_dir}/conversations.parquet").groupBy(F.col("conv_id").alias("graph_id")).agg(F.count("*").alias("turns"))
    return graph_batches(t, 8)


# --- pushes ------------------------------------------------------------------------------------------------------------------------

add("push_eligible", lambda w: w.eligible, sql("SELECT * FROM v_eligible"))
add("push_capped", lambda w: exchange.capped(w.eligible, w.pg.degrees, NC), sql("SELECT * FROM v_capped"))
add("push_capped_uniform", lambda w: exchange.capped(w.eligible, w.pg.degrees, NC, by="uniform"), sql(capped("v_eligible", md5(*ABOUT))))
add("push_capped_top", lambda w: exchange.capped(w.eligible, w.pg.degrees, 16, by="top_degree"), sql(capped("v_eligible", "g.deg DESC", 16)))
add("push_capped_total", lambda w: exchange.capped(w.eligible, w.pg.degrees, NC, mode="total"), sql(capped("v_eligible", race("g.deg", *ABOUT), NC, "epoch, it, layer, from_rank")))
add("push_timeline", lambda w: w.plan.push_plan, sql("SELECT * FROM v_push"))
add("push_used_only", lambda w: exchange.used_only(w.plan.push_plan, w.plan.hit_plan, w.plan.rounds), sql("SELECT * FROM v_push p WHERE EXISTS (SELECT 1 FROM v_hits h WHERE h.hit AND h.rank = p.to_rank AND h.layer = p.layer AND h.vid = p.vid AND h.version_it = p.arrive_it)"))
add(
    "push_layer0_rows", lambda w: w.plan.push_plan.where("layer = 0").join(w.features, "vid").groupBy("from_rank", "to_rank").agg(F.count("*").alias("rows"), *[F.sum(F.get("x", F.lit(k))).alias(f"s{k}") for k in range(4)]),
    sql("SELECT from_rank, to_rank, count(*) AS rows, " + ", ".join(f"sum(x{k}) AS s{k}" for k in range(4)) + " FROM v_push JOIN v_x USING (vid) WHERE layer = 0 GROUP BY from_rank, to_rank"),
)
add("push_volume", lambda w: exchange.volume(w.plan.push_plan, 128, "sent_it", "layer", "from_rank", "to_rank"), sql("SELECT sent_it, layer, from_rank, to_rank, count(*) AS rows, count(*) * 512 AS bytes FROM v_push GROUP BY ALL"))
add("pull_remote_rows", lambda w: exchange.pulled(w.global_sample[1]), sql("SELECT epoch, rank, it, vid, part AS owner FROM gl_f0 WHERE part <> rank"))
add("pull_volume", lambda w: exchange.volume(exchange.pulled(w.global_sample[1]), 128, "rank", "owner"), sql("SELECT rank, part AS owner, count(*) AS rows, count(*) * 512 AS bytes FROM gl_f0 WHERE part <> rank GROUP BY rank, part"))
add("naive_volume", lambda w: measures.naive_volume(w.plan.frontier, 128), sql("SELECT layer, count(*) AS rows, count(*) * 512 AS bytes FROM v_demand GROUP BY layer"))

# --- caches ----------------------------------------------------------------------------------------------------------------------

add("residency_asof", lambda w: w.hits(replace(ORACLE, cs=None)), sql(hits(cs=10**9)))
add("residency_capped", lambda w: w.hits(replace(ORACLE, cs=40)), sql(hits(cs=40)))
TIGHT_ORDER = race("g.deg", *ABOUT)
VIEWS["v_tight"] = capped("v_eligible", TIGHT_ORDER, 16)
VIEWS["v_tight_push"] = pushed("v_tight", 2)
add("residency_tight", lambda w: w.hits(TIGHT), sql(hits("v_tight_push", 50, 3, 2)))
for _d in (0, 2, 3):
    VIEWS[f"v_push_d{_d}"] = pushed("v_capped", _d)
_delays = " UNION ALL ".join(f"SELECT CAST({d} AS INTEGER) AS value, layer, count(*) AS probes, count(*) FILTER (hit) AS hits FROM ({hits('v_push' if d == 1 else f'v_push_d{d}', CS, LS, d)}) GROUP BY layer" for d in (0, 1, 2, 3))
add("residency_delay_sweep", lambda w: sweep(w.plan, w.pg, ORACLE, d=[0, 1, 2, 3]), sql(_delays))
add("residency_life_sweep", lambda w: sweep(w.plan, w.pg, ORACLE, ls=[0, 1, 4]), sql(" UNION ALL ".join(f"SELECT CAST({x} AS INTEGER) AS value, layer, count(*) AS probes, count(*) FILTER (hit) AS hits FROM ({hits(ls=x)}) GROUP BY layer" for x in (0, 1, 4))))
add("residency_size_sweep", lambda w: sweep(w.plan, w.pg, ORACLE, cs=[10, 50, 200]), sql(" UNION ALL ".join(f"SELECT CAST({x} AS INTEGER) AS value, layer, count(*) AS probes, count(*) FILTER (hit) AS hits FROM ({hits(cs=x)}) GROUP BY layer" for x in (10, 50, 200))))
_limits = (0, 8, 32)
for _n in _limits:
    VIEWS[f"v_lim{_n}"] = capped("v_eligible", TIGHT_ORDER, _n)
    VIEWS[f"v_lim{_n}_push"] = pushed(f"v_lim{_n}")
add("residency_limit_sweep", lambda w: sweep(w.plan, w.pg, ORACLE, nc=list(_limits)), sql(" UNION ALL ".join(f"SELECT CAST({x} AS INTEGER) AS value, layer, count(*) AS probes, count(*) FILTER (hit) AS hits FROM ({hits(f'v_lim{x}_push')}) GROUP BY layer" for x in _limits)))
VIEWS["v_clock"] = "SELECT to_rank, layer, vid, arrive_it FROM v_push UNION ALL SELECT to_rank, layer, vid, arrive_it + (SELECT m FROM v_rounds) FROM nx_push"
VIEWS["nx_clock"] = "SELECT epoch, rank, it + (SELECT m FROM v_rounds) AS it, layer, vid FROM nx_demand"
_two = hits("v_clock", CS, LS, 0, "nx_clock").replace("unnest(range(0, (SELECT m FROM v_rounds)))", "unnest(range(0, 2 * (SELECT m FROM v_rounds)))")
add("residency_two_epochs", lambda w: w.next_plan.hit_plan, sql(f"SELECT epoch, rank, CAST(it - m AS INTEGER) AS it, layer, vid, hit AND it - m >= {D} AS hit, CASE WHEN hit AND it - m >= {D} THEN CAST(version_it - m AS INTEGER) END AS version_it FROM ({_two}), v_rounds"))
add("warmup_misses", lambda w: w.plan.hit_plan.where(F.col("it") < D).groupBy("layer").agg(F.count("*").alias("probes"), F.count_if("hit").alias("hits")), sql(f"SELECT layer, count(*) AS probes, CAST(0 AS BIGINT) AS hits FROM v_demand WHERE it < {D} GROUP BY layer"))
add("prune_misses", lambda w: w.plan.exec_blocks, sql("SELECT * FROM v_exec"))
NOW = 3
LINES = f"SELECT to_rank AS rank, layer, vid, max(arrive_it) AS written FROM v_push WHERE arrive_it <= {NOW} GROUP BY ALL"


def _lines(w, until=NOW):
    p = w.plan.push_plan.where(F.col("arrive_it") <= until)
    return p.groupBy(F.col("to_rank").alias("rank"), "layer", "vid").agg(F.max("arrive_it").alias("written"))


def _step(w):
    """Iteration after iteration, each on the lines before it."""
    spec, lines = CacheSpec(cs=60, ls=2), _lines(w, -1)
    for now in range(NOW + 1):
        coming = w.plan.push_plan.where(F.col("arrive_it") == now).select(F.col("to_rank").alias("rank"), "layer", "vid")
        lines = cache.admit(lines, coming, now, spec)
    return lines


add("cache_admit_step", _step, sql(f"SELECT h.rank, h.layer, h.vid, l.written FROM ({held(cs=60)}) h JOIN ({LINES}) l USING (rank, layer, vid) WHERE h.now = {NOW}"))
add("cache_expire", lambda w: cache.expire(_lines(w), NOW, CacheSpec(ls=1)), sql(f"SELECT * FROM ({LINES}) WHERE written >= {NOW - 1}"))
add("cache_evict_oldest", lambda w: cache.kept(_lines(w).withColumn("now", F.lit(NOW)), 50).drop("now"), sql(f"SELECT rank, layer, vid, written FROM (SELECT *, row_number() OVER (PARTITION BY rank, layer ORDER BY written DESC, vid) AS n FROM ({LINES})) WHERE n <= 50"))
_asked = lambda w: w.plan.frontier.where((F.col("kind") == "halo") & (F.col("it") == NOW)).select("rank", "layer", "vid")
ASKED = f"SELECT rank, layer, vid FROM v_demand WHERE it = {NOW}"
add("cache_probe", lambda w: cache.probe(_lines(w), _asked(w)), sql(f"SELECT a.rank, a.layer, a.vid, l.vid IS NOT NULL AS hit FROM ({ASKED}) a LEFT JOIN ({LINES}) l ON l.rank = a.rank AND l.layer = a.layer AND l.vid = a.vid"))
add(
    "cache_fetch", lambda w: cache.fetch(_lines(w).where("layer = 0").join(w.features.withColumnRenamed("x", "row"), "vid"), cache.probe(_lines(w), _asked(w))).select("rank", "layer", "vid", *[F.get("row", F.lit(k)).alias(f"x{k}") for k in range(4)]),
    sql(f"SELECT a.rank, a.layer, x.* FROM ({ASKED}) a JOIN ({LINES}) l ON l.rank = a.rank AND l.layer = a.layer AND l.vid = a.vid JOIN v_x x ON x.vid = a.vid WHERE a.layer = 0"),
)

# --- measures --------------------------------------------------------------------------------------------------------------------

add("hit_rate", lambda w: measures.hit_rate(w.plan.hit_plan), sql("SELECT layer, count(*) AS probes, count(*) FILTER (hit) AS hits, count(*) FILTER (hit) / count(*) AS hit_rate FROM v_hits GROUP BY layer"))
add("hit_rollup", lambda w: measures.hit_rollup(w.plan.hit_plan), sql("SELECT rank, layer, count(*) AS probes, count(*) FILTER (hit) AS hits FROM v_hits GROUP BY ROLLUP (rank, layer)"))
add("staleness_hist", lambda w: measures.staleness(w.plan.hit_plan), sql("SELECT layer, it - version_it AS age, count(*) AS rows FROM v_hits WHERE hit GROUP BY ALL"))
add("frontier_sizes", lambda w: measures.frontier_sizes(w.plan.frontier), sql("SELECT layer, kind, count(*) AS rows FROM lo_frontier GROUP BY layer, kind"))
add("minibatch_counts", lambda w: measures.minibatch_counts(w.plan.seeds), sql("SELECT min(n) AS least, max(n) AS most, CAST(sum(n) AS BIGINT) AS total FROM (SELECT max(it) + 1 AS n FROM v_seeds GROUP BY rank)"))
add("load_imbalance", lambda w: measures.load_imbalance(w.plan.exec_blocks.groupBy("rank").agg(F.count("*").alias("rows"))), sql("SELECT max(n) AS most, avg(n) AS mean, (max(n) - avg(n)) / avg(n) AS imbalance FROM (SELECT count(*) AS n FROM v_exec GROUP BY rank)"))
_volume = lambda src, run: f"SELECT '{run}' AS run, layer, count(*) AS edges, count(DISTINCT (rank, it, dst)) AS rows FROM {src} GROUP BY layer"
add(
    "compute_volume", lambda w: measures.compute_volume(w.plan.exec_blocks).withColumn("run", F.lit("push")).unionByName(measures.compute_volume(w.global_sample[0]).withColumn("run", F.lit("pull"))),
    sql(_volume("v_exec", "push") + " UNION ALL " + _volume("gl_blocks", "pull")),
)
add("steps_per_rank", lambda w: _steps(w), sql(" UNION ALL ".join(f"SELECT CAST({p} AS INTEGER) AS ranks, CAST(max(n) AS BIGINT) AS rounds FROM (SELECT ceil(count(*) / 64) AS n FROM v_train GROUP BY vid % {p})" for p in (2, 4, 8, 16))))
add("global_batch_size", lambda w: _steps(w, True), sql(" UNION ALL ".join(f"SELECT CAST({p} AS INTEGER) AS ranks, CAST({p} * 64 AS BIGINT) AS batch, CAST(floor((SELECT count(*) FROM v_train) / ({p} * 64)) AS BIGINT) AS full_steps" for p in (2, 4, 8, 16))))


def _steps(w, whole: bool = False):
    ranks = w.spark.range(1).select(F.explode(F.array(*map(F.lit, (2, 4, 8, 16)))).alias("ranks"))
    if whole:
        n = w.train.agg(F.count("*").alias("n"))
        return ranks.join(n).select("ranks", (F.col("ranks") * 64).cast("long").alias("batch"), F.floor(F.col("n") / (F.col("ranks") * 64)).cast("long").alias("full_steps"))
    per = w.train.join(ranks).groupBy("ranks", F.pmod("vid", "ranks").alias("rank")).agg(F.ceil(F.count("*") / 64).alias("n"))
    return per.groupBy("ranks").agg(F.max("n").cast("long").alias("rounds"))


add("iter_gaps", lambda w: _gaps(w), sql("SELECT layer, gap, count(*) AS n FROM (SELECT layer, it - lag(it) OVER (PARTITION BY rank, layer, vid ORDER BY it) AS gap FROM v_demand) WHERE gap IS NOT NULL GROUP BY layer, gap"))


def _gaps(w):
    before = F.lag("it").over(Window.partitionBy("rank", "layer", "vid").orderBy("it"))
    return cache.demand(w.plan.frontier).withColumn("gap", F.col("it") - before).where("gap IS NOT NULL").groupBy("layer", "gap").agg(F.count("*").alias("n"))


def flagship(spark, sf_dir):
    """One epoch's plan on the purchase graph between two ranks: probes, hits and hit rate per layer."""
    from ..plans.epoch import SampleConfig
    from .workload import Workload

    w = Workload(spark, sf_dir, P=2, sample=SampleConfig((3, 3), 16), spec=CacheSpec(cs=200, ls=2, nc=32, d=1))
    return measures.hit_rate(w.plan.hit_plan)
