"""Surrounding operators that users of the methods need: sources, joins, windows, sets, strings, vectors, functions and streams."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import sqlapi
from ..functions.draws import draw as draw_column
from ..functions.vectors import cosine, millionths
from ..operators import cache, graph, partition
from ..operators.cache import CacheSpec
from ..session import bucketed, fresh_path, stage
from ..sources.tables import register_sources, table, through, write_by_part
from ..streaming import cache as stream_cache
from ..streaming import edges as stream
from .numeric import W, cols, flat, m6
from .registry import add
from .sql import P, draw, md5, sql
from .workload import ORACLE, TIGHT

# --- sources and sinks -----------------------------------------------------------------------------------------------------------

_lines = lambda w: table(w.spark, w.sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_returnflag").where("l_quantity > 45 AND l_returnflag IN ('A', 'R')")
_lines_sql = "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_returnflag FROM lineitem WHERE l_quantity > 45 AND l_returnflag IN ('A', 'R')"
add("scan_parquet", _lines, _lines_sql)
for _fmt in ("csv", "json", "orc"):
    add(f"scan_{_fmt}", lambda w, f=_fmt: through(_lines(w), f), _lines_sql)


def _bucketed(w):
    t = bucketed(w.edges.select("src", "dst", "w"), "dst", 8)
    return t.groupBy("dst").agg(F.count("*").alias("deg")).select(F.col("dst").alias("vid"), "deg")


def _by_part(w):
    path = fresh_path(w.spark, "parts")
    write_by_part(w.pg.placed.select("src", "dst", "w", F.col("p_dst").alias("part")), path)
    return w.spark.read.parquet(path).where("part = 1").select("src", "dst", "w", F.col("part").cast("int").alias("part"))


def _ring(w):
    """The customers on a ring: the source makes as many vertices as there are customers, and the table gives the sources' segments."""
    register_sources(w.spark)
    c = table(w.spark, w.sf_dir, "customer").select(F.col("c_custkey").alias("src"), F.col("c_mktsegment").alias("segment"))
    ring = w.spark.read.format("ring_graph").option("vertices", c.count()).option("reach", 3).option("parts", 4).load()
    return ring.join(c, "src").select("src", "dst", "segment")


add("source_ring_graph", _ring, "SELECT c_custkey AS src, (c_custkey + k) % (SELECT count(*) FROM customer) AS dst, c_mktsegment AS segment FROM customer, range(1, 4) b(k)")
add("sink_bucketed", _bucketed, sql("SELECT * FROM v_deg"))
add("sink_by_part", _by_part, sql("SELECT src, dst, w, p_dst AS part FROM v_placed WHERE p_dst = 1"))

# --- features ----------------------------------------------------------------------------------------------------------------------

add(
    "vertex_features",
    lambda w: table(w.spark, w.sf_dir, "customer").select(
        F.col("c_custkey").alias("vid"), F.when(F.col("c_acctbal").between(0, 5000), 1).otherwise(0).alias("mid"), F.col("c_mktsegment").like("A%").alias("starts_a"), F.col("c_nationkey").isin(1, 2, 3).alias("near"), F.coalesce("c_acctbal", F.lit(0.0)).alias("balance")
    ),
    "SELECT c_custkey AS vid, CAST(CASE WHEN c_acctbal BETWEEN 0 AND 5000 THEN 1 ELSE 0 END AS INTEGER) AS mid, c_mktsegment LIKE 'A%' AS starts_a, c_nationkey IN (1, 2, 3) AS near, coalesce(c_acctbal, 0) AS balance FROM customer",
)


def _standard(w):
    c = table(w.spark, w.sf_dir, "part").select("p_partkey", "p_retailprice")
    s = c.agg(F.avg("p_retailprice").alias("m"), F.stddev_pop("p_retailprice").alias("s"))  # one row
    return c.join(F.broadcast(s)).select("p_partkey", F.round((F.col("p_retailprice") - F.col("m")) / F.col("s"), 6).alias("z"))


add("standardize", _standard, "SELECT p_partkey, round((p_retailprice - (SELECT avg(p_retailprice) FROM part)) / (SELECT stddev_pop(p_retailprice) FROM part), 6) AS z FROM part")
add(
    "event_time_features", lambda w: table(w.spark, w.sf_dir, "events").groupBy(F.hour("ts").alias("hour"), F.dayofweek("ts").alias("dow")).agg(F.count("*").alias("n"), F.count_distinct(F.date_trunc("day", "ts")).alias("days")),
    "SELECT CAST(hour(ts) AS INTEGER) AS hour, CAST(dayofweek(ts) + 1 AS INTEGER) AS dow, count(*) AS n, count(DISTINCT date_trunc('day', ts)) AS days FROM events GROUP BY ALL",
)
add("event_edges", lambda w: graph.event_edges(w.spark, w.sf_dir).groupBy("src", "dst").agg(F.count("*").alias("w")), "SELECT user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst, count(*) AS w FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY ALL")
_tokens = lambda w: table(w.spark, w.sf_dir, "documents").select("doc_id", F.explode(F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit("[a-z]{3,}"), F.lit(0))).alias("token"))
_tokens_sql = "SELECT doc_id, unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z]{3,}')) AS token FROM documents"
add("doc_tokens", lambda w: _tokens(w).groupBy("token").agg(F.count_distinct("doc_id").alias("df"), F.count("*").alias("tf")), f"SELECT token, count(DISTINCT doc_id) AS df, count(*) AS tf FROM ({_tokens_sql}) GROUP BY token")
add(
    "doc_hash_features", lambda w: _tokens(w).groupBy("doc_id", F.pmod(draw_column("tok", F.col("token")), F.lit(16)).cast("int").alias("slot")).agg(F.count("*").alias("n")),
    f"SELECT doc_id, CAST({draw(chr(39) + 'tok' + chr(39), 'token')} % 16 AS INTEGER) AS slot, count(*) AS n FROM ({_tokens_sql}) GROUP BY ALL",
)
add("page_hosts", lambda w: table(w.spark, w.sf_dir, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host")).agg(F.count("*").alias("pages"), F.sum(F.length(F.regexp_replace("html", "<[^>]*>", ""))).alias("text_chars")), "SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, count(*) AS pages, CAST(sum(length(regexp_replace(html, '<[^>]*>', '', 'g'))) AS BIGINT) AS text_chars FROM pages GROUP BY ALL")
_vec = lambda w: table(w.spark, w.sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("embedding"))
add(
    "vec_cosine", lambda w: _vec(w).alias("a").join(_vec(w).alias("b"), F.col("b.vec_id") == F.col("a.vec_id") + 1).select(F.col("a.vec_id").alias("vec_id"), F.round(cosine(F.col("a.embedding"), F.col("b.embedding")), 6).alias("cosine")),
    "SELECT a.vec_id, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1",
)
add(
    "knn_exact", lambda w: graph.nearest(_vec(w), 3).select("src", "dst", "rank"),
    f"SELECT src, dst, CAST(r AS INTEGER) AS rank FROM (SELECT b.vec_id AS src, a.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY {m6('list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[]))')} DESC, b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 3",
)

# --- joins -------------------------------------------------------------------------------------------------------------------------

add("join_broadcast_parts", lambda w: table(w.spark, w.sf_dir, "customer").join(F.broadcast(table(w.spark, w.sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")), "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
for _hint in ("shuffle_hash", "merge"):
    add(f"join_rows_edges_{_hint}", lambda w, h=_hint: w.edges.hint(h).join(w.features.withColumnRenamed("vid", "src"), "src").groupBy(F.pmod("dst", F.lit(10)).alias("b")).agg(millionths(F.sum(F.get("x", F.lit(0)))).alias("s")), sql(f"SELECT e.dst % 10 AS b, {m6('sum(x0)')} AS s FROM v_edges e JOIN v_x x ON x.vid = e.src GROUP BY 1"))
add(
    "join_interval_cache",
    lambda w: cache.demand(w.plan.frontier).join(w.plan.push_plan.select(F.col("to_rank").alias("rank"), "layer", "vid", "arrive_it"), ["rank", "layer", "vid"]).where("it BETWEEN arrive_it AND arrive_it + 2").groupBy("rank", "layer", "it").agg(F.count("*").alias("n")),
    sql("SELECT q.rank, q.layer, q.it, count(*) AS n FROM v_demand q JOIN v_push a ON a.to_rank = q.rank AND a.layer = q.layer AND a.vid = q.vid AND q.it BETWEEN a.arrive_it AND a.arrive_it + 2 GROUP BY ALL"),
)
add("semi_boundary", lambda w: w.parts.join(w.pg.directory, "vid", "left_semi"), sql("SELECT * FROM v_parts WHERE vid IN (SELECT vid FROM v_halo)"))
add("anti_misses", lambda w: table(w.spark, w.sf_dir, "orders").join(table(w.spark, w.sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey", "o_custkey"), "SELECT o_orderkey, o_custkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
add("outer_degrees", lambda w: w.vertices.join(w.pg.degrees, "vid", "full_outer").groupBy(F.coalesce("deg", F.lit(0)).alias("deg")).agg(F.count("*").alias("n")), sql("SELECT coalesce(deg, 0) AS deg, count(*) AS n FROM v_verts FULL JOIN v_deg USING (vid) GROUP BY 1"))
add(
    "two_hop", lambda w: graph.two_hop_counts(w.edges),
    sql("SELECT a.src, count(DISTINCT b.dst) AS n FROM v_edges a JOIN v_edges b ON a.dst = b.src WHERE a.src <> b.dst GROUP BY a.src"),
)
add(
    "lateral_topk", lambda w: w.spark.sql("SELECT v.vid, n.src, n.w FROM {v} v, LATERAL (SELECT e.src, e.w FROM {e} e WHERE e.dst = v.vid ORDER BY e.w DESC, e.src LIMIT 2) n", v=w.train, e=w.edges),
    sql("SELECT vid, src, w FROM (SELECT v.vid, e.src, e.w, row_number() OVER (PARTITION BY v.vid ORDER BY e.w DESC, e.src) AS r FROM v_train v JOIN v_edges e ON e.dst = v.vid) WHERE r <= 2"),
)

# --- aggregates, windows, sorts, sets -------------------------------------------------------------------------------------------------

add("ntile_parts", lambda w: w.vertices.select("vid", F.ntile(4).over(Window.partitionBy(F.pmod("vid", F.lit(8))).orderBy("vid")).alias("tile")), sql("SELECT vid, CAST(ntile(4) OVER (PARTITION BY vid % 8 ORDER BY vid) AS INTEGER) AS tile FROM v_verts"))
add("topk_degree", lambda w: w.pg.degrees.orderBy(F.desc("deg"), "vid").limit(15), sql("SELECT * FROM v_deg ORDER BY deg DESC, vid LIMIT 15"))
add("degree_percentiles", lambda w: w.pg.degrees.agg(F.percentile("deg", F.lit(0.5)).alias("p50"), F.percentile("deg", F.lit(0.9)).alias("p90"), F.max("deg").alias("top")), sql("SELECT quantile_cont(deg, 0.5) AS p50, quantile_cont(deg, 0.9) AS p90, max(deg) AS top FROM v_deg"))
add("approx_frontier", lambda w: w.plan.frontier.groupBy("layer").agg(F.approx_count_distinct("vid", 0.02).alias("about"), F.approx_percentile("vid", F.lit(0.5)).alias("middle")))
add("hll_halo_overlap", lambda w: w.pg.halos.groupBy("part").agg(F.hll_sketch_agg("vid").alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("distinct_halos")))
_of = lambda w, p: w.pg.halos.where(F.col("part") == p).select("vid")
add("set_intersect_halo", lambda w: _of(w, 0).intersect(w.parts.where("part = 1").select("vid")), sql(f"SELECT vid FROM v_halo WHERE part = 0 AND vid % {P} = 1"))
add("set_except", lambda w: cache.demand(w.plan.frontier).select("rank", "layer", "vid").exceptAll(w.plan.hit_plan.where("hit").select("rank", "layer", "vid")), sql("SELECT rank, layer, vid FROM v_hits WHERE NOT hit"))
add("set_union", lambda w: _of(w, 0).union(_of(w, 1)).distinct(), sql("SELECT DISTINCT vid FROM v_halo WHERE part IN (0, 1)"))
BLOCK = 1000  # neighbours in one row, however many a hub has
add(
    "adjacency_lists",
    lambda w: w.edges.withColumn("block", F.floor((F.row_number().over(Window.partitionBy("dst").orderBy("src")) - 1) / BLOCK)).groupBy(F.col("dst").alias("vid"), "block").agg(F.sort_array(F.collect_list("src")).alias("a")).select("vid", "block", F.size("a").cast("long").alias("n"), F.md5(F.array_join(F.transform("a", lambda x: x.cast("string")), ",")).alias("digest")),
    sql(f"SELECT dst AS vid, block, count(*) AS n, md5(string_agg(CAST(src AS VARCHAR), ',' ORDER BY src)) AS digest FROM (SELECT dst, src, CAST(floor((row_number() OVER (PARTITION BY dst ORDER BY src) - 1) / {BLOCK}) AS BIGINT) AS block FROM v_edges) GROUP BY dst, block"),
)
add(
    "array_mean_rows", lambda w: flat(w.features.groupBy(F.floor(F.col("vid") / 64).alias("vid")).agg(F.collect_list("x").alias("r")).select("vid", F.transform(F.sequence(F.lit(0), F.lit(W - 1)), lambda k: F.aggregate("r", F.lit(0.0), lambda s, x: s + F.get(x, k)) / F.size("r")).alias("x"))),
    sql(f"SELECT CAST(floor(vid / 64) AS BIGINT) AS vid, {cols([f'avg(x{k})' for k in range(W)])} FROM v_x GROUP BY 1"),
)

# --- user-defined functions ------------------------------------------------------------------------------------------------------------

add("udf_vec_mean", lambda w: flat(w.features.groupBy(F.pmod("vid", F.lit(50)).alias("vid")).agg(sqlapi.vec_mean("x").alias("x"))), sql(f"SELECT vid % 50 AS vid, {cols([f'avg(x{k})' for k in range(W)])} FROM v_x GROUP BY 1"))
add("udf_relu_vec", lambda w: flat(w.features.select("vid", sqlapi.relu_vec("x").alias("x"))), sql(f"SELECT vid, {cols([f'greatest(x{k}, 0)' for k in range(W)])} FROM v_x"))


def _udtf(w):
    sqlapi.register(w.spark)
    lists = w.edges.join(w.train, F.col("dst") == F.col("vid")).groupBy("dst").agg(F.collect_list("src").alias("adj"))
    return w.spark.sql("SELECT l.dst, s.src, s.n FROM {l} l, LATERAL sample_neighbors(l.dst, l.adj, 3, 1) s", l=lists)


add("udtf_sample", _udtf, sql(f"SELECT dst, src, CAST(r - 1 AS INTEGER) AS n FROM (SELECT e.dst, e.src, row_number() OVER (PARTITION BY e.dst ORDER BY {md5(1, 'e.dst', 'e.src')}, e.src) AS r FROM v_edges e JOIN v_train t ON t.vid = e.dst) WHERE r <= 3"))

# --- streams -----------------------------------------------------------------------------------------------------------------------------

_events = lambda w: stream.event_stream(w.spark, w.sf_dir)
add("stream_tumbling", lambda w: stream.drained(stream.tumbling(_events(w)), "complete"), "SELECT CAST(floor(epoch(ts) / 3600) * 3600 AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
add("stream_sliding", lambda w: stream.drained(stream.sliding(_events(w)), "complete"), "SELECT CAST(floor(epoch(ts) / 3600) * 3600 - 3600 * k AS BIGINT) AS start, count(*) AS n FROM events, (VALUES (0), (1)) AS t(k) GROUP BY ALL")
add(
    "stream_session", lambda w: stream.drained(stream.sessions(_events(w)), "complete"),
    """SELECT user_id, CAST(min(s) AS BIGINT) AS start, CAST(max(s) + 1800 AS BIGINT) AS "end", count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY s, event_id) AS g FROM (
      SELECT *, CASE WHEN s - lag(s) OVER (PARTITION BY user_id ORDER BY s, event_id) <= 1800 THEN 0 ELSE 1 END AS fresh FROM (SELECT event_id, user_id, CAST(floor(epoch(ts)) AS BIGINT) AS s FROM events))) GROUP BY user_id, g""",
)
add("stream_late_edges", lambda w: stream.drained(stream.late_edges(stream.event_stream(w.spark, w.sf_dir, 4, F.when(F.pmod("event_id", F.lit(20)) == 0, F.col("event_id") + 400).otherwise(F.col("event_id")))), "append"))
add("stream_dedup_edges", lambda w: stream.drained(stream.distinct_edges(_events(w)), "append"), "SELECT DISTINCT user_id AS src, CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL")
add("stream_edge_parts", lambda w: stream.drained(stream.edge_parts(_events(w), partition.by_hash(table(w.spark, w.sf_dir, "events").select(F.col("user_id").alias("vid")).distinct(), P)), "append"), f"SELECT event_id, user_id AS vid, CAST(json_extract_string(props, '$.k') AS BIGINT) AS key, CAST(user_id % {P} AS INTEGER) AS part FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL")
add("stream_degree", lambda w: stream.drained(stream.running_degree(_events(w)), "complete"), "SELECT user_id AS vid, count(*) AS deg FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY user_id")


def trace_stream(w, spec: CacheSpec, chunks: int = 3):
    """The writes and probes of an epoch's plan as a stream, a few iterations at a time."""
    writes = w.pushes(spec).select(F.col("to_rank").alias("rank"), "layer", "vid", F.col("arrive_it").alias("it"), F.lit(0).alias("kind"))
    probes = cache.demand(w.plan.frontier).select("rank", "layer", "vid", "it", F.lit(1).alias("kind"))
    trace = stage(writes.unionByName(probes).where(F.col("it") < w.plan.rounds))
    path = fresh_path(w.spark, "trace")
    step = -(-w.plan.rounds // chunks)
    for k in range(chunks):
        trace.where((F.col("it") >= k * step) & (F.col("it") < (k + 1) * step)).coalesce(1).write.mode("append").parquet(path)
    return w.spark.readStream.schema(trace.schema).option("maxFilesPerTrigger", 1).parquet(path)


def stream_hits(w, spec: CacheSpec):
    conf, key = w.spark.conf, "spark.sql.streaming.stateStore.providerClass"
    before = conf.get(key, None)
    conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return stream.drained(stream_cache.cache_hits(trace_stream(w, spec), spec), "append")
    finally:
        conf.set(key, before) if before else conf.unset(key)


from .sql import hits as _hits  # noqa: E402 - beside its only use

add("stream_cache_hits", lambda w: stream_hits(w, replace(ORACLE, cs=40)), sql(f"SELECT rank, it, layer, vid, hit, version_it FROM ({_hits(cs=40)})"))
add("stream_cache_tight", lambda w: stream_hits(w, TIGHT), sql(f"SELECT rank, it, layer, vid, hit, version_it FROM ({_hits('v_tight_push', 50, 3, 2)})"))
add("stream_clock", lambda w: stream.clocked(_events(w), "event_id"), "SELECT event_id AS tick, CAST(floor((event_id - low) / step) AS BIGINT) AS it FROM events, (SELECT min(event_id) AS low, CAST(ceil((max(event_id) - min(event_id) + 1) / 4) AS BIGINT) AS step FROM events)")
