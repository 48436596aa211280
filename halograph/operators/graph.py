"""Graphs from relational tables. Vertex ids are whole numbers; edges are directed pairs (src, dst, w), both ways where undirected."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.draws import below, draw
from ..functions.vectors import EDGE
from ..session import ship_package, stage
from ..sources.tables import table


def symmetric(edges: DataFrame) -> DataFrame:
    """Both directions, one row per pair, weights added, no self loops."""
    both = edges.select("src", "dst", "w").union(edges.select("dst", "src", "w"))
    return both.where("src <> dst").groupBy("src", "dst").agg(F.sum("w").cast("long").alias("w"))


def _offset(spark: SparkSession, sf_dir: str, *tables: str) -> int:
    """Rows of the tables: where the next table's vertex ids begin. Known from the files' footers."""
    return sum(table(spark, sf_dir, t).count() for t in tables)


def purchase_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer and part of every line: (src, dst, w), w the number of lines."""
    base = _offset(spark, sf_dir, "customer")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy(F.col("o_custkey").alias("src"), (F.col("l_partkey") + base).alias("dst")).agg(F.count("*").alias("w"))


def purchase(spark: SparkSession, sf_dir: str) -> DataFrame:
    return symmetric(purchase_pairs(spark, sf_dir))


def supply(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts and suppliers; suppliers are hubs. Suppliers' ids follow the parts'."""
    base = _offset(spark, sf_dir, "part")
    lines = table(spark, sf_dir, "lineitem")
    pairs = lines.groupBy(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + base).alias("dst")).agg(F.count("*").alias("w"))
    return symmetric(pairs)


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers, parts, suppliers and nations in one range of ids."""
    c, p, s = (_offset(spark, sf_dir, t) for t in ("customer", "part", "supplier"))
    supplied = table(spark, sf_dir, "lineitem").groupBy((F.col("l_partkey") + c).alias("src"), (F.col("l_suppkey") + c + p).alias("dst")).agg(F.count("*").alias("w"))
    home = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("src"), (F.col("c_nationkey") + c + p + s).cast("long").alias("dst"), F.lit(1).cast("long").alias("w"))
    base = table(spark, sf_dir, "supplier").select((F.col("s_suppkey") + c + p).alias("src"), (F.col("s_nationkey") + c + p + s).cast("long").alias("dst"), F.lit(1).cast("long").alias("w"))
    return symmetric(purchase_pairs(spark, sf_dir).union(supplied).union(home).union(base))


BLOCK_VECTORS = 4096


def nearest(vectors: DataFrame, k: int = 10, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """Exact cosine neighbours (src, dst, sim in millionths, rank) of all vectors: every block of vectors meets every block, one pair of
    blocks a task. A matrix product finds who can be among a vector's k nearest of a block; those are scored again by the terms in their
    order, as Spark and SQL add them. Vectors without a direction (null, zeros) come last."""
    n = max(1, -(-vectors.count() // BLOCK_VECTORS))
    ship_package(vectors.sparkSession)

    def pack(t: pa.Table) -> pa.Table:
        return pa.table({"block": t.column("block")[:1], "ids": pa.array([t.column("id").to_pylist()], pa.list_(pa.int64())), "rows": pa.array([_rows(t.column("v")).tobytes()], pa.binary())})

    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v"))
    dealt = rows.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(n)).cast("int"))
    blocks = stage(dealt.groupBy("block").applyInArrow(pack, "block int, ids array<long>, rows binary"), "blocks").repartitionById(n, F.col("block"))
    a, b = (blocks.select(F.col("ids").alias(f"ids_{e}"), F.col("rows").alias(f"rows_{e}")) for e in "ab")

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(len(batch)):
                ids, x, other, y = (np.asarray(c[i].values) if j % 2 == 0 else np.frombuffer(c[i].as_buffer()) for j, c in enumerate(batch.columns))
                for src, dst, sim in _block_nearest(ids, x.reshape(len(ids), -1), other, y.reshape(len(other), -1), k):
                    yield pa.record_batch([pa.array(src), pa.array(dst), pa.array(sim, mask=sim == NO_DIRECTION)], names=["src", "dst", "sim"])

    scored = a.crossJoin(b).mapInArrow(score, "src long, dst long, sim long")
    w = Window.partitionBy("dst").orderBy(F.desc_nulls_last("sim"), "src")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


NO_DIRECTION = np.iinfo(np.int64).min


def _rows(column: pa.ChunkedArray) -> np.ndarray:
    """A matrix of the lists; a null is a row of NaN."""
    lists = column.to_pylist()
    width = max((len(v) for v in lists if v is not None), default=1)
    return np.array([[np.nan] * width if v is None else v for v in lists], np.float64)


def _unit(x: np.ndarray) -> np.ndarray:
    with np.errstate(invalid="ignore", divide="ignore"):
        return x / np.sqrt((x * x).sum(1))[:, None]


def _block_nearest(ids: np.ndarray, x: np.ndarray, other: np.ndarray, y: np.ndarray, k: int, step: int = 256) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(src, dst, sim) of the k nearest among other for every one of ids."""

    def dot(u: np.ndarray, i: np.ndarray, v: np.ndarray, j: np.ndarray) -> np.ndarray:
        total = np.zeros(len(i))
        for c in range(u.shape[1]):
            total += u[i, c] * v[j, c]
        return total

    if x.shape[1] != y.shape[1]:  # a block of nulls alone knows no width
        x, y = (np.full((len(z), max(x.shape[1], y.shape[1])), np.nan) if np.isnan(z).all() else z for z in (x, y))
    every = lambda z: np.arange(len(z))
    nx, ny = np.sqrt(dot(x, every(x), x, every(x))), np.sqrt(dot(y, every(y), y, every(y)))
    ux, uy = _unit(x), _unit(y).T
    shared = len(np.intersect1d(ids, other)) > 0
    for lo in range(0, len(ids), step):
        about = np.nan_to_num(ux[lo : lo + step] @ uy, nan=-2.0)
        if shared:
            about[ids[lo : lo + step, None] == other[None, :]] = -4.0
        most = min(k, len(other))
        edge = np.partition(about, len(other) - most, axis=1)[:, len(other) - most]
        i, j = np.nonzero((about >= np.minimum(edge, 1.0)[:, None] - 3e-6) & (about > -3.0))
        i = i + lo
        with np.errstate(invalid="ignore", divide="ignore"):
            cosine = dot(x, i, y, j) / (nx[i] * ny[j])
        sim = np.where(np.isnan(cosine), NO_DIRECTION, np.floor(np.nan_to_num(cosine) * 1e6 + EDGE).astype(np.int64))
        order = np.lexsort((other[j], np.where(sim == NO_DIRECTION, 10**9, -sim), i))
        i, j, sim = i[order], j[order], sim[order]
        first = np.flatnonzero(np.diff(i, prepend=-1))
        place = np.arange(len(i)) - np.repeat(first, np.diff(np.append(first, len(i))))
        keep = place < k
        yield other[j[keep]], ids[i[keep]], sim[keep]


EDGES_A_BLOCK = 1 << 21
PIECE_BITS = 20
PATHS_AT_ONCE = 1 << 21


def two_hop_counts(edges: DataFrame) -> DataFrame:
    """(src, n): how many other vertices end a path of two edges that begins at src, where there are any.

    Paths are not exchanged: a middle vertex sends its list of ends once to each block of sources that lead to it, and a block expands its
    paths a few million at a time. Blocks are ranges of ids, so where near ids share neighbours a list goes to few of them. Lists are cut
    into ranges of ids as well, which bounds a hub's rows."""
    spark = edges.sparkSession
    ship_package(spark)
    count, low, high = edges.agg(F.count("*"), F.min("src"), F.max("src")).first()
    n = max(1, -(-(count or 0) // EDGES_A_BLOCK))
    width = (high or 0) - (low or 0) + 1
    e = edges.select("src", "dst")
    block = F.floor((F.col("src") - F.lit(low or 0)) * F.lit(n) / F.lit(width)).cast("int")
    # dealt by the middle first: single edges are smaller than lists of one that partial aggregates would exchange
    into = e.repartition("dst").groupBy(F.col("dst").alias("mid"), block.alias("block")).agg(F.collect_list("src").alias("s"))
    piece = F.shiftright("dst", PIECE_BITS).alias("piece")
    out = e.repartition("src").groupBy(F.col("src").alias("mid"), piece).agg(F.sort_array(F.collect_list((F.col("dst").bitwiseAND(F.lit((1 << PIECE_BITS) - 1))).cast("int"))).alias("o"))
    sent = into.join(out, "mid").select("block", "s", "piece", "o")

    def count_block(t: pa.Table) -> pa.Table:
        src, ends, at = _list(t.column("s")), *_list(t.column("o"), True)
        lengths = np.diff(at)
        row = np.repeat(np.arange(t.num_rows), np.diff(_list(t.column("s"), True)[1]))
        base = t.column("piece").to_numpy().astype(np.int64) << PIECE_BITS
        got = list(_block_counts(src, row, ends, at[:-1], lengths, base))
        ids, n = (np.concatenate([g[c] for g in got]) if got else np.zeros(0, np.int64) for c in (0, 1))
        return pa.table({"src": ids, "n": n})

    return sent.groupBy("block").applyInArrow(count_block, "src long, n long")


def _list(column: pa.ChunkedArray, where: bool = False):
    """The values of all lists, and where each begins."""
    column = pa.concat_arrays(column.chunks)
    at = column.offsets.to_numpy()
    values = column.values.to_numpy()[at[0] : at[-1]]
    return (values, at - at[0]) if where else values


def _block_counts(src: np.ndarray, row: np.ndarray, ends: np.ndarray, first: np.ndarray, length: np.ndarray, base: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """src[k] leads to the ends of row[k]: (sources, how many different other ends). A source with more paths than fit at once keeps the
    ends that it has found."""
    order = np.argsort(src, kind="stable")
    src, row = src[order], row[order]
    paths = np.cumsum(length[row])
    starts = np.append(np.flatnonzero(np.diff(src, prepend=src[:1] - 1)), len(src))

    def reach(lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
        r, m = row[lo:hi], length[row[lo:hi]]
        at = np.repeat(first[r] - np.append(0, np.cumsum(m)[:-1]), m) + np.arange(m.sum())
        return np.repeat(src[lo:hi], m), np.repeat(base[r], m) + ends[at]

    k = 0
    while k < len(starts) - 1:
        lo = starts[k]
        before = paths[lo - 1] if lo else 0
        last = max(k + 1, int(np.searchsorted(paths[starts[1:] - 1], before + PATHS_AT_ONCE, "right")))
        hi = starts[last]
        if last == k + 1 and paths[hi - 1] - before > PATHS_AT_ONCE:
            found = np.zeros(0, np.int64)
            while lo < hi:
                before = paths[lo - 1] if lo else 0
                to = min(hi, max(lo + 1, int(np.searchsorted(paths, before + PATHS_AT_ONCE, "right"))))
                found = np.union1d(found, reach(lo, to)[1])
                lo = to
            n = len(found) - int((found == src[hi - 1]).sum())
            yield src[hi - 1 : hi][: n > 0], np.array([n][: n > 0], np.int64)
        else:
            s, x = reach(lo, hi)
            ids, where = src[starts[k:last]], np.repeat(np.arange(last - k), np.diff(paths[starts[k + 1 : last + 1] - 1] - before, prepend=0))
            other = s != x
            where, x = where[other], x[other]
            floor, span = (int(x.min()), int(x.max() - x.min()) + 1) if len(x) else (0, 1)
            key = np.sort(where * span + (x - floor))
            n = np.bincount(key[np.flatnonzero(np.diff(key, prepend=-1))] // span, minlength=last - k) if len(key) else np.zeros(last - k, np.int64)
            yield ids[n > 0], n[n > 0].astype(np.int64)
        k = last


def documents(spark: SparkSession, sf_dir: str, most: int = 8) -> DataFrame:
    """Documents that share a rare token (one of 2 to `most` documents); a token gives at most most * (most - 1) / 2 pairs, so none is a
    hub. Exact copies are joined through their tokens as well."""
    words = F.array_distinct(F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit(r"[^\s.,;:!?]{5,}"), F.lit(0)))
    t = table(spark, sf_dir, "documents").select("doc_id", F.explode(words).alias("token"))
    # a token's documents are counted up to one more than `most`, and no more of them are moved
    few = t.withColumn("k", F.row_number().over(Window.partitionBy("token").orderBy("doc_id"))).where(F.col("k") <= most + 1)
    rare = few.groupBy("token").agg(F.collect_list("doc_id").alias("d")).where(F.size("d").between(2, most))
    pairs = rare.select(F.explode("d").alias("src"), "d").select("src", F.explode("d").alias("dst")).where("src < dst")
    return symmetric(pairs.groupBy("src", "dst").agg(F.count("*").alias("w")))


def trigram_features(spark: SparkSession, sf_dir: str, width: int = 64) -> DataFrame:
    """(vid, x): shares of hashed overlapping trigrams of whole texts."""
    grams = F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit("(?s)(?=(.{3}))"), F.lit(1))
    t = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("vid"), F.explode(grams).alias("g"))
    slot = F.pmod(F.xxhash64("g"), F.lit(width)).cast("int")
    counts = t.groupBy("vid", slot.alias("slot")).agg(F.count("*").alias("n"))
    rows = counts.groupBy("vid").agg(F.map_from_entries(F.collect_list(F.struct("slot", "n"))).alias("m"), F.sum("n").alias("total"))
    x = F.array(*[F.coalesce(F.try_element_at("m", F.lit(k)), F.lit(0)) * width / F.col("total") for k in range(width)])
    every = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("vid"))
    return every.join(rows.select("vid", x.alias("x")), "vid", "left").select("vid", F.coalesce("x", F.array(*[F.lit(0.0)] * width)).alias("x"))


def language_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vid, label): languages numbered by name."""
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("vid"), "lang").where("lang IS NOT NULL")
    names = sorted(r[0] for r in d.select("lang").distinct().collect())  # four rows
    return d.select("vid", (F.array_position(F.array(*map(F.lit, names)), F.col("lang")) - 1).cast("int").alias("label"))


def conversation_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many small graphs: each conversation is a path over its turns (graph_id, src, dst)."""
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn")
    after = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    return t.withColumn("dst", after).where("dst IS NOT NULL").select(F.col("conv_id").alias("graph_id"), F.col("turn").alias("src"), "dst")


def event_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user, key, ts) of every event, the key from its JSON properties."""
    key = F.get_json_object("props", "$.k").cast("long")
    return table(spark, sf_dir, "events").select(F.col("user_id").alias("src"), key.alias("dst"), "ts").where("dst IS NOT NULL")


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("deg"))


def purchase_vertices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vid, vtype, label): customers by segment, parts by size."""
    base = _offset(spark, sf_dir, "customer")
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("vid"), F.lit("customer").alias("vtype"), F.col("c_mktsegment").alias("label"))
    p = table(spark, sf_dir, "part").select((F.col("p_partkey") + base).alias("vid"), F.lit("part").alias("vtype"), F.col("p_type").alias("label"))
    return c.union(p)


def same_host_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vid, deg) of the pages' graph, in which pages of one host are all joined: from counts, since its edges grow with their square."""
    host = F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1)
    h = table(spark, sf_dir, "pages").select("page_id", host.alias("host"))
    n = h.groupBy("host").agg((F.count("*") - 1).alias("deg")).where("deg > 0")
    return h.join(n, "host").select(F.col("page_id").alias("vid"), "deg")


def feature(vid: Column, dim: Column | int, seed: int = 1) -> Column:
    """Hash features: multiples of 1/1024 in [-1/2, 1/2), exact in any order of summing."""
    return (F.pmod(draw(seed, "x", vid, dim), F.lit(1024)) - 512) / F.lit(1024.0)


def hash_features(vertices: DataFrame, width: int, seed: int = 1) -> DataFrame:
    """(vid, x): features of every vertex as one array."""
    return vertices.select("vid", F.array(*[feature(F.col("vid"), F.lit(k), seed) for k in range(width)]).alias("x"))


def with_split(vertices: DataFrame, train_share: float, seed: int = 1) -> DataFrame:
    """Adds is_train, drawn from the vertex id."""
    return vertices.withColumn("is_train", below(train_share, seed, "split", F.col("vid")))
