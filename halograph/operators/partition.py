"""Vertex partitions and what follows from them: halos, ids, catalog, directory, quality."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import digest
from ..session import stage
from .ranking import running


def by_hash(vertices: DataFrame, parts: int) -> DataFrame:
    return vertices.select("vid", F.pmod("vid", F.lit(parts)).cast("int").alias("part"))


def by_range(vertices: DataFrame, parts: int) -> DataFrame:
    """Ranges of ids of equal width, which hold equally many vertices where ids are dense."""
    low, high = vertices.agg(F.min("vid"), F.max("vid")).first()
    width = max(1, (high or 0) - (low or 0) + 1)
    return vertices.select("vid", F.floor((F.col("vid") - (low or 0)) * parts / width).cast("int").alias("part"))


def place(edges: DataFrame, parts: DataFrame) -> DataFrame:
    """Edges with the parts of both ends and the source's degree: everything that sampling needs, joined once and stored."""
    deg = edges.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("deg_src"))
    of = parts.join(deg, parts["vid"] == deg["v"]).select("vid", "part", "deg_src")
    src = of.select(F.col("vid").alias("src"), F.col("part").alias("p_src"), "deg_src")
    dst = of.select(F.col("vid").alias("dst"), F.col("part").alias("p_dst"))
    return edges.join(src, "src").join(dst, "dst").select("src", "dst", "w", "p_src", "p_dst", "deg_src")


def cut_edges(placed: DataFrame) -> DataFrame:
    return placed.where("p_src <> p_dst")


def halos(placed: DataFrame) -> DataFrame:
    """(part, vid): foreign sources of a part's edges. Each cut edge gives a halo on either side."""
    return cut_edges(placed).select(F.col("p_dst").alias("part"), F.col("src").alias("vid")).distinct()


def catalog(parts: DataFrame, halo: DataFrame, placed: DataFrame) -> DataFrame:
    """(part, pid, vid, kind, deg): solids first, then halos, numbered densely from 0 within a part."""
    deg = placed.groupBy(F.col("dst").alias("vid")).agg(F.count("*").alias("deg"))
    both = parts.select("part", "vid", F.lit("solid").alias("kind")).union(halo.select("part", "vid", F.lit("halo").alias("kind")))
    pid = F.row_number().over(Window.partitionBy("part").orderBy(F.desc("kind"), "vid")) - 1
    return both.join(deg, "vid", "left").select("part", pid.alias("pid"), "vid", "kind", F.coalesce("deg", F.lit(0)).alias("deg"))


def directory(halo: DataFrame, parts: DataFrame) -> DataFrame:
    """(owner, vid, remote): which ranks keep a vertex as halo. One shuffle by vertex, where broadcasting all lists would not scale."""
    return halo.withColumnRenamed("part", "remote").join(parts.withColumnRenamed("part", "owner"), "vid").select("owner", "vid", "remote")


def quality(placed: DataFrame, train: DataFrame, parts: DataFrame) -> DataFrame:
    """Per part and in total (part null): vertices, training vertices, edges, cut edges, halos."""
    v = parts.join(train.select("vid", F.lit(1).alias("t")), "vid", "left").groupBy("part").agg(F.count("*").alias("vertices"), F.count("t").alias("train"))
    e = placed.groupBy(F.col("p_dst").alias("part")).agg(F.count("*").alias("edges"), F.count_if(F.col("p_src") != F.col("p_dst")).alias("cut"))
    h = halos(placed).groupBy("part").agg(F.count("*").alias("halos"))
    joined = v.join(e, "part", "left").join(h, "part", "left").na.fill(0)
    return joined.groupingSets([["part"], []], "part").agg(*[F.sum(c).alias(c) for c in ("vertices", "train", "edges", "cut", "halos")])


def vertex_cut(edges: DataFrame, parts: int) -> DataFrame:
    """Edges dealt by the hash of the end with the lower degree; vertices are copied where their edges go. (vid, part) of the copies."""
    deg = edges.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("d"))
    e = edges.where("src < dst").join(deg.select(F.col("v").alias("src"), F.col("d").alias("ds")), "src").join(deg.select(F.col("v").alias("dst"), F.col("d").alias("dd")), "dst")
    key = F.when(F.col("ds") <= F.col("dd"), F.col("src")).otherwise(F.col("dst"))
    dealt = e.withColumn("part", F.pmod(key, F.lit(parts)).cast("int"))
    return dealt.select(F.col("src").alias("vid"), "part").union(dealt.select("dst", "part")).distinct()


def labelprop_round(edges: DataFrame, parts: DataFrame, limit: int, seed: int = 1, turn: int = 0) -> DataFrame:
    """One round of size-capped label propagation. Vertices of this turn's parity ask for the part that most of their edges lead to; each
    part admits as many as it has room for, largest gain first."""
    near = edges.join(parts.select(F.col("vid").alias("src"), "part"), "src").groupBy(F.col("dst").alias("vid"), "part").agg(F.sum("w").alias("pull"))
    here = near.select("vid", F.col("part").alias("home"), F.col("pull").alias("held"))
    best = near.groupBy("vid").agg(F.max(F.struct("pull", (-F.col("part")).alias("n"))).alias("b")).select("vid", F.col("b.pull").alias("pull"), (-F.col("b.n")).cast("int").alias("to"))
    wish = parts.withColumnRenamed("part", "home").join(best, "vid").join(here, ["vid", "home"], "left")
    wish = wish.withColumn("gain", F.col("pull") - F.coalesce("held", F.lit(0))).where((F.col("to") != F.col("home")) & (F.col("gain") > 0) & (F.pmod(F.col("vid"), F.lit(2)) == turn % 2))
    room = parts.groupBy("part").agg(F.greatest(F.lit(0), F.lit(limit) - F.count("*")).alias("room")).withColumnRenamed("part", "to")
    wish = wish.select("vid", "to", "gain", digest(seed, turn, F.col("vid")).alias("draw"))
    ranked = running(wish, "to", [("gain", True), ("draw", False), ("vid", False)], n=F.lit(1))
    moved = ranked.join(room, "to").where("n <= room").select("vid", "to")
    return parts.join(moved, "vid", "left").select("vid", F.coalesce("to", "part").alias("part"))


def by_label_propagation(edges: DataFrame, vertices: DataFrame, parts: int, rounds: int = 8, slack: float = 0.05, seed: int = 1) -> DataFrame:
    """Label propagation from a hash start, with sizes kept below (1 + slack) times the mean. Each round is a table in shared storage."""
    now = stage(by_hash(vertices, parts), "labels")
    limit = int((1 + slack) * now.count() / parts) + 1
    for turn in range(rounds):
        now = stage(labelprop_round(edges, now, limit, seed, turn), "labels")
    return now
