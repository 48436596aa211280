"""Layers, heads and measures over them. Weights are dyadic and results are in millionths, so engines agree to the last digit."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import measures
from ..functions.draws import uniform
from ..functions.vectors import EDGE, dyadic, dyadic_matrix, leaky_relu, millionths, relu, sigmoid
from ..model.network import RATES, ModelSpec
from ..operators import graph, layers
from ..plans import infer
from ..plans.training import TrainConfig, allreduce, train
from ..sources.tables import table
from .registry import add
from .sql import VIEWS, draw, sql
from .workload import inline

W = 4


def m6(x: str) -> str:
    return f"CAST(floor(({x}) * 1e6::DOUBLE + {EDGE}::DOUBLE) AS BIGINT)"


def flat(df, n: int = W, col: str = "x"):
    """vid and y0.. in millionths."""
    return df.select("vid", *[millionths(F.get(col, F.lit(k))).alias(f"y{k}") for k in range(n)])


def cols(exprs: list[str]) -> str:
    return ", ".join(f"{m6(e)} AS y{k}" for k, e in enumerate(exprs))


def lin(names: list[str], w: np.ndarray, j: int, b: float | None = None) -> str:
    terms = [f"{n} * ({float(w[k, j])!r}::DOUBLE)" for k, n in enumerate(names)]
    return " + ".join(([f"({b!r}::DOUBLE)"] if b is not None else []) + terms)


X = [f"x{k}" for k in range(W)]
JOINED = "FROM v_edges e JOIN v_x x ON x.vid = e.src"
for _op, _f in (("mean", "avg"), ("sum", "sum"), ("max", "max"), ("min", "min")):
    add(f"agg_{_op}", lambda w, op=_op: flat(layers.aggregate(w.edges, w.features, W, op)), sql(f"SELECT e.dst AS vid, {cols([f'{_f}({x})' for x in X])} {JOINED} GROUP BY e.dst"))
VIEWS["v_strong"] = "SELECT * FROM v_edges WHERE w > 1"  # leaves many vertices without an edge
for _tag, _edges, _of in (("", "v_edges", lambda w: w.edges), ("_isolated", "v_strong", lambda w: w.edges.where("w > 1"))):
    add(f"agg_gcn{_tag}", lambda w, of=_of: flat(layers.aggregate(of(w), w.features, W, "gcn")), sql(f"SELECT o.vid, {cols([f'(coalesce(a.s{k}, 0) + o.x{k}) / (coalesce(a.n, 0) + 1)' for k in range(W)])} FROM v_x o LEFT JOIN (SELECT e.dst, count(*) AS n, {', '.join(f'sum(x{k}) AS s{k}' for k in range(W))} FROM {_edges} e JOIN v_x x ON x.vid = e.src GROUP BY e.dst) a ON o.vid = a.dst"))
add("agg_edge_feat", lambda w: layers.aggregate_edges(w.edges).select("vid", "total", millionths(F.col("mean")).alias("mean")), sql(f"SELECT dst AS vid, CAST(sum(w) AS BIGINT) AS total, {m6('avg(w)')} AS mean FROM v_edges GROUP BY dst"))
add("agg_broadcast", lambda w: flat(layers.aggregate_scaled(w.edges, w.features, W, [F.col("w") / 8.0, (F.col("w") + 1) / 8.0]), 2 * W), sql(f"SELECT e.dst AS vid, {cols([f'sum({c} / 8.0::DOUBLE * {x})' for c in ('w', '(w + 1)') for x in X])} {JOINED} GROUP BY e.dst"))
add("agg_local_remote", lambda w: flat(layers.aggregate_split(w.pg.placed.where("p_src = p_dst"), w.pg.placed.where("p_src <> p_dst"), w.features, W)), sql(f"SELECT e.dst AS vid, {cols([f'avg({x})' for x in X])} {JOINED} GROUP BY e.dst"))
add(
    "agg_isolated", lambda w: flat(layers.with_isolated(layers.aggregate(w.edges.where("w > 1"), w.features, W), w.vertices, W)),
    sql(f"SELECT v.vid, {cols([f'coalesce(m{k}, 0)' for k in range(W)])} FROM v_verts v LEFT JOIN (SELECT e.dst AS vid, {', '.join(f'avg(x{k}) AS m{k}' for k in range(W))} {JOINED} WHERE e.w > 1 GROUP BY e.dst) a USING (vid)"),
)

A = dyadic_matrix(W, 3, 1)
B0 = dyadic_matrix(1, 3, 3)[0]
add("update_affine_relu", lambda w: flat(layers.update(w.features, A, B0), 3), sql(f"SELECT vid, {cols([f'greatest(0, {lin(X, A, j, float(B0[j]))})' for j in range(3)])} FROM v_x"))
for _k in ("fused", "unfused", "blocked"):
    add(f"update_{_k}" if _k != "blocked" else "blocked_matmul", lambda w, k=_k: flat(layers.update_arrow(w.features, A, B0, kernel=k), 3), sql(f"SELECT vid, {cols([f'greatest(0, {lin(X, A, j, float(B0[j]))})' for j in range(3)])} FROM v_x"))
add("activations", lambda w: w.features.select("vid", *[millionths(f(F.get("x", F.lit(0)))).alias(n) for n, f in (("relu", relu), ("leaky", leaky_relu), ("sigmoid", sigmoid))]), sql(f"SELECT vid, {m6('greatest(x0, 0)')} AS relu, {m6('CASE WHEN x0 >= 0 THEN x0 ELSE x0 * 0.2::DOUBLE END')} AS leaky, {m6('1 / (1 + exp(-x0))')} AS sigmoid FROM v_x"))
add("dropout_mask", lambda w: flat(w.features.select("vid", layers.dropout(F.col("x"), W, 0.5, 1, "drop", 0, 0, 1, F.col("vid")).alias("x"))), sql("SELECT vid, " + cols([f"CASE WHEN ({draw(1, chr(39) + 'drop' + chr(39), 0, 0, 1, 'vid', k)} + 0.5::DOUBLE) / 4294967296::DOUBLE < 0.5 THEN 0 ELSE x{k} / 0.5::DOUBLE END" for k in range(W)]) + " FROM v_x"))
add("dropout_rate", lambda w: w.features.agg(F.count_if(uniform(1, "drop", 0, 0, 1, F.col("vid"), 0) < 0.5).alias("dropped")), sql(f"SELECT count(*) FILTER (({draw(1, chr(39) + 'drop' + chr(39), 0, 0, 1, 'vid', 0)} + 0.5::DOUBLE) / 4294967296::DOUBLE < 0.5) AS dropped FROM v_verts"))

# --- GraphSAGE -------------------------------------------------------------------------------------------------------------------

S1 = {"wn": dyadic_matrix(W, 3, 1), "ws": dyadic_matrix(W, 3, 2), "b": dyadic_matrix(1, 3, 3)[0]}
S2 = {"wn": dyadic_matrix(3, 2, 5), "ws": dyadic_matrix(3, 2, 6), "b": dyadic_matrix(1, 2, 7)[0]}


def sage_view(rows: str, x: list[str], p: dict, act: bool, edges: str = "v_edges") -> str:
    n = p["wn"].shape[1]
    mean = ", ".join(f"avg({c}) AS m{k}" for k, c in enumerate(x))
    out = []
    for j in range(n):
        e = f"{lin([f'coalesce(m{k}, 0)' for k in range(len(x))], p['wn'], j)} + {lin([f'o.{c}' for c in x], p['ws'], j, float(p['b'][j]))}"
        out.append(f"{f'greatest(0, {e})' if act else e} AS h{j}")
    return f"SELECT o.vid, {', '.join(out)} FROM {rows} o LEFT JOIN (SELECT e.dst, {mean} FROM {edges} e JOIN {rows} r ON r.vid = e.src GROUP BY e.dst) a ON a.dst = o.vid"


VIEWS["v_sage1"] = sage_view("v_x", X, S1, True)
VIEWS["v_sage_strong"] = sage_view("v_x", X, S1, True, "v_strong")
add("sage_layer_isolated", lambda w: flat(layers.sage(w.edges.where("w > 1"), w.features, S1), 3), sql(f"SELECT vid, {cols(['h0', 'h1', 'h2'])} FROM v_sage_strong"))
VIEWS["v_sage2"] = sage_view("v_sage1", ["h0", "h1", "h2"], S2, False)
add("sage_layer", lambda w: flat(layers.sage(w.edges, w.features, S1), 3), sql(f"SELECT vid, {cols(['h0', 'h1', 'h2'])} FROM v_sage1"))
add("sage_forward", lambda w: flat(layers.sage(w.edges, layers.sage(w.edges, w.features, S1), S2, act=False), 2), sql(f"SELECT vid, {cols(['h0', 'h1'])} FROM v_sage2"))
SAGE = ModelSpec("sage", (W, 3, 2), dropout=0.0)
SAGE_P = {f"layer{k}.{n}": v for k, p in enumerate((S1, S2)) for n, v in p.items()}
add("infer_full_sage", lambda w: flat(infer.full(w.edges, w.features, SAGE, SAGE_P), 2, "logits"), sql(f"SELECT vid, {cols(['h0', 'h1'])} FROM v_sage2"))

# --- attention -------------------------------------------------------------------------------------------------------------------

H, D = 2, 2
G = {"wu": dyadic_matrix(W, H * D, 2), "wv": dyadic_matrix(W, H * D, 4), "b": dyadic_matrix(1, H * D, 5)[0], "au": dyadic_matrix(H, D, 6), "av": dyadic_matrix(H, D, 8)}


def gat_views(tag: str, pre: bool, op: str, edges: str = "v_edges") -> None:
    act = lambda e: f"greatest(0, {e})" if pre else e
    z = lambda w: ", ".join(f"{act(lin(X, G[w], j, float(G['b'][j]) if pre else None))} AS z{j}" for j in range(H * D))
    inner = lambda a, h: " + ".join(f"z{h * D + k} * ({float(G[a][h, k])!r}::DOUBLE)" for k in range(D))
    for end, w, a in (("u", "wu", "au"), ("v", "wv", "av")):
        VIEWS[f"{tag}_{end}"] = f"SELECT *, {', '.join(f'{inner(a, h)} AS s{h}' for h in range(H))} FROM (SELECT vid, {z(w)} FROM v_x)"
    VIEWS[f"{tag}_score"] = f"SELECT src, dst, z0, z1, z2, z3, {', '.join(f'CASE WHEN r{h} >= 0 THEN r{h} ELSE r{h} * 0.2::DOUBLE END AS score{h}' for h in range(H))} FROM (SELECT e.src, e.dst, u.z0, u.z1, u.z2, u.z3, {', '.join(f'u.s{h} + v.s{h} AS r{h}' for h in range(H))} FROM {edges} e JOIN {tag}_u u ON u.vid = e.src JOIN {tag}_v v ON v.vid = e.dst)"
    VIEWS[f"{tag}_alpha"] = f"SELECT *, {', '.join(f'e{h} / sum(e{h}) OVER (PARTITION BY dst) AS alpha{h}' for h in range(H))} FROM (SELECT *, {', '.join(f'exp(score{h} - max(score{h}) OVER (PARTITION BY dst)) AS e{h}' for h in range(H))} FROM {tag}_score)"
    sums = [f"coalesce(a{j}, 0)" if op == "sum" else f"(coalesce(a{j}, 0) + z{j}) / (coalesce(n, 0) + 1)" for j in range(H * D)]
    if not pre:
        sums = [f"greatest(0, {s} + ({float(G['b'][j])!r}::DOUBLE))" for j, s in enumerate(sums)]
    near = ", ".join(f"sum(alpha{j // D} * z{j}) AS a{j}" for j in range(H * D))
    VIEWS[f"{tag}_out"] = f"SELECT v.vid, {', '.join(f'{s} AS h{j}' for j, s in enumerate(sums))} FROM {tag}_v v LEFT JOIN (SELECT dst, count(*) AS n, {near} FROM {tag}_alpha GROUP BY dst) q ON q.dst = v.vid"


HS = [f"h{j}" for j in range(H * D)]
for _name, _tag, _pre, _op, _edges, _of in (
    ("gat_layer", "ga", True, "sum", "v_edges", lambda w: w.edges), ("gat_layer_original", "go", False, "sum", "v_edges", lambda w: w.edges),
    ("gat_layer_gcn", "gg", True, "gcn", "v_edges", lambda w: w.edges), ("gat_original_gcn", "gog", False, "gcn", "v_edges", lambda w: w.edges),
    ("gat_layer_isolated", "gi", True, "gcn", "v_strong", lambda w: w.edges.where("w > 1")),
):
    gat_views(_tag, _pre, _op, _edges)
    add(_name, lambda w, pre=_pre, op=_op, of=_of: flat(layers.gat(of(w), w.features, G, H, pre, op=op)), sql(f"SELECT vid, {cols(HS)} FROM {_tag}_out"))
add("gat_multihead", lambda w: flat(layers.gat(w.edges, w.features, G, H, combine="mean", op="sum"), D), sql(f"SELECT vid, {cols([f'(h{k} + h{D + k}) / 2' for k in range(D)])} FROM ga_out"))
_scored = lambda w: layers.attention_scores(w.edges, w.features, G, H)
add("attention_scores", lambda w: _scored(w).select("src", "dst", *[millionths(F.col(f"score{h}")).alias(f"y{h}") for h in range(H)]), sql(f"SELECT src, dst, {cols([f'score{h}' for h in range(H)])} FROM ga_score"))
add("edge_softmax", lambda w: layers.edge_softmax(_scored(w), H).select("src", "dst", *[millionths(F.col(f"alpha{h}")).alias(f"y{h}") for h in range(H)]), sql(f"SELECT src, dst, {cols([f'alpha{h}' for h in range(H)])} FROM ga_alpha"))

# --- heads, losses, gradients ---------------------------------------------------------------------------------------------------

_logits = lambda w: layers.sage(w.edges, w.features, S1, act=False)
VIEWS["v_logits"] = sage_view("v_x", X, S1, False)
_label = lambda: F.pmod("vid", F.lit(3)).cast("int")  # noqa: E731 - columns need a session, modules must not
add("cross_entropy", lambda w: layers.cross_entropy(_logits(w), _label(), 3).select("vid", millionths(F.col("loss")).alias("loss")), sql(f"SELECT vid, {m6('ln(exp(h0) + exp(h1) + exp(h2)) - CASE vid % 3 WHEN 0 THEN h0 WHEN 1 THEN h1 ELSE h2 END')} AS loss FROM v_logits"))


def _predicted(w):
    rounded = _logits(w).select("vid", F.transform("x", millionths).alias("logits"))
    return infer.predict_nodes(rounded).withColumn("label", _label())


VIEWS["v_pred"] = f"SELECT vid, CAST(CASE WHEN a >= b AND a >= c THEN 0 WHEN b >= c THEN 1 ELSE 2 END AS INTEGER) AS pred, CAST(vid % 3 AS INTEGER) AS label FROM (SELECT vid, {m6('h0')} AS a, {m6('h1')} AS b, {m6('h2')} AS c FROM v_logits)"
add("predict_node", lambda w: _predicted(w), sql("SELECT * FROM v_pred"))
add("accuracy", lambda w: measures.accuracy(_predicted(w)), sql("SELECT count(*) AS n, count(*) FILTER (pred = label) AS correct, count(*) FILTER (pred = label) / count(*) AS accuracy FROM v_pred"))
add("confusion", lambda w: measures.confusion(_predicted(w)), sql("SELECT label, pred, count(*) AS n FROM v_pred GROUP BY CUBE (label, pred)"))
add("confusion_cube", lambda w: _predicted(w).join(w.parts, "vid").cube("part", "label", "pred").agg(F.count("*").alias("n")), sql("SELECT part, label, pred, count(*) AS n FROM v_pred JOIN v_parts USING (vid) GROUP BY CUBE (part, label, pred)"))
add(
    "topk_pred", lambda w: _logits(w).select("vid", F.posexplode(F.transform("x", millionths)).alias("class", "score")).orderBy(F.desc("score"), "vid", "class").limit(20),
    sql(f"SELECT vid, CAST(class AS INTEGER) AS class, score FROM (SELECT vid, unnest([0, 1, 2]) AS class, unnest([{m6('h0')}, {m6('h1')}, {m6('h2')}]) AS score FROM v_logits) ORDER BY score DESC, vid, class LIMIT 20"),
)
add(
    "link_scores", lambda w: infer.link_scores(w.features, graph.purchase_pairs(w.spark, w.sf_dir).select("src", "dst")).select("src", "dst", millionths(F.col("score")).alias("score")),
    sql(f"SELECT a AS src, b AS dst, {m6(' + '.join(f'p.x{k} * q.x{k}' for k in range(W)))} AS score FROM v_pairs JOIN v_x p ON p.vid = a JOIN v_x q ON q.vid = b"),
)
add(
    "link_negatives", lambda w: infer.negatives(graph.purchase_pairs(w.spark, w.sf_dir), graph._offset(w.spark, w.sf_dir, "customer"), graph._offset(w.spark, w.sf_dir, "part")),
    sql(f"SELECT a AS src, CAST(floor({draw(1, chr(39) + 'neg' + chr(39), 'a', 'b')} * (SELECT count(*) FROM part) / 4294967296::DOUBLE) + (SELECT count(*) FROM customer) AS BIGINT) AS dst FROM v_pairs"),
)


def _readout(w):
    t = w.spark.read.parquet(f"{w.sf_dir}/conversations.parquet")
    rows = t.select(F.col("conv_id").alias("graph_id"), F.array(F.length(F.coalesce("text", F.lit(""))).cast("double"), F.col("turn").cast("double")).alias("x"))
    return infer.graph_readout(rows, 2).select("graph_id", "n", *[millionths(F.get("x", F.lit(k))).alias(f"y{k}") for k in range(2)])


add("graph_readout", _readout, f"SELECT conv_id AS graph_id, count(*) AS n, {cols(['avg(coalesce(length(text), 0))', 'avg(turn)'])} FROM conversations GROUP BY conv_id")
_grad_rows = lambda w: w.features.select("x", F.array(*[F.get("x", F.lit((k + 1) % W)) + F.lit(0.25) for k in range(3)]).alias("d"))
add("weight_grad_chunked", lambda w: layers.weight_grad(_grad_rows(w).repartition(5), "x", "d", W, 3).select("i", "j", millionths(F.col("g")).alias("g")), sql(" UNION ALL ".join(f"SELECT CAST({i} AS INTEGER) AS i, CAST({j} AS INTEGER) AS j, {m6(f'sum(x{i} * (x{(j + 1) % W} + 0.25::DOUBLE))')} AS g FROM v_x" for i in range(W) for j in range(3))))


def _rank_grads(w):
    return w.features.groupBy(F.pmod("vid", F.lit(4)).alias("rank")).agg(F.array(*[F.sum(F.get("x", F.lit(k))) for k in range(W)]).alias("g"))


def _reduced(w):
    total = allreduce(_rank_grads(w), "sql")
    assert np.array_equal(total, allreduce(_rank_grads(w), "tree"))
    return inline(w.spark, "i int, g double", [(k, float(v)) for k, v in enumerate(total)]).select("i", millionths(F.col("g")).alias("g"))


add("grad_allreduce", _reduced, sql(" UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS i, {m6(f'sum(x{k})')} AS g FROM v_x" for k in range(W))))
add("dyadic_weights", lambda w: table(w.spark, w.sf_dir, "part").select(F.col("p_partkey").alias("i"), F.explode(F.sequence(F.lit(0), F.lit(3))).alias("j")).withColumn("w", dyadic(F.col("i"), F.col("j"), 5)), "SELECT p_partkey AS i, CAST(j AS INTEGER) AS j, ((7 * p_partkey + 13 * j + 5) % 17 - 8) / 16.0::DOUBLE AS w FROM part, range(4) b(j)")


def _rates(w):
    """Each supplier's rate for each model: of one rank where its large lines fill one minibatch at most, else of many."""
    lines = table(w.spark, w.sf_dir, "lineitem").where("l_quantity > 45").groupBy(F.col("l_suppkey").alias("supplier")).agg(F.when(F.count("*") > 64, "many").otherwise("one").alias("ranks"))
    rates = inline(w.spark, "model string, ranks string, rate double", [(m, r, v) for m, pair in RATES.items() for r, v in zip(("one", "many"), pair)])
    return lines.join(F.broadcast(rates), "ranks").select("supplier", "model", "ranks", "rate")


add("lr_table", _rates, """SELECT supplier, model, ranks, rate FROM (SELECT l_suppkey AS supplier, CASE WHEN count(*) > 64 THEN 'many' ELSE 'one' END AS ranks FROM lineitem WHERE l_quantity > 45 GROUP BY 1)
    JOIN (VALUES ('sage', 'one', 0.003::DOUBLE), ('sage', 'many', 0.006::DOUBLE), ('gat', 'one', 0.001::DOUBLE), ('gat', 'many', 0.001::DOUBLE)) AS t(model, ranks, rate) USING (ranks)""")


def _agg_error(w):
    """Root of squared differences between means over served neighbours and over all sampled ones, summed by rank."""

    def mean(blocks, tag):
        rows = blocks.where("layer = 0").join(w.features.withColumnRenamed("vid", "src"), "src")
        return rows.groupBy("rank", "it", "dst").agg(*[F.avg(F.get("x", F.lit(k))).alias(f"{tag}{k}") for k in range(W)])

    both = mean(w.plan.blocks, "a").join(mean(w.plan.exec_blocks, "b"), ["rank", "it", "dst"], "left")
    square = sum((F.pow(F.col(f"a{k}") - F.coalesce(f"b{k}", F.lit(0.0)), 2) for k in range(W)), F.lit(0.0))
    return both.groupBy("rank").agg(F.count("*").alias("rows"), millionths(F.sum(F.sqrt(square))).alias("error"))


_mean_sql = lambda src, tag: f"SELECT rank, it, dst, {', '.join(f'avg(x{k}) AS {tag}{k}' for k in range(W))} FROM {src} JOIN v_x ON vid = src WHERE layer = 0 GROUP BY rank, it, dst"
_square = " + ".join(f"pow(a{k} - coalesce(b{k}, 0), 2)" for k in range(W))
add("agg_error", _agg_error, sql(f"SELECT rank, count(*) AS rows, {m6(f'sum(sqrt({_square}))')} AS error FROM ({_mean_sql('lo_blocks', 'a')}) p LEFT JOIN ({_mean_sql('v_exec', 'b')}) q USING (rank, it, dst) GROUP BY rank"))

# --- measures over logs and times that the tables give ----------------------------------------------------------------------------



def _times(w):
    """(series, ranks, seconds): lines of the fullest rank, which stand for its seconds, if parts are dealt to so many ranks; a series for
    each return flag."""
    slots = table(w.spark, w.sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("series"), F.pmod("l_partkey", F.lit(16)).alias("slot")).agg(F.count("*").alias("n"))
    dealt = slots.withColumn("ranks", F.explode(F.array(*map(F.lit, (2, 4, 8, 16)))))
    return dealt.groupBy("series", "ranks", F.pmod("slot", "ranks").alias("rank")).agg(F.sum("n").alias("n")).groupBy("series", "ranks").agg(F.max("n").cast("double").alias("seconds"))


_speed = """WITH t AS (SELECT series, ranks, max(n)::DOUBLE AS seconds FROM (SELECT l_returnflag AS series, ranks, l_partkey % ranks AS rank, count(*) AS n FROM lineitem, (VALUES (2), (4), (8), (16)) AS r(ranks) GROUP BY ALL) GROUP BY series, ranks),
    b AS (SELECT series, min(ranks) AS r0, arg_min(seconds, ranks) AS s0 FROM t GROUP BY series) SELECT series, ranks, s0 / seconds AS speedup"""
add("speedup_table", lambda w: measures.speedup(_times(w)).drop("efficiency"), _speed + " FROM t JOIN b USING (series)")
add("scaling_efficiency", lambda w: measures.speedup(_times(w)).drop("speedup"), _speed.replace("s0 / seconds AS speedup", "s0 / seconds * r0 / ranks AS efficiency") + " FROM t JOIN b USING (series)")


def _fetched(w):
    """Rows that are fetched for every line against those that are fetched once for each part, by return flag."""
    lines = table(w.spark, w.sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("name"))
    return lines.agg(F.count("*").cast("double").alias("base"), F.count_distinct("l_partkey").cast("double").alias("optimised"))


add("ablation_gain", lambda w: measures.gain(_fetched(w)), "SELECT name, (base - optimised) / base AS share, base / optimised AS factor FROM (SELECT l_returnflag AS name, count(*)::DOUBLE AS base, count(DISTINCT l_partkey)::DOUBLE AS optimised FROM lineitem GROUP BY 1)")


def _log(w):
    """(run, epoch, accuracy, loss): by type of event and day, the share of the type's users that have come so far, and 1024s of those that
    have not. It rises to 1, which is a run's target."""
    e = table(w.spark, w.sf_dir, "events").where("event_type IS NOT NULL AND ts IS NOT NULL").select(F.col("event_type").alias("run"), "user_id", (F.dayofmonth("ts") - 1).alias("epoch"))
    new = e.groupBy("run", "user_id").agg(F.min("epoch").alias("epoch")).groupBy("run", "epoch").agg(F.count("*").alias("n"))
    days = e.select("run", "epoch").distinct().join(new, ["run", "epoch"], "left").na.fill(0, ["n"])
    known, total = (F.sum("n").over(w) for w in (Window.partitionBy("run").orderBy("epoch"), Window.partitionBy("run")))
    return days.select("run", "epoch", known.alias("known"), total.alias("total")).select("run", "epoch", (F.col("known") / F.col("total")).alias("accuracy"), ((F.col("total") - F.col("known")) / F.lit(1024.0)).alias("loss"))


_log_sql = """(SELECT run, epoch, known / total AS accuracy, CAST(total - known AS DOUBLE) / 1024.0::DOUBLE AS loss FROM (
    SELECT run, epoch, sum(n) OVER (PARTITION BY run ORDER BY epoch) AS known, sum(n) OVER (PARTITION BY run) AS total FROM (
      SELECT run, epoch, count(*) FILTER (epoch = first) AS n FROM (SELECT run, user_id, epoch, min(epoch) OVER (PARTITION BY run, user_id) AS first FROM (
        SELECT DISTINCT event_type AS run, user_id, CAST(day(ts) - 1 AS INTEGER) AS epoch FROM events WHERE event_type IS NOT NULL AND ts IS NOT NULL)) GROUP BY run, epoch))) AS l"""
_targets = lambda w: _log(w).groupBy("run").agg(F.max("accuracy").alias("target"))
_converged_sql = f"SELECT run, min(epoch) AS epoch FROM (SELECT *, max(accuracy) OVER (PARTITION BY run) AS target FROM {_log_sql}) WHERE target - accuracy < 0.01::DOUBLE GROUP BY run"
add("convergence_epoch", lambda w: measures.convergence_epoch(_log(w), _targets(w)), _converged_sql)
add("loss_moving_avg", lambda w: measures.loss_moving_average(_log(w)), f"SELECT *, avg(loss) OVER (PARTITION BY run ORDER BY epoch ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS smooth FROM {_log_sql}")


def _to_target(w):
    """Epochs to the target times the mean seconds of an epoch."""
    e = table(w.spark, w.sf_dir, "events").where("event_type IS NOT NULL AND ts IS NOT NULL").select(F.col("event_type").alias("run"), F.expr(SECOND).alias("s"), F.dayofmonth("ts").alias("day"))
    spans = e.groupBy("run").agg(((F.max("s") - F.min("s")) / F.count_distinct("day")).alias("seconds"))
    return measures.convergence_epoch(_log(w), _targets(w)).join(spans, "run").select("run", ((F.col("epoch") + 1) * F.col("seconds")).alias("total"))


add("time_to_target", _to_target, f"""SELECT run, (epoch + 1) * seconds AS total FROM ({_converged_sql})
    JOIN (SELECT event_type AS run, (max(floor(epoch(ts))) - min(floor(epoch(ts)))) / count(DISTINCT day(ts)) AS seconds FROM events WHERE event_type IS NOT NULL AND ts IS NOT NULL GROUP BY 1) USING (run)""")
SECOND = "timestampdiff(SECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', CAST(ts AS TIMESTAMP_NTZ))"
TYPES = ["click", "error", "purchase", "signup", "view"]


def _parts(w):
    """(run, epoch, part, seconds): seconds since a user's event before, by half of the day, day and type of event."""
    before = F.lag("s").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    e = table(w.spark, w.sf_dir, "events").withColumn("s", F.expr(SECOND))
    gaps = e.withColumn("gap", F.col("s") - before).where("gap IS NOT NULL")
    return gaps.select(F.when(F.hour("ts") < 12, "morning").otherwise("evening").alias("run"), (F.dayofmonth("ts") - 1).alias("epoch"), F.col("event_type").alias("part"), F.col("gap").cast("double").alias("seconds"))


_parts_sql = "(SELECT CASE WHEN hour(ts) < 12 THEN 'morning' ELSE 'evening' END AS run, day(ts) - 1 AS epoch, event_type AS part, (s - lag(s) OVER (PARTITION BY user_id ORDER BY ts, event_id))::DOUBLE AS seconds FROM (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS s FROM events)) AS t"
add("time_breakdown", lambda w: _parts(w).groupBy("run", "part").agg(F.avg("seconds").alias("seconds")), f"SELECT run, part, avg(seconds) AS seconds FROM {_parts_sql} WHERE seconds IS NOT NULL GROUP BY run, part")
add("breakdown_pivot", lambda w: _parts(w).groupBy("run").pivot("part", TYPES).agg(F.avg("seconds")), "SELECT run, " + ", ".join(f"avg(seconds) FILTER (part = '{p}') AS {p}" for p in TYPES) + f" FROM {_parts_sql} WHERE seconds IS NOT NULL GROUP BY run")
add("byte_op_ratio", lambda w: w.plan.exec_blocks.groupBy("layer").agg((F.count("*") * 3072).alias("bytes"), (F.count("*") * 256).alias("ops"), F.lit(measures.byte_op_ratio(256)).alias("ratio")), sql("SELECT layer, count(*) * 3072 AS bytes, count(*) * 256 AS ops, 12.0::DOUBLE AS ratio FROM v_exec GROUP BY layer"))

# --- training: no SQL can follow it; tests hold it against exact references --------------------------------------------------------


def trained(w, mode: str, kind: str = "sage", epochs: int = 2, d: int = 1, **more):
    """A run on the executors, kept for the queries that read its log."""
    from dataclasses import replace

    from ..plans.epoch import SampleConfig

    key = (mode, kind, epochs, d, *sorted(more.items()))
    if key not in w.runs:
        cfg = TrainConfig(ModelSpec(kind, (16, 32, 6), dropout=0.0), SampleConfig((10, 3), 64), replace(w.spec, d=d), mode, epochs, rate=0.01, **more)
        w.runs[key] = train(w.pg, w.trained_features, w.trained_labels, cfg)
    return w.runs[key]


def training_log(mode: str, kind: str = "sage", epochs: int = 2, **more):
    def run(w):
        r = trained(w, mode, kind, epochs, **more)
        return inline(w.spark, "epoch int, rounds int, loss double, train_accuracy double, edges double", [(m["epoch"], m["rounds"], float(m["loss"]), float(m["train_accuracy"]), float(m["edges"])) for m in r.log])

    return run


add("train_push_log", training_log("push"))
add("train_push_gat_log", training_log("push", "gat", 1))
add("train_pull_log", training_log("pull"))
add("train_no_remote_log", training_log("none", epochs=1))
add("train_sync_log", training_log("push", epochs=1, d=0))
add("train_step_engine_log", training_log("push", epochs=1, engine="step"))

# measures of runs: seconds differ from run to run, so only their form is checked here and their arithmetic in the tests


def _runs(w) -> list[tuple[str, object]]:
    return [("push", trained(w, "push")), ("pull", trained(w, "pull"))]


def _of_runs(w, measure):
    out = None
    for name, r in _runs(w):
        df = measure(r.times).select(F.lit(name).alias("run"), "*")
        out = df if out is None else out.unionByName(df)
    return out


add("measured_parts", lambda w: _of_runs(w, lambda t: measures.forward_with_remote(measures.epoch_parts(t))))
add("measured_waiting", lambda w: _of_runs(w, measures.waiting))


def _hidden(w):
    """All planned pushes are carried out in both runs."""
    runs = [trained(w, "push", epochs=1, d=d, used_only=False) for d in (1, 0)]
    return measures.hidden(*[(r.times, r.plans[0].push_plan) for r in runs])


add("measured_hidden", _hidden)
add("measured_imbalance", lambda w: _of_runs(w, measures.time_imbalance))
add("measured_epoch_time", lambda w: inline(w.spark, "run string, epoch int, seconds double", [(name, m["epoch"], float(m["run_seconds"])) for name, r in _runs(w) for m in r.log]))
add("measured_gain", lambda w: measures.gain(inline(w.spark, "name string, base double, optimised double", [("push over pull", *(min(float(m["run_seconds"]) for m in r.log) for _, r in reversed(_runs(w))))])))
add("sampled_inference", lambda w: infer.predict_nodes(infer.sampled(w.pg, w.train, w.trained_features, ModelSpec("sage", (16, 32, 6), dropout=0.0), trained(w, "push").params, w.sample_two)))
