"""SimHash near-duplicate detection by a self-join of binary tries.

Fingerprints are gathered once per distinct value. Two fingerprints at distance 4 or less differ in at most 2 of their upper 32 bits, or
in at most 1 of their lower 32 bits. So the self-join runs over two tries: one on the bits in order with a budget of 2 for the first 32
levels, one on the rotated bits with a budget of 1 there; both have a budget of 4 below. Larger distances take more tries, each on bits
rotated further. Pairs of nodes are traversed together, the differing bits add up, and a pair is left as soon as its budget is exceeded. The top levels are dealt out: every pair of prefixes within
the budget is one group, and each group gives a spanning forest of its links, never all pairs. Forests are merged by alternating star
contractions over tables in the shared folder.

Null and empty texts have fingerprint zero and link like any other. Texts of fewer than four words are one shingle. Repeated rows keep
one row each. An empty table gives an empty result. Exact copies, however many, are one fingerprint in the join.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship_package
from .common import materialise, observed

SHINGLE = 4
SEED = 42
DISTANCE = 4


def tries(distance: int, n: int = 2) -> list[tuple[int, int, int]]:
    """(rotation, levels, budget of those levels) of the n tries that find all pairs within the distance: if every part of the bits had
    more errors than its budget, they would add up to more than the distance."""
    levels, spare = 64 // n, distance + 1 - n
    return [(k * levels, levels, spare // n + (k < spare % n)) for k in range(n)]


#: distinct fingerprints that a prefix should hold on average
PREFIX_TARGET = 16_384
#: pairs of nodes that are traversed at once, and the product of two nodes' sizes below which their leaves are compared at once
FRONTIER, LEAF = 1_000_000, 12

_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).astype(np.int64)


def fingerprint(text: str | bytes | None) -> int:
    """The 64-bit fingerprint of one text."""
    data = text.encode() if isinstance(text, str) else text or b""
    words = data.lower().split()  # of bytes: A-Z only, and exactly the six ASCII white spaces
    n = len(words)
    if not n:
        return 0
    line, digest = b" ".join(words), xxhash.xxh64_intdigest
    if n <= SHINGLE:
        return digest(line, SEED)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, n) + 1) - 1
    first = np.concatenate(([0], ends[:-1] + 1))[: n - SHINGLE + 1].tolist()
    m = n - SHINGLE + 1
    return _majority(np.fromiter((digest(line[a:b], SEED) for a, b in zip(first, ends[SHINGLE - 1 :].tolist(), strict=True)), np.uint64, m))


def _majority(hashes: np.ndarray) -> int:
    """The bits that are set in over half of the hashes."""
    octets = hashes.astype(">u8").view(np.uint8).reshape(len(hashes), 8)
    ones = np.concatenate([np.bincount(octets[:, k], minlength=256) @ _BITS for k in range(8)])
    return int.from_bytes(np.packbits(2 * ones > len(hashes)).tobytes(), "big")


def word_fingerprint(text: str | bytes | None) -> int:
    """The fingerprint of a text's distinct words. It moves far less than that of shingles when a few words change."""
    data = text.encode() if isinstance(text, str) else text or b""
    words = set(data.lower().split())
    return _majority(np.fromiter((xxhash.xxh64_intdigest(w, SEED) for w in words), np.uint64, len(words))) if words else 0


def with_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", of: Callable[[bytes | None], int] = fingerprint) -> DataFrame:
    """One row (doc_id, fp) per input row; fp holds the unsigned value's bits in a long."""
    ship_package(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = b.column(1).cast(pa.large_binary())
            got = np.fromiter((of(t.as_py()) for t in texts), np.uint64, len(b))
            yield pa.record_batch([b.column(0), pa.array(got.view(np.int64))], names=["doc_id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, fp long")


# --- the trie self-join inside one group ------------------------------------------------------------------------------------


def _split(values: np.ndarray, lo: np.ndarray, hi: np.ndarray, depth: int) -> np.ndarray:
    """Where the children with bit `depth` set begin, for nodes that are ranges of the sorted values."""
    low = values[lo] >> np.uint64(64 - depth) << np.uint64(64 - depth) if depth else np.zeros(len(lo), np.uint64)
    return np.clip(np.searchsorted(values, low | np.uint64(1 << (63 - depth))), lo, hi)


def node_pairs(a: np.ndarray, b: np.ndarray | None, upper: int, distance: int = DISTANCE, depth: int = 0, spent: int = 0, levels: int = 32) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs (i in a, j in b) of sorted values within the distance, of it at most `upper` in the first levels; b None: pairs i < j
    inside a. depth: levels that both sides share among themselves, spent: bits in which the two sides differ there."""
    own = b is None
    b = a if own else b
    if not len(a) or not len(b):
        return
    one = np.ones(1, np.int64)
    stack = [(depth, 0 * one, len(a) * one, 0 * one, len(b) * one, spent * one)]
    while stack:
        depth, la, ha, lb, hb, err = stack.pop()
        if len(la) > FRONTIER:
            half = len(la) // 2
            stack += [(depth, *(x[:half] for x in (la, ha, lb, hb, err))), (depth, *(x[half:] for x in (la, ha, lb, hb, err)))]
            continue
        product = (ha - la) * (hb - lb)
        leaf = (product <= LEAF) | (depth == 64)
        if leaf.any():
            yield from _compare(a, b, own, la[leaf], ha[leaf], lb[leaf], hb[leaf], upper, distance, levels)
        go = ~leaf
        if not go.any():
            continue
        la, ha, lb, hb, err = (x[go] for x in (la, ha, lb, hb, err))
        ma, mb = _split(a, la, ha, depth), _split(b, lb, hb, depth)
        same = own & (la == lb) & (ha == hb)
        kids = [(la, ma, lb, mb, err, None), (ma, ha, mb, hb, err, None), (la, ma, mb, hb, err + 1, None), (ma, ha, lb, mb, err + 1, ~same)]
        budget = upper if depth < levels else distance
        parts = []
        for c0, c1, d0, d1, e, also in kids:
            ok = (c1 > c0) & (d1 > d0) & (e <= budget)
            ok = ok if also is None else ok & also
            parts.append(tuple(x[ok] for x in (c0, c1, d0, d1, e)))
        merged = [np.concatenate(x) for x in zip(*parts, strict=True)]
        if len(merged[0]):
            stack.append((depth + 1, *merged))


def _compare(a, b, own, la, ha, lb, hb, upper, distance, levels):
    """Leaves of small pairs of nodes, compared directly. Nodes of equal values at level 64 can't come up: values are distinct."""
    wide = hb - lb
    n = (ha - la) * wide
    for at in range(0, len(n), FRONTIER // LEAF):
        part = slice(at, at + FRONTIER // LEAF)
        m = n[part]
        inside = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
        w = np.repeat(wide[part], m)
        i, j = np.repeat(la[part], m) + inside // w, np.repeat(lb[part], m) + inside % w
        if own:
            i, j = i[keep := i < j], j[keep]
        x = a[i] ^ b[j]
        ok = (np.bitwise_count(x) <= distance) & (np.bitwise_count(x >> np.uint64(64 - levels)) <= upper)
        if ok.any():
            yield i[ok], j[ok]


def _roots(n: int, pairs: Iterator[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
    """Smallest index reachable, for n items; pairs are merged as they come and never kept."""
    root = np.arange(n)
    for i, j in pairs:
        while True:
            ri, rj = root[i], root[j]
            if not (differ := ri != rj).any():
                break
            i, j = i[differ], j[differ]
            high, low = np.maximum(ri, rj)[differ], np.minimum(ri, rj)[differ]
            np.minimum.at(root, high, low)
            while not np.array_equal(up := root[root], root):
                root = up
    return root


def _turn(x: np.ndarray, k: int) -> np.ndarray:
    return x << np.uint64(k) | x >> np.uint64(64 - k) if k else x


def _group_pairs(table: pa.Table, distance: int, n: int = 2) -> tuple[np.ndarray, Iterator[tuple[np.ndarray, np.ndarray]]]:
    """The fingerprints of one pair of prefixes, and the pairs of their positions within the distance."""
    rotation, levels, upper = tries(distance, n)[table.column("trie")[0].as_py()]
    values = table.column("fp").to_numpy().view(np.uint64)
    side = table.column("side").to_numpy()
    spent, bits = table.column("spent")[0].as_py(), table.column("bits")[0].as_py()
    a, b = (np.unique(_turn(values[side == k], rotation)) for k in (0, 1))
    if spent == 0:
        both, pairs = a, node_pairs(a, None, upper, distance, bits, 0, levels)
    else:
        both, pairs = np.concatenate([a, b]), ((i, j + len(a)) for i, j in node_pairs(a, b, upper, distance, bits, spent, levels))
    return _turn(both, 64 - rotation if rotation else 0), pairs


def _forest(table: pa.Table, distance: int, n: int = 2) -> pa.Table:
    """The links of one pair of prefixes as edges from each fingerprint to the smallest that it reaches here."""
    values, pairs = _group_pairs(table, distance, n)
    root = _roots(len(values), pairs)
    far = root != np.arange(len(values))
    signed = values.view(np.int64)
    return pa.table({"u": signed[far], "v": signed[root[far]]})


def dealt(distinct: DataFrame, count: int, distance: int, n: int = 2, target: int = PREFIX_TARGET) -> DataFrame:
    """The `count` fingerprints of column fp, each dealt to the pairs of prefixes that it can have links in; further columns go along."""
    bits = min(24, 64 // n, max(3, math.ceil(math.log2(max(1, count / target)))))
    parts = None
    for k, (rotation, _, upper) in enumerate(tries(distance, n)):
        masks = [sum(1 << x for x in c) for r in range(min(upper, bits) + 1) for c in combinations(range(bits), r)]
        turned = F.col("fp") if not rotation else F.shiftleft("fp", rotation).bitwiseOR(F.shiftrightunsigned("fp", 64 - rotation))
        prefix = F.shiftrightunsigned(turned, 64 - bits).cast("int")
        rows = (
            distinct.withColumns({"p": prefix, "m": F.explode(F.array(*map(F.lit, masks)))})
            .withColumn("q", F.col("p").bitwiseXOR(F.col("m")))
            .select(
                F.lit(k).alias("trie"), F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"),
                (F.col("p") > F.col("q")).cast("int").alias("side"), F.bit_count("m").cast("int").alias("spent"), F.lit(bits).alias("bits"), *distinct.columns,
            )
        )
        parts = rows if parts is None else parts.unionByName(rows)
    return parts


def links(distinct: DataFrame, count: int, distance: int = DISTANCE, n: int = 2, target: int = PREFIX_TARGET) -> DataFrame:
    """Edges (u, v) that connect exactly what is linked among the `count` distinct fingerprints of column fp."""
    return dealt(distinct, count, distance, n, target).groupBy("trie", "a", "b").applyInArrow(lambda t: _forest(t, distance, n), "u long, v long")


# --- components over all groups ---------------------------------------------------------------------------------------------

SALTS = 16


def _with_least(edges: DataFrame) -> DataFrame:
    """Edges (u, v) with the smallest neighbour m of u. The pre-aggregated minimum is spread over salts, so a hub's edges are too."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    spread = least.select("u", "m", F.explode(F.array(*map(F.lit, range(SALTS)))).alias("salt"))
    return edges.withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(SALTS)).cast("int")).join(spread, ["u", "salt"]).select("u", "v", "m")


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(u, root) for every vertex other than its component's smallest, by alternating large-star and small-star contractions."""
    def put(e: DataFrame) -> tuple[DataFrame, tuple]:
        out, m = observed(e, "edges", n=F.count(F.lit(1)), h=F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")))
        return out, (m["n"], m["h"])

    edges, before = put(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    for _ in range(rounds):
        if not before[0]:
            break
        mirrored = edges.union(edges.select("v", "u"))
        large = _with_least(mirrored).where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v"))
        large = large.where("u <> v").distinct()
        small = _with_least(large)
        again = small.select(F.col("v").alias("u"), F.col("m").alias("v")).union(small.select("u", F.col("m").alias("v")))
        edges, after = put(again.where("u <> v").distinct())
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("the contraction did not settle")
    return edges.select("u", F.col("v").alias("root"))


def near_duplicates(docs: DataFrame, distance: int = DISTANCE) -> DataFrame:
    """One row per input row: doc_id, fp (long) and component_id, the smallest doc_id reachable by links of at most `distance` bits."""
    return linked(materialise(with_fingerprints(docs), "prints"), distance)


def linked(prints: DataFrame, distance: int = DISTANCE) -> DataFrame:
    """The same from a table of (doc_id, fp)."""
    distinct = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    stars = components(links(distinct.select("fp"), distinct.count(), distance))
    rooted = distinct.join(stars.withColumnRenamed("u", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    smallest = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    spread = smallest.select("root", "component_id", F.explode(F.array(*map(F.lit, range(SALTS)))).alias("salt"))
    rooted = rooted.withColumn("salt", F.pmod(F.xxhash64("fp"), F.lit(SALTS)).cast("int"))
    named = materialise(rooted.join(spread, ["root", "salt"]).select("fp", "component_id"), "named")
    # both sides come straight from tables, so that Spark can split a fingerprint that many rows share
    return prints.join(named, "fp").select("doc_id", "fp", "component_id")


# --- near copies by similarity: fingerprints propose, shingles decide -----------------------------------------------------------

SIMILAR, WORDS = 0.8, 5
#: fingerprints of distinct words within so many bits are compared; their tries, and how many a prefix should hold
WORD_DISTANCE, WORD_TRIES, WORD_TARGET = 7, 4, 1024
#: bins of a sketch, one byte each
BINS = 512
#: documents of either side that are compared in one task
SIDE = 256
#: ids up to which a list of ids is broadcast (8 bytes each); longer ones are joined by a shuffle
FEW_IDS = 1_000_000


def shingle_set(text: str | bytes | None) -> np.ndarray:
    """Hashes of the distinct five-word shingles; a shorter text is one shingle."""
    data = text.encode() if isinstance(text, str) else text or b""
    w = data.lower().split()
    return np.unique(np.fromiter((xxhash.xxh64_intdigest(b" ".join(w[i : i + WORDS]), SEED) for i in range(max(1, len(w) - WORDS + 1))), np.uint64))


def sketch(text: str | bytes | None) -> np.ndarray:
    """Of each bin of the text's shingles one byte of the least hash, from 1 on; 0 where the bin is empty."""
    h = shingle_set(text)  # sorted, so the first of a bin is its least
    bins, first = np.unique(h // np.uint64((1 << 64) // BINS), return_index=True)
    out = np.zeros(BINS, np.uint8)
    out[bins.astype(np.int64)] = h[first] % np.uint64(255) + np.uint64(1)
    return out


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Estimated Jaccard similarities of rows of sketches: the share of equal bins among those that are not empty on both sides, less what
    equal bytes come to by chance. Its standard error is 0.018 at a similarity of 0.8; small texts are nearly exact."""
    some = np.maximum(1, ((a | b) != 0).sum(1))
    both = ((a != 0) & (b != 0)).sum(1)
    same = ((a == b) & (a != 0)).sum(1)
    return (same - (both - same) / 254) / some


def _sketches(docs: DataFrame) -> DataFrame:
    ship_package(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.record_batch([b.column(0), pa.array([sketch(t.as_py()).tobytes() for t in b.column(1).cast(pa.large_binary())], pa.binary())], names=["doc_id", "s"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, s binary")


def _by_ids(docs: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """Semi or anti join by doc_id. Whole texts are only shuffled where the list of ids is too long to be sent around."""
    return docs.join(F.broadcast(ids) if ids.count() <= FEW_IDS else ids, "doc_id", how)


def _matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(-1, BINS)


def _alike(pairs: DataFrame, sketches: DataFrame, similar: float) -> DataFrame:
    """Of the pairs (x, y) of ids those whose sketches are that similar, as (u, v) with u the larger id."""
    pairs = pairs.select(F.greatest("x", "y").alias("x"), F.least("x", "y").alias("y")).where("x <> y").distinct()
    joined = pairs.join(sketches.select(F.col("doc_id").alias("x"), F.col("s").alias("sx")), "x").join(sketches.select(F.col("doc_id").alias("y"), F.col("s").alias("sy")), "y")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            good = pa.array(likeness(_matrix(b.column(2)), _matrix(b.column(3))) >= similar)
            yield pa.record_batch([b.column(0).filter(good), b.column(1).filter(good)], names=["u", "v"])

    return joined.select("x", "y", "sx", "sy").mapInArrow(run, "u long, v long")


def _blocks(table: pa.Table, distance: int) -> pa.Table:
    """The documents of one pair of prefixes, dealt to pairs of blocks of at most SIDE documents: whoever has a proposed link there that
    is not settled yet. So a ball of many documents is not written out as pairs."""
    values, pairs = _group_pairs(table, distance, WORD_TRIES)
    doc, root = (table.column(c).to_numpy() for c in ("doc_id", "root"))
    order = np.argsort(values, kind="stable")
    owner = order[np.searchsorted(values, table.column("fp").to_numpy().view(np.uint64), sorter=order)]
    by = np.lexsort((doc, owner))
    owner, doc, root = owner[by], doc[by], root[by]
    ends = np.searchsorted(owner, np.arange(len(values) + 1))
    one = root[ends[:-1]]
    several = np.zeros(len(values), bool)
    np.logical_or.at(several, owner, root != one[owner])
    first, last = ends[:-1] // SIDE, (ends[1:] - 1) // SIDE
    n, width = int(last.max()) + 1, len(doc)
    codes = [np.zeros(0, np.int64)]

    def put(i: np.ndarray, j: np.ndarray) -> None:
        """Documents (positions) i and j meet in the task of their blocks."""
        task = (i // SIDE) * n + j // SIDE
        codes.append(np.unique(np.concatenate([task * width + i, task * width + j])))
        if sum(map(len, codes)) > 4 * FRONTIER:
            codes[:] = [np.unique(np.concatenate(codes))]

    def all_of(i: int, j: int) -> None:
        a, b = np.arange(ends[i], ends[i + 1]), np.arange(ends[j], ends[j + 1])
        for x in np.split(a, np.arange(SIDE - ends[i] % SIDE, len(a), SIDE)):
            for y in np.split(b, np.arange(SIDE - ends[j] % SIDE, len(b), SIDE)):
                put(np.concatenate([x, np.full(len(y), x[0])]), np.concatenate([np.full(len(x), y[0]), y]))

    single = ends[1:] - ends[:-1] == 1
    for i, j in pairs:
        i, j = np.minimum(i, j), np.maximum(i, j)
        go = (one[i] != one[j]) | several[i] | several[j]
        i, j = i[go], j[go]
        easy = single[i] & single[j]
        put(ends[i[easy]], ends[j[easy]])
        for x, y in zip(i[~easy].tolist(), j[~easy].tolist(), strict=True):
            all_of(x, y)
    if table.column("trie")[0].as_py() == 0 and table.column("spent")[0].as_py() == 0:
        for x in np.flatnonzero(several).tolist():  # texts of one fingerprint
            all_of(x, x)
    code = np.unique(np.concatenate(codes))
    at = code % width
    return pa.table({"trie": pa.array(np.full(len(at), table.column("trie")[0].as_py(), np.int32)), **{c: pa.array(np.full(len(at), table.column(c)[0].as_py(), np.int32)) for c in ("a", "b")}, "block": code // width, "fp": values[owner[at]].view(np.int64), "doc_id": doc[at], "root": root[at]})


def _settled(table: pa.Table, distance: int, similar: float) -> pa.Table:
    """A spanning forest of the similar pairs in one task's documents, where their roots differ."""
    doc, fp, root = (table.column(c).to_numpy() for c in ("doc_id", "fp", "root"))
    s = _matrix(table.column("s"))
    i, j = np.triu_indices(len(doc), 1)
    fp = fp.view(np.uint64)
    near = (np.bitwise_count(fp[i] ^ fp[j]) <= distance) & (root[i] != root[j])
    i, j = i[near], j[near]
    top = np.unique(root, return_inverse=True)[1]
    u, v = [], []
    for at in range(0, len(i), 4096):
        a, b = i[at : at + 4096], j[at : at + 4096]
        apart = top[a] != top[b]
        a, b = a[apart], b[apart]
        good = likeness(s[a], s[b]) >= similar
        for x, y in zip(a[good].tolist(), b[good].tolist(), strict=True):
            if top[x] != top[y]:
                top[top == top[y]] = top[x]
                u.append(max(doc[x], doc[y]))
                v.append(min(doc[x], doc[y]))
    return pa.table({"u": pa.array(u, pa.int64()), "v": pa.array(v, pa.int64())})


def similar_documents(docs: DataFrame, similar: float = SIMILAR, distance: int = WORD_DISTANCE, prints: DataFrame | None = None) -> DataFrame:
    """(u, root) for each doc_id that a chain of pairs with a similarity of at least `similar` joins to a smaller one. Candidates are all
    pairs whose word fingerprints the trie join finds within the distance, and sketches of five-word shingles decide. prints: (doc_id,
    fp) of the documents to compare, all of docs unless given.

    First each document is compared with the smallest fingerprint that its own reaches in a group, which settles copies of one another
    however many they are. Where a candidate component is not one class by then, its documents meet in blocks of SIDE by SIDE, and
    pairs that are already joined are not compared again."""
    prints = materialise(with_fingerprints(docs, of=word_fingerprint), "word-prints") if prints is None else prints
    reps = materialise(prints.groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")), "word-reps")
    proposed = materialise(links(reps.select("fp"), reps.count(), distance, WORD_TRIES, WORD_TARGET).distinct(), "proposed")
    balls = materialise(components(proposed), "balls")  # (u, root) of fingerprints
    ball = balls.select(F.col("u").alias("fp"), F.col("root").alias("ball")).union(balls.select("root", "root").distinct())
    ball = materialise(ball.union(reps.where("n > 1").select("fp", "fp").join(ball.select("fp"), "fp", "left_anti").select("fp", "fp")), "ball")
    members = materialise(prints.join(ball, "fp").select("doc_id", "fp", "ball"), "members")
    sketches = materialise(_sketches(_by_ids(docs.select("doc_id", "text"), members.select("doc_id").distinct(), "left_semi")), "sketches")
    rep = reps.select("fp", "rep")
    stars = proposed.join(prints.select(F.col("fp").alias("u"), F.col("doc_id").alias("x")), "u").join(rep.select(F.col("fp").alias("v"), F.col("rep").alias("y")), "v").select("x", "y")
    stars = stars.union(members.join(rep, "fp").select(F.col("doc_id").alias("x"), F.col("rep").alias("y")))
    found = materialise(_alike(stars, sketches, similar), "found")
    tops = materialise(components(found).withColumnRenamed("u", "doc_id"), "tops")
    rooted = materialise(members.join(tops, "doc_id", "left").withColumn("root", F.coalesce("root", "doc_id")), "rooted")
    open_balls = rooted.groupBy("ball").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("ball")
    left = materialise(rooted.join(open_balls, "ball", "left_semi").select("fp", "doc_id", "root"), "left")
    if count := left.count():
        blocks = dealt(left, count, distance, WORD_TRIES, WORD_TARGET).groupBy("trie", "a", "b").applyInArrow(lambda t: _blocks(t, distance), "trie int, a int, b int, block long, fp long, doc_id long, root long")
        tasks = materialise(blocks, "blocks").join(sketches, "doc_id").groupBy("trie", "a", "b", "block")
        found = found.union(materialise(tasks.applyInArrow(lambda t: _settled(t, distance, similar), "u long, v long"), "found"))
    return components(found)


def drop_near_duplicates(docs: DataFrame, similar: float | None = SIMILAR) -> DataFrame:
    """Of each group of near copies the row with the smallest doc_id stays, with the input's columns. Groups are components of links
    between shingle fingerprints and then, unless `similar` is None, of similarities of at least that among what is left.
    Repeated ids keep one row; rows without an id stay. Decisions are made on narrow tables; texts are filtered at the end."""
    texts = docs.where("doc_id IS NOT NULL").select("doc_id", "text")
    classes = materialise(near_duplicates(texts), "classes")
    gone = classes.where("doc_id <> component_id").select("doc_id").distinct()
    if similar is not None:
        gone = materialise(gone, "gone")
        left = _by_ids(texts, gone, "left_anti")
        words = materialise(with_fingerprints(left, of=word_fingerprint).distinct(), "word-prints")
        gone = gone.union(similar_documents(texts, similar, prints=words).select(F.col("u").alias("doc_id")))
    left = _by_ids(docs, materialise(gone.distinct(), "gone"), "left_anti")
    repeated = materialise(docs.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id"), "repeated")
    if not repeated.count():
        return left
    several = _by_ids(left, repeated, "left_semi").select("doc_id", F.struct(*[docs[c] for c in docs.columns]).alias("row"))
    key = F.xxhash64(*[F.col("row")[c].cast("string") for c in docs.columns])
    single = several.withColumn("key", key).groupBy("doc_id").agg(F.min_by("row", "key").alias("row")).select("row.*")
    return _by_ids(left, repeated, "left_anti").select(*docs.columns).union(single)


def op8_simhash_trie(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return near_duplicates(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
