"""Bulk-synchronous best-fit packing of tokenised documents into sequences.

Pieces are range-sorted by length over the cluster, and a piece is known by its length and its rank among those of that length. Lengths
are whole numbers up to the sequence size, so equal documents, and equal gaps, are swept as runs (a first rank or sequence, and a count):
a hot length is one run. Runs of documents and of gaps are dealt to RANGES ranges of sizes. In a superstep every range sweeps its own in
ascending order, all ranges at once: a gap takes the longest free document that is not longer, and the same length again where that
fits and is there for every gap of its run; which gap gets which document is settled by rank within the runs. Then gaps are updated: a
gap that took a document is swept again in its range, or goes to the range of its new size, and one that found none goes to the next
lower range that still has documents. Supersteps repeat until no gap can take anything; the longest
documents left then open new sequences, never more at once than their tokens need. At last pieces look up their place by length and rank.
The driver sees sums for each range, and at the end the runs of the plan, which depend on the sequence size and not on the input.

Null text is an empty document, which is its closing id alone. Repeated rows are packed once each, with the doc_id that they have, null
too. An empty table gives an empty result. Other columns of the input are left out.
Only documents longer than a sequence are cut, into full pieces of which the first may be shorter.
"""

from __future__ import annotations

import json
import re
import zlib
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship_package
from .common import materialise, observed

SIZE = 2048
END_ID = 0
#: ranges of sizes that are swept at once
RANGES = 8
LONG_SPACE = re.compile(r"\s{2000}")
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
PLACED = PIECES + ", sequence_id long, offset long"


# --- tokens -----------------------------------------------------------------------------------------------------------------

_ENCODERS: dict[str, object] = {}


class Encoder:
    """Byte-level BPE of a tokenizers file. Its ranks are run by tiktoken, which gives the same ids several times faster; texts that
    hold the string of a special token go to tokenizers itself, and so do those with very long white space, on which tiktoken's splitting
    runs out of stack."""

    def __init__(self, path: str) -> None:
        import tiktoken
        from tokenizers import Tokenizer

        self.plain = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.fast = None
        pre = spec["pre_tokenizer"] or {}
        if pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and spec["normalizer"] is None and not spec["model"].get("ignore_merges"):
            to_byte = _byte_of_letter()
            ranks = {bytes(to_byte[c] for c in piece): i for piece, i in spec["model"]["vocab"].items() if piece not in self.special}
            # Fixed value: the published splitting pattern of this family of tokenizers.
            pattern = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
            self.fast = tiktoken.Encoding("packing", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})

    def ids(self, text: str) -> np.ndarray:
        if self.fast is None or LONG_SPACE.search(text) or any(s in text for s in self.special):
            return np.array(self.plain.encode(text, add_special_tokens=False).ids, "<u4")
        return np.array(self.fast.encode_ordinary(text), "<u4")


def _byte_of_letter() -> dict[str, int]:
    """Byte-level BPE writes bytes as letters: printable ones as themselves, the rest from code point 256 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


def encoder(path: str) -> Encoder:
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def document_ids(text: str | None, path: str) -> np.ndarray:
    return np.append(encoder(path).ids(text or ""), np.uint32(END_ID)).astype("<u4")


def cuts(n: int, size: int = SIZE) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: full ones, after a first that takes what is over."""
    if n <= size:
        return [(0, n)]
    first = n % size or size
    return [(0, first), *((s, size) for s in range(first, n, size))]


def pieces(docs: DataFrame, tokenizer: str, size: int = SIZE) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows: list[tuple] = []
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = document_ids(text.as_py(), tokenizer)
                rows += [(doc_id, k, s, n, zlib.crc32(ids[s : s + n].tobytes())) for k, (s, n) in enumerate(cuts(len(ids), size))]
            names = ("doc_id", "piece", "start", "length", "ids_crc32")
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)] if rows else [pa.array([], t) for t in kinds], names=names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text")).mapInArrow(run, PIECES)


# --- the plan over runs -----------------------------------------------------------------------------------------------------

FREE, GAP, PUT = 0, 1, 2
#: kind FREE: n documents of a size from rank `first` on; GAP: n gaps of a size in sequences from `first` on; PUT: n documents of a size
#: from rank `first` on, placed in sequences from `seq` on, each in a gap of `gap`. place: the range that sweeps the run next.
RUNS = "kind int, size long, first long, n long, gap long, seq long, place int"


def range_of(size: int | np.ndarray, most: int):
    return size * RANGES // (most + 1)


def sweep(t: pa.Table, most: int) -> pa.Table:
    """One superstep of one range: sweeps until no gap of its own sizes is new."""
    runs = [tuple(r.values()) for r in t.select(["size", "kind", "first", "n"]).to_pylist()]
    here = t.column("place")[0].as_py()
    out: list[tuple] = []
    while runs:
        free: list[list[int]] = []  # [size, first, n], the longest last
        again = []
        for size, kind, first, n in sorted(runs):
            if kind == FREE:
                free.append([size, first, n])
                continue
            while n and free:
                top = free[-1]
                use = min(n, top[2])
                # what is longest for a gap is longest again for what it leaves, as often as it fits and there is one for every gap
                each = min(size // top[0], top[2] // use)
                out += [(PUT, top[0], top[1] + k * use, use, size - k * top[0], first, here) for k in range(each)]
                left = size - each * top[0]
                if left and range_of(left, most) == here:
                    again.append((left, GAP, first, use))
                elif left:
                    out.append((GAP, left, first, use, None, None, range_of(left, most)))
                top[1], top[2], first, n = top[1] + each * use, top[2] - each * use, first + use, n - use
                if not top[2]:
                    free.pop()
            if n:
                out.append((GAP, size, first, n, None, None, here - 1))
        runs = [(size, FREE, first, n) for size, first, n in free] + again if again else []
    out += [(FREE, size, first, n, None, None, here) for size, first, n in free]
    kinds = (pa.int32(), *[pa.int64()] * 5, pa.int32())
    return pa.table([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=[f.split()[0] for f in RUNS.split(", ")])


def opened(state: DataFrame, n_sequences: int, most: int, need: int | None) -> DataFrame:
    """The state after the `need` longest free documents (None: all that are longer than half a sequence) have begun new sequences. Gaps of
    before go: nothing that is left fits them."""
    free = state.where(f"kind = {FREE}")  # a run for each size, so the window below has at most `most` rows
    before = F.coalesce(F.sum("n").over(Window.orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    take = F.when(F.col("size") * 2 > most, F.col("n")).otherwise(0) if need is None else F.greatest(F.lit(0), F.least(F.col("n"), F.lit(need) - F.col("before")))
    cut = free.withColumn("before", before).withColumn("take", take.cast("long")).withColumn("new", F.col("before") + n_sequences)
    none = F.lit(None).cast("long")
    rest = F.struct(F.lit(FREE).alias("kind"), "size", (F.col("first") + F.col("take")).alias("first"), (F.col("n") - F.col("take")).alias("n"), none.alias("gap"), none.alias("seq"), "place")
    put = F.struct(F.lit(PUT).alias("kind"), "size", "first", F.col("take").alias("n"), F.lit(most).cast("long").alias("gap"), F.col("new").alias("seq"), "place")
    left = F.lit(most).cast("long") - F.col("size")
    gap = F.struct(F.lit(GAP).alias("kind"), left.alias("size"), F.col("new").alias("first"), F.when(left > 0, F.col("take")).otherwise(0).alias("n"), none.alias("gap"), none.alias("seq"), F.floor(left * RANGES / (most + 1)).cast("int").alias("place"))
    made = cut.select(F.inline(F.array(*[x.cast(f"struct<{RUNS.replace(' ', ':').replace(',:', ',')}>") for x in (rest, put, gap)]))).where("n > 0")
    return made


def plan(lengths: DataFrame, size: int = SIZE) -> DataFrame:
    """RUNS of kind PUT for (length, n), a row for each length."""
    spark = lengths.sparkSession
    place = F.floor(F.col("length") * RANGES / (size + 1)).cast("int")
    none = F.lit(None).cast("long")
    state = lengths.select(
        F.lit(FREE).alias("kind"), F.col("length").cast("long").alias("size"), F.lit(0).cast("long").alias("first"), F.col("n").cast("long").alias("n"), none.alias("gap"), none.alias("seq"), place.alias("place")
    )

    def put(df: DataFrame) -> tuple[DataFrame, dict]:
        """The state in shared storage, with the free tokens and the gaps of each range and the sequences or places that were given."""
        total = lambda kind, place, c: F.sum(F.when((F.col("kind") == kind) & (F.col("place") == place), c))
        tokens = {f"t{r}": total(FREE, r, F.col("n") * F.col("size")) for r in range(RANGES)}
        gaps = {f"g{r}": total(GAP, r, F.col("n")) for r in range(RANGES)}
        return observed(df, "runs", given=F.sum(F.when(F.col("kind") == PUT, F.col("n"))), **tokens, **gaps)

    state, seen = put(opened(state, 0, size, None))
    steps, n_sequences = [state], seen["given"] or 0
    while free := {r: seen[f"t{r}"] for r in range(RANGES) if seen[f"t{r}"]}:
        target = [max((k for k in free if k <= r), default=-1) for r in range(RANGES)]
        if any(seen[f"g{r}"] and target[r] >= 0 for r in range(RANGES)):
            to = F.when(F.col("kind") == FREE, F.col("place")).when(F.col("place") >= 0, F.get(F.array(*map(F.lit, target)), F.col("place"))).otherwise(-1)
            now = state.where(f"kind <> {PUT}").withColumn("place", to).where("place >= 0").groupBy("place").applyInArrow(lambda t: sweep(t, size), RUNS)
            state, seen = put(now)
        else:
            state, seen = put(opened(state, n_sequences, size, max(1, -(-sum(free.values()) // size))))
            n_sequences += seen["given"]
        steps.append(state)
    return spark.read.schema(RUNS).parquet(*[f for s in steps for f in s.inputFiles()]).where(f"kind = {PUT}") if any(s.inputFiles() for s in steps) else state.where("false")


def pack(docs: DataFrame, tokenizer: str | None = None, size: int = SIZE) -> DataFrame:
    """One row per piece: PLACED. docs needs doc_id and text; its other columns are left out."""
    spark, tokenizer = docs.sparkSession, tokenizer or default_tokenizer()
    cut = materialise(pieces(docs, tokenizer, size), "pieces")
    n_parts = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def ranked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Adds the partition and the place among its pieces of the same length."""
        seen: Counter[int] = Counter()
        part = TaskContext.get().partitionId()
        for b in batches:
            place = np.empty(len(b), np.int64)
            length = b.column(3).to_numpy()
            order = np.argsort(length, kind="stable")
            values, first, count = np.unique(length[order], return_index=True, return_counts=True)
            for v, f, c in zip(values.tolist(), first, count, strict=True):
                place[order[f : f + c]] = np.arange(seen[v], seen[v] + c)
                seen[v] += int(c)
            yield pa.record_batch([*b.columns, pa.array(np.full(len(b), part, np.int32)), pa.array(place)], names=[*b.schema.names, "part", "place"])

    dealt = cut.repartitionByRange(n_parts, "length", F.xxhash64("doc_id", "piece", "ids_crc32"))
    dealt = materialise(dealt.mapInArrow(ranked, PIECES + ", part int, place long"), "ranked")
    counts = materialise(dealt.groupBy("length", "part").agg(F.count("*").alias("n")), "counts")
    runs = plan(counts.groupBy("length").agg(F.sum("n").alias("n")), size)
    base: dict[tuple[int, int], int] = {}
    seen: Counter[int] = Counter()
    for length, part, n in sorted(map(tuple, counts.collect())):  # at most size + partitions rows, since pieces are range-sorted
        base[part, length] = seen[length]
        seen[length] += n
    lookup: dict[int, list] = defaultdict(list)
    for r in runs.collect():
        lookup[r.size].append((r.first, r.seq, size - r.gap))
    lookup = {n: tuple(np.array(x, np.int64) for x in zip(*sorted(runs), strict=True)) for n, runs in lookup.items()}
    shared = spark.sparkContext.broadcast((base, lookup))

    def placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, lookup = shared.value
        for b in batches:
            length, part, place = (b.column(k).to_numpy() for k in (3, 5, 6))
            sequence, offset = np.empty(len(b), np.int64), np.empty(len(b), np.int64)
            pair = length * np.int64(1 << 31) + part
            order = np.argsort(pair, kind="stable")
            edges = np.flatnonzero(np.diff(pair[order])) + 1
            for rows in np.split(order, edges) if len(b) else ():
                n, p = int(length[rows[0]]), int(part[rows[0]])
                ranks, first, at = lookup[n]
                rank = place[rows] + base[p, n]
                k = np.searchsorted(ranks, rank, side="right") - 1
                sequence[rows], offset[rows] = first[k] + rank - ranks[k], at[k]
            yield pa.record_batch([*b.columns[:5], pa.array(sequence), pa.array(offset)], names=["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return dealt.mapInArrow(placed, PLACED)


def sequences(docs: DataFrame, placed: DataFrame, tokenizer: str | None = None, size: int = SIZE) -> DataFrame:
    """The packed sequences themselves: sequence_id, ids (array) and the pieces' (doc_id, offset, length). Needs unique doc_ids."""
    ship_package(docs.sparkSession)
    tokenizer = tokenizer or default_tokenizer()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = document_ids(text.as_py(), tokenizer)
                parts = cuts(len(ids), size)
                yield pa.record_batch(
                    [pa.array([doc_id] * len(parts), pa.int64()), pa.array(range(len(parts)), pa.int32()), pa.array([ids[s : s + n].tolist() for s, n in parts], pa.list_(pa.int64()))],
                    names=["doc_id", "piece", "ids"],
                )

    tokens = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text")).mapInArrow(run, "doc_id long, piece int, ids array<long>")
    joined = placed.join(tokens, ["doc_id", "piece"])
    ordered = F.sort_array(F.collect_list(F.struct("offset", "length", "doc_id", "ids")))
    return joined.groupBy("sequence_id").agg(ordered.alias("p")).select(
        "sequence_id",
        F.flatten(F.transform("p", lambda x: x["ids"])).alias("ids"),
        F.transform("p", lambda x: F.struct(x["doc_id"].alias("doc_id"), x["offset"].alias("offset"), x["length"].alias("length"))).alias("pieces"),
    )


def op6_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


