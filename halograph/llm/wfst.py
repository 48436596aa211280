"""SentencePiece encoding and decoding as a weighted finite-state transducer.

A model file compiles into three machines: a normaliser that writes a text's characters as symbols (spaces as marks, repeated and outer
spaces dropped where the model says so, a character that no piece has as the symbols of its bytes), a trie over symbols that accepts
pieces, bytes and fallbacks, and for BPE models a filter of neighbouring pieces. Texts are cut where no piece crosses (before a run of
spaces that follows another character), and distinct words are composed with the trie all at once: a step moves every live (word,
start) arc by one symbol, and arcs that reach a piece enter the lattice. The shortest path in the
tropical semiring is found for all words together, position by position. Unigram models weigh a piece by minus its score. In BPE models a
pair of neighbours has weight zero where merging their joint text gives these two again, and infinite weight otherwise: the only path of
finite weight is the merge sequence's result, so ids equal the library's for either kind of model.

Null text encodes as empty, which has no ids. Words of any length are handled. A worker remembers the ids of words it has met, up to
MEMO_CHARS characters, and then begins anew. Repeated rows are encoded each; an empty table gives an empty result; other columns of the
input are left out. Models with a character map or with user-defined pieces are refused, since their ids would come out wrong.
"""

from __future__ import annotations

import heapq
import re
import struct
from collections import defaultdict
from collections.abc import Iterator
from itertools import count, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship_package

NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6  # fixed values: kinds of pieces in model files
UNIGRAM, BPE = 1, 2  # fixed values: kinds of models
SPACE = "▁"
#: pairs of pieces whose verdict a worker remembers
PAIRS = 2_000_000
#: characters whose words are composed at once, and characters of words whose ids a worker remembers
BATCH_CHARS, MEMO_CHARS = 4_000_000, 4_000_000


def _fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """The fields of a protocol-buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 127) << shift
            shift += 7
            if b < 128:
                return out

    while at < len(data):
        key = varint()
        kind = key & 7
        if kind == 0:
            yield key >> 3, varint()
        else:
            n = varint() if kind == 2 else {1: 8, 5: 4}[kind]
            yield key >> 3, data[at : at + n]
            at += n


class Model:
    """The compiled machines of one model file."""

    def __init__(self, path: str) -> None:
        with open(path, "rb") as f:
            top = list(_fields(f.read()))
        self.pieces, self.scores, self.kinds = [], [], []
        self.kind, self.dummy_prefix, self.squeeze, self.escape, charsmap = UNIGRAM, True, True, True, b""
        for n, v in top:
            if n == 1:
                one = dict(_fields(v))
                self.pieces.append(one.get(1, b"").decode())
                self.scores.append(struct.unpack("<f", one[2])[0] if 2 in one else 0.0)
                self.kinds.append(one.get(3, NORMAL))
            elif n == 2:
                self.kind = dict(_fields(v)).get(3, self.kind)
            elif n == 3:
                spec = dict(_fields(v))
                charsmap = spec.get(2, b"")
                self.dummy_prefix, self.squeeze, self.escape = (bool(spec.get(k, 1)) for k in (3, 4, 5))
        if charsmap:
            raise ValueError("only identity normalisers are compiled; this model has a character map")
        if self.kind not in (UNIGRAM, BPE):
            raise ValueError("only unigram and BPE models are compiled")
        if USER in self.kinds:
            raise ValueError("this model has user-defined pieces, which are not compiled")
        self.unknown = self.kinds.index(UNKNOWN)
        self.byte_id = {int(p[3:5], 16): i for i, (p, k) in enumerate(zip(self.pieces, self.kinds)) if k == BYTE}
        usable = [i for i, k in enumerate(self.kinds) if k == NORMAL and self.pieces[i]]
        self.score_of = {self.pieces[i]: self.scores[i] for i in usable}
        low = min((s for s, k in zip(self.scores, self.kinds) if k == NORMAL), default=0.0)
        self.unknown_weight = -(low - 10.0)  # fixed value: the library's penalty for unknown symbols
        self._trie(usable)
        # words may be cut before a run of marks unless a piece has a mark after another symbol
        self.cuttable = not any(re.search(f"[^{SPACE}]{SPACE}", self.pieces[i]) for i in usable)
        mark = f" {SPACE}" if self.escape else SPACE
        self.word = re.compile(f"[{mark}]*[^{mark}]+|[{mark}]+")
        self.verdicts: dict[int, bool] = {}
        self.decoded = self._decoded()
        self._forget()

    def _forget(self) -> None:
        self.number: defaultdict[str, int] = defaultdict(count().__next__)
        self.memo, self.memo_begin, self.memo_chars = np.zeros(0, np.int32), np.zeros(1, np.int64), 0

    def _trie(self, usable: list[int]) -> None:
        """States numbered as met; transitions in an open hash table of numpy arrays. Accepts pieces, the symbols of bytes, and for a
        character that only longer pieces have a fallback, which is a further output beyond the model's pieces."""
        letters = sorted({c for i in usable for c in self.pieces[i]})
        n_letters = len(letters)
        self.symbol = np.zeros(0x110000, np.int32)
        self.symbol[[ord(c) for c in letters]] = np.arange(1, n_letters + 1)
        self.byte_symbol = n_letters + 1  # of byte 0; a model without bytes has one symbol here for whatever it lacks
        if self.escape:
            self.symbol[ord(" ")] = self.symbol[ord(SPACE)]
        width = n_letters + 1 + 256
        moves: dict[int, int] = {}
        final = [-1]

        def accept(symbols: list[int], out: int) -> None:
            s = 0
            for c in symbols:
                key = s * width + c
                if key not in moves:
                    moves[key] = len(final)
                    final.append(-1)
                s = moves[key]
            if final[s] < 0:
                final[s] = out

        sym = {c: k + 1 for k, c in enumerate(letters)}
        for i in usable:
            accept([sym[c] for c in self.pieces[i]], i)
        self.spelled = list(self.pieces)  # of outputs, with the fallbacks
        self.output = [[i] for i in range(len(self.pieces))]
        weight = [-s for s in self.scores]
        for b, i in self.byte_id.items():
            accept([self.byte_symbol + b], i)
            weight[i] = 0.0 if 0x80 <= b < 0xC0 else self.unknown_weight  # a character counts once, by its first byte
        if not self.byte_id:
            accept([self.byte_symbol], self.unknown)
            weight[self.unknown] = self.unknown_weight
        free = np.zeros(len(self.pieces), bool)
        free[[*self.byte_id.values(), self.unknown]] = True  # nothing merges with these
        for c in letters:
            if c not in self.score_of:
                accept([sym[c]], len(self.spelled))
                self.spelled.append(c)
                self.output.append([self.byte_id[b] for b in c.encode()] if self.byte_id else [self.unknown])
                weight.append(self.unknown_weight)
        self.free = np.concatenate([free, np.zeros(len(self.spelled) - len(free), bool)])
        self.width, self.final = width, np.array(final, np.int32)
        bits = max(4, (3 * len(moves)).bit_length())
        self.mask = (1 << bits) - 1
        self.shift = np.uint64(64 - bits)
        self.keys, self.next = np.full(1 << bits, -1, np.int64), np.full(1 << bits, -1, np.int32)
        keys, to = np.array(list(moves), np.int64), np.array(list(moves.values()), np.int32)
        slot = self._slot(keys)
        while len(keys):
            empty = self.keys[slot] == -1
            first = np.zeros(len(keys), bool)
            _, k = np.unique(np.where(empty, slot, -1), return_index=True)
            first[k] = True
            put = empty & first
            self.keys[slot[put]], self.next[slot[put]] = keys[put], to[put]
            keys, to, slot = keys[~put], to[~put], (slot[~put] + 1) & self.mask
        self.piece_weight = np.array(weight, np.float64)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def step(self, state: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        """The next states, -1 where there is none."""
        keys = state.astype(np.int64) * self.width + symbol
        slot = self._slot(keys)
        out = np.full(len(keys), -1, np.int32)
        live = np.flatnonzero(symbol > 0)
        while len(live):
            at = slot[live]
            seen = self.keys[at]
            hit = seen == keys[live]
            out[live[hit]] = self.next[at[hit]]
            live = live[~hit & (seen != -1)]
            slot[live] = (slot[live] + 1) & self.mask
        return out

    def symbols(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The normaliser's output for all words, one after another, and where each word's symbols begin (with the end as last entry)."""
        n = np.fromiter(map(len, words), np.int64, len(words))
        text = "".join(words)
        points = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        out = self.symbol[points]
        keep = np.ones(len(out), bool)
        if self.squeeze:
            space = points == 32
            keep[1:] = ~(space[1:] & space[:-1])
            keep[(np.cumsum(n) - n)[n > 0]] = True  # a word before ends in another character
        lacking = np.flatnonzero(out == 0)
        if len(lacking) and self.byte_id:
            octets = np.frombuffer("".join([text[k] for k in lacking.tolist()]).encode(), np.uint8)
            long = points[lacking]
            size = np.ones(len(out), np.int64)
            size[lacking] += (long > 0x7F).astype(np.int64) + (long > 0x7FF) + (long > 0xFFFF)
            size[~keep] = 0
            wide = np.repeat(out, size)
            wide[wide == 0] = self.byte_symbol + octets.astype(np.int32)
            out = wide
        else:
            out[lacking] = self.byte_symbol
            size, out = keep.astype(np.int64), out[keep]
        ends = np.concatenate(([0], np.cumsum(size)))[np.concatenate(([0], np.cumsum(n)))]
        return out, ends

    def prepared(self, text: str) -> str:
        """The text between the normaliser's outer states: without outer spaces where they are dropped, after the dummy prefix."""
        if self.squeeze:
            text = text.lstrip(" ").rstrip(f" {SPACE}" if self.escape else " ")
        return " " + text if self.dummy_prefix and text else text

    def shown(self, text: str) -> str:
        """What decoding gives back of a text."""
        text = re.sub(" +", " ", self.prepared(text)) if self.squeeze else self.prepared(text)
        return text.replace(SPACE, " ").removeprefix(" " if self.dummy_prefix else "")

    # --- neighbours in BPE models --------------------------------------------------------------------------------------------

    def merged(self, text: str) -> list[str]:
        """Merges of neighbours by best score, then leftmost, until none is left."""
        parts: list[str | None] = list(text)
        after, before = list(range(1, len(parts) + 1)), list(range(-1, len(parts) - 1))
        queue: list[tuple[float, int, int, str]] = []

        def offer(i: int, j: int) -> None:
            if i >= 0 and j < len(parts) and (s := self.score_of.get(both := parts[i] + parts[j])) is not None:
                heapq.heappush(queue, (-s, i, j, both))

        for i in range(len(parts) - 1):
            offer(i, i + 1)
        while queue:
            _, i, j, both = heapq.heappop(queue)
            if parts[i] is None or parts[j] is None or after[i] != j or parts[i] + parts[j] != both:
                continue
            parts[i], parts[j] = both, None
            after[i] = after[j]
            if after[j] < len(parts):
                before[after[j]] = i
            offer(before[i], i)
            offer(i, after[i])
        return [p for p in parts if p is not None]

    def compatible(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Whether two pieces may follow each other; each distinct pair is settled once."""
        n = len(self.spelled)
        pairs, where = np.unique(left.astype(np.int64) * n + right, return_inverse=True)
        if len(self.verdicts) > PAIRS:
            self.verdicts.clear()
        out = np.empty(len(pairs), bool)
        for k, p in enumerate(pairs.tolist()):
            v = self.verdicts.get(p)
            if v is None:
                a, b = self.spelled[p // n], self.spelled[p % n]
                v = self.verdicts[p] = self.merged(a + b) == [a, b]
            out[k] = v
        return out[where]

    # --- composition and shortest paths --------------------------------------------------------------------------------------

    def encode_words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words, one after another, and where each word's begin (with the end as last entry)."""
        symbols, begin = self.symbols(words)
        n = np.diff(begin)
        word = np.repeat(np.arange(len(words)), n)
        stop = np.repeat(begin[1:], n)
        # arcs of the composition: (start, end, piece), found step by step for all starts at once
        start = np.arange(len(symbols))
        state, at = np.zeros(len(symbols), np.int32), start.copy()
        arcs = [(start[:0], start[:0], self.final[:0])]
        while len(start):
            state = self.step(state, symbols[at])
            at = at + 1
            live = state >= 0
            start, state, at = start[live], state[live], at[live]
            piece = self.final[state]
            hit = piece >= 0
            arcs.append((start[hit], at[hit], piece[hit]))
            more = at < stop[start]
            start, state, at = start[more], state[more], at[more]
        lo, hi, piece = (np.concatenate(x) for x in zip(*arcs, strict=True))
        return self._paths(lo, hi, piece.astype(np.int64), begin, word)

    def _paths(self, lo, hi, piece, begin, word):
        """Best arc into every position, for all words at once, in order of the position inside the word."""
        offset = hi - begin[word[lo]]
        order = np.lexsort((lo, offset))
        lo, hi, piece, offset = lo[order], hi[order], piece[order], offset[order]
        first = lo == begin[word[lo]]
        cost = np.full(begin[-1] + 1, np.inf)
        into = np.full(begin[-1] + 1, -1, np.int64)  # arc that ends there, by its end's position; a word's own end is its last + 1
        edges = np.concatenate((np.flatnonzero(np.diff(offset, prepend=-1)), [len(lo)]))
        for a, b in zip(edges[:-1].tolist(), edges[1:].tolist()):
            l, h, p, f = lo[a:b], hi[a:b], piece[a:b], first[a:b]
            if self.kind == BPE:
                # a start must be reachable; its best arc is the last piece before it
                prior = np.where(f, -1, into[l])
                good = f | (prior >= 0)
                last = np.where(prior >= 0, piece[prior], 0)
                test = np.flatnonzero(good & ~f & ~self.free[p] & ~self.free[last])
                good[test] = self.compatible(last[test], p[test])
                into[h[good]] = a + np.flatnonzero(good)
            else:
                weight = self.piece_weight[p] + np.where(f, 0.0, cost[l])
                best = np.lexsort((l, weight, h))
                k = best[np.flatnonzero(np.diff(h[best], prepend=-1))]
                cost[h[k]], into[h[k]] = weight[k], a + k
        # walk back from the ends of all words together
        heads = begin[:-1]
        at = begin[1:].copy()
        live = np.flatnonzero(at > heads)
        steps: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(live):
            arc = into[at[live]]
            steps.append((live, piece[arc], lo[arc]))
            at[live] = lo[arc]
            live = live[at[live] > heads[live]]
        return self._emit(steps, len(heads))

    def _emit(self, steps, n_words):
        """The outputs of the arcs in order; a run of unknown symbols is one id."""
        if not steps:
            return np.zeros(0, np.int32), np.zeros(n_words + 1, np.int64)
        w, p, at = (np.concatenate(x) for x in zip(*steps, strict=True))
        order = np.argsort(at, kind="stable")  # positions rise over all words, so this is the order of the output
        w, p = w[order], p[order]
        several = np.flatnonzero(p >= len(self.pieces))
        if len(several):
            n = np.ones(len(p), np.int64)
            n[several] = [len(self.output[k]) for k in p[several].tolist()]
            ids = [i for k in p[several].tolist() for i in self.output[k]]
            from_fallback = np.repeat(p >= len(self.pieces), n)
            w, p = np.repeat(w, n), np.repeat(p, n)
            p[from_fallback] = ids
        if not self.byte_id:
            again = np.zeros(len(p), bool)
            again[1:] = (p[1:] == self.unknown) & (p[:-1] == self.unknown) & (w[1:] == w[:-1])
            w, p = w[~again], p[~again]
        return p.astype(np.int32), np.concatenate(([0], np.cumsum(np.bincount(w, minlength=n_words))))

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        """Ids of each text. A word is composed once as long as it is remembered."""
        if self.memo_chars > MEMO_CHARS:
            self._forget()
        plain = [self.prepared(t or "") for t in texts]
        cut = [self.word.findall(t) if self.cuttable else [t] * bool(t) for t in plain]
        seen, of = len(self.number), self.number.__getitem__
        index = [np.fromiter(map(of, ws), np.int64, len(ws)) for ws in cut]
        words = list(islice(self.number, seen, None))
        ids, ends = [self.memo], [self.memo_begin]
        chars = at = 0
        for k in range(len(words) + 1):
            if k == len(words) or (chars > BATCH_CHARS and k > at):
                got, begin = self.encode_words(words[at:k])
                ids.append(got)
                ends.append(begin[1:] + ends[-1][-1])
                self.memo_chars += chars
                at, chars = k, 0
            if k < len(words):
                chars += len(words[k])
        self.memo, self.memo_begin = flat, begin = np.concatenate(ids), np.concatenate(ends)
        out = []
        for w in index:
            n = begin[w + 1] - begin[w]
            out.append(flat[np.repeat(begin[w] - (np.cumsum(n) - n), n) + np.arange(n.sum())])
        return out

    # --- the way back --------------------------------------------------------------------------------------------------------

    def _decoded(self) -> list[bytes]:
        out = []
        for i, (p, k) in enumerate(zip(self.pieces, self.kinds)):
            if k == BYTE:
                out.append(bytes([int(p[3:5], 16)]))
            elif k == UNKNOWN:
                out.append(" ⁇ ".encode())  # fixed value: what the library shows for an unknown piece
            else:
                out.append(b"" if k == CONTROL else p.replace(SPACE, " ").encode())
        return out

    def decode(self, ids: np.ndarray) -> str:
        text = b"".join([self.decoded[i] for i in ids.tolist()]).decode("utf-8", "replace")
        return text[1:] if self.dummy_prefix and text.startswith(" ") else text


_MODELS: dict[str, Model] = {}


def model(path: str) -> Model:
    if path not in _MODELS:
        _MODELS[path] = Model(path)
    return _MODELS[path]


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def encode(docs: DataFrame, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids) for every row."""
    ship_package(docs.sparkSession)
    path = path or default_model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model(path)
        for b in batches:
            for part in _portions(b):
                yield pa.record_batch([part.column(0), _lists(m.encode(part.column(1).to_pylist()))], names=["doc_id", "ids"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, ids array<int>")


def decode(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text) from (doc_id, ids)."""
    ship_package(encoded.sparkSession)
    path = path or default_model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model(path)
        for b in batches:
            texts = [m.decode(np.asarray(x.values, np.int64)) if x.is_valid else None for x in b.column(1)]
            yield pa.record_batch([b.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def _portions(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """Slices of at most BATCH_CHARS bytes of text, or one row."""
    size = np.diff(np.frombuffer(b.column(1).cast(pa.large_binary()).buffers()[1], np.int64)[b.column(1).offset :][: len(b) + 1])
    at = 0
    while at < len(b):
        n = max(1, int(np.searchsorted(np.cumsum(size[at:]), BATCH_CHARS)))
        yield b.slice(at, n)
        at += n


def _lists(arrays: list[np.ndarray]) -> pa.Array:
    ends = np.concatenate(([0], np.cumsum([len(a) for a in arrays]))).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(arrays) if arrays else np.zeros(0), pa.int32()))


def op2_sentencepiece_wfst(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every whole text encoded and decoded again: doc_id, n_ids, ids, and whether the text came back (it does, by the model's own rules
    on white space)."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    ship_package(spark)
    path = default_model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model(path)
        for b in batches:
            for part in _portions(b):
                texts = part.column(1).to_pylist()
                ids = m.encode(texts)
                back = [m.decode(i) == m.shown(t or "") for i, t in zip(ids, texts, strict=True)]
                yield pa.record_batch([part.column(0), pa.array([len(i) for i in ids], pa.int64()), _lists(ids), pa.array(back, pa.bool_())], names=["doc_id", "n_ids", "ids", "round_trip"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_ids long, ids array<int>, round_trip boolean")
