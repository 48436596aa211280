"""Transducer, archives, shards, chat and license scans against libraries, plain Python and exact round trips."""

import hashlib
import math
import re
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import regex
from pyspark.sql import functions as F

from halograph.llm import chat, common, licenses, sharding, warc, wfst

from .conftest import SF


def test_transducer_gives_the_librarys_ids(texts):
    import sentencepiece

    path = wfst.default_model()
    library, m = sentencepiece.SentencePieceProcessor(model_file=path), wfst.model(path)
    plain = [t or "" for _, t in texts] + ["日本語 テキスト ▁ x", "a\x00b", "tab\tnew\nline  two   three", "naïve café ﬁ", "the" * 500, "aaaaaaaaaaaaaaaaab" * 20]
    ids = m.encode(plain)
    for t, i in zip(plain, ids, strict=True):
        assert i.tolist() == library.encode(t, num_threads=1), t[:80]
        assert m.decode(i) == library.decode(i.tolist())


def _small_model(pieces, kind, **normaliser):
    """A model file written by hand: (piece, score, kind of piece)."""
    field = lambda n, body: bytes([n << 3 | 2, len(body)]) + body
    out = b"".join(field(1, field(1, p.encode()) + b"\x15" + struct.pack("<f", s) + bytes([0x18, k])) for p, s, k in pieces)
    flags = {"dummy_prefix": 3, "squeeze": 4, "escape": 5}
    return out + field(2, bytes([0x18, kind])) + field(3, field(1, b"identity") + b"".join(bytes([flags[k] << 3, int(v)]) for k, v in normaliser.items()))


ODD_TEXTS = ["", " ", "the cat", "日本語 x", "aaaaabaaa", "qz🙂q", "  two  spaces ", "a▁b ▁ c", "ab abc abcd", "\n\n x\t", "bcbc cb dd", "éé e é"]


def _held_against_the_library(tmp_path, data, texts):
    import sentencepiece

    (tmp_path / "m.model").write_bytes(data)
    library, m = sentencepiece.SentencePieceProcessor(model_file=str(tmp_path / "m.model")), wfst.Model(str(tmp_path / "m.model"))
    for t, i in zip(texts, m.encode(texts), strict=True):
        assert i.tolist() == library.encode(t), t[:80]
    again = m.encode(texts)  # from memory
    assert [i.tolist() for i in again] == [library.encode(t) for t in texts]


BYTE_FALLBACK = bytes([0x12, 3, 0x98, 0x02, 1])


def test_unigram_models_take_the_shortest_path(tmp_path, texts):
    """The pieces of the given model under scores whose sums are exact in the library's floats as well."""
    m = wfst.model(wfst.default_model())
    pieces = [(p, -round(64 * np.log2(k + 2)) / 64, kind) for k, (p, kind) in enumerate(zip(m.pieces, m.kinds, strict=True))]
    plain = [t for _, t in texts if t and len(t) < 3000][:80] + ODD_TEXTS
    _held_against_the_library(tmp_path, _small_model(pieces, wfst.UNIGRAM, squeeze=False) + BYTE_FALLBACK, plain)


@pytest.mark.parametrize("kind", [wfst.UNIGRAM, wfst.BPE])
@pytest.mark.parametrize("with_bytes", [True, False])
@pytest.mark.parametrize("squeeze", [True, False])
def test_small_models(tmp_path, kind, with_bytes, squeeze):
    """Characters that only longer pieces have, characters that no piece has, and models without byte pieces."""
    pieces = [("<unk>", 0.0, wfst.UNKNOWN), ("<s>", 0.0, wfst.CONTROL)]
    pieces += [(f"<0x{b:02X}>", 0.0, wfst.BYTE) for b in range(256)] if with_bytes else []
    words = ["▁", "a", "b", "c", "ab", "bc", "abc", "▁a", "▁ab", "aa", "d", "▁x"]
    pieces += [(w, -1.0 - k / 8, wfst.NORMAL) for k, w in enumerate(words)]
    data = _small_model(pieces, kind, squeeze=squeeze)
    data += BYTE_FALLBACK if with_bytes else b""
    rng = np.random.default_rng(3)
    _held_against_the_library(tmp_path, data, ODD_TEXTS + ["".join(rng.choice(list("aabbccd xé▁"), 12)) for _ in range(300)])


def test_models_that_would_give_wrong_ids_are_refused(tmp_path):
    (tmp_path / "m.model").write_bytes(_small_model([("<unk>", 0.0, wfst.UNKNOWN), ("<tool>", 0.0, wfst.USER), ("a", -1.0, wfst.NORMAL)], wfst.BPE))
    with pytest.raises(ValueError, match="user-defined"):
        wfst.Model(str(tmp_path / "m.model"))


def test_memory_is_bounded(monkeypatch):
    monkeypatch.setattr(wfst, "MEMO_CHARS", 50)
    m = wfst.Model(wfst.default_model())
    first = [m.encode([f"word{k} and another{k}"])[0].tolist() for k in range(30)]
    assert len(m.number) < 20
    assert first == [m.encode([f"word{k} and another{k}"])[0].tolist() for k in range(30)]


def test_transducer_query_columns(spark, docs, texts):
    got = wfst.encode(docs).collect()
    m = wfst.model(wfst.default_model())
    want = Counter((i, tuple(m.encode([t])[0].tolist())) for i, t in texts)
    assert Counter((r.doc_id, tuple(r.ids)) for r in got) == want
    back = {r.doc_id: r.text for r in wfst.decode(wfst.encode(docs)).collect()}
    assert all(back[i] == (t or "") for i, t in texts)
    assert wfst.encode(docs.limit(0)).count() == 0


def test_archives(spark):
    pages = [(r.page_id, r.url, r.html) for r in spark.read.parquet(f"{SF}/pages.parquet").collect()]
    long = "x" * 1200
    pages += [(1000, "http://a/é\n", long), (1001, None, long), (1002, "u", long), (1003, "u", None), (1004, "u", ""), (1005, "u", "s"), (1006, "u", "s"), (None, "n", long), (None, None, None), (1007, "🙂", "🙂" * 250), (1008, "", "🙂" * 250), (1009, "", "y" * 999), (1010, "", "y" * 999)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumns({"digest": F.lit(1), "rep": F.lit(2), "n": F.lit(3)}).repartition(3)
    manifest = warc.write_archives(df, common.fresh_path(spark, "warc"))
    got = Counter(tuple(r) for r in warc.read_archives(manifest).collect())
    top = defaultdict(lambda: -1)
    raw = [(p, (h or "").encode()) for p, _, h in pages]
    for p, b in raw:
        if len(b) >= 1000 and p is not None:
            top[b] = max(top[b], p)
    want = Counter()
    for p, b in raw:
        to = top[b] if b in top and top[b] != p else None
        want[(p, len(b), hashlib.sha1(b).hexdigest(), "revisit" if to is not None else "response", to)] += 1
    assert got == want
    payloads = []
    for r in manifest.collect():
        fs, place = warc._store(r.archive)
        with fs.open_input_file(place) as f:
            assert int.from_bytes(f.read(4), "little") == warc.DICT_MAGIC
            f.seek(0)
            payloads += [x for fields, _, x in warc.read_records(f) if fields["warc-type"] == "response"]
    assert Counter(payloads) == Counter(b for p, b in raw if not (b in top and top[b] != p))
    assert warc.read_archives(warc.write_archives(df.limit(0), common.fresh_path(spark, "warc"))).count() == 0


def test_small_archives_roll_and_need_no_dictionary(tmp_path, monkeypatch):
    monkeypatch.setattr(warc, "ARCHIVE_BYTES", 3000)
    w = warc.ArchiveWriter(str(tmp_path), "part", "2000-01-01T00:00:00Z")
    for k in range(10):
        body = f"payload {k} ".encode() * 40
        w.add(warc.build_record(k, "u", body, hashlib.sha1(body).hexdigest(), None, False, "2000-01-01T00:00:00Z"))
    w.close()
    assert len(w.done) > 1 and sum(n for _, n, _ in w.done) == 10
    back = []
    for path, _, _ in w.done:
        with open(path, "rb") as f:
            back += [int(fields["page-id"]) for fields, _, _ in warc.read_records(f)]
    assert back == list(range(10))


def test_shards(spark, docs, texts):
    clash = docs.withColumns({c: F.lit(None).cast("int") for c in ("row", "key", "tie", "shard", "grown", "bucket", "place", "number", "slot", "base", "_key", "_place", "_shard")})
    table = common.materialise(clash, "shard-input")
    rows = sharding.slots(sharding.shuffle(table, common.fresh_path(spark, "shards"), shards=5, bucket_bytes=50_000))
    got = rows.select("row.doc_id", "row.text", "shard", "grown", "slot", "bucket", F.col("row.key").alias("mine")).collect()
    assert rows.select("row.*").columns == table.columns and all(r.mine is None for r in got)
    assert Counter((r.doc_id, r.text) for r in got) == Counter(texts)
    by = defaultdict(list)
    for r in got:
        by[r.shard].append(r.slot)
        assert r.grown in (r.shard, 5)
    assert all(sorted(s) == list(range(len(s))) for s in by.values()) and len(by) == 5
    assert len({r.bucket for r in got}) > 5
    home = defaultdict(set)
    for r in got:
        home[r.doc_id].add(r.shard)
    assert all(len(s) == 1 for s in home.values())
    again = sharding.slots(sharding.shuffle(table, common.fresh_path(spark, "shards"), shards=5, bucket_bytes=50_000))
    assert sorted((r.doc_id, r.slot) for r in again.select("row.doc_id", "slot").collect()) == sorted((r.doc_id, r.slot) for r in got)
    assert sharding.slots(sharding.shuffle(docs.limit(0), common.fresh_path(spark, "shards"))).count() == 0
    order = [r.doc_id for r in sorted(got, key=lambda r: (r.shard, r.slot))]
    assert abs(np.corrcoef(order, range(len(order)))[0, 1]) < 0.3


def test_repeated_rows_fill_no_bucket(spark):
    """Two thousand equal rows and null ids: the law keeps them in one shard, whose buckets share them."""
    df = spark.createDataFrame([(7, "same text")] * 2000 + [(None, None)] * 500 + [(k, "other") for k in range(100)], "doc_id long, text string").repartition(4)
    rows = sharding.slots(sharding.shuffle(df, common.fresh_path(spark, "shards"), shards=3, bucket_bytes=4_000)).select("row.doc_id", "shard", "bucket", "slot").collect()
    assert Counter(r.doc_id for r in rows) == Counter({7: 2001, None: 500} | {k: 1 for k in range(100) if k != 7})
    same = [r for r in rows if r.doc_id == 7]
    assert len({r.shard for r in same}) == 1 and max(Counter(r.bucket for r in same).values()) < 400
    for s in range(3):
        mine = sorted(r.slot for r in rows if r.shard == s)
        assert mine == list(range(len(mine)))


def test_shard_query(spark):
    rows = sharding.op7_two_pass_shuffle(spark, SF).collect()
    text = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    for r in rows:
        assert r.size == len((text[r.doc_id] or "").encode()) + 16 and r.text_crc32 == zlib.crc32((text[r.doc_id] or "").encode())
        assert 0 <= r.shard < 40 and r.grown_shard in (r.shard, 40)
    assert len(rows) == len(text)


ODD_TURNS = [
    (1, 0, "user", r"\### Assistant: </turn> ok"), (1, 1, "assistant", "\\b\\h\\l \\\\ <</turn>\n### "), (1, 2, "user", "tail"), (2, 0, "sys: tem#", None), (2, 1, None, "x"),
    (3, 5, "assistant", "same"), (3, 5, "assistant", "same"), (3, None, "assistant", "first"), (3, 2, "user", ""), (None, 0, "assistant", "no id"), (4, 0, "user", "only"),
]


@pytest.fixture(scope="session")
def turns(spark):
    rows = ODD_TURNS + [(5, k, "assistant" if k % 2 else "user", f"turn {k} {'#' * (k % 3)}") for k in range(1300)]
    return rows, spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumns({"position": F.lit(1), "s": F.lit(1), "start": F.lit(2)}).repartition(4)


def test_chat_round_trip(turns):
    rows, df = turns
    formatted = chat.format_turns(df)
    by = defaultdict(list)
    for r in formatted.collect():
        by[r.conv_id].append(r)
    want = defaultdict(list)
    for c, t, role, text in rows:
        want[c].append((-1 if t is None else t, role or "", text or ""))
    assert by.keys() == want.keys()
    whole = {c: "".join(r.piece for r in sorted(v, key=lambda r: r.position)) for c, v in by.items()}
    spark = df.sparkSession
    for r in spark.createDataFrame(list(whole.items()), "c long, t string").select("c", chat.parse(F.col("t")).alias("turns")).collect():
        assert [(x.role, x.text) for x in r.turns] == [x[1:] for x in sorted(want[r.c])]
    seen = defaultdict(list)
    for e in chat.examples(formatted).collect():
        t = whole[e.conv_id]
        assert t[e.target_start : e.target_end] == e.target
        assert t[: e.context_end].count("</turn>") == e.example
        seen[e.conv_id].append((e.example, e.target))
    for c, v in want.items():
        unescaped = [t.replace("\\l", "<").replace("\\h", "#").replace("\\b", "\\") for _, t in sorted(seen[c])]
        assert unescaped == [x[2] for x in sorted(v) if x[1] == "assistant"]
    small = {(r.conv_id, r.example): r for r in chat.expand(formatted.where("conv_id < 5")).collect()}
    for e in chat.examples(formatted.where("conv_id < 5")).collect():
        r = small[e.conv_id, e.example]
        assert r.context == whole[e.conv_id][: e.context_end] and (r.context + r.target)[r.mask[0].start : r.mask[0].end] == e.target
    assert chat.format_turns(df.limit(0)).count() == 0


def test_chat_plan_is_native(turns):
    assert "Python" not in chat.format_turns(turns[1])._jdf.queryExecution().toString()


def test_license_scan(spark):
    rows = [
        (1, "a/LICENSE", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software)"),
        (2, "a/b/c/x.txt", "plain text"), (3, "a/b/y.txt", "words\nLicensed under the Apache License, Version 2.0.\nmore words " + "w " * 50), (4, "a/b/c/LICENSE.txt", "This work is licensed under the GNU General Public License, version 3."),
        (5, "a/b/c/d/z.txt", None), (6, "other/z.txt", "My driving license was renewed by the office in town last week, thanks."), (7, None, "Released under the MIT License."), (8, "top.txt", ""),
        (9, "a/b/q.txt", "x " * 100 + "\nLicensed under CC BY-NC 4.0.\n" + "x " * 9_000 + "\n" + "Licensed under CC BY-NC 4.0."), (2, "a/b/c/x.txt", "plain text"),
    ]
    df = spark.createDataFrame(rows, "doc_id long, p string, text string").withColumns({"id": F.lit(1), "line": F.lit(2), "dir": F.lit(3), "license": F.lit("?")})
    got = {r.id: (r.own_license, r.license, r.inherited_from) for r in licenses.scan(df, F.col("p")).collect()}
    assert got == {
        1: ("MIT", "MIT", None), 2: (None, "GPL-3.0", "a/b/c"), 3: ("Apache-2.0", "Apache-2.0", None), 4: ("GPL-3.0", "GPL-3.0", None), 5: (None, "GPL-3.0", "a/b/c"),
        6: (None, None, None), 7: ("MIT", "MIT", None), 8: (None, None, None), 9: ("CC-BY-NC-4.0", "CC-BY-NC-4.0", None),
    }
    assert licenses.scan(df, F.col("p")).count() == len(rows)
    filler = " ".join(f"ordinary{k} words" for k in range(30))
    isc = dict(licenses.FILES)["ISC"]
    odd = [
        (20, "m/LICENSE", dict(licenses.FILES)["MIT"]), (21, "m/a.py", "Licensed under the Apache License, Version 2.0. " + filler), (22, "m/b.py", filler + " released under the mit license and " + filler), (23, "m/c.py", filler),
        (24, "i/COPYING", "\n".join(isc[k : k + 70] for k in range(0, len(isc), 70))), (25, "i/x.c", "int main"), (26, "z/notes.txt", "She asked for permission to copy the poem. The warranty of the car was void."), (27, "b/LICENSE", dict(licenses.FILES)["BSD-2-Clause"]),
        (28, "u/LICENSE", dict(licenses.FILES)["Unlicense"]), (29, "q/LICENSE", "nothing of this kind " + filler),
    ]
    got = {r.id: (r.own_license, r.license, r.inherited_from) for r in licenses.scan(spark.createDataFrame(odd, "doc_id long, p string, text string"), F.col("p")).collect()}
    assert got == {
        20: ("MIT", "MIT", None), 21: ("Apache-2.0", "Apache-2.0", None), 22: ("MIT", "MIT", None), 23: (None, "MIT", "m"), 24: ("ISC", "ISC", None), 25: (None, "ISC", "i"), 26: (None, None, None),
        27: ("BSD-2-Clause", "BSD-2-Clause", None), 28: ("Unlicense", "Unlicense", None), 29: (None, None, None),
    }
    assert licenses.scan(df.limit(0), F.col("p")).count() == 0


TOKEN = re.compile(r"[a-z]+[0-9]*|[0-9]+(?:\.[0-9]+)*")


def plain_cosines(units, frequencies, shelf, n):
    """{unit: (score, template's place, license, within, shared)} by dictionaries."""
    df_of = Counter(w for x in frequencies for w in set(TOKEN.findall(x.lower())))
    vocabulary = {w for _, t in shelf for w in TOKEN.findall(t.lower())}
    idf = lambda w: math.log(n / (1 + df_of[w])) + 1 if w in vocabulary else math.log(n / 2) + 1
    vec = lambda s: {w: (1 + math.log(c)) * idf(w) for w, c in Counter(TOKEN.findall(s.lower())).items()}
    norm = lambda v: math.sqrt(sum(x * x for x in v.values()))
    right = [(name, u, norm(u)) for name, t in shelf for u in [vec(t)]]
    out = {}
    for x in units:
        v = vec(x)
        inner = norm({w: c for w, c in v.items() if w in vocabulary})
        found = []
        for k, (name, u, length) in enumerate(right):
            both = v.keys() & u.keys()
            if both:
                dot = sum(v[w] * u[w] for w in both) / length
                found.append((round(dot / norm(v), 6), -k, name, round(dot / inner, 6), len(both)))
        if found:
            out[x] = max(found)
    return out


def test_license_scores_match_plain_cosines(spark):
    lines = [t for _, t in licenses.TEMPLATES] + ["licensed under the MIT license version 2.0 or later", "a copyright notice of nobody", "License license LICENSE"]
    df = spark.createDataFrame([(x,) for x in lines], "line string")
    want = plain_cosines(set(lines), set(lines), licenses.TEMPLATES, len(set(lines)) + len(licenses.TEMPLATES))
    got = {r.line: r for r in licenses.cosines(df).collect()}
    assert got.keys() == want.keys()
    for x, (score, _, name, within, shared) in want.items():
        assert (got[x].license, got[x].shared) == (name, shared) and abs(got[x].score - score) < 2e-6 and abs(got[x].within - within) < 2e-6, x


def test_license_query_against_plain_python(spark):
    """All rows of the query on a table."""
    sf = SF.replace("sf0.001", "sf0.01")
    cue = re.compile(licenses.CUE)
    docs = {r.doc_id: r for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    found = defaultdict(set)  # id -> (line number, passage, is a window, words)
    for i, r in docs.items():
        for at, line in enumerate(re.split("\r?\n", r.text or "")):
            if not cue.search(line):
                continue
            for sentence in regex.split(r"(?<=[.;!?])\s+(?=[\p{Lu}(\"'])", line):
                if not cue.search(sentence):
                    continue
                w = re.findall(r"\S+", sentence)
                found[i].add((at, sentence, False, len(w)))
                for n, step in licenses.WINDOWS if len(w) > licenses.LONG else ():
                    for k in range(0, max(0, len(w) - n) + 1, step):
                        part = " ".join(w[k : k + n])
                        if cue.search(part):
                            found[i].add((at, part, True, step))
    lines = {x[1] for v in found.values() for x in v}
    scores = plain_cosines(lines, lines, licenses.TEMPLATES, len(lines) + len(licenses.TEMPLATES))
    own, paths, n_lines, files = {}, {}, {}, {}
    for i, r in docs.items():
        paths[i] = f"{r.source}/{r.lang}/{i // 100}/{i}.txt"
        by_line = defaultdict(list)
        for at, x, cut, words in found[i]:
            score, _, name, within, shared = scores.get(x, (0, 0, None, 0, 0))
            if (within >= licenses.SIMILAR_WINDOW and shared >= licenses.WINDOW_WORDS) if cut else score >= licenses.SIMILAR:
                by_line[at].append((within if cut else score, name, cut, words))
        n_lines[i] = len(by_line)
        own[i] = max(((s, n) for v in by_line.values() for s, n, *_ in v), default=None)
        share = sum(max(sum(x[3] for x in v if x[2]), sum(x[3] for x in v if not x[2])) for v in by_line.values())
        files[i] = bool(by_line) and share >= licenses.FILE_SHARE * len(re.findall(r"\S+", r.text or ""))
    whole = plain_cosines({docs[i].text for i in docs if files[i]}, lines, licenses.FILES, len(lines) + len(licenses.FILES))
    for i in docs:
        if files[i] and (f := whole.get(docs[i].text)) and f[0] >= licenses.SIMILAR:
            own[i] = max(own[i], (f[0], f[2]))
    given = {}
    for i in docs:
        if files[i] and own[i]:
            d = paths[i].rsplit("/", 1)[0]
            given[d] = max(given.get(d, (0, "")), own[i])
    rows = {r.doc_id: r for r in licenses.op10_license_scan(spark, sf).collect()}
    assert rows.keys() == docs.keys() and sum(v is not None for v in own.values()) > 20
    for i, r in rows.items():
        d, near = paths[i].rsplit("/", 1)[0], None
        while d and near is None:
            near = d if d in given else None
            d = d.rsplit("/", 1)[0] if "/" in d else ""
        mine = own[i][1] if own[i] else None
        want = (paths[i], n_lines[i], mine, files[i] and own[i] is not None, mine or (given[near][1] if near else None), None if mine else near)
        assert (r.path, r.n_license_lines, r.own_license, r.is_license_file, r.license, r.inherited_from) == want, i
        assert (r.own_score is None) == (own[i] is None) and (own[i] is None or abs(r.own_score - own[i][0]) < 2e-6)
