"""Image copies: held-out recall on cropped and edited copies, brute force on descriptors, and formats."""

import math
import struct
import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from halograph.llm import media
from halograph.llm.simhash import components

from .conftest import SF


def test_copies_are_found_and_others_are_not(spark):
    rows = media.op5_image_copies(spark, SF).collect()
    by = defaultdict(dict)
    for r in rows:
        by[r.vec_id][r.variant] = r.class_id
    vectors = {r.vec_id: tuple(r.embedding) for r in spark.read.parquet(f"{SF}/embeddings.parquet").collect()}
    first = {}
    for i in sorted(vectors):
        first.setdefault(vectors[i], i)
    copies = [(v, x) for v, got in by.items() for x in ("cropped", "edited") if x in got]
    assert len(copies) >= 40
    found = sum(by[v][x] == by[v]["original"] for v, x in copies)
    assert found >= 0.9 * len(copies), found / len(copies)
    wrong = sum(got["original"] != 3 * first[vectors[v]] for v, got in by.items())
    assert wrong <= 0.01 * len(by)
    assert len(rows) == len(vectors) + len(copies)


def test_edge_cases(spark):
    grey = media.render(b"a")
    flat = np.full((64, 64), 7, np.uint8)
    rows = [(1, media.png_bytes(grey)), (2, media.png_bytes(grey)), (3, None), (4, b"no image"), (5, media.png_bytes(flat)), (6, b"P5 64 64 255\n" + grey.tobytes()), (7, media.png_bytes(grey[:5, :5])), (2, media.png_bytes(grey)), (8, None), (9, b"P5 x"), (10, b"\x89PNG\r\n\x1a\n"), (11, media.png_bytes(grey)[:40]), (12, media.png_bytes(grey)[:20]), (13, media.png_bytes(grey)[:-30]), (None, media.png_bytes(grey.T)), (None, None)]
    df = spark.createDataFrame(rows, "id long, image binary").withColumns({"u": F.lit(1), "sha": F.lit("x"), "corner": F.lit(2)})
    rows = [tuple(r) for r in media.copy_classes(df).collect()]
    got = sorted(r for r in rows if r[0] is not None)
    assert len(rows) == len(got) + 2
    assert got[:10] == [(1, 1), (2, 1), (2, 1), (3, 3), (4, 4), (5, 5), (6, 1), (7, 7), (8, 3), (9, 9)] and got[10:] == [(k, k) for k in (10, 11, 12, 13)]
    for cut in range(0, 120, 7):
        media.read_image(media.png_bytes(grey)[:cut])
    assert media.copy_classes(df.limit(0)).count() == 0


def test_png_filters():
    rng = np.random.default_rng(0)
    grey = rng.integers(0, 256, (12, 9), dtype=np.uint8)
    a = np.pad(grey.astype(int), ((1, 0), (1, 0)))
    rows = []
    for y in range(12):
        kind = y % 5
        left, up, corner, x = a[y + 1, :-1], a[y, 1:], a[y, :-1], a[y + 1, 1:]
        p = left + up - corner
        near = np.where((abs(p - left) <= abs(p - up)) & (abs(p - left) <= abs(p - corner)), left, np.where(abs(p - up) <= abs(p - corner), up, corner))
        guess = [0, left, up, (left + up) // 2, near][kind]
        rows.append(bytes([kind]) + ((x - guess) & 255).astype(np.uint8).tobytes())
    chunk = lambda kind, body: struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))
    data = b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", struct.pack(">IIBBBBB", 9, 12, 8, 0, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(b"".join(rows))) + chunk(b"IEND", b"")
    assert np.array_equal(media.read_image(data), grey)


FEATURES = "id long, corner int, y double, x double, level int, angle int, d0 long, d1 long"


def pack(rows):
    return np.array([(r[2], r[3], r[4], r[5], r[6] % (1 << 64), r[7] % (1 << 64)) for r in rows], media._PACKED)


def _descriptors(rng, n, images):
    base = rng.integers(0, 1 << 62, (60, 2))
    rows = []
    for k in range(n):
        d = [int(x) for x in base[k % 60]]
        for bit in rng.choice(128, rng.integers(0, 4), replace=False):
            d[bit // 64] ^= 1 << int(bit % 64)
        d = [x - (1 << 64) if x >> 63 else x for x in d]
        rows.append((k * 7 % images, k, float(rng.integers(0, 50)), float(rng.integers(0, 50)), 0, int(rng.integers(0, 3)), *d))
    return rows


@pytest.mark.parametrize("blocks", [5, 6, 7])
def test_keys_find_all_pairs_within_the_radius(spark, blocks):
    rows = _descriptors(np.random.default_rng(1), 240, 23)
    keys = media.keyed(spark.createDataFrame(rows, FEATURES), blocks)
    a, b = (keys.select("choice", "value", *[F.col(c).alias(f"{c}_{s}") for c in ("id", "corner")]) for s in "ab")
    met = {(r.corner_a, r.corner_b) for r in a.join(b, ["choice", "value"]).where("id_a < id_b").collect()}
    bits = lambda r: (r[6] % (1 << 64)) << 64 | r[7] % (1 << 64)
    want = {(x[1], y[1]) for x in rows for y in rows if x[0] < y[0] and (bits(x) ^ bits(y)).bit_count() <= media.RADIUS}
    assert want <= met and len(want) > 50


def test_keys_widen_with_the_corners():
    assert [media.n_blocks(n) for n in (0, 10**6, 10**8, 10**11, 10**15)] == [5, 5, 6, 6, 7]


def plain_votes(a, b):
    """Agreeing corners by a loop over matches."""
    bits = lambda r: (r[6] % (1 << 64)) << 64 | r[7] % (1 << 64)
    best = 0
    found = [(x, y) for x in a for y in b if (bits(x) ^ bits(y)).bit_count() <= media.RADIUS]
    for n in range(8):
        bins = defaultdict(lambda: (set(), set()))
        for x, y in found:
            scale = media.SCALES[x[4]] / media.SCALES[y[4]]
            turn = (y[5] - x[5]) % media.ANGLES
            c, s = (f(2 * math.pi * turn / media.ANGLES) * scale for f in (math.cos, math.sin))
            dy, dx = y[2] - (c * x[2] + s * x[3]), y[3] - (c * x[3] - s * x[2])
            key = (math.floor(dy / 12 + 0.5 * (n & 1)), math.floor(dx / 12 + 0.5 * (n >> 1 & 1)), (turn + 3 * (n >> 2)) % 24 // 6, round(math.log2(scale) * 2))
            bins[key][0].add(x[1])
            bins[key][1].add(y[1])
        best = max([best, *(min(len(p), len(q)) for p, q in bins.values())])
    return best


@pytest.mark.parametrize("crowd", [1024, 20, 5, 1])
def test_links_join_what_brute_force_joins(spark, monkeypatch, crowd):
    """Classes of all image pairs that agree, with a frame that every image has and copies of one image by the dozen."""
    monkeypatch.setattr(media, "CROWD", crowd)
    rng = np.random.default_rng(6)
    rows = []
    frame = [[int(x) for x in rng.integers(0, 1 << 62, 2)] for _ in range(3)]
    sources = [[(float(rng.integers(0, 60)), float(rng.integers(0, 60)), *map(int, rng.integers(0, 1 << 62, 2))) for _ in range(9)] for _ in range(12)]
    for image in range(60):
        source = 0 if image < 25 else int(rng.integers(0, 12))
        shift = rng.integers(0, 20, 2)
        keep = rng.choice(9, rng.integers(3, 9), replace=False)
        points = [(sources[source][k][0] + shift[0], sources[source][k][1] + shift[1], *sources[source][k][2:]) for k in keep]
        points += [(float(rng.integers(0, 60)), float(rng.integers(0, 60)), *f) for f in frame]
        for corner, (y, x, d0, d1) in enumerate(points):
            d = [d0, d1]
            for bit in rng.choice(126, rng.integers(0, 3), replace=False):
                d[bit // 63] ^= 1 << int(bit % 63)
            rows.append((image, corner, float(y), float(x), 0, 4, *d))
    by = defaultdict(list)
    for r in rows:
        by[r[0]].append(r)
    parent = list(range(60))

    def top(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(60):
        for j in range(i):
            if plain_votes(by[j], by[i]) >= media.MIN_VOTES:
                parent[max(top(i), top(j))] = min(top(i), top(j))
    corners = spark.createDataFrame([(i, pack(by[i]).tobytes()) for i in range(60)], "id long, corners binary").repartition(3)
    got = {r.u: r.root for r in components(media.linked(corners)).collect()}
    assert {i: got.get(i, i) for i in range(60)} == {i: top(i) for i in range(60)}
    assert 2 < len({top(i) for i in range(60)}) < 50


def test_votes_match_plain_loops():
    rng = np.random.default_rng(9)
    for _ in range(30):
        rows = _descriptors(rng, 60, 2)
        a, b = ([r for r in rows if r[0] == k] for k in (0, 1))
        want = plain_votes(a, b)
        got = media.votes(pack(a), pack(b))
        assert got == want or max(got, want) < media.MIN_VOTES


@pytest.mark.parametrize("grid", [24, 11])
def test_recall_by_kind_of_edit(grid, monkeypatch):
    """Share of copies that are linked, and of strangers that are not, on finer and coarser textures. The figures stand in the README."""
    monkeypatch.setattr(media, "GRID", grid)
    images = [media.render(bytes([k])) for k in range(60)]
    corners = lambda x: _corners(media.png_bytes(x))
    whole = [corners(x) for x in images]
    noise = np.random.default_rng(0).normal(0, 2, images[0].shape)
    small = lambda x: media.resize(x[None].astype(np.float32), 48, 48)[0].astype(np.uint8)
    edits = {
        "cropped": media.cropped, "edited": media.edited, "turned 90": lambda x: np.rot90(x).copy(), "mirrored": lambda x: x[:, ::-1].copy(), "rescaled 0.75": small,
        "noise": lambda x: np.clip(x + noise, 0, 255).astype(np.uint8), "requantised": lambda x: (x // 8 * 8).astype(np.uint8),
    }
    share = {n: sum(media.votes(w, corners(f(x))) >= media.MIN_VOTES for w, x in zip(whole, images, strict=True)) / 60 for n, f in edits.items()}
    print(grid, share)
    assert share["cropped"] >= 0.95 and share["edited"] >= 0.95
    assert sum(media.votes(whole[i], whole[j]) >= media.MIN_VOTES for i in range(60) for j in range(i)) == 0


def _corners(data):
    return media.describe([data])[0]
