"""Media columns: copies among images by local descriptors, also where they are cropped or edited.

Images are columns of bytes (grey or RGB PNG, or binary PGM). Each is searched for Harris corners on several scales; a corner gets an
orientation from the centroid of its patch, and TESTS comparisons of points of the rotated patch as a binary descriptor. Descriptors are
cut into blocks; two within RADIUS bits agree in all but RADIUS of them, so tables keyed by every choice of the others find all such
pairs. How many blocks there are, and so how wide a key is, follows from the number of corners: chance agreements stay few however many
images there are. Corners that match propose pairs of images; a pair's matches then vote for a rotation, a scale and a shift, and images
are linked where MIN_VOTES different corners agree. Classes are the components of the links.

Under a key with at most CROWD corners all pairs are compared, and two images with MIN_VOTES matching corners on either side are a
candidate. A more crowded key, of very many copies of one image or of what very many images have in common, such as a frame's corners,
proposes pairs in two ways. First each corner's image is paired with the one of the smallest id there, so copies of one image find each
other in as many steps as there are copies. Then images of classes that are still different are paired, from all corners but the
MIN_VOTES - 1 most crowded ones of an image: images that share MIN_VOTES matches share one of the others. Images that match under other
keys as well, but too seldom there, are candidates if corners under crowded keys could make up for it.

Images with equal bytes are one image in the joins, however many there are. Null or unreadable images have no corners and are classes of
their own (equal ones share it). Repeated ids keep their rows; an empty table gives an empty result; other columns are left out.
"""

from __future__ import annotations

import struct
import zlib
from collections import defaultdict
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import ship_package
from .common import materialise
from .simhash import components

SCALES = (1.0, 0.75, 0.5)
PATCH = 8
MARGIN = PATCH + 2
ANGLES = 24
TESTS, RADIUS = 128, 4
#: corners per scale: one for so many pixels inside the margin
PIXELS_PER_CORNER = 36
MIN_VOTES = 4
#: corners under a key up to which all pairs are compared, and crowded keys up to which they are sent to all tasks, 12 bytes each
CROWD, FEW_KEYS = 1024, 500_000
#: tolerance of a vote in pixels of the full scale, and in steps of orientation
SHIFT_BIN, ANGLE_BIN = 6, 3
SEED = 11


# --- images -----------------------------------------------------------------------------------------------------------------


def png_bytes(grey: np.ndarray) -> bytes:
    h, w = grey.shape
    chunk = lambda kind, body: struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))
    rows = np.concatenate([np.zeros((h, 1), np.uint8), grey.astype(np.uint8)], axis=1).tobytes()
    return b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", struct.pack(">IIBBBBB", w, h, 8, 0, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(rows, 1)) + chunk(b"IEND", b"")


def read_image(data: bytes | None) -> np.ndarray | None:
    """Grey levels, or None where the bytes aren't an image that is understood."""
    try:
        if data and data[:8] == b"\x89PNG\r\n\x1a\n":
            return _read_png(data)
        if data and data[:2] == b"P5":
            head = data.split(None, 4)[:4]
            w, h = int(head[1]), int(head[2])
            return np.frombuffer(data[-w * h :], np.uint8).reshape(h, w).astype(np.float32)
    except (ValueError, IndexError, struct.error, zlib.error):
        pass
    return None


def _read_png(data: bytes) -> np.ndarray | None:
    at, body, w = 8, [], 0
    while at + 8 <= len(data):
        n, kind = struct.unpack(">I4s", data[at : at + 8])
        part = data[at + 8 : at + 8 + n]
        if kind == b"IHDR":
            w, h, depth, colour, _, _, interlace = struct.unpack(">IIBBBBB", part)
            if depth != 8 or interlace or colour not in (0, 2):
                return None
        elif kind == b"IDAT":
            body.append(part)
        at += 12 + n
    if not w:
        return None  # cut off before the header
    bpp = 3 if colour == 2 else 1
    raw = np.frombuffer(zlib.decompress(b"".join(body)), np.uint8).reshape(h, w * bpp + 1)
    out = raw[:, 1:].copy()
    if raw[:, 0].any():
        prior = np.zeros(w * bpp, np.uint8)
        for y in range(h):
            _unfilter(int(raw[y, 0]), out[y], prior, bpp)
            prior = out[y]
    grey = out.reshape(h, w, bpp).astype(np.float32)
    return grey[:, :, 0] if bpp == 1 else grey @ np.array([0.299, 0.587, 0.114], np.float32)


def _unfilter(kind: int, row: np.ndarray, prior: np.ndarray, bpp: int) -> None:
    if kind == 2:
        row += prior
    elif kind:
        for i in range(len(row)):
            a = int(row[i - bpp]) if i >= bpp else 0
            b, c = int(prior[i]), int(prior[i - bpp]) if i >= bpp else 0
            if kind == 1:
                guess = a
            elif kind == 3:
                guess = (a + b) // 2
            else:
                p = a + b - c
                guess = min((abs(p - a), 0, a), (abs(p - b), 1, b), (abs(p - c), 2, c))[2]
            row[i] = (int(row[i]) + guess) & 255


# --- corners and descriptors, for stacks of images of one shape ----------------------------------------------------------------


def resize(stack: np.ndarray, h: int, w: int) -> np.ndarray:
    """Bilinear."""
    n, h0, w0 = stack.shape
    y, x = (np.arange(h) + 0.5) * h0 / h - 0.5, (np.arange(w) + 0.5) * w0 / w - 0.5
    y, x = np.clip(y, 0, h0 - 1), np.clip(x, 0, w0 - 1)
    y0, x0 = np.minimum(y.astype(int), max(0, h0 - 2)), np.minimum(x.astype(int), max(0, w0 - 2))
    fy, fx = (y - y0)[None, :, None].astype(np.float32), (x - x0)[None, None, :].astype(np.float32)
    y1, x1 = np.minimum(y0 + 1, h0 - 1), np.minimum(x0 + 1, w0 - 1)
    rows = stack[:, y0] * (1 - fy) + stack[:, y1] * fy
    return rows[:, :, x0] * (1 - fx) + rows[:, :, x1] * fx


def _box(a: np.ndarray, r: int) -> np.ndarray:
    for axis in (1, 2):
        p = np.pad(a, [(r + 1, r) if k == axis else (0, 0) for k in range(3)], mode="edge").cumsum(axis, dtype=np.float64)
        n = p.shape[axis]
        a = ((p.take(range(2 * r + 1, n), axis) - p.take(range(0, n - 2 * r - 1), axis)) / (2 * r + 1)).astype(np.float32)
    return a


def _layout() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Offsets of the orientation's disc, and the compared points for each orientation."""
    g = np.arange(-PATCH + 2, PATCH - 1)
    dy, dx = (x.ravel() for x in np.meshgrid(g, g, indexing="ij"))
    disc = dy**2 + dx**2 <= (PATCH - 2) ** 2
    rng = np.random.Generator(np.random.PCG64(SEED))
    points = np.clip(rng.normal(0, PATCH / 2.2, (TESTS, 2, 2)), -PATCH + 2, PATCH - 2)
    turn = 2 * np.pi * np.arange(ANGLES) / ANGLES
    c, s = np.cos(turn)[:, None, None], np.sin(turn)[:, None, None]
    py = np.rint(points[None, ..., 0] * c + points[None, ..., 1] * s).clip(-PATCH, PATCH).astype(int)
    px = np.rint(points[None, ..., 1] * c - points[None, ..., 0] * s).clip(-PATCH, PATCH).astype(int)
    return dy[disc], dx[disc], py, px


DISC_Y, DISC_X, TEST_Y, TEST_X = _layout()


def corners(stack: np.ndarray, scale: float) -> dict[str, np.ndarray]:
    """Corners of a stack at one scale: image, y, x (in the full scale), angle (a step), d0 and d1 (the descriptor)."""
    n, h, w = stack.shape
    empty = {k: np.zeros(0, t) for k, t in (("image", int), ("y", float), ("x", float), ("angle", int), ("d0", np.uint64), ("d1", np.uint64))}
    if min(h, w) <= 2 * MARGIN + 2:
        return empty
    gy, gx = np.gradient(stack, axis=(1, 2))
    yy, xx, xy = _box(gy * gy, 2), _box(gx * gx, 2), _box(gx * gy, 2)
    strength = yy * xx - xy * xy - 0.05 * (yy + xx) ** 2
    inner = strength[:, MARGIN:-MARGIN, MARGIN:-MARGIN]
    around = np.max([strength[:, MARGIN + a : h - MARGIN + a, MARGIN + b : w - MARGIN + b] for a in (-2, -1, 0, 1, 2) for b in (-2, -1, 0, 1, 2) if a or b], axis=0)
    peak = np.where((inner > around) & (inner > 1.0), inner, -np.inf).reshape(n, -1)
    most = max(4, peak.shape[1] // PIXELS_PER_CORNER)
    best = np.argpartition(-peak, min(most, peak.shape[1] - 1), axis=1)[:, :most] if most < peak.shape[1] else np.tile(np.arange(peak.shape[1]), (n, 1))
    ok = np.take_along_axis(peak, best, 1) > -np.inf
    image = np.repeat(np.arange(n), ok.sum(1))
    place = best[ok]
    y, x = place // inner.shape[2] + MARGIN, place % inner.shape[2] + MARGIN
    smooth = _box(stack, 1)
    disc = smooth[image[:, None], y[:, None] + DISC_Y, x[:, None] + DISC_X]
    angle = np.rint(np.arctan2(disc @ DISC_Y.astype(np.float32), disc @ DISC_X.astype(np.float32)) / (2 * np.pi) * ANGLES).astype(int) % ANGLES
    ty, tx = TEST_Y[angle], TEST_X[angle]
    at = image[:, None]
    bits = smooth[at, y[:, None] + ty[:, :, 0], x[:, None] + tx[:, :, 0]] < smooth[at, y[:, None] + ty[:, :, 1], x[:, None] + tx[:, :, 1]]
    words = np.packbits(bits, axis=1).view(">u8").astype(np.uint64)
    return {"image": image, "y": y / scale, "x": x / scale, "angle": angle, "d0": words[:, 0], "d1": words[:, 1]}


#: a corner as it is stored: an image's corners are one value of bytes, whose size is bounded by the image's
_PACKED = np.dtype([("y", "<f4"), ("x", "<f4"), ("level", "<i4"), ("angle", "<i4"), ("d0", "<u8"), ("d1", "<u8")])


def describe(images: list[bytes | None]) -> list[np.ndarray]:
    """The corners of each image, in a fixed order; images of one shape are worked on together."""
    out = [np.zeros(0, _PACKED)] * len(images)
    shapes = defaultdict(list)
    for i, data in enumerate(images):
        grey = read_image(data)
        if grey is not None and min(grey.shape) > 2 * MARGIN + 2:
            shapes[grey.shape].append((i, grey))
    for (h, w), group in shapes.items():
        stack, parts = np.stack([g for _, g in group]), []
        for level, scale in enumerate(SCALES):
            c = corners(stack if scale == 1 else resize(stack, int(h * scale), int(w * scale)), scale)
            rows = np.zeros(len(c["image"]), _PACKED)
            rows["level"] = level
            for name in ("y", "x", "angle", "d0", "d1"):
                rows[name] = c[name]
            parts.append((c["image"], rows))
        image, rows = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.argsort(image, kind="stable")
        ends = np.searchsorted(image[order], np.arange(len(group) + 1))
        for k, (i, _) in enumerate(group):
            out[i] = rows[order[ends[k] : ends[k + 1]]]
    return out


def features(images: DataFrame) -> DataFrame:
    """(id, corners) of every image of (id, image)."""
    ship_package(images.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, len(b), 256):
                part = b.slice(at, 256)
                yield pa.record_batch([part.column(0), pa.array([c.tobytes() for c in describe(part.column(1).to_pylist())], pa.binary())], names=["id", "corners"])

    return images.select(F.col("id").cast("long").alias("id"), "image").mapInArrow(run, "id long, corners binary")


def descriptors(corners: DataFrame) -> DataFrame:
    """(id, corner, d0, d1), a row for each corner."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [np.frombuffer(x, _PACKED) for x in b.column(1).to_pylist()]
            n = np.array([len(x) for x in got], np.int64)
            flat = np.concatenate(got) if got else np.zeros(0, _PACKED)
            number = np.arange(len(flat)) - np.repeat(np.cumsum(n) - n, n)
            yield pa.record_batch([b.column(0).take(pa.array(np.repeat(np.arange(len(n)), n))), pa.array(number.astype(np.int32)), *[pa.array(np.ascontiguousarray(flat[c]).view(np.int64)) for c in ("d0", "d1")]], names=["id", "corner", "d0", "d1"])

    return corners.select("id", "corners").mapInArrow(run, "id long, corner int, d0 long, d1 long")


# --- joins and consensus --------------------------------------------------------------------------------------------------------


def n_blocks(corners: int) -> int:
    """Blocks of a descriptor: RADIUS of them may differ, and the others must be wide enough for chance agreements to stay few."""
    blocks = RADIUS + 1
    while TESTS * (blocks - RADIUS) // blocks < np.log2(max(2, corners)) and blocks < 2 * RADIUS:
        blocks += 1
    return blocks


def _bits(low: int, high: int) -> Column:
    """Bits low to high of a descriptor, as a number."""

    def cut(word: str, a: int, b: int) -> Column:
        return F.shiftrightunsigned(word, a).bitwiseAND(F.lit((1 << (b - a)) - 1).cast("long"))

    if high <= 64:
        return cut("d0", low, high)
    if low >= 64:
        return cut("d1", low - 64, high - 64)
    return F.shiftleft(cut("d1", 0, high - 64), 64 - low) + cut("d0", low, 64)


def keyed(points: DataFrame, blocks: int) -> DataFrame:
    """Each descriptor under every key: a choice of blocks, and a hash of what stands there (one block's bits are their own)."""
    edges = [TESTS * k // blocks for k in range(blocks + 1)]
    part = [_bits(a, b) for a, b in zip(edges[:-1], edges[1:], strict=True)]
    choices = list(combinations(range(blocks), blocks - RADIUS))
    values = [part[c[0]] if len(c) == 1 else F.xxhash64(*[part[k] for k in c]) for c in choices]
    return points.select("id", "corner", "d0", "d1", F.posexplode(F.array(*values)).alias("choice", "value"))


def _near(a: str, b: str) -> Column:
    return F.bit_count(F.col(f"{a}0").bitwiseXOR(F.col(f"{b}0"))) + F.bit_count(F.col(f"{a}1").bitwiseXOR(F.col(f"{b}1"))) <= RADIUS


def grouped(keys: DataFrame) -> DataFrame:
    """(choice, value, g): the corners under each key that has several, at most CROWD + 1 of them."""
    order = Window.partitionBy("choice", "value").orderBy("id", "corner")
    few = keys.withColumn("r", F.row_number().over(order)).where(F.col("r") <= CROWD + 1)
    lists = few.groupBy("choice", "value").agg(F.collect_list(F.struct("id", "corner", "d0", "d1")).alias("g"))
    return lists.where(F.size("g") > 1)


def within_keys(groups: DataFrame) -> DataFrame:
    """(u, v, n_u, n_v): images whose corners match under keys that are not crowded, and how many corners of either do."""
    rows = groups.where(F.size("g") <= CROWD).select("choice", "value", F.inline("g"))
    a, b = (rows.select("choice", "value", *[F.col(c).alias(f"{s}_{c}") for c in ("id", "corner")], *[F.col(c).alias(f"{s}{c[1]}") for c in ("d0", "d1")]) for s in "uv")
    found = a.join(b, ["choice", "value"]).where((F.col("u_id") > F.col("v_id")) & _near("u", "v"))
    return found.groupBy(F.col("u_id").alias("u"), F.col("v_id").alias("v")).agg(*[F.size(F.collect_set(f"{s}_corner")).alias(f"n_{s}") for s in "uv"])


def with_smallest(keys: DataFrame) -> DataFrame:
    """Pairs (u, v) of images whose corners match, v the smallest id under a key."""
    w = Window.partitionBy("choice", "value").orderBy("id", "corner")
    first = lambda c: F.first(c).over(w)
    rows = keys.select("id", "d0", "d1", first("id").alias("v"), first("d0").alias("e0"), first("d1").alias("e1"))
    return rows.where((F.col("id") > F.col("v")) & _near("d", "e")).select(F.col("id").alias("u"), "v").distinct()


def between_classes(keys: DataFrame, classes: DataFrame) -> DataFrame:
    """Pairs (u, v) of images of different classes whose corners match under crowded keys, the smaller image's corner not among its most
    crowded."""
    key = ["choice", "value"]
    crowd = keys.groupBy(*key).agg(F.count("*").alias("crowd"))
    k = keys.join(classes, "id").join(crowd, key)
    mixed = k.groupBy(*key).agg(F.min("class").alias("lo"), F.max("class").alias("hi")).where("lo <> hi").select(*key)
    heat = k.groupBy("id", "corner").agg(F.max("crowd").alias("heat"))
    rank = F.row_number().over(Window.partitionBy("id").orderBy(F.desc("heat"), "corner"))
    cool = heat.withColumn("r", rank).where(F.col("r") >= MIN_VOTES).select("id", "corner")
    right = materialise(k.join(mixed, key, "left_semi").select(*key, "class", "id", "corner", "d0", "d1"), "mixed")
    left = right.join(cool, ["id", "corner"], "left_semi")
    sides = [df.select(*key, F.col("class").alias(f"class_{s}")).distinct() for df, s in ((left, "a"), (right, "b"))]
    apart = sides[0].join(sides[1], key).where("class_a <> class_b")
    a, b = (df.select(*key, F.col("class").alias(f"class_{s}"), F.col("id").alias(f"id_{s}"), F.col("d0").alias(f"{s}0"), F.col("d1").alias(f"{s}1")) for df, s in ((left, "a"), (right, "b")))
    found = apart.join(a, [*key, "class_a"]).join(b, [*key, "class_b"]).where((F.col("id_a") < F.col("id_b")) & _near("a", "b"))
    return found.select(F.col("id_b").alias("u"), F.col("id_a").alias("v")).distinct()


def votes(a: np.ndarray, b: np.ndarray) -> int:
    """How many different corners of both images agree on one rotation, scale and shift. Bins overlap, so no agreement is cut by an
    edge."""
    i, j = np.nonzero(np.bitwise_count(a["d0"][:, None] ^ b["d0"]) + np.bitwise_count(a["d1"][:, None] ^ b["d1"]) <= RADIUS)
    if min(len(np.unique(i)), len(np.unique(j))) < MIN_VOTES:
        return min(len(np.unique(i)), len(np.unique(j)))
    p, q, size = a[i], b[j], np.array(SCALES)
    scale = size[p["level"]] / size[q["level"]]  # pixels of b for one of a
    turn = (q["angle"] - p["angle"]) % ANGLES
    c, s = np.cos(2 * np.pi * turn / ANGLES) * scale, np.sin(2 * np.pi * turn / ANGLES) * scale
    dy, dx = q["y"] - (c * p["y"] + s * p["x"]), q["x"] - (c * p["x"] - s * p["y"])
    zoom = np.round(np.log2(scale) * 2)
    best = 0
    for n in range(8):
        bins = np.stack([np.floor(dy / (2 * SHIFT_BIN) + 0.5 * (n & 1)), np.floor(dx / (2 * SHIFT_BIN) + 0.5 * (n >> 1 & 1)), (turn + ANGLE_BIN * (n >> 2)) % ANGLES // (2 * ANGLE_BIN), zoom])
        _, which = np.unique(bins, axis=1, return_inverse=True)
        which = which.ravel()
        ends = [np.bincount(np.unique(np.stack([which, x]), axis=1)[0]) for x in (i, j)]
        best = max(best, int(np.minimum(*ends).max()))
    return best


def consensus(pairs: DataFrame, corners: DataFrame, least: int = MIN_VOTES) -> DataFrame:
    """Of the pairs (u, v) those whose corners agree."""
    joined = pairs.join(corners.select(F.col("id").alias("u"), F.col("corners").alias("a")), "u").join(corners.select(F.col("id").alias("v"), F.col("corners").alias("b")), "v")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            of = lambda k: [np.frombuffer(x, _PACKED) for x in batch.column(k).to_pylist()]
            good = pa.array([votes(a, b) >= least for a, b in zip(of(2), of(3), strict=True)], pa.bool_())
            yield pa.record_batch([batch.column(0).filter(good), batch.column(1).filter(good)], names=["u", "v"])

    return joined.select("u", "v", "a", "b").mapInArrow(run, "u long, v long")


def linked(corners: DataFrame) -> DataFrame:
    """Links (u, v) that join all images whose corners agree, from a table of (id, corners)."""
    points = descriptors(corners)
    n = corners.agg(F.sum(F.octet_length("corners"))).first()[0] or 0
    keys = keyed(points, n_blocks(n // _PACKED.itemsize))
    groups = materialise(grouped(keys), "groups")
    some = within_keys(groups)
    crowded = materialise(groups.where(F.size("g") > CROWD).select("choice", "value"), "crowded")
    n_crowded = crowded.count()
    if not n_crowded:
        return consensus(some.where(F.least("n_u", "n_v") >= MIN_VOTES), corners)
    many = materialise(keys.join(F.broadcast(crowded) if n_crowded <= FEW_KEYS else crowded, ["choice", "value"]), "many")
    hot = materialise(many.groupBy("id").agg(F.count_distinct("corner").alias("hot")), "hot")
    of = lambda c: hot.select(F.col("id").alias(c), F.col("hot").alias(f"hot_{c}"))
    some = some.join(of("u"), "u", "left").join(of("v"), "v", "left").na.fill(0, ["hot_u", "hot_v"])
    helped = F.when((F.col("hot_u") > 0) & (F.col("hot_v") > 0), F.least(F.col("n_u") + F.col("hot_u"), F.col("n_v") + F.col("hot_v"))).otherwise(F.least("n_u", "n_v"))
    pairs = some.where(helped >= MIN_VOTES).select("u", "v")
    near = materialise(consensus(pairs.union(with_smallest(many)).distinct(), corners), "near")
    classes = corners.select("id").distinct().join(components(near).withColumnRenamed("u", "id"), "id", "left").select("id", F.coalesce("root", "id").alias("class"))
    return near.union(consensus(between_classes(many, materialise(classes, "by-smallest")), corners))


#: ids of images that are equal to another up to which they are sent to all tasks, 8 bytes each; more are joined by a shuffle
FEW_IDS = 500_000


def copy_classes(images: DataFrame) -> DataFrame:
    """(id, class_id) for every row of (id, image): class_id is the smallest id among the image's copies, itself included."""
    hashed = images.select(F.col("id").cast("long").alias("id"), F.sha2(F.coalesce("image", F.lit(b"")), 256).alias("sha"), "image")
    rows = materialise(hashed.select("id", "sha"), "shas")
    distinct = materialise(rows.groupBy("sha").agg(F.min("id").alias("rep")), "reps")
    # images are only exchanged where there are too many copies to name them to all tasks
    again = materialise(rows.join(distinct, "sha").where("id <> rep").select("id", "sha").distinct(), "again")
    some = hashed.join(F.broadcast(again) if again.count() <= FEW_IDS else again, ["id", "sha"], "left_anti").where("id IS NOT NULL").select("id", "image")
    corners = materialise(features(some), "corners")
    stars = components(linked(corners))
    rooted = materialise(distinct.join(stars, distinct["rep"] == stars["u"], "left").select("sha", F.coalesce("root", "rep").alias("class_id")), "classes")
    return rows.join(rooted, "sha").select("id", "class_id")


# --- images for the given tables, which hold none ---------------------------------------------------------------------------------

SIDE, GRID = 64, 24
#: every so many rows also come as a cropped and as an edited copy
COPIED_EVERY = 20


def render(vector: bytes) -> np.ndarray:
    """A grey texture that depends on all of a vector's bytes."""
    rng = np.random.Generator(np.random.PCG64(zlib.crc32(vector)))
    grid = rng.random((1, GRID, GRID), np.float32) * 255
    return resize(grid, SIDE, SIDE)[0].astype(np.uint8)


def cropped(grey: np.ndarray) -> np.ndarray:
    return grey[6:-4, 3:-5]


def edited(grey: np.ndarray) -> np.ndarray:
    """Darker, with a box pasted over a corner."""
    out = (grey * 0.8 + 20).astype(np.uint8)
    out[:18, :18] = 255
    return out


def rendered(vectors: DataFrame) -> DataFrame:
    """(id, variant, image): id is 3 * vec_id for originals, plus 1 for the cropped and 2 for the edited copy."""
    ship_package(vectors.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for vec_id, v in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                if vec_id is None:
                    continue  # without an id there is nothing to name the image by
                grey = render(np.asarray(v.values, np.float32).tobytes() if v.is_valid else b"")
                rows.append((3 * vec_id, "original", png_bytes(grey)))
                if vec_id % COPIED_EVERY == 0:
                    rows += [(3 * vec_id + 1, "cropped", png_bytes(cropped(grey))), (3 * vec_id + 2, "edited", png_bytes(edited(grey)))]
            if rows:
                yield pa.record_batch([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.string(), pa.binary()), strict=True)], names=["id", "variant", "image"])

    return vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding").mapInArrow(run, "id long, variant string, image binary")


def op5_image_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, variant and class_id of every rendered image and planted copy; class_id is the class's smallest image id."""
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    images = rendered(vectors)
    names = F.get(F.array(F.lit("original"), F.lit("cropped"), F.lit("edited")), F.pmod("id", F.lit(3)).cast("int"))
    return copy_classes(images.select("id", "image")).select(F.floor(F.col("id") / 3).cast("long").alias("vec_id"), names.alias("variant"), "class_id")
