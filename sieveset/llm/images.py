"""Copies of images by local descriptors.

Corners are found at several scales by the Harris measure. Each gets an orientation, the direction of its patch's centre of
brightness, and 256 binary tests that are turned with it. The tests run across the orientation, so that either outcome is as likely and
their bits tell much. Descriptors of a block of queries are filed in TABLES Hamming tables, each under KEY_BITS of their bits; an image's
descriptors fetch those that share a key, and all that agree in all but MAX_BITS bits are matches, whatever else is in the block. Two
images with MIN_VOTES matches of about one turn and scale are tried: of their matches the largest set that one similarity
(shift, turn, scale) explains must reach MIN_INLIERS. A copy has many descriptors, of which the tables need not find every one;
recall against all pairs is tested.

An image is a struct of height, width and pixels (grey, a byte each). Equal images form a class and are searched once.

Defined cases: a null or flat image has no corner and matches nothing but its own class; images under 24 pixels a side have no
descriptor; repeated rows share a class; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import BINARY, INT, LONG, attach, fields, materialise, table, to_python

SCALES = (1.0, 0.75, 0.5)
#: Corners at full scale and at each other, at most: the strongest. They describe an image; rows are never capped.
CORNERS, CORNERS_SMALL = 40, 36
RADIUS = 10
TESTS = 256
TURNS = 36
MAX_BITS = 44
TABLES, KEY_BITS = 16, 28
MIN_VOTES, MIN_INLIERS = 6, 11
TOLERANCE = 2.5
SEED = 3
#: Queries that are looked up in one pass over the images.
QUERY_BLOCK = 2000
#: Images of a task, about.
TASK_IMAGES = 500
#: Candidates that are compared at a time.
SLICE = 1 << 18
QUERY_EVERY = 100


def _pattern() -> np.ndarray:
    """Offsets (turn, test, end, y/x) of the binary tests, for each turn."""
    rng = np.random.default_rng(SEED)
    pairs = np.zeros((0, 2, 2))
    while len(pairs) < TESTS:  # those whose ends lie across the orientation, which points along x
        more = np.clip(rng.normal(0, RADIUS / 2.2, (8 * TESTS, 2, 2)), -RADIUS * 0.7, RADIUS * 0.7)
        dy, dx = np.abs(more[:, 1] - more[:, 0]).T
        pairs = np.concatenate([pairs, more[(dy > 2.5 * dx) & (dy > 2)]])
    pairs = pairs[:TESTS]
    angles = np.arange(TURNS) * 2 * np.pi / TURNS
    y = pairs[..., 0] * np.cos(angles)[:, None, None] + pairs[..., 1] * np.sin(angles)[:, None, None]
    x = -pairs[..., 0] * np.sin(angles)[:, None, None] + pairs[..., 1] * np.cos(angles)[:, None, None]
    return np.stack([np.rint(y), np.rint(x)], -1).astype(np.int64)


_PATTERN = _pattern()


def _resized(image: np.ndarray, scale: float) -> np.ndarray:
    h, w = image.shape
    nh, nw = max(1, round(h * scale)), max(1, round(w * scale))
    y, x = (np.arange(nh) + 0.5) * h / nh - 0.5, (np.arange(nw) + 0.5) * w / nw - 0.5
    y, x = np.clip(y, 0, h - 1), np.clip(x, 0, w - 1)
    y0, x0 = np.minimum(y.astype(int), max(0, h - 2)), np.minimum(x.astype(int), max(0, w - 2))
    y1, x1 = np.minimum(y0 + 1, h - 1), np.minimum(x0 + 1, w - 1)
    fy, fx = (y - y0)[:, None], (x - x0)[None, :]
    top = image[y0][:, x0] * (1 - fx) + image[y0][:, x1] * fx
    low = image[y1][:, x0] * (1 - fx) + image[y1][:, x1] * fx
    return top * (1 - fy) + low * fy


def _box(a: np.ndarray, r: int) -> np.ndarray:
    """Sums over squares of side 2 r + 1, zero outside."""
    p = np.pad(a, ((r + 1, r), (r + 1, r))).cumsum(0).cumsum(1)
    s = 2 * r + 1
    return p[s:, s:] - p[:-s, s:] - p[s:, :-s] + p[:-s, :-s]


def describe(image: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(n, 4) of y, x, angle, size in the image's own pixels, and (n, 4) descriptors of four 64-bit numbers."""
    places, words = [], []
    if min(image.shape) < 2 * RADIUS + 4:
        return np.zeros((0, 4)), np.zeros((0, 4), np.uint64)
    offset = np.arange(-RADIUS, RADIUS + 1)
    disc = (offset[:, None] ** 2 + offset[None, :] ** 2) <= RADIUS**2
    for scale in SCALES:
        small = _resized(image.astype(float), scale) if scale != 1 else image.astype(float)
        if min(small.shape) < 2 * RADIUS + 4:
            continue
        smooth = _box(small, 1) / 9
        gy, gx = np.gradient(smooth)
        xx, yy, xy = _box(gx * gx, 2), _box(gy * gy, 2), _box(gx * gy, 2)
        harris = xx * yy - xy * xy - 0.05 * (xx + yy) ** 2
        inner = np.full(harris.shape, -np.inf)
        inner[RADIUS:-RADIUS, RADIUS:-RADIUS] = harris[RADIUS:-RADIUS, RADIUS:-RADIUS]
        peak = inner.copy()
        for dy in (-1, 0, 1):
            for dx in (-1, 0, 1):
                peak = np.maximum(peak, np.roll(inner, (dy, dx), (0, 1)))
        y, x = np.nonzero((inner >= peak) & (inner > 1e-3))
        if not len(y):
            continue
        best = np.lexsort((x, y, -inner[y, x]))[: CORNERS if scale == 1 else CORNERS_SMALL]
        y, x = y[best], x[best]
        patch = smooth[y[:, None, None] + offset[:, None], x[:, None, None] + offset[None, :]] * disc
        angle = np.arctan2((patch * offset[:, None]).sum((1, 2)), (patch * offset[None, :]).sum((1, 2)))
        turn = np.rint(angle * TURNS / (2 * np.pi)).astype(int) % TURNS
        where = _PATTERN[turn]
        value = smooth[y[:, None, None] + where[..., 0], x[:, None, None] + where[..., 1]]
        bits = np.packbits(value[..., 0] < value[..., 1], axis=1, bitorder="little")
        places.append(np.stack([y / scale, x / scale, angle, np.full(len(y), 1 / scale)], 1))
        words.append(np.ascontiguousarray(bits).view(np.uint64))
    if not places:
        return np.zeros((0, 4)), np.zeros((0, 4), np.uint64)
    return np.concatenate(places), np.concatenate(words)


def pixels(image: dict | None) -> np.ndarray:
    if not image or not image["pixels"] or len(image["pixels"]) != image["height"] * image["width"]:
        return np.zeros((0, 0), np.uint8)
    return np.frombuffer(image["pixels"], np.uint8).reshape(image["height"], image["width"])


def inliers(a: np.ndarray, b: np.ndarray, least: int = 1) -> tuple[int, float, float]:
    """Largest consensus among matched places (rows of y, x, angle, size): its size, turn and scale; size ``least - 1`` if it is below ``least``.

    Each match alone gives a similarity; the one that carries most of a's places to b's wins. Matches that end at one place count once.
    """
    scale = b[:, 3] / a[:, 3]
    turn = b[:, 2] - a[:, 2]
    c, s = (np.cos(turn) * scale)[:, None], (np.sin(turn) * scale)[:, None]
    dy, dx = a[None, :, 0] - a[:, None, 0], a[None, :, 1] - a[:, None, 1]
    y, x = b[:, None, 0] + c * dy + s * dx, b[:, None, 1] - s * dy + c * dx
    ok = (np.abs(y - b[None, :, 0]) < TOLERANCE) & (np.abs(x - b[None, :, 1]) < TOLERANCE)
    best, sums = (least - 1, 0.0, 1.0), ok.sum(1)
    for i in np.argsort(-sums, kind="stable"):
        if sums[i] <= best[0]:
            break
        n = min(_places(a[ok[i]]), _places(b[ok[i]]))
        if n > best[0]:
            best = (n, float(turn[i]), float(scale[i]))
    return best


def _places(x: np.ndarray) -> int:
    return len({(round(y), round(z)) for y, z in x[:, :2].tolist()})


_DRAWN = np.stack([np.random.default_rng(SEED + 1 + k).permutation(TESTS)[:KEY_BITS] for k in range(TABLES)])


def table_keys(words: np.ndarray) -> np.ndarray:
    """(descriptors, TABLES) of keys, each made of KEY_BITS bits drawn from all."""
    bits = np.unpackbits(np.ascontiguousarray(words).view(np.uint8).reshape(len(words), TESTS // 8), axis=1, bitorder="little")
    out = np.zeros((len(words), TABLES), np.int64)
    for i in range(KEY_BITS):
        out |= bits[:, _DRAWN[:, i]].astype(np.int64) << i
    return out


class QueryTables:
    """Hamming tables of the descriptors of a block of queries: each table's keys in order, with where they lead."""

    def __init__(self, queries: list[tuple[int, np.ndarray, np.ndarray]]):
        self.ids = np.array([q for q, p, _ in queries], np.int64)
        self.owner = np.concatenate([np.full(len(p), i) for i, (_, p, _) in enumerate(queries)] or [np.zeros(0, int)]).astype(np.int64)
        self.places = np.concatenate([p for _, p, _ in queries] or [np.zeros((0, 4))])
        self.words = np.ascontiguousarray(np.concatenate([w for _, _, w in queries] or [np.zeros((0, 4), np.uint64)]))
        # one table number above each key, so that one search serves all tables
        keys = (table_keys(self.words) | np.arange(TABLES) << KEY_BITS).ravel()
        order = np.argsort(keys, kind="stable")
        self.keys, first = np.unique(keys[order], return_index=True)
        self.filed, self.ends = (order // TABLES).astype(np.int32), np.r_[first, len(order)]

    def near(self, words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Matches as rows of ``words`` and numbers of filed descriptors: those that share a key and differ in MAX_BITS bits at most."""
        asked = (table_keys(words) | np.arange(TABLES) << KEY_BITS).ravel()
        at = np.minimum(np.searchsorted(self.keys, asked), len(self.keys) - 1)
        hit = np.flatnonzero(self.keys[at] == asked)
        start, size = self.ends[at[hit]], self.ends[at[hit] + 1] - self.ends[at[hit]]
        found = [np.zeros(0, np.int64)]
        for cut in np.split(np.arange(len(hit)), np.flatnonzero(np.diff(np.cumsum(size) // SLICE)) + 1):
            n = size[cut]
            if not len(n):
                continue
            mine = np.repeat(hit[cut] // TABLES, n)
            theirs = self.filed[np.repeat(start[cut] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))]
            both = np.unique(mine * len(self.words) + theirs)  # a pair may share several keys
            mine, theirs = both // len(self.words), both % len(self.words)
            found.append(both[np.bitwise_count(words[mine] ^ self.words[theirs]).sum(1, dtype=np.int64) <= MAX_BITS])
        both = np.unique(np.concatenate(found))
        return both // max(1, len(self.words)), both % max(1, len(self.words))

    def search(self, places: np.ndarray, words: np.ndarray) -> list[tuple[int, int, float, float]]:
        """(query, inliers, turn, scale) of the queries that one image agrees with."""
        if not len(words) or not len(self.words):
            return []
        mine, theirs = self.near(words)
        if not len(mine):
            return []
        owner = self.owner[theirs]
        out = []
        order = np.argsort(owner, kind="stable")
        sizes = np.bincount(owner, minlength=len(self.ids))
        ends = np.cumsum(sizes)
        often = np.flatnonzero(sizes >= MIN_INLIERS)
        of = np.full(len(self.ids), -1)
        of[often] = np.arange(len(often))
        some = of[owner] >= 0
        votes = self._votes(places[mine[some]], self.places[theirs[some]], of[owner[some]], len(often))
        for q in often[votes >= MIN_VOTES]:
            own = order[ends[q] - sizes[q] : ends[q]]
            if min(len(np.unique(theirs[own])), len(np.unique(mine[own]))) < MIN_INLIERS:
                continue
            n, turn, scale = inliers(self.places[theirs[own]], places[mine[own]], MIN_INLIERS)
            if n >= MIN_INLIERS:
                out.append((int(self.ids[q]), n, turn, scale))
        return out

    @staticmethod
    def _votes(a: np.ndarray, b: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
        """Of each owner the most matches whose turns lie within three neighbouring steps and whose scales are about one."""
        if not n:
            return np.zeros(0, np.int64)
        turn = np.rint((a[:, 2] - b[:, 2]) * TURNS / (2 * np.pi)).astype(np.int64) % TURNS
        scale = np.rint(2 * np.log2(a[:, 3] / b[:, 3])).astype(np.int64) + 2
        count = np.bincount((owner * 5 + scale) * TURNS + turn, minlength=n * 5 * TURNS).reshape(n, 5, TURNS)
        return (count + np.roll(count, 1, 2) + np.roll(count, -1, 2)).max((1, 2))


IMAGE = T.StructType([T.StructField("height", INT), T.StructField("width", INT), T.StructField("pixels", BINARY)])


def _described(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = [describe(pixels(x)) for x in batch.column("image").to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column("image_id"), pa.array([p.astype(np.float32).tobytes() for p, _ in found], pa.binary()), pa.array([w.tobytes() for _, w in found], pa.binary())], ["image_id", "places", "words"])


def _unpack(places: bytes, words: bytes) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(places, np.float32).reshape(-1, 4).astype(float), np.frombuffer(words, np.uint64).reshape(-1, 4)


def search(images: DataFrame, queries: DataFrame, block: int = QUERY_BLOCK) -> DataFrame:
    """(query_id, image_id, inliers, turn_degrees, scale): images that hold a query's picture, whole or in part.

    Both have image_id and image. Queries are looked up block by block: a pass over the images takes one
    block, whose descriptors have a fixed size at most and so can be sent to all tasks.
    """
    spark = images.sparkSession
    kinds = fields(image_id=LONG, places=BINARY, words=BINARY)
    asked = materialise(to_python(queries.select("image_id", "image"), _described, kinds), "image-queries")
    known = to_python(images.select("image_id", "image"), _described, kinds)
    n_blocks = max(1, -(-asked.count() // block))
    if n_blocks > 1:  # described once, read for each block
        known = materialise(known, "image-descriptors")
    schema = T.StructType([T.StructField("query_id", LONG), T.StructField("image_id", LONG), T.StructField("inliers", LONG), T.StructField("turn_degrees", T.DoubleType()), T.StructField("scale", T.DoubleType())])
    out = None
    for b in range(n_blocks):
        part = asked.where(F.pmod(F.xxhash64("image_id"), F.lit(n_blocks)) == b).orderBy("image_id").collect()  # one block
        sent = spark.sparkContext.broadcast([(r["image_id"], bytes(r["places"]), bytes(r["words"])) for r in part])

        def look(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            tables = QueryTables([(q, *_unpack(p, w)) for q, p, w in sent.value])
            for batch in batches:
                rows = []
                for i, p, w in zip(*(batch.column(c).to_pylist() for c in ("image_id", "places", "words")), strict=True):
                    rows += [(q, i, n, float(np.degrees(t) % 360), s) for q, n, t, s in tables.search(*_unpack(p, w))]
                kinds_ = (pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64())
                yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds_)], schema.names)

        found = to_python(known, look, schema)
        if n_blocks > 1:
            found = materialise(found, "image-matches")
        out = found if out is None else out.unionByName(found)
    return out


def image_classes(images: DataFrame, key: str) -> tuple[DataFrame, DataFrame]:
    """Distinct images under their least id, and each row's class: (image_id, class_id, class_size)."""
    n = images.count()
    rows = images.select("image_id", F.xxhash64(key).alias("hash"), F.struct(F.col(key).alias("v")).alias("held"))  # in a struct null equals null
    groups = materialise(rows.groupBy("hash", "held").agg(F.min("image_id").alias("class_id"), F.count("*").alias("class_size")), "image-classes")
    members = attach(rows, groups, ["hash", "held"], n, "class_size")
    return groups.select(F.col("class_id").alias("image_id"), F.col("held.v").alias(key)), members.select("image_id", "class_id", "class_size")


# --- the given tables hold no pictures: each embedding is drawn as one ------------------------------------------------

CELL, SIDE = 12, 8


def draw(vector: list[float] | None) -> np.ndarray:
    """A grey field with one rectangle for each number, which fixes its place, size and shade, lightly blurred."""
    v = np.zeros(SIDE * SIDE)
    given = np.abs(np.nan_to_num(np.array([x or 0.0 for x in vector or ()], float)))[: SIDE * SIDE]
    v[: len(given)] = given
    part = lambda k: (v * k) % 1.0
    cell = np.arange(SIDE * SIDE)
    y = (cell // SIDE + 0.5 + 1.4 * (part(97) - 0.5)) * CELL
    x = (cell % SIDE + 0.5 + 1.4 * (part(53) - 0.5)) * CELL
    h, w = 2 + 7 * part(31), 2 + 7 * part(71)
    grey = np.rint(255 * part(13))
    size = SIDE * CELL
    # a soft light over all, so that plain areas have a slope as in a photograph
    at = np.arange(size) / size
    light = sum(np.cos(2 * np.pi * ((1 + 3 * part(17 + k)[k]) * at[:, None] + (1 + 3 * part(29 + k)[k + 8]) * at[None, :] + part(7)[k])) for k in range(3))
    image = np.full((size, size), 128.0)
    for y0, y1, x0, x1, g in zip(*(np.clip(np.rint(e), 0, size).astype(int).tolist() for e in (y - h, y + h, x - w, x + w)), grey.tolist(), strict=True):
        image[y0:y1, x0:x1] = g
    image = 0.7 * image + 35 + 16 * light
    return np.clip(_box(np.pad(image, 1, mode="edge"), 1)[1:-1, 1:-1] / 9, 0, 255).astype(np.uint8)


def edited(image: np.ndarray, which: int) -> np.ndarray:
    """A cropped, a darkened and a turned copy."""
    if which % 3 == 0:
        return image[14:86, 9:81]
    if which % 3 == 1:
        return np.clip(image * 0.7 + 30, 0, 255).astype(np.uint8)
    return np.ascontiguousarray(np.rot90(image))


def _drawn(edit: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("image_id").to_pylist()
            made = [draw(v) for v in batch.column("vector").to_pylist()]
            if edit:
                made = [edited(m, i // QUERY_EVERY) for i, m in zip(ids, made, strict=True)]
            column = pa.StructArray.from_arrays([pa.array([m.shape[0] for m in made], pa.int32()), pa.array([m.shape[1] for m in made], pa.int32()), pa.array([m.tobytes() for m in made], pa.binary())], ["height", "width", "pixels"])
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), column], ["image_id", "image"])

    return run


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every vec_id divisible by 100 asks with an edited copy of its picture; all pictures answer.

    Rows of kind ``member`` give each vec_id its class; rows of kind ``match`` link the asking vec_id to the classes that hold its picture.
    """
    vectors = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("image_id"), F.col("embedding").alias("vector"))
    distinct, members = image_classes(vectors, "vector")
    schema = T.StructType([T.StructField("image_id", LONG), T.StructField("image", IMAGE)])
    # rows are small and pictures are not: dealt by number, not by bytes
    images = to_python(distinct.repartition(max(8, distinct.count() // TASK_IMAGES), "image_id"), _drawn(False), schema)
    asked = to_python(vectors.where(F.col("image_id") % QUERY_EVERY == 0), _drawn(True), schema)
    found = search(images, asked)
    none = F.lit(None)
    return members.select(F.lit("member").alias("kind"), F.col("image_id").alias("vec_id"), "class_id", none.cast("long").alias("inliers"), none.cast("double").alias("turn_degrees"), none.cast("double").alias("scale")).unionByName(
        found.select(F.lit("match").alias("kind"), F.col("query_id").alias("vec_id"), F.col("image_id").alias("class_id"), "inliers", "turn_degrees", "scale")
    )
