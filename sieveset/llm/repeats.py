"""Repeated passages: every byte under a 200-byte string that also starts elsewhere is removed.

Which windows of 200 bytes recur is decided over all documents:

1. Each window has an anchor, its least 48-byte string under a hash. Windows in a row with one anchor form a run. Equal
   windows have equal anchors, so a window whose anchor string occurs once cannot recur; its run is dropped.
2. Runs whose anchor recurs are grouped with the text they span. Where the same span occurs twice, all its windows recur. Spans are
   told by two independent 64-bit hashes (a polynomial and XXH3) and their anchor; their bytes are not compared.
3. The spans that are left are those on the edges of repeated passages. They are brought together by anchor, and a suffix
   array, built by grouping suffixes on their Lyndon prefixes, finds which of their windows have an equal neighbour, byte by byte.

Only hashes and positions move for all documents; text moves for the spans of step 3. Anchors of over HOT_SPANS different
spans are dealt by window instead, by two such hashes of each window, so no anchor has to fit one task.

Defined cases: a null text is empty; rows with a null doc_id are treated like all others; very long texts are hashed in slabs; matches never cross documents; a text of under 200 bytes loses nothing; repeated rows match
each other; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BINARY, LONG, STRING, attach, fields, materialise, table, to_python
from .lyndon import suffix_array

WINDOW = 200
GRAM = 48
#: Bytes of a text that are hashed at a time; positions in it take 20 bits.
SLAB = 1 << 19
_POSITION_BITS = 20
#: Different spans of one anchor that one task sorts, at most.
HOT_SPANS = 16_384
#: Bytes that are sorted together, unless one anchor has more.
SORT_BYTES = 1 << 18

_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_U = np.uint64
#: Stands for a null doc_id while spans are looked for.
NO_ID = -(1 << 63)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, _U(base))
    out[0] = 1
    return np.multiply.accumulate(out)


def _mixed(h: np.ndarray) -> np.ndarray:
    for factor in (0xD6E8FEB86659FD93, 0xC2B2AE3D27D4EB4F):
        h = (h ^ (h >> _U(32))) * _U(factor)
    return h ^ (h >> _U(32))


def _window_minimum(v: np.ndarray, w: int) -> np.ndarray:
    """Least of each w values in a row, from running minima of blocks of w in both directions."""
    n = len(v)
    padded = np.full(-(-n // w) * w, ~_U(0))
    padded[:n] = v
    blocks = padded.reshape(-1, w)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    back = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[: n - w + 1], ahead[w - 1 : n])


class Hasher:
    """Hashes of substrings of one text at a time, independent of where they stand."""

    def __init__(self, size: int = SLAB + WINDOW):
        self.up, self.down = _powers(_BASE, size), _powers(_INVERSE, size)

    def prefix(self, data: np.ndarray) -> np.ndarray:
        out = np.zeros(len(data) + 1, _U)
        np.cumsum((data.astype(_U) + _U(1)) * self.up[: len(data)], out=out[1:])
        return out

    def spans(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return _mixed((prefix[end] - prefix[start]) * self.down[start] + (end - start).astype(_U) * _U(0x9FB21C651E98DF25))

    def grams(self, prefix: np.ndarray, k: int) -> np.ndarray:
        n = len(prefix) - k
        return _mixed((prefix[k:] - prefix[:-k]) * self.down[:n])


def second_hashes(data: bytes, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """XXH3 of substrings, which shares nothing with the polynomial."""
    from xxhash import xxh3_64_intdigest

    view = memoryview(data)
    return np.fromiter((xxh3_64_intdigest(view[a:b]) for a, b in zip(start.tolist(), end.tolist(), strict=True)), _U, len(start))


def runs_of(data: bytes, hasher: Hasher) -> tuple[np.ndarray, ...]:
    """Anchor, two span hashes, first window and number of windows of each run of a text."""
    out = []
    n_windows = len(data) - WINDOW + 1
    whole = np.frombuffer(data, np.uint8)
    low = _U((1 << _POSITION_BITS) - 1)
    for at in range(0, n_windows, SLAB):
        part = whole[at : min(len(data), at + SLAB + WINDOW - 1)]
        prefix = hasher.prefix(part)
        grams = hasher.grams(prefix, GRAM)
        tagged = (grams & ~low) | np.arange(len(grams), dtype=_U)
        place = (_window_minimum(tagged, WINDOW - GRAM + 1) & low).astype(np.int64)
        start = np.flatnonzero(np.r_[True, place[1:] != place[:-1]])
        count = np.diff(np.r_[start, len(place)])
        end = start + count - 1 + WINDOW
        out.append((grams[place[start]], hasher.spans(prefix, start, end), second_hashes(data, at + start, at + end), start + at, count))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hasher = Hasher()
    for batch in batches:
        found, owners, tags = [], [], []
        for doc, tag, text in zip(batch.column("doc_id").to_pylist(), batch.column("tag").to_pylist(), batch.column("text"), strict=True):
            data = text.as_py()
            if len(data) >= WINDOW:
                found.append(runs_of(data, hasher))
                owners.append(np.full(len(found[-1][0]), doc, np.int64))
                tags.append(np.full(len(found[-1][0]), tag, np.int64))
        if found:
            anchor, span, span2, start, count = (np.concatenate(x) for x in zip(*found, strict=True))
            cols = [anchor.view(np.int64), span.view(np.int64), span2.view(np.int64), np.concatenate(owners), np.concatenate(tags), start, count]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["anchor", "span", "span2", "doc_id", "tag", "start", "windows"])


def _segments(flags: np.ndarray) -> list[tuple[int, int]]:
    """(first, last + 1) of each stretch of true."""
    edges = np.flatnonzero(np.diff(np.r_[False, flags, False]))
    return list(zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True))


def recurring_windows(spans: list[bytes], hasher: Hasher) -> list[np.ndarray]:
    """For each span, which of its windows occur at another place among the spans.

    Windows with a hash of their own are set aside. What stands between them is cut out, equal cuts are merged, and a
    suffix array over the cuts puts equal windows next to each other, where they are compared byte by byte.
    """
    flags = [np.zeros(max(0, len(s) - WINDOW + 1), bool) for s in spans]
    hashes = []
    for s, f in zip(spans, flags, strict=True):
        prefix = hasher.prefix(np.frombuffer(s, np.uint8))
        first = np.arange(len(f))
        hashes.append(hasher.spans(prefix, first, first + WINDOW))
    every = np.concatenate(hashes)
    _, back, times = np.unique(every, return_inverse=True, return_counts=True)
    maybe = np.split(times[back] > 1, np.cumsum([len(f) for f in flags])[:-1])
    cuts: dict[bytes, list[tuple[int, int]]] = {}
    for i, (s, m) in enumerate(zip(spans, maybe, strict=True)):
        for a, b in _segments(m):
            cuts.setdefault(s[a : b - 1 + WINDOW], []).append((i, a))
    if not cuts:
        return flags
    texts = list(cuts)
    joined = b"".join(texts)
    ends = np.cumsum([len(t) for t in texts])
    text: list[int] = []
    for t in texts:  # each cut ends with a symbol below all bytes
        text += [c + 2 for c in t]
        text.append(1)
    order = np.array(suffix_array(text), np.int64)
    owner = np.repeat(np.arange(len(texts)), [len(t) + 1 for t in texts])
    local = np.arange(len(text)) - np.repeat(np.r_[0, ends[:-1]] + np.arange(len(texts)), [len(t) + 1 for t in texts])
    lengths = np.array([len(t) for t in texts])
    order = order[local[order] + WINDOW <= lengths[owner[order]]]
    at = np.r_[0, ends[:-1]][owner[order]] + local[order]
    view = np.lib.stride_tricks.sliding_window_view(np.frombuffer(joined, np.uint8), WINDOW)
    same = np.zeros(len(order), bool)
    for i in range(0, len(order) - 1, 4096):
        x = view[at[i : i + 4097]]
        equal = (x[1:] == x[:-1]).all(1)
        same[i : i + len(equal)] |= equal
        same[i + 1 : i + 1 + len(equal)] |= equal
    found = [np.zeros(n - WINDOW + 1, bool) for n in lengths]
    for o, l_ in zip(owner[order[same]].tolist(), local[order[same]].tolist(), strict=True):
        found[o][l_] = True
    for f, where in zip(found, cuts.values(), strict=True):
        for i, a in where:
            flags[i][a : a + len(f)] |= True if len(where) > 1 else f
    return flags


def _sort_spans(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by anchor. Gives the stretches of bytes that recur, for spans that occur once."""
    hasher = Hasher()
    rows: list[tuple] = []
    size = 0

    def flush() -> pa.RecordBatch:
        out = []
        for (_, doc, tag, start, times, _), f in zip(rows, recurring_windows([r[5] for r in rows], hasher), strict=True):
            if times == 1:
                out += [(doc, tag, start + a, start + b - 1 + WINDOW) for a, b in _segments(f)]
        rows.clear()
        return pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], pa.int64()) for i in range(4)], ["doc_id", "tag", "lo", "hi"])

    for batch in batches:
        for row in zip(*(batch.column(c).to_pylist() for c in ("anchor", "doc_id", "tag", "start", "times", "text")), strict=True):
            if rows and size >= SORT_BYTES and row[0] != rows[-1][0]:
                yield flush()
                size = 0
            rows.append(row)
            size += len(row[5])
    if rows:
        yield flush()


def _window_hashes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Two independent hashes of each window of a span."""
    hasher = Hasher()
    for batch in batches:
        for doc, tag, start, times, text in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "tag", "start", "times", "text")), strict=True):
            data = np.frombuffer(text, np.uint8)
            first = np.arange(len(data) - WINDOW + 1)
            h1 = hasher.spans(hasher.prefix(data), first, first + WINDOW)
            h2 = second_hashes(text, first, first + WINDOW)
            cols = [h1.view(np.int64), h2.view(np.int64), np.full(len(first), doc), np.full(len(first), tag), first + start, np.full(len(first), times)]
            yield pa.RecordBatch.from_arrays([pa.array(np.asarray(c, np.int64)) for c in cols], ["h1", "h2", "doc_id", "tag", "at", "times"])


def repeated_spans(docs: DataFrame) -> DataFrame:
    """doc_id (NO_ID for null), tag (a hash of the text) and spans, the maximal stretches (lo, hi) of bytes to remove, of documents that have any."""
    rows = _texts(docs)
    kinds = fields(anchor=LONG, span=LONG, span2=LONG, doc_id=LONG, tag=LONG, start=LONG, windows=LONG)
    runs = materialise(to_python(rows, _runs, kinds), "repeat-runs")
    n = runs.count()
    again = materialise(runs.groupBy("anchor").agg(F.count("*").alias("uses")).where("uses > 1"), "repeat-anchors")
    shared = materialise(attach(runs, again, ["anchor"], n, "uses").drop("uses"), "repeat-shared")
    n = shared.count()
    spans = shared.groupBy("anchor", "span", "span2").agg(F.count("*").alias("times"), F.min(F.struct("doc_id", "tag", "start", "windows")).alias("at"))
    spans = materialise(spans, "repeat-spans")
    whole = attach(shared, spans.where("times > 1").select("anchor", "span", "span2", "times"), ["anchor", "span", "span2"], n, "times")
    whole = whole.select("doc_id", "tag", F.col("start").alias("lo"), (F.col("start") + F.col("windows") - 1 + WINDOW).alias("hi"))

    mixed = materialise(spans.groupBy("anchor").agg(F.count("*").alias("kinds")).where("kinds > 1"), "repeat-mixed")
    edges = attach(spans, mixed, ["anchor"], spans.count(), "kinds").select("anchor", "kinds", "times", "at.*")
    edges = edges.groupBy("doc_id", "tag").agg(F.collect_list(F.struct("anchor", "kinds", "times", "start", "windows")).alias("list"))
    edges = materialise(edges, "repeat-edges")
    picked = rows.join(edges.hint("shuffle_hash"), ["doc_id", "tag"])  # as many rows as documents at most: dealt by id
    cut = F.transform("list", lambda e: e.withField("text", F.substring("text", (e["start"] + 1).cast("int"), (e["windows"] + WINDOW - 1).cast("int"))))
    texts = materialise(picked.select("doc_id", "tag", F.explode(cut).alias("e")).select("doc_id", "tag", "e.*"), "repeat-texts")
    dealt = texts.where(F.col("kinds") <= HOT_SPANS).repartition("anchor").sortWithinPartitions("anchor")
    sorted_ = to_python(dealt, _sort_spans, fields(doc_id=LONG, tag=LONG, lo=LONG, hi=LONG))

    hot = to_python(texts.where(F.col("kinds") > HOT_SPANS), _window_hashes, fields(h1=LONG, h2=LONG, doc_id=LONG, tag=LONG, at=LONG, times=LONG))
    if not mixed.where(F.col("kinds") > HOT_SPANS).isEmpty():
        hot = materialise(hot, "repeat-windows")
        twice = hot.groupBy("h1", "h2").agg(F.sum("times").alias("uses")).where("uses > 1")
        by_window = attach(hot, materialise(twice, "repeat-window-hashes"), ["h1", "h2"], max(1, hot.count()), "uses").where("times = 1")
        sorted_ = sorted_.unionByName(by_window.select("doc_id", "tag", F.col("at").alias("lo"), (F.col("at") + WINDOW).alias("hi")))

    found = whole.unionByName(sorted_).groupBy("doc_id", "tag").agg(F.array_sort(F.collect_list(F.struct("lo", "hi"))).alias("list"))
    return found.select("doc_id", "tag", merged(F.col("list")).alias("spans"))


def merged(spans):
    """Sorted stretches with overlapping and touching ones joined; one step per stretch, whatever their number."""
    empty = F.expr("cast(array() as array<struct<lo:bigint,hi:bigint>>)")
    start = F.struct(empty.alias("done"), F.lit(None).cast("bigint").alias("lo"), F.lit(None).cast("bigint").alias("hi"))

    def step(acc, x):
        opened = F.struct(acc["done"].alias("done"), x["lo"].alias("lo"), x["hi"].alias("hi"))
        grown = F.struct(acc["done"].alias("done"), acc["lo"].alias("lo"), F.greatest(acc["hi"], x["hi"]).alias("hi"))
        closed = F.struct(F.concat(acc["done"], F.array(F.struct(acc["lo"].alias("lo"), acc["hi"].alias("hi")))).alias("done"), x["lo"].alias("lo"), x["hi"].alias("hi"))
        return F.when(acc["lo"].isNull(), opened).when(x["lo"] <= acc["hi"], grown).otherwise(closed)

    return F.aggregate(spans, start, step, lambda acc: F.concat(acc["done"], F.array(F.struct(acc["lo"].alias("lo"), acc["hi"].alias("hi")))))


def _texts(docs: DataFrame) -> DataFrame:
    """Rows with one id and text share what is found, so a null id may pass as any number."""
    data = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    own = F.col("doc_id").cast("long")
    return docs.select(F.coalesce(own, F.lit(NO_ID)).alias("doc_id"), own.isNull().alias("none"), F.xxhash64(data).alias("tag"), data.alias("text"))


def _remove(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = []
        for doc, text, spans in zip(batch.column("doc_id").to_pylist(), batch.column("text"), batch.column("spans").to_pylist(), strict=True):
            data, digest, at, gone = text.as_py(), hashlib.sha256(), 0, 0
            kept = []
            for s in spans or ():
                kept.append(data[at : s["lo"]])
                gone += s["hi"] - s["lo"]
                at = s["hi"]
            kept.append(data[at:])
            rest = b"".join(kept)
            digest.update(rest)
            out.append((doc, len(data), gone, len(spans or ()), digest.hexdigest(), rest))
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
        yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], k) for i, k in enumerate(kinds)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])


def remove_repeats(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, n_bytes, n_removed, n_spans, kept_sha256 and the kept bytes."""
    spans = materialise(repeated_spans(docs), "repeat-found")
    rows = _texts(docs).join(spans.hint("shuffle_hash"), ["doc_id", "tag"], "left")
    rows = rows.withColumn("doc_id", F.when(~F.col("none"), F.col("doc_id")))
    return to_python(rows.select("doc_id", "text", "spans"), _remove, fields(doc_id=LONG, n_bytes=LONG, n_removed=LONG, n_spans=LONG, kept_sha256=STRING, kept=BINARY))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents")).drop("kept")
