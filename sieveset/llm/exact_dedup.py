"""Exact dedup by composable polynomial fingerprints.

A text's fingerprint is its polynomial over two primes, with its length. Hashes of adjoining chunks combine: the left one is
shifted by the right one's length and added. So the chunks of a huge document are hashed by many tasks and summed.
Documents with equal fingerprints are then compared with the one that stays, chunk by chunk; those that differ after all
are told apart by their digest.

Texts are equal when identical after lower-casing A-Z only. Of equal texts the row with the largest doc_id stays.

Defined cases: a null text equals an empty one; a null doc_id ranks before all others; of repeated rows with one doc_id and text exactly one stays; equal doc_ids with
different texts are different documents; an empty table gives an empty result; further columns are ignored by ``find_copies`` and
pass through ``drop_copies``.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import LONG, STRING, attach, fields, lower_ascii, materialise, table, to_python

#: Bytes of a chunk. Documents of more are hashed by several tasks.
CHUNK = 65_536
#: Two primes below 2**31, and a base for each. Fixed values.
PRIMES = (2_147_483_647, 2_147_483_629)
BASES = (1_000_003, 998_244_353)
#: Ids of copies are broadcast up to so many; beyond, texts meet them by a shuffle.
BROADCAST_IDS = 250_000
#: Copies that are compared in one portion, on average at most.
SHARE = 64


class Polynomial:
    """Hash of bytes as a polynomial modulo each prime; bytes count from 1, so leading zeros matter."""

    def __init__(self, chunk: int = CHUNK):
        self.chunk = chunk
        self.powers = []
        for p, b in zip(PRIMES, BASES, strict=True):
            table_ = np.ones(chunk, np.uint64)
            done = 1
            while done < chunk:  # doubling: the next run is the last one shifted
                step = np.uint64(pow(b, done, p))
                n = min(done, chunk - done)
                table_[done : done + n] = table_[:n] * step % np.uint64(p)
                done += n
            self.powers.append(np.ascontiguousarray(table_[::-1]))

    def of_chunk(self, data: np.ndarray) -> tuple[int, int]:
        """``data``: at most one chunk of uint8. Sums stay below 2**56."""
        if not len(data):
            return 0, 0
        wide = data.astype(np.uint64) + np.uint64(1)
        return tuple(int(np.dot(wide, w[self.chunk - len(data) :])) % p for w, p in zip(self.powers, PRIMES, strict=True))

    @staticmethod
    def shift(hashes: tuple[int, int], length: int) -> tuple[int, int]:
        """The share of a chunk after which ``length`` bytes follow."""
        return tuple(h * pow(b, length, p) % p for h, p, b in zip(hashes, PRIMES, BASES, strict=True))

    def combine(self, left: tuple[int, int], right: tuple[int, int], right_length: int) -> tuple[int, int]:
        return tuple((x + y) % p for x, y, p in zip(self.shift(left, right_length), right, PRIMES, strict=True))

    def of(self, data: bytes) -> tuple[int, int]:
        out, whole = (0, 0), np.frombuffer(data, np.uint8)
        for at in range(0, len(data), self.chunk):
            part = whole[at : at + self.chunk]
            out = self.combine(out, self.of_chunk(part), len(part))
        return out


def _hash_whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    poly = Polynomial()
    for batch in batches:
        sizes, first, second, digests = [], [], [], []
        for text in batch.column("text"):
            data = (text.as_py() or b"").lower()
            a, b = poly.of(data)
            sizes.append(len(data))
            first.append(a)
            second.append(b)
            digests.append(hashlib.sha256(data).hexdigest())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("raw"), pa.array(sizes, pa.int64()), pa.array(first, pa.int64()), pa.array(second, pa.int64()), pa.array(digests, pa.string())], ["doc_id", "raw", "n_bytes", "h1", "h2", "text_sha256"])


def _hash_chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each chunk's share of its document's fingerprint."""
    poly = Polynomial()
    for batch in batches:
        out = [poly.shift(poly.of_chunk(np.frombuffer(c.as_py().lower(), np.uint8)), after) for c, after in zip(batch.column("chunk"), batch.column("after").to_pylist(), strict=True)]
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", "raw", "n_bytes", "text_sha256", "copy")), pa.array([a for a, _ in out], pa.int64()), pa.array([b for _, b in out], pa.int64())], ["doc_id", "raw", "n_bytes", "text_sha256", "copy", "h1", "h2"])


def _chunks(data: Column) -> Column:
    """Numbered chunks of a binary column; an empty one has one empty chunk."""
    starts = F.sequence(F.lit(0), F.greatest(F.lit(0), F.octet_length(data) - 1), F.lit(CHUNK))
    return F.posexplode(F.transform(starts, lambda s: F.substring(data, s + 1, F.lit(CHUNK))))


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, raw (a hash of the text as it is), n_bytes, h1, h2, text_sha256 and a row number ``uid``."""
    data = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), data.alias("text"))
    rows = rows.withColumn("raw", F.xxhash64("text"))
    kinds = fields(doc_id=LONG, raw=LONG, n_bytes=LONG, h1=LONG, h2=LONG, text_sha256=STRING)
    small = to_python(rows.where(F.octet_length("text") <= CHUNK), _hash_whole, kinds)
    huge = rows.where(F.octet_length("text") > CHUNK).withColumns({"n_bytes": F.octet_length("text").cast("long"), "copy": F.monotonically_increasing_id(), "text_sha256": F.sha2(lower_ascii(F.col("text").cast("string")).cast("binary"), 256)})
    cut = huge.select("doc_id", "raw", "n_bytes", "text_sha256", "copy", _chunks(F.col("text")).alias("at", "chunk"))
    cut = cut.withColumn("after", F.greatest(F.lit(0), F.col("n_bytes") - (F.col("at") + 1) * CHUNK)).drop("at").repartition("doc_id", "after")
    shares = to_python(cut, _hash_chunks, fields(doc_id=LONG, raw=LONG, n_bytes=LONG, text_sha256=STRING, copy=LONG, h1=LONG, h2=LONG))
    combined = shares.groupBy("doc_id", "raw", "n_bytes", "text_sha256", "copy").agg(*((F.sum(h) % p).alias(h) for h, p in zip(("h1", "h2"), PRIMES, strict=True))).drop("copy")
    return materialise(small.unionByName(combined).withColumn("uid", F.monotonically_increasing_id()), "fingerprints")


KEY = ["n_bytes", "h1", "h2"]


def _groups(rows: DataFrame, key: list[str]) -> DataFrame:
    """Size of each group and its row that stays. Partial results are made before the shuffle, so a hot group costs one row a task."""
    first = F.max(F.struct("doc_id", (-F.col("uid")).alias("nuid"), "raw"))
    grouped = rows.groupBy(*key).agg(F.count("*").alias("group_size"), first.alias("first")).where("group_size > 1")
    return grouped.select(*key, "group_size", F.col("first.doc_id").alias("keep_id"), (-F.col("first.nuid")).alias("keep_uid"), F.col("first.raw").alias("keep_raw"))


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Streams chunks sorted by place and rank: the staying row's chunk comes first and is held, one at a time."""
    held, at = None, None
    for batch in batches:
        bad = []
        for place, rank, doc, raw, chunk in zip(*(batch.column(c).to_pylist() for c in ("place", "rank", "doc_id", "raw", "chunk")), strict=True):
            data = chunk.lower()
            if rank == 0:
                held, at = data, place
            elif place != at or data != held:
                bad.append((doc, raw))
        yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in bad], pa.int64()) for i in (0, 1)], ["doc_id", "raw"])


def _texts(docs: DataFrame) -> DataFrame:
    data = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), data.alias("text")).withColumn("raw", F.xxhash64("text"))


def differing_copies(docs: DataFrame, copies: DataFrame, n_copies: int) -> DataFrame:
    """(doc_id, raw) of copies whose text is not that of the row which stays, compared chunk by chunk.

    Only texts of copies move. A group is dealt in portions of SHARE, each with the chunks of the row that stays, so
    a group of any size spreads over many tasks.
    """
    others = copies.where("uid != keep_uid")
    portion = F.pmod(F.xxhash64("doc_id", "raw"), F.expr(f"group_size div {SHARE} + 1")).alias("portion")
    others = others.select("doc_id", "raw", "keep_id", "keep_raw", F.concat_ws(":", *KEY, portion).alias("group"))
    asked = others.select("doc_id", "raw", "group", F.lit(1).alias("rank")).distinct()
    led = others.select(F.col("keep_id").alias("doc_id"), F.col("keep_raw").alias("raw"), "group", F.lit(0).alias("rank")).distinct()
    tasks = asked.unionByName(led).withColumnsRenamed({"doc_id": "_id", "raw": "_raw"})
    if n_copies <= BROADCAST_IDS:
        tasks = F.broadcast(tasks)
    texts = _texts(docs)
    cut = texts.join(tasks, texts["doc_id"].eqNullSafe(tasks["_id"]) & (texts["raw"] == tasks["_raw"])).select("doc_id", "raw", "rank", "group", _chunks(F.col("text")).alias("at", "chunk"))
    placed = cut.select(F.concat_ws(":", "group", "at").alias("place"), "rank", "doc_id", "raw", "chunk")
    dealt = placed.repartition("place").sortWithinPartitions("place", "rank")
    return to_python(dealt, _compare, fields(doc_id=LONG, raw=LONG)).distinct()


def grouped_copies(docs: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """All rows' fingerprints; of rows with copies also group_size, keep_id, keep_uid, keep_raw; the number of the latter."""
    prints = fingerprints(docs)
    n = prints.count()
    copies = materialise(attach(prints, materialise(_groups(prints, KEY), "fingerprint-groups"), KEY, n), "copies")
    n_copies = copies.count()
    if n_copies and not materialise(differing_copies(docs, copies, n_copies), "differing").isEmpty():
        # a fingerprint that two texts share: those groups are made anew, by digest
        exact = [*KEY, "text_sha256"]
        copies = materialise(attach(prints, materialise(_groups(prints, exact), "digest-groups"), exact, n), "copies")
        n_copies = copies.count()
    return prints, copies, n_copies


def find_copies(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256."""
    prints, copies, _ = grouped_copies(docs)
    known = copies.select("uid", "keep_id", "group_size", (F.col("uid") == F.col("keep_uid")).alias("kept"))
    return prints.select("uid", "doc_id", "text_sha256").join(known, "uid", "left").select(
        "doc_id",
        F.coalesce("keep_id", "doc_id").alias("keep_id"),
        F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"),
        F.coalesce("kept", F.lit(True)).alias("kept"),
        "text_sha256",
    )


def drop_copies(docs: DataFrame) -> DataFrame:
    """``docs`` without the copies, all columns as they were. Texts stay where they are unless the ids of copies are too many to broadcast."""
    _, copies, n_copies = grouped_copies(docs)
    twin = F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("raw") == F.col("keep_raw"))
    others = copies.where("uid != keep_uid")
    gone = others.where(~twin).select(F.col("doc_id").alias("_gone_id"), F.col("raw").alias("_gone_raw")).distinct()
    raw = F.xxhash64(F.coalesce(F.col("text"), F.lit("")).cast("binary"))
    gone = F.broadcast(gone) if n_copies <= BROADCAST_IDS else gone
    kept = docs.withColumn("_raw", raw)
    kept = kept.join(gone, kept["doc_id"].cast("long").eqNullSafe(gone["_gone_id"]) & (kept["_raw"] == gone["_gone_raw"]), "left_anti")
    if not others.where(twin).isEmpty():  # repeated rows
        kept = kept.dropDuplicates(["doc_id", "_raw"])
    return kept.drop("_raw")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_copies(table(spark, sf_dir, "documents"))


def oracle() -> str:
    return """
with d as (select doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) as text_sha256 from documents)
select doc_id, max(doc_id) over (partition by text_sha256) as keep_id, count(*) over (partition by text_sha256) as group_size,
       doc_id = max(doc_id) over (partition by text_sha256) as kept, text_sha256 from d"""
