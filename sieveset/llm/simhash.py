"""SimHash near-dedup with covering-code anchors.

Each half of the 64-bit fingerprint is covered by a code: its last 31 bits by the perfect Hamming code of length 31, its first bit
by itself. Every word of 32 bits lies within one bit of exactly one anchor (the covering radius), its home. Fingerprints that
differ in at most 3 bits differ in at most 1 bit in some half, so the other one lies within radius plus threshold, two
bits, of that home. Each distinct fingerprint is replicated to all anchors within two bits, 17 or so a half, and at each anchor those
at home are compared with all others. Anchors with many fingerprints are cut into pairs of blocks, so no anchor has to fit a task.

Equal fingerprints are one node, whatever their number. At an anchor only a spanning forest of the links is emitted,
which leaves components as they are.

Defined cases: a null or empty text, or one of blanks only, has fingerprint zero and is linked like any other; fewer than
three words make one shingle; a null doc_id ranks after all others, and of several texts with a null id each keeps its own row;
very long texts are counted slab by slab; repeated rows are one node; an empty table gives an empty result; further columns are
ignored by ``near_copies`` and pass through ``drop_near_copies``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import LONG, attach, dealt_cells, fields, lead, materialise, table, to_python
from .components import components

SEED = 42
WORDS = 3
MAX_BITS = 3
#: Members of an anchor that are compared at a time.
BLOCK = 2048
#: Shingles that are counted at a time, so a huge text needs bounded memory.
SLAB = 1 << 16
#: Ids of rows that go, two numbers each, are broadcast up to so many (some 20 MB as a hash table); beyond, rows meet them by a shuffle.
BROADCAST_IDS = 250_000


def fingerprint(text: bytes | None, words: int = WORDS, seed: int = SEED) -> int:
    """64 bits; one is set when it is set in over half of the shingles' hashes."""
    from xxhash import xxh64_intdigest

    parts = (text or b"").lower().split()
    if not parts:
        return 0
    if len(parts) <= words:
        return xxh64_intdigest(b" ".join(parts), seed)
    n = len(parts) - words + 1
    counts = np.zeros(64, np.int64)
    for at in range(0, n, SLAB):
        piece = parts[at : min(n, at + SLAB) + words - 1]
        shingles = map(b" ".join, zip(*(piece[i:] for i in range(words)), strict=False))
        hashes = np.fromiter((xxh64_intdigest(s, seed) for s in shingles), np.uint64, len(piece) - words + 1)
        counts += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(counts * 2 > n, bitorder="little").tobytes(), "little")


def _signed(values: list[int]) -> pa.Array:
    return pa.array(np.array(values, np.uint64).view(np.int64), pa.int64())


def _fingerprints(words: int, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [fingerprint(t.as_py(), words, seed) for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i, c in enumerate(batch.schema.names) if c != "text"), _signed(found)], [*(c for c in batch.schema.names if c != "text"), "fp"])

    return run


# The Hamming code of length 31: bit i of a word has column i + 1, and the sum of the columns of its set bits is the syndrome.
_COLUMNS = np.arange(1, 32, dtype=np.uint32)


def _syndrome(word: np.ndarray) -> np.ndarray:
    out = np.zeros_like(word)
    for i in range(31):
        out ^= np.where(word >> np.uint32(i) & np.uint32(1), _COLUMNS[i], np.uint32(0))
    return out


def _flip(word: np.ndarray, syndrome: np.ndarray) -> np.ndarray:
    """The code word that cancels the syndrome; 0 leaves the word."""
    bit = np.where(syndrome > 0, np.uint32(1) << (np.maximum(syndrome, np.uint32(1)) - np.uint32(1)), np.uint32(0))
    return word ^ bit


def anchors(half: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each 32-bit word: its home anchor, then (row, anchor) for every other anchor within two bits.

    Within two bits of a word w lie: its home h, the home with the top bit flipped (if that costs two bits or less), and the
    code words at distance two of the lower 31 bits: flips of two columns that sum to the syndrome.
    """
    top, low = half & np.uint32(1 << 31), half & np.uint32((1 << 31) - 1)
    syndrome = _syndrome(low)
    home = _flip(low, syndrome) | top
    rows, out = [np.arange(len(half))], [home ^ np.uint32(1 << 31)]
    for i in range(1, 32):  # pairs of columns i < j with i ^ j = syndrome
        j = syndrome ^ np.uint32(i)
        ok = (j > i) & (syndrome > 0)
        if ok.any():
            rows.append(np.flatnonzero(ok))
            out.append((low[ok] ^ np.uint32(1 << (i - 1)) ^ (np.uint32(1) << (j[ok] - np.uint32(1)))) | top[ok])
    return home, np.concatenate(rows), np.concatenate(out)


def _replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        fps = batch.column("fp").to_numpy().view(np.uint64)
        for which in (0, 1):
            half = ((fps >> np.uint64(32 * which)) & np.uint64(0xFFFFFFFF)).astype(np.uint32)
            home, rows, far = anchors(half)
            for anchor, at_home, own in ((home, True, np.arange(len(fps))), (far, False, rows)):
                key = anchor.astype(np.int64) * 2 + which
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(np.full(len(own), at_home)), pa.array(fps[own].view(np.int64))], ["anchor", "home", "fp"])


def forest(homes: np.ndarray, others: np.ndarray, max_bits: int = MAX_BITS) -> list[tuple[int, int]]:
    """Links of a spanning forest among the fingerprints of one anchor; pairs without one at home meet at another anchor."""
    members = np.concatenate([homes, others])
    root = np.arange(len(members))
    links: list[tuple[int, int]] = []
    for i in range(len(homes)):
        for at in range(i + 1, len(members), BLOCK):
            near = at + np.flatnonzero(np.bitwise_count(members[at : at + BLOCK] ^ members[i]) <= max_bits)
            for j in near[root[near] != root[i]]:
                if root[j] != root[i]:
                    links.append((int(members[i]), int(members[j])))
                    root[root == root[j]] = root[i]
    return links


def _compare(max_bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Partitions are sorted by anchor and cell; a cell's fingerprints may span batches."""
        keep: list[np.ndarray] = []

        def links_of(new: np.ndarray, h: np.ndarray, f: np.ndarray) -> list[tuple[int, int]]:
            out = []
            starts = np.flatnonzero(new)
            ends = np.r_[starts[1:], len(new)]
            for s, e in zip(starts[ends - starts > 1], ends[ends - starts > 1], strict=True):
                if h[s:e].any():
                    out += forest(f[s:e][h[s:e]], f[s:e][~h[s:e]], max_bits)
            return out

        def emit(links: list[tuple[int, int]]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([_signed([x[i] for x in links]) for i in (0, 1)], ["u", "v"])

        for batch in batches:
            cols = [batch.column(c).to_numpy(zero_copy_only=False) for c in ("anchor", "i", "j", "home", "fp")]
            if keep:
                cols = [np.concatenate([k, x]) for k, x in zip(keep, cols, strict=True)]
            if not len(cols[0]):
                continue
            new = np.r_[True, np.any([x[1:] != x[:-1] for x in cols[:3]], axis=0)]
            last = int(np.flatnonzero(new)[-1])
            keep = [x[last:] for x in cols]
            yield emit(links_of(new[:last], cols[3][:last], cols[4][:last].view(np.uint64)))
        if keep:
            new = np.r_[True, np.zeros(len(keep[0]) - 1, bool)]
            yield emit(links_of(new, keep[3], keep[4].view(np.uint64)))

    return run


def links(distinct: DataFrame, max_bits: int = MAX_BITS) -> DataFrame:
    """(u, v): links between distinct fingerprints that keep their components."""
    kinds = T.StructType([T.StructField("anchor", LONG), T.StructField("home", T.BooleanType()), T.StructField("fp", LONG)])
    spread = lambda df: to_python(df, _replicate, kinds)
    dealt = dealt_cells(spread(distinct), distinct, spread, "anchor", "fp").select("anchor", "i", "j", "home", "fp")
    return to_python(dealt.sortWithinPartitions("anchor", "i", "j"), _compare(max_bits), fields(u=LONG, v=LONG)).distinct()


def near_copies(docs: DataFrame, words: int = WORDS, seed: int = SEED, max_bits: int = MAX_BITS) -> DataFrame:
    """doc_id, raw (a hash of the text), fp (signed), component_id, lead_raw (raw of the row of that id),
    component_size and class_size (rows with this fingerprint)."""
    data = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(data).alias("raw"), data.alias("text"))
    prints = materialise(to_python(rows, _fingerprints(words, seed), fields(doc_id=LONG, raw=LONG, fp=LONG)), "simhash")
    n = prints.count()
    nodes = materialise(prints.groupBy("fp").agg(lead("doc_id", "raw").alias("least"), F.count("*").alias("class_size")), "simhash-nodes")
    roots = components(links(nodes.select("fp"), max_bits))
    # few fingerprints have a link
    rooted = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    rooted = materialise(rooted, "simhash-rooted")
    whole = rooted.groupBy("root").agg(F.min("least").alias("lead"), F.sum("class_size").alias("component_size"), F.count("*").alias("nodes"))
    whole = whole.select("root", F.col("lead.doc_id").alias("component_id"), F.col("lead.raw").alias("lead_raw"), "component_size", "nodes")
    n_nodes = nodes.count()
    named = attach(rooted.drop("least"), materialise(whole, "simhash-components"), ["root"], max(1, n_nodes), "nodes").drop("nodes", "root")
    return attach(prints, materialise(named, "simhash-named"), ["fp"], n, "class_size")


def drop_near_copies(docs: DataFrame, words: int = WORDS, seed: int = SEED, max_bits: int = MAX_BITS) -> DataFrame:
    """``docs`` with the row of the least doc_id of each component, all columns as they were."""
    return keep_leads(docs, near_copies(docs, words, seed, max_bits))


def drop_similar(docs: DataFrame, **given) -> DataFrame:
    """``docs`` with the first row of each component of texts whose sets of shingles are similar (``similar.similar_copies``)."""
    from .similar import similar_copies

    return keep_leads(docs, similar_copies(docs, **given))


def keep_leads(docs: DataFrame, found: DataFrame) -> DataFrame:
    """``docs`` without the rows that ``found`` (doc_id, raw, component_id, lead_raw) says are not their component's first."""
    found = materialise(found, "near-copies")
    gone = found.where("not (doc_id <=> component_id and raw = lead_raw)").select(F.col("doc_id").alias("_gone_id"), F.col("raw").alias("_gone_raw")).distinct()
    n = gone.count()
    left = docs.withColumn("_raw", F.xxhash64(F.coalesce(F.col("text"), F.lit("")).cast("binary")))
    same = left["doc_id"].cast("long").eqNullSafe(F.col("_gone_id")) & (F.col("_raw") == F.col("_gone_raw"))
    left = left.join(F.broadcast(gone) if n <= BROADCAST_IDS else gone, same, "left_anti")
    if not found.groupBy("doc_id", "raw").count().where("count > 1").isEmpty():  # repeated rows
        left = left.dropDuplicates(["doc_id", "_raw"])
    return left.drop("_raw")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_copies(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "component_size")
