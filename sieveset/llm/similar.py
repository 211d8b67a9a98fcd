"""Near copies by shingle similarity: wide SimHash fingerprints meet at covering-code anchors, whole sets decide.

Two sets of similarity LIMIT differ in some 15% of their SimHash bits, far more than a threshold on 64 bits can bridge. So a text has a
wide fingerprint (FAMILIES times 64 bits), of which many parts of a few bits are drawn. Each part is cut into words of the lengths of
perfect Hamming codes, and its anchor is the tuple of the words' homes: code words that cover all words within one bit. The threshold is
zero here, so a text is replicated to one anchor a part. Parts are as many as make two sets at the limit meet with probability RECALL;
what meets is compared by 128 bits, what is near by those is checked on the whole sets, so no link is wrong.

At each anchor the texts that near pairs connect get links to the least of them, so groups of any size give as many links as members, which many anchors share. These
loose components hold every near pair that met. Then each text goes, with its whole set, to its loose component, large
ones cut into pairs of blocks, and all pairs there that the wide fingerprint allows are decided on their sets, unless they are
linked already. No pair is ever a row of a join.

Defined cases: texts with one set are one node and linked (all blank ones, for instance); a text of at most as many words as a shingle has one
shingle; a null doc_id ranks after all others; repeated rows are one node; a very long text is hashed slab by slab; an empty
table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BINARY, INT, LONG, LONGS, attach, dealt_cells, fields, lead, materialise, to_python
from .components import forest_components, merge
from .shingle_sets import LIMIT, SEED, WORDS, shingles, similar

#: Fingerprints of 64 bits each, and those of them that travel with every replica.
FAMILIES, CARRIED = 9, 2
#: Probability that two large sets at the limit share an anchor.
RECALL = 0.98
#: Members of an anchor, on average at most; a larger table takes one more code word a part, and more parts.
CROWD = 4096
#: Differing bits allowed of the carried 128: 3.9 deviations above the mean at a similarity of 0.8.
NEAR_BITS = 36
#: Whole sets that are compared together, about.
SET_ROWS = 1024
#: Texts with a near one are sent to all tasks up to so many, some 120 bytes each; beyond, texts meet them by a shuffle.
BROADCAST_ROWS = 100_000
#: Shingles whose bits are counted at a time.
SLAB = 1 << 14

_U = np.uint64


def remixed(hashes: np.ndarray, family: int) -> np.ndarray:
    """An independent 64-bit hash of each hash (a shift-multiply finaliser; any good one would do)."""
    z = hashes ^ _U(family * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        z = (z ^ (z >> _U(shift))) * _U(factor)
    return z ^ (z >> _U(31))


def wide_print(found: np.ndarray) -> np.ndarray:
    """FAMILIES numbers of 64 bits; a bit is set when it is set in over half of the shingles' hashes."""
    out = np.zeros(FAMILIES, _U)
    for k in range(FAMILIES):
        counts = np.zeros(64, np.int64)
        for at in range(0, len(found), SLAB):
            bits = np.unpackbits(remixed(found[at : at + SLAB], k + 1).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            counts += bits.sum(0, dtype=np.int64)
        out[k] = np.packbits(counts * 2 > len(found), bitorder="little").view(_U)[0]
    return out


# --- covering codes --------------------------------------------------------------------------------------------------


def homes(length: int) -> np.ndarray:
    """The home of every word of ``length`` = 2**r - 1 bits: the one code word of the Hamming code within one bit."""
    words = np.arange(1 << length, dtype=np.int64)
    syndrome = np.zeros_like(words)
    for i in range(length):
        syndrome ^= np.where(words >> i & 1, i + 1, 0)
    return words ^ np.where(syndrome > 0, 1 << np.maximum(syndrome - 1, 0), 0)


def flip_rate(limit: tuple[int, int] = LIMIT) -> float:
    """Probability that a SimHash bit of two sets of one size differs at this Jaccard similarity."""
    j = limit[0] / limit[1]
    return math.acos(2 * j / (1 + j)) / math.pi


def same_home(length: int, p: float) -> float:
    """Probability that a random word and a copy with flip rate ``p`` have one home.

    The word is a code word or one bit away from one; its copy shares the home if it lies within a bit of it too.
    """
    q, n = 1 - p, length
    none, one, two = q**n, p * q ** (n - 1), p * p * q ** (n - 2)
    at_home, beside = 1 / (n + 1), n / (n + 1)
    return at_home * (none + n * one) + beside * (none + one + (n - 1) * two)


def plan(n: int, limit: tuple[int, int] = LIMIT, recall: float = RECALL) -> tuple[tuple[int, ...], int]:
    """Code lengths of a part and the number of parts for ``n`` texts: anchors stay small, recall stays the same."""
    codes = (15, 7)
    crowd = lambda c: n / 2 ** sum(x - (x + 1).bit_length() + 1 for x in c)
    while crowd(codes) > CROWD and len(codes) < 4:
        codes = (*codes, 7) if codes[-1] == 15 else (*codes[:-1], 15)
    chance = math.prod(same_home(c, flip_rate(limit)) for c in codes)
    return codes, math.ceil(math.log(1 - recall) / math.log(1 - chance))


class Anchors:
    """Anchors of wide fingerprints: for each part drawn bits, cut into code words' lengths, brought home."""

    def __init__(self, codes: tuple[int, ...], parts: int, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.codes, self.parts = codes, parts
        self.drawn = np.stack([rng.permutation(64 * FAMILIES)[: sum(codes)] for _ in range(parts)])
        self.tables = {c: homes(c) for c in set(codes)}

    def of(self, wide: np.ndarray) -> np.ndarray:
        """(rows, parts) of numbers that name part and homes."""
        bits = np.unpackbits(wide.view(np.uint8).reshape(len(wide), -1), axis=1, bitorder="little")
        out = np.broadcast_to(np.arange(self.parts, dtype=np.int64), (len(wide), self.parts)).copy()
        at = 0
        for c in self.codes:
            word = np.zeros((len(wide), self.parts), np.int64)
            for i in range(c):
                word |= bits[:, self.drawn[:, at + i]].astype(np.int64) << i
            out = (out << c) | self.tables[c][word]
            at += c
        return out


# --- passes over rows -------------------------------------------------------------------------------------------------


def _prints(words: int, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh64_intdigest

        for batch in batches:
            sid, n, wide = [], [], []
            for t in batch.column("text"):
                found = shingles(t.as_py(), words, seed)
                sid.append(xxh64_intdigest(found.tobytes(), seed))
                n.append(len(found))
                wide.append(wide_print(found).view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("raw"), pa.array(np.array(sid, _U).view(np.int64)), pa.array(n, pa.int32()), pa.array(wide, pa.list_(pa.int64()))], ["doc_id", "raw", "sid", "n", "wide"])

    return run


def _matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return np.ascontiguousarray(column.flatten().to_numpy(zero_copy_only=False)).view(_U).reshape(-1, FAMILIES)


def _spread(codes: tuple[int, ...], parts: int, seed: int):
    """One row for each part: its anchor, the text's set and the carried bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = Anchors(codes, parts, seed)
        for batch in (b.slice(at, 1024) for b in batches for at in range(0, b.num_rows, 1024)):
            wide, sid = _matrix(batch.column("wide")), batch.column("sid").to_numpy()
            anchor = made.of(wide)
            cols = [anchor.ravel(), np.repeat(sid, parts), *(np.repeat(wide[:, k].view(np.int64), parts) for k in range(CARRIED))]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["anchor", "sid", "f0", "f1"])

    return run


def ahead(group: np.ndarray) -> Iterator[tuple[np.ndarray, int]]:
    """Rows i and steps s such that rows i and i + s are of one group; rows of a group stand together."""
    start = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    size = np.diff(np.r_[start, len(group)])
    left = np.repeat(start + size, size) - np.arange(len(group)) - 1  # rows of the group that follow
    rows, s = np.flatnonzero(left >= 1), 1
    while len(rows):
        yield rows, s
        s += 1
        rows = rows[left[rows] >= s]


def whole_groups(batches: Iterator[pa.RecordBatch], keys: tuple[str, ...]) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Sorted batches cut where a group of ``keys`` ends, with the number of each row's group."""
    kept: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        table = pa.Table.from_batches([*kept, batch]).combine_chunks()
        number = _numbers(table, keys)
        cut = int(np.searchsorted(number, number[-1]))
        kept = table.slice(cut).to_batches()
        if cut:
            yield table.slice(0, cut), number[:cut]
    if kept:
        table = pa.Table.from_batches(kept).combine_chunks()
        yield table, _numbers(table, keys)


def _numbers(table: pa.Table, keys: tuple[str, ...]) -> np.ndarray:
    new = np.zeros(table.num_rows, bool)
    for k in keys:
        x = table.column(k).to_numpy()
        new[1:] |= x[1:] != x[:-1]
    return np.cumsum(new)


CELL = ("anchor", "i", "j")


def _loose_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by cell and sid. Every text that near pairs of its cell connect to others is linked to the one of least sid, so cells that share texts share links."""
    for table, group in whole_groups(batches, CELL):
        sid = table.column("sid").to_numpy()
        carried = [table.column(f"f{k}").to_numpy().view(_U) for k in range(CARRIED)]
        root = np.arange(len(sid))
        for rows, s in ahead(group):
            rows = rows[root[rows] != root[rows + s]]
            near = rows[sum(np.bitwise_count(c[rows] ^ c[rows + s]) for c in carried) <= NEAR_BITS]
            merge(root, near, near + s)
        own = np.flatnonzero(root != np.arange(len(sid)))
        yield _edges(sid[own], sid[root[own]])


def _edges(u: np.ndarray, v: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.minimum(u, v)), pa.array(np.maximum(u, v))], ["u", "v"])


def _links(limit: tuple[int, int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows sorted by cell and size. Texts that pairs of similar sets of a cell connect, linked to the first of them."""
        for table, group in whole_groups(batches, ("anchor", "i", "j")):
            sid, n = table.column("sid").to_numpy(), table.column("n").to_numpy().astype(np.int64)
            wide, held = _matrix(table.column("wide")), table.column("held")
            root = np.arange(len(sid))
            for rows, s in ahead(group):
                rows = rows[(root[rows] != root[rows + s]) & (n[rows] * limit[1] >= n[rows + s] * limit[0])]
                bits = np.bitwise_count(wide[rows] ^ wide[rows + s]).sum(1, dtype=np.int64)
                for a in rows[bits <= wide_limit(n[rows])].tolist():
                    if root[a] != root[a + s] and similar(np.frombuffer(held[a].as_buffer(), _U), np.frombuffer(held[a + s].as_buffer(), _U), limit):
                        root[root == max(root[a], root[a + s])] = min(root[a], root[a + s])
            own = np.flatnonzero(root != np.arange(len(sid)))
            yield _edges(sid[own], sid[root[own]])

    return run


def _held(words: int, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [shingles(t.as_py(), words, seed).tobytes() for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("sid", "n", "wide", "anchor")), pa.array(found, pa.binary())], ["sid", "n", "wide", "anchor", "held"])

    return run


def wide_limit(n: np.ndarray) -> np.ndarray:
    """Differing bits allowed of all: 3.3 deviations above the mean at a similarity of 0.8, more for sets of few shingles."""
    return 116 + 120 // np.maximum(n, 1)


def similar_copies(docs: DataFrame, words: int = WORDS, limit: tuple[int, int] = LIMIT, seed: int = SEED, codes: tuple[tuple[int, ...], int] | None = None) -> DataFrame:
    """doc_id, raw (a hash of the text), component_id and lead_raw (id and raw of the component's first row)."""
    data = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(data).alias("raw"), data.alias("text"))
    prints = materialise(to_python(rows, _prints(words, seed), fields(doc_id=LONG, raw=LONG, sid=LONG, n=INT, wide=LONGS)), "near-rows")
    nodes = prints.groupBy("sid").agg(lead("doc_id", "raw").alias("least"), F.count("*").alias("class_size"), F.min("n").alias("n"), F.min("wide").alias("wide"))
    nodes = materialise(nodes, "near-nodes")
    n_rows, n_nodes = prints.count(), nodes.count()
    asked = nodes.where("n > 0").select("sid", "wide", "n")
    lengths, parts = codes or plan(n_nodes, limit)
    spread = lambda df: to_python(df, _spread(lengths, parts, seed), fields(anchor=LONG, sid=LONG, f0=LONG, f1=LONG))

    cells = dealt_cells(spread(asked.select("sid", "wide")), asked.select("sid", "wide"), spread, "anchor", "sid")
    loose = to_python(cells.sortWithinPartitions(*CELL, "sid").select(*CELL, "sid", "f0", "f1"), _loose_links, fields(u=LONG, v=LONG)).distinct()
    clusters = forest_components(loose).select(F.col("node").alias("sid"), F.col("root").alias("anchor"))
    live = nodes.join(clusters, "sid").select("sid", "n", "wide", "anchor", F.col("least.doc_id").alias("_id"), F.col("least.raw").alias("_raw"))
    live = materialise(live, "near-live")
    first = F.broadcast(live) if live.count() <= BROADCAST_ROWS else live
    texts = rows.join(first, rows["doc_id"].eqNullSafe(first["_id"]) & (rows["raw"] == first["_raw"])).dropDuplicates(["sid"])
    sets = to_python(texts.select("sid", "n", "wide", "anchor", "text"), _held(words, seed), fields(sid=LONG, n=INT, wide=LONGS, anchor=LONG, held=BINARY))
    sets = materialise(sets, "near-sets")
    cells = dealt_cells(sets, live.select("sid", "anchor"), lambda df: df, "anchor", "sid", SET_ROWS)
    links = to_python(cells.select(*CELL, "sid", "n", "wide", "held").sortWithinPartitions(*CELL, "n", "sid"), _links(limit), fields(u=LONG, v=LONG))

    roots = forest_components(links).withColumnRenamed("node", "sid")
    rooted = materialise(nodes.join(roots, "sid", "left").withColumn("root", F.coalesce("root", "sid")), "near-rooted")
    whole = rooted.groupBy("root").agg(F.min("least").alias("lead"), F.count("*").alias("nodes"))
    whole = materialise(whole.select("root", F.col("lead.doc_id").alias("component_id"), F.col("lead.raw").alias("lead_raw"), "nodes"), "near-components")
    of_node = materialise(attach(rooted.select("sid", "class_size", "root"), whole, ["root"], max(1, n_nodes), "nodes").drop("nodes", "root"), "near-named")
    return attach(prints.select("doc_id", "raw", "sid"), of_node, ["sid"], max(1, n_rows), "class_size").select("doc_id", "raw", "component_id", "lead_raw")

