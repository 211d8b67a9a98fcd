"""Uniform shuffle into shards of exact size by a hypergeometric communication matrix.

Rows lie in blocks. How many rows each block sends to each shard is drawn first, from the exact law that a uniform shuffle
would give: multivariate hypergeometric, block by block, from what the shards still lack. Each block is then permuted by
itself and cut by its row of the matrix, rows are exchanged, and each shard is permuted again. Shards differ by one row at
most; every arrangement of rows is as likely as any other, up to the quality of the seeded hash.

Defined cases: a null text has 0 bytes and the crc32 of an empty text; a null doc_id is a row like any other; repeated rows are rows of their own; an empty table gives
an empty result; with fewer rows than shards the last shards are empty; further columns are ignored by ``assign_shards``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import LONG, LONGS, fields, materialise, table, to_python

N_SHARDS = 24
SEED = 11
#: Rows of a block, and rows that are put in order together, at most and on average.
BLOCK_ROWS = 16_384
#: Blocks whose rows of the matrix one task draws, on average.
GROUP_BLOCKS = 256


def _log_choose(n: int, k: np.ndarray) -> np.ndarray:
    return _log_gamma(np.float64(n + 1)) - _log_gamma(k + 1.0) - _log_gamma(n - k + 1.0)


def _log_gamma(x):
    """log Gamma for x >= 1 by Stirling's series, after shifting small arguments up."""
    x = np.asarray(x, np.float64)
    shift = np.zeros_like(x)
    small = x < 16
    y = np.where(small, x + 16, x)
    for i in range(16):
        shift = np.where(small, shift + np.log(np.maximum(x + i, 1e-300)), shift)
    inv = 1 / y
    return (y - 0.5) * np.log(y) - y + 0.9189385332046727 + inv / 12 - inv**3 / 360 + inv**5 / 1260 - shift


def hypergeometric(rng: np.random.Generator, good: int, bad: int, draws: int) -> int:
    """Number of good ones in ``draws`` without replacement, by inversion of the law within 12 deviations of its mean.

    Unlike the library's generator it takes populations of over 10**9.
    """
    low, high = max(0, draws - bad), min(draws, good)
    if low >= high:
        return low
    total = good + bad
    mean = draws * good / total
    spread = (mean * (bad / total) * (total - draws) / max(1, total - 1)) ** 0.5
    low, high = max(low, int(mean - 12 * spread) - 8), min(high, int(mean + 12 * spread) + 8)
    k = np.arange(low, high + 1, dtype=np.float64)
    logs = _log_choose(good, k) + _log_choose(bad, draws - k)
    weights = np.exp(logs - logs.max())
    edges = np.cumsum(weights)
    return low + int(np.searchsorted(edges, rng.random() * edges[-1], side="right"))


def draw_rows(sizes: list[int], lacking: list[int], rng: np.random.Generator) -> np.ndarray:
    """Rows that each of several parts sends to each shard, when together they fill what the shards lack."""
    lacking = list(lacking)
    out = np.zeros((len(sizes), len(lacking)), np.int64)
    for b, size in enumerate(sizes):
        rest = sum(lacking)
        for s, want in enumerate(lacking):
            if not size:
                break
            rest -= want
            got = hypergeometric(rng, want, rest, size)
            out[b, s] = got
            size -= got
            lacking[s] -= got
    return out


def capacities(n: int, n_shards: int) -> list[int]:
    return [n // n_shards + (s < n % n_shards) for s in range(n_shards)]


def communication_matrix(blocks: list[int], n_shards: int = N_SHARDS, seed: int = SEED) -> np.ndarray:
    """Rows that each block sends to each shard. Row sums are the blocks' sizes; column sums differ by one at most."""
    return draw_rows(blocks, capacities(sum(blocks), n_shards), np.random.default_rng(seed))


def _draw_group(seed: int):
    """The matrix rows of a group of blocks, from the group's own row: the law of the whole is the same."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for group, blocks, lacking in zip(*(batch.column(c).to_pylist() for c in ("group", "blocks", "lacking")), strict=True):
                drawn = draw_rows([b["n"] for b in blocks], lacking, np.random.default_rng([seed, group]))
                yield pa.RecordBatch.from_arrays([pa.array([b["block"] for b in blocks], pa.int64()), pa.array(np.cumsum(drawn, 1).tolist(), pa.list_(pa.int64()))], ["block", "cuts"])

    return run


def assign_shards(docs: DataFrame, n_shards: int = N_SHARDS, seed: int = SEED) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot.

    The matrix is drawn in two levels: the driver draws a row for each group of GROUP_BLOCKS blocks, 24 numbers for four million rows, and
    tasks split a group's row among its blocks, which gives the same law as drawing block by block. Slots come
    from running sums over slices of the second permutation, so no task holds a shard.
    """
    spark = docs.sparkSession
    data = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    at = F.monotonically_increasing_id()
    rows = docs.select("doc_id", (F.octet_length(data).cast("long") + 8).alias("size"), F.crc32(data).alias("text_crc32"), at.alias("uid"))
    # from here on a row's number, and so its block, is fixed
    rows = materialise(rows.withColumn("block", F.shiftright("uid", BLOCK_ROWS.bit_length() - 1)), "shard-rows")
    sizes = rows.groupBy("block").agg(F.count("*").alias("n")).withColumn("group", F.pmod(F.xxhash64("block"), F.lit(1 << 40)))
    sizes = materialise(sizes, "shard-blocks")
    n_groups = max(1, sizes.count() // GROUP_BLOCKS)
    sizes = sizes.withColumn("group", F.col("group") % n_groups)
    groups = sizes.groupBy("group").agg(F.sum("n").alias("n")).orderBy("group").collect()  # one row for GROUP_BLOCKS * BLOCK_ROWS rows
    n = sum(r["n"] for r in groups)
    matrix = communication_matrix([r["n"] for r in groups], n_shards, seed)
    lacking = spark.createDataFrame([(r["group"], m.tolist()) for r, m in zip(groups, matrix, strict=True)], "group long, lacking array<long>")
    blocks = sizes.groupBy("group").agg(F.array_sort(F.collect_list(F.struct("block", "n"))).alias("blocks")).join(lacking, "group")
    sends = to_python(blocks.select("group", "blocks", "lacking"), _draw_group(seed), fields(block=LONG, cuts=LONGS))

    first = Window.partitionBy("block").orderBy(F.xxhash64(F.lit(seed), "uid"), "uid")
    sent = rows.withColumn("place", F.row_number().over(first)).join(sends, "block")
    sent = sent.withColumn("shard", F.size(F.filter("cuts", lambda c: c < F.col("place"))).cast("int")).drop("cuts", "place", "block")

    slices = max(16, n // n_shards // BLOCK_ROWS + 1)
    sent = sent.withColumn("key", F.xxhash64(F.lit(seed + 1), "uid")).withColumn("slice", F.pmod(F.shiftrightunsigned("key", 32), F.lit(slices)))
    sent = materialise(sent, "shard-sent")
    sums = sent.groupBy("shard", "slice").agg(F.count("*").alias("n"))
    before = Window.partitionBy("shard").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select("shard", "slice", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    second = Window.partitionBy("shard", "slice").orderBy("key", "uid")
    placed = sent.withColumn("rank", F.row_number().over(second)).join(starts, ["shard", "slice"])
    return placed.select("doc_id", "size", "text_crc32", "shard", (F.col("start") + F.col("rank") - 1).cast("long").alias("slot"), "uid")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = assign_shards(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
