"""Filters as relations: the same answers from joins and aggregates alone, and peeling without any kernel.

Reference forms, for checking and for sets of middle size; a cuckoo-like filter answers by (fingerprint, pair of buckets),
wherever an entry was put, since both buckets of a pair lead to each other.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sieveset.functions.hashing import _lit, high32_col, reduce_range_col, with_mix64
from sieveset.kernels import filters as K
from sieveset.kernels.peel import peel_rounds
from sieveset.sources.staging import materialise

from .probe import block_bit, bloom_place, cuckoo_buckets_cols
from .spec import ALTERNATE, CELL0, CELL1, CELL2, PLACE, PRINT, FilterSpec, attempt_seed, blocked_blocks, bloom_bits, capacity, cuckoo_buckets, role_seed, segments


def cells_of(keys: DataFrame, n: int, spec: FilterSpec, attempt: int = 0) -> DataFrame:
    """k64 with its three cells and its fingerprint."""
    seed, c = attempt_seed(spec.seed, 0, attempt), capacity(n, spec.slack_hundredths, spec.extra)
    seg1, seg2 = segments(c)
    out = with_mix64(keys.select("k64"), "k64", {f"h{r}": role_seed(seed, r) for r in (CELL0, CELL1, CELL2, PRINT)})
    place = lambda r, lo, hi: F.lit(lo).cast("long") + reduce_range_col(high32_col(F.col(f"h{r}")), hi - lo)
    return out.select("k64", place(CELL0, 0, seg1).alias("c0"), place(CELL1, seg1, seg2).alias("c1"), place(CELL2, seg2, c).alias("c2"), F.col(f"h{PRINT}").bitwiseAND(_lit((1 << spec.fp_bits) - 1)).alias("fp"))


def degrees(cells: DataFrame) -> DataFrame:
    """cell, degree and mask: how many keys touch it, and the exclusive-or of them."""
    return cells.select("k64", F.explode(F.array("c0", "c1", "c2")).alias("cell")).groupBy("cell").agg(F.count("*").alias("degree"), F.bit_xor("k64").alias("mask"))


def peel_relational(cells: DataFrame, max_rounds: int = 200) -> DataFrame | None:
    """(k64, own, round), or None when a core is left. Each round is two aggregates and an anti join, and ends in a written table."""
    alive, out = materialise(cells.select("k64", "c0", "c1", "c2"), "alive"), None
    for step in range(max_rounds):
        single = degrees(alive).where("degree = 1")
        gone = materialise(single.groupBy(F.col("mask").alias("k64")).agg(F.min("cell").alias("own")).withColumn("round", F.lit(step)), "peeled")
        if gone.isEmpty():
            return out if alive.isEmpty() else None
        out = gone if out is None else out.unionByName(gone)
        alive = materialise(alive.join(gone, "k64", "left_anti"), "alive")
    return None


def assign_relational(cells: DataFrame, peeled: DataFrame) -> DataFrame:
    """(cell, value) of the cells that a key owns, from the last round to the first."""
    steps = materialise(cells.join(peeled, "k64"), "steps")
    last = steps.agg(F.max("round")).first()[0]
    table = steps.sparkSession.createDataFrame([], "cell long, value long")
    for step in range(-1 if last is None else last, -1, -1):
        own = steps.where(F.col("round") == step).select("own", "fp", F.explode(F.array("c0", "c1", "c2")).alias("cell"))
        new = own.join(table, "cell", "left").groupBy("own", "fp").agg(F.bit_xor(F.coalesce("value", F.lit(0).cast("long"))).alias("x"))
        table = materialise(table.unionByName(new.select(F.col("own").alias("cell"), F.col("fp").bitwiseXOR(F.col("x")).alias("value"))), "table")
    return table


def peel_table(keys: DataFrame, spec: FilterSpec, attempt: int = 0) -> DataFrame:
    """(k64, cell, round) of one shard, by the kernel."""
    kinds = T.StructType([T.StructField(n, T.LongType()) for n in ("k64", "cell", "round")])

    def run(group: pa.Table) -> pa.Table:
        import numpy as np

        values = np.unique(group.column("k64").to_numpy())
        c = capacity(len(values), spec.slack_hundredths, spec.extra)
        order, own, rounds = peel_rounds(K.three_cells(values, attempt_seed(spec.seed, 0, attempt), c), c)
        return pa.table({"k64": pa.array(values[order]), "cell": pa.array(own), "round": pa.array(rounds)})

    return keys.select("k64").withColumn("shard", F.lit(0)).groupBy("shard").applyInArrow(run, kinds)


def bloom_bits_of(keys: DataFrame, n: int, spec: FilterSpec) -> DataFrame:
    """(k64, i, bit): positions of each key."""
    seed, m = attempt_seed(spec.seed, 0, 0), bloom_bits(n, spec)
    hashed = with_mix64(keys.select("k64"), "k64", {"h": role_seed(seed, PLACE)})
    return hashed.select("k64", F.posexplode(F.array(*(bloom_place(F.col("h"), i, m) for i in range(spec.hashes)))).alias("i", "bit"))


def bloom_words(keys: DataFrame, n: int, spec: FilterSpec) -> DataFrame:
    """(word_index, word): the filter as a pure aggregate; partial words are or-ed where the keys are read."""
    bits = bloom_bits_of(keys, n, spec)
    one = F.expr("shiftleft(1L, cast(bit & 63 as int))")
    return bits.groupBy(F.shiftright("bit", 6).alias("word_index")).agg(F.bit_or(one).alias("word"))


def bloom_probe(keys: DataFrame, words: DataFrame, n: int, spec: FilterSpec) -> DataFrame:
    """k64 and probes_used: the place of the first unset bit, or all hashes when every bit is set; maybe_member tells which."""
    asked = bloom_bits_of(keys, n, spec).withColumn("word_index", F.shiftright("bit", 6)).join(words, "word_index", "left")
    hit = F.coalesce(F.call_function("bit_get", F.col("word"), F.expr("cast(bit & 63 as int)")) == 1, F.lit(False))
    by = asked.groupBy("k64").agg(F.min(F.when(~hit, F.col("i"))).alias("miss"))
    return by.select("k64", F.coalesce(F.col("miss") + 1, F.lit(spec.hashes)).cast("long").alias("probes_used"), F.col("miss").isNull().cast("int").alias("maybe_member"))


def blocked_words(keys: DataFrame, n: int, spec: FilterSpec) -> DataFrame:
    """(block, w0..w7): each word of a block an or over its keys."""
    seed, blocks = attempt_seed(spec.seed, 0, 0), blocked_blocks(n, spec)
    hashed = with_mix64(keys.select("k64"), "k64", {"h": role_seed(seed, PLACE)})
    bits = hashed.select(reduce_range_col(high32_col(F.col("h")), blocks).alias("block"), *(F.call_function("shiftleft", F.lit(1).cast("long"), block_bit(F.col("h"), j).cast("int")).alias(f"b{j}") for j in range(8)))
    return bits.groupBy("block").agg(*(F.bit_or(f"b{j}").alias(f"w{j}") for j in range(8)))


def cuckoo_entries(keys: DataFrame, n: int, spec: FilterSpec) -> DataFrame:
    """(k64, f, l1, l2)."""
    seed, buckets = attempt_seed(spec.seed, 0, 0), cuckoo_buckets(n, spec)
    hashed = with_mix64(keys.select("k64"), "k64", {"hp": role_seed(seed, PLACE), "hf": role_seed(seed, PRINT)})
    hashed = hashed.withColumn("f", F.greatest(F.col("hf").bitwiseAND(_lit((1 << spec.fp_bits) - 1)), F.lit(1).cast("long")))
    hashed = with_mix64(hashed, "f", {"ha": role_seed(seed, ALTERNATE)})
    l1, l2 = cuckoo_buckets_cols(F.col("hp"), F.col("ha"), buckets, spec.kind.endswith("pow2"))
    return hashed.select("k64", "f", l1.alias("l1"), l2.alias("l2"))


def cuckoo_members(asked: DataFrame, keys: DataFrame, n: int, spec: FilterSpec) -> DataFrame:
    """Keys that the filter reports: a semi join on fingerprint and pair of buckets."""
    # written first: a filter that the join implies would be pushed through the mixer's steps and grow with each
    pair = lambda df: materialise(df.select("k64", "f", F.least("l1", "l2").alias("lo"), F.greatest("l1", "l2").alias("hi")), "entries")
    return pair(cuckoo_entries(asked, n, spec)).join(pair(cuckoo_entries(keys, n, spec)).drop("k64").distinct(), ["f", "lo", "hi"], "left_semi").select("k64")


def gcs_sorted(keys: DataFrame, n: int, spec: FilterSpec) -> DataFrame:
    """(k64, v): reduced hashes."""
    hashed = with_mix64(keys.select("k64"), "k64", {"h": role_seed(attempt_seed(spec.seed, 0, 0), PLACE)})
    return hashed.select("k64", reduce_range_col(high32_col(F.col("h")), n << spec.fp_bits).alias("v"))
