"""Closed forms: space, false positives, accesses; and where curves cross."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sieveset.functions.hashing import derived_seed, high32_col, reduce_mod_col, with_mix64
from sieveset.kernels.filters import build, three_cells
from sieveset.kernels.peel import peel_rounds
from sieveset.operators.spec import FilterSpec, LoadExceeded, attempt_seed, capacity

#: Bits per key as a multiple of log2(1/fpp) and an addend. A cuckoo filter at its fullest has 3 bits more than its fingerprints give.
FULL_LOAD = 0.953
CURVES = {"bound": (1.0, 0.0), "bloom": (1 / math.log(2), 0.0), "cuckoo": (1 / FULL_LOAD, 3 / FULL_LOAD), "xor": (1.23, 0.0), "xor_plus": (1.0824, 0.5125)}


def bound_bits(fpp: float) -> float:
    return -math.log2(fpp)


def space_curve(kind: str, fpp: float) -> float:
    """Bits per key that a false-positive probability costs."""
    a, b = CURVES[kind]
    return a * bound_bits(fpp) + b


def fpp_curve(kind: str, bits: float) -> float:
    a, b = CURVES[kind]
    return min(1.0, 2 ** -((bits - b) / a))


def crossover(one: str, other: str, low: float = 1e-12, high: float = 0.5) -> float | None:
    """The false-positive probability at which two kinds need the same space, by bisection of its logarithm."""
    gap = lambda e: space_curve(one, 2**-e) - space_curve(other, 2**-e)
    a, b = -math.log2(high), -math.log2(low)
    if gap(a) * gap(b) > 0:
        return None
    for _ in range(200):
        mid = (a + b) / 2
        a, b = (mid, b) if gap(a) * gap(mid) > 0 else (a, mid)
    return 2**-a


def overhead_ratio(bits_per_key: float, fpp: float) -> float:
    return bits_per_key / bound_bits(fpp)


def access_model(kind: str, hit: float, hashes: int = 8) -> float:
    """Memory accesses of a probe on average, at a share of hits."""
    if kind == "bloom":
        return hit * hashes + (1 - hit) * sum(i * 0.5**i for i in range(1, hashes)) + (1 - hit) * hashes * 0.5 ** (hashes - 1)
    return {"xor": 3, "xor_plus": 4, "cuckoo": 2, "blocked_bloom": 1}[kind]


def space_table(spark: SparkSession, kinds: tuple[str, ...] = tuple(CURVES)) -> DataFrame:
    """(kind, log2_inverse_fpp, milli_bits) on a grid."""
    curves = spark.createDataFrame([(k, *CURVES[k]) for k in kinds], "kind string, a double, b double")
    grid = spark.range(1, 33).select(F.col("id").cast("int").alias("log2_inverse_fpp"))
    return grid.crossJoin(F.broadcast(curves)).select("kind", "log2_inverse_fpp", F.round((F.col("a") * F.col("log2_inverse_fpp") + F.col("b")) * 1000, 0).cast("long").alias("milli_bits"))


def dealt_groups(keys: DataFrame, size: int, trials: int) -> tuple[DataFrame, int, int]:
    """All rows of ``keys`` (k64, distinct) dealt by hash to groups of about ``size``; the groups' number and how many trials each makes, for ``trials`` at least in all."""
    groups = max(1, keys.count() // size)
    return keys.withColumn("part", F.pmod(F.xxhash64(F.lit(3), "k64"), F.lit(groups))), groups, -(-trials // groups)


#: Sets are peeled side by side in about so many cells; so many tasks share the passes over a table.
PEEL_CELLS, CURVE_TASKS = 1 << 17, 64
#: Of the hash that deals keys to groups.
DEAL_SEED = derived_seed(42, 3)


def sets_peeled(sets: np.ndarray, extra: int, seed: int) -> int:
    """How many of ``sets`` (one a row) pass the mapping step, each with a seed of its own."""
    n, size = sets.shape
    c, ok = capacity(size, extra=extra), 0
    step = max(1, PEEL_CELLS // c)
    for at in range(0, n, step):
        some = sets[at : at + step]
        cells = three_cells(some, attempt_seed(seed, extra, np.arange(at, at + len(some), dtype=np.uint64)[:, None]), c)
        cells += np.arange(len(some))[:, None] * c
        order, _, _ = peel_rounds(cells.reshape(3, -1), c * len(some), partly=True)
        ok += int((np.bincount(order // size, minlength=len(some)) == size).sum())
    return ok


def success_curve(keys: DataFrame, sizes: tuple[int, ...], extras: tuple[int, ...], trials: int, group: int, seed: int = 42) -> DataFrame:
    """(size, extra, trials, successes) of the mapping step over random sets of ``keys`` (k64, distinct), each trial with a set and a seed of its own.

    Keys are dealt by hash to groups of ``group`` or more. A pass cuts all keys of a group, in random order, into sets of each size, the last one
    filled up from the first; it is repeated until there are ``trials`` sets of the size or more in all. A size beyond a group's keys has no sets there.
    """
    keys = keys.where("k64 is not null")
    groups = max(1, keys.count() // group)
    each, copies = -(-trials // groups), -(-CURVE_TASKS // groups)
    dealt = with_mix64(keys, "k64", {"h": DEAL_SEED}).select("k64", reduce_mod_col(high32_col(F.col("h")), groups).alias("part"))
    shared = dealt.withColumn("share", F.explode(F.sequence(F.lit(0), F.lit(copies - 1)))).repartition(groups * copies, "part", "share")
    kinds = T.StructType([T.StructField("size", T.IntegerType()), T.StructField("extra", T.IntegerType()), T.StructField("n", T.LongType()), T.StructField("ok", T.LongType())])

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        part, share = (x.as_py() for x in key)
        own, out = np.sort(rows.column("k64").to_numpy()), []
        cuts = {s: -(-len(own) // s) for s in sizes if s <= len(own)}
        for t in range(share, each, copies):
            due = {s: n for s, n in cuts.items() if t * n < each}
            if not due:
                break
            drawn, own_seed = np.random.default_rng((seed, part, t)).permutation(own), derived_seed(derived_seed(seed, part), t)
            for s, n in due.items():
                sets = np.resize(drawn, (n, s))
                out += [(s, e, n, sets_peeled(sets, e, own_seed)) for e in extras]
        names = pa.schema([("size", pa.int32()), ("extra", pa.int32()), ("n", pa.int64()), ("ok", pa.int64())])
        return pa.Table.from_pylist([dict(zip(names.names, x, strict=True)) for x in out], schema=names)

    return shared.groupBy("part", "share").applyInArrow(run, kinds).groupBy("size", "extra").agg(F.sum("n").alias("trials"), F.sum("ok").alias("successes"))


def cuckoo_failures(keys: DataFrame, n: int, loads: tuple[int, ...], trials: int, seed: int = 42) -> DataFrame:
    """(load, trials, failures) of filling flexible cuckoo tables with all ``keys``, about ``n`` a table, at the first seed, loads in hundredths."""
    dealt, _, each = dealt_groups(keys, n, trials)
    kinds = T.StructType([T.StructField("load", T.IntegerType()), T.StructField("failed", T.LongType())])

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        own, out = np.sort(rows.column("k64").to_numpy()), []
        for t in range(key[0].as_py() * each, (key[0].as_py() + 1) * each):
            for load in loads:
                try:
                    build(own, FilterSpec("cuckoo", 12, load=load / 100, seed=seed + 1000 * t, max_attempts=1, search=False))
                    out.append((load, 0))
                except LoadExceeded:
                    out.append((load, 1))
        return pa.table({"load": pa.array([x for x, _ in out], pa.int32()), "failed": pa.array([x for _, x in out], pa.int64())})

    return dealt.groupBy("part").applyInArrow(run, kinds).groupBy("load").agg(F.count("*").alias("trials"), F.sum("failed").alias("failures"))


def milli(bits: Column, keys: Column) -> Column:
    """Thousandths of bits per key, as a whole number."""
    return (bits * 1000 / keys).cast("long")
