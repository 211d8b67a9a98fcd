"""The experiments, re-expressed on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sieveset.operators.build import build_filter
from sieveset.operators.filterset import FilterSet
from sieveset.operators.probe import confusion
from sieveset.operators.spec import FilterSpec
from sieveset.sources.staging import table

PCTS = (0, 25, 50, 75, 100)
RANK_SLICE = 65_536


def members(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").where("o_orderstatus = 'F'").select(F.col("o_orderkey").alias("k64"))


def others(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").where("o_orderstatus <> 'F'").select(F.col("o_orderkey").alias("k64"))


def probes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k64")).distinct()


def ranked(keys: DataFrame, key: str = "k64") -> tuple[DataFrame, int]:
    """Adds ``rank`` from 1 by ascending key, and the number of rows; ranks are taken inside slices of the keys' range."""
    low, high, n = keys.agg(F.min(key), F.max(key), F.count("*")).first()
    if not n:
        return keys.withColumn("rank", F.lit(0).cast("long")), 0
    width = max(1, (high - low + 1) * RANK_SLICE // max(n, 1))
    cut = keys.withColumn("_slice", F.expr(f"({key} - {low}L) div {width}L"))
    before = Window.orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = cut.groupBy("_slice").agg(F.count("*").alias("_n")).select("_slice", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    inside = F.row_number().over(Window.partitionBy("_slice").orderBy(key))
    return cut.withColumn("_in", inside).join(starts, "_slice").withColumn("rank", F.col("_start") + F.col("_in")).drop("_slice", "_in", "_start"), n


def query_mix(member_keys: DataFrame, other_keys: DataFrame, pcts: tuple[int, ...] = PCTS) -> DataFrame:
    """(k64, is_member, hit_pct): for each hit ratio as many queries, mixed of members and others by ascending key."""
    a, n = ranked(member_keys)
    b, m = ranked(other_keys)
    total = 4 * (min(n, m) // 4)
    own = F.explode(F.array(*(F.struct(F.lit(p).alias("hit_pct"), F.lit(total * p // 100).alias("want")) for p in pcts))).alias("x")
    pick = lambda df, real, limit: df.select("k64", "rank", own).where(limit).select("k64", F.lit(real).alias("is_member"), F.col("x.hit_pct").alias("hit_pct"))
    return pick(a, 1, F.col("rank") <= F.col("x.want")).unionByName(pick(b, 0, F.col("rank") <= F.lit(total) - F.col("x.want")))


def standard_mix(spark: SparkSession, sf_dir: str, pcts: tuple[int, ...] = PCTS) -> DataFrame:
    return query_mix(members(spark, sf_dir), others(spark, sf_dir), pcts)


def standard_filter(spark: SparkSession, sf_dir: str, spec: FilterSpec) -> FilterSet:
    return build_filter(members(spark, sf_dir), "k64", spec, shards=1)


def mix_confusion(spark: SparkSession, sf_dir: str, spec: FilterSpec, pcts: tuple[int, ...] = PCTS) -> DataFrame:
    return confusion(standard_filter(spark, sf_dir, spec), standard_mix(spark, sf_dir, pcts))


#: The compared filters, by name. GCS and the quotient filter take 8 bits, like the small xor filters.
COMPARED = {
    "blocked": FilterSpec("blocked_bloom"),
    "bloom8": FilterSpec("bloom", bits_per_key=8),
    "bloom12": FilterSpec("bloom", bits_per_key=12),
    "bloom16": FilterSpec("bloom", bits_per_key=16),
    "css13": FilterSpec("cuckoo_semisort", 13),
    "cuckoo12": FilterSpec("cuckoo", 12),
    "cuckoo16": FilterSpec("cuckoo", 16),
    "gcs8": FilterSpec("gcs"),
    "xor8": FilterSpec("xor"),
    "xor16": FilterSpec("xor", 16),
    "xorplus8": FilterSpec("xor_plus"),
    "xorplus16": FilterSpec("xor_plus", 16),
    "cuckoo12_pow2": FilterSpec("cuckoo_pow2", 12),
    "cuckoo16_pow2": FilterSpec("cuckoo_pow2", 16),
    "css13_pow2": FilterSpec("cuckoo_semisort_pow2", 13),
    "cqf": FilterSpec("cqf"),
    "morton": FilterSpec("morton"),
    "exact": FilterSpec("exact"),
}
