"""Building filter sets from key columns, shard by shard."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sieveset.functions.hashing import canonical_key, derived_seed, high32_col, reduce_range_col, with_mix64
from sieveset.kernels import filters as K
from sieveset.sources.staging import materialise

from .filterset import FilterSet, schema, to_row
from .spec import SHARD, FilterSpec


def with_key(df: DataFrame, key: str, mode: str = "identity", name: str = "k64") -> DataFrame:
    """Adds the canonical 64-bit key of a column; null stays null, as null is no element of a set."""
    return df.withColumn(name, canonical_key(F.col(key), df.schema[key].dataType.simpleString(), mode))


def distinct_keys(df: DataFrame, key: str, mode: str = "identity") -> DataFrame:
    """Only the key column is read; a key that fills a third of the rows costs one row a task, as copies go before the shuffle."""
    return with_key(df.select(key), key, mode).select("k64").where(F.col("k64").isNotNull()).distinct()


def with_shard(df: DataFrame, spec: FilterSpec, shards: int, key: str = "k64") -> DataFrame:
    """Adds ``shard`` by a seed of its own, so that cells inside a shard stay uniform."""
    if shards == 1:
        return df.withColumn("shard", F.lit(0))
    out = with_mix64(df, key, {"_shard_hash": derived_seed(spec.seed, 500 + SHARD)})
    return out.withColumn("shard", reduce_range_col(high32_col(F.col("_shard_hash")), shards).cast("int")).drop("_shard_hash")


def plan_shards(n_keys: int, spec: FilterSpec) -> int:
    return max(1, -(-n_keys // spec.shard_keys))


def _to_batch(rows: list[dict], kinds: T.StructType) -> pa.Table:
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(kinds)
    columns = []
    for f in arrow:
        values = [r[f.name] for r in rows]
        columns.append(pa.array([np.ascontiguousarray(v, f.type.value_type.to_pandas_dtype()) for v in values], f.type) if pa.types.is_list(f.type) else pa.array(values, f.type))
    return pa.Table.from_arrays(columns, schema=arrow)


def _builder(spec: FilterSpec, filter_id: str | None, shards: int, groups: tuple[str, ...] = ()):
    kinds = schema(spec)

    def run(key: tuple, keys: pa.Table) -> pa.Table:
        values = np.unique(keys.column("k64").to_numpy())
        shard = key[-1].as_py()
        name = filter_id if filter_id is not None else "/".join("null" if k.as_py() is None else str(k.as_py()) for k in key[:-1])
        return _to_batch([to_row(K.build(values, spec, shard), spec, name, shard, shards)], kinds)

    return run


def build_filter(df: DataFrame, key: str, spec: FilterSpec, n_keys: int | None = None, shards: int | None = None, filter_id: str = "f") -> FilterSet:
    """A filter set over the distinct non-null values of ``key``.

    Keys go to shards of about ``spec.shard_keys`` by hash, each shard is built by one task, and an unlucky seed is drawn anew
    for its shard alone. The set is written, so it is built once. Without ``n_keys`` or ``shards`` the keys are
    counted first, roughly: only the number of shards depends on it.
    """
    keys = distinct_keys(df, key, spec.hash_mode)
    if shards is None:
        n_keys = n_keys if n_keys is not None else keys.agg(F.approx_count_distinct("k64", 0.05)).first()[0]
        shards = plan_shards(n_keys, spec)
    frame = with_shard(keys, spec, shards).repartition(shards, "shard").groupBy("shard").applyInArrow(_builder(spec, filter_id, shards), schema(spec))
    frame = materialise(frame, "filter")
    if frame.isEmpty():  # no key at all: shards without keys have no row, and rows that aren't there say no
        frame = df.sparkSession.createDataFrame(_to_batch([to_row(K.build(np.zeros(0, np.int64), spec), spec, filter_id, 0, shards)], schema(spec)))
    return FilterSet(frame, spec, shards)


def build_filter_per_group(df: DataFrame, groups: list[str], key: str, spec: FilterSpec) -> FilterSet:
    """One filter for each group, in one pass; filter_id is the group's values joined by slashes. A group must fit a task."""
    rows = with_key(df.select(*groups, key), key, spec.hash_mode).where(F.col("k64").isNotNull()).select(*groups, "k64").distinct().withColumn("shard", F.lit(0))
    frame = rows.groupBy(*groups, "shard").applyInArrow(_builder(spec, None, 1), schema(spec))
    return FilterSet(materialise(frame, "filters"), spec, 1)


def rebuild(old: FilterSet, df: DataFrame, key: str, filter_id: str) -> FilterSet:
    """A set of the same kind over new keys, under a new id. The old one stays valid for whoever still holds it."""
    return build_filter(df, key, old.spec, filter_id=filter_id)


def merge_bloom(a: FilterSet, b: FilterSet) -> FilterSet:
    """The Bloom filter of both key sets: words are or-ed. Both must have been built with one size and one seed."""
    if {a.spec.kind, b.spec.kind} != {"bloom"} or a.shard_count != b.shard_count:
        raise ValueError("only Bloom filters of one shape merge")
    words = a.frame.unionByName(b.frame).select("*", F.posexplode("aux").alias("at", "word"))
    merged = words.groupBy("shard", "at").agg(F.bit_or("word").alias("word"), F.min("capacity").alias("lo"), F.max("capacity").alias("hi"), F.sum("n_keys").alias("n"), F.first("seed").alias("seed"), F.first("num_hashes").alias("num_hashes"))
    if not merged.where("lo != hi").isEmpty():
        raise ValueError("filters of different sizes don't merge; build both with the same room")
    rows = merged.groupBy("shard").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "word"))), lambda x: x["word"]).alias("aux"), F.max("n").alias("n_keys"), F.first("lo").alias("capacity"), F.first("seed").alias("seed"), F.first("num_hashes").alias("num_hashes"))
    given = {"filter_id": F.lit("merged"), "kind": F.lit("bloom"), "shard_count": F.lit(a.shard_count), "fp_bits": F.lit(a.spec.fp_bits), "seg1": F.lit(0), "seg2": F.lit(0), "attempts": F.lit(1), "cells": F.expr("array()"), "bits_total": F.col("capacity"), "empty": F.lit(0), "empty_last": F.lit(0)}
    rows = rows.withColumns(given)
    return FilterSet(materialise(rows.select(*(F.col(f.name) if f.name == "aux" else F.col(f.name).cast(f.dataType.simpleString()).alias(f.name) for f in schema(a.spec))), "filter"), a.spec, a.shard_count)


def build_static_map(df: DataFrame, key: str, value: str, spec: FilterSpec) -> FilterSet:
    """A map from keys to values of at most ``fp_bits`` bits in the space of a filter; unknown keys get any value."""
    spec = FilterSpec.from_json(spec.to_json())
    rows = with_key(df.select(key, value), key, spec.hash_mode).where(F.col("k64").isNotNull()).groupBy("k64").agg(F.max(value).cast("long").alias("v"))
    shards = plan_shards(rows.count(), spec)
    kinds = schema(spec)

    def run(group: tuple, rows_: pa.Table) -> pa.Table:
        shard = group[0].as_py()
        keys, values = rows_.column("k64").to_numpy(), rows_.column("v").to_numpy()
        order = np.argsort(keys)
        return _to_batch([to_row(K.build_xor(keys[order], spec, shard, values[order]), spec, "map", shard, shards)], kinds)

    frame = with_shard(rows, spec, shards).repartition(shards, "shard").groupBy("shard").applyInArrow(run, kinds)
    return FilterSet(materialise(frame, "map"), spec, shards)


def sort_baseline(keys: DataFrame) -> DataFrame:
    """The yardstick of building: all keys in order."""
    return keys.orderBy("k64")


def key_count(df: DataFrame, key: str, exact: bool = True) -> Column:
    return F.count_distinct(key) if exact else F.approx_count_distinct(key)
