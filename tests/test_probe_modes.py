"""Every kind of filter, in every way of asking, gives what its arrays say; members are never missed."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from sieveset.kernels import filters as K
from sieveset.operators.build import build_filter, build_static_map
from sieveset.operators.filterset import FilterSet, from_row
from sieveset.operators.probe import NATIVE, confusion, lookup_map, prefilter, probe, surely_absent
from sieveset.operators.spec import FilterSpec

SPECS = [
    FilterSpec("xor"),
    FilterSpec("xor", 16),
    FilterSpec("xor", 5),
    FilterSpec("xor_plus"),
    FilterSpec("xor_plus", 16, rank="sparse_samples"),
    FilterSpec("bloom", bits_per_key=12),
    FilterSpec("blocked_bloom"),
    FilterSpec("cuckoo", 12),
    FilterSpec("cuckoo_pow2", 16),
    FilterSpec("cuckoo_semisort", 13),
    FilterSpec("gcs"),
    FilterSpec("cqf"),
    FilterSpec("morton"),
    FilterSpec("exact"),
]


@pytest.mark.parametrize("spec", SPECS, ids=lambda s: f"{s.kind}-{s.fp_bits}")
def test_modes_agree(spark, sf_dir, spec):
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet")
    fs = build_filter(orders.where("o_orderstatus = 'F'"), "o_orderkey", spec)
    asked = orders.select("o_orderkey", (F.col("o_orderstatus") == "F").alias("real")).unionByName(spark.createDataFrame([(None, None), (-1, False), (2**63 - 1, False), (-(2**63), False)], "o_orderkey long, real boolean"))
    built = from_row(fs.frame.toPandas().to_dict("records")[0], spec)
    keys = [r[0] for r in asked.select("o_orderkey").collect()]
    want = dict(zip([k for k in keys if k is not None], K.contains(built, spec, np.array([k for k in keys if k is not None])), strict=True))
    for mode in ["udf", "shuffle"] + ["native"] * (spec.kind in NATIVE):
        got = probe(fs, asked, "o_orderkey", mode).collect()
        assert len(got) == len(keys)
        for r in got:
            assert r["maybe_member"] == (None if r["o_orderkey"] is None else int(want[r["o_orderkey"]])), (mode, r)
            assert not r["real"] or r["maybe_member"] == 1


@pytest.mark.parametrize("shards", [1, 2, 7])
def test_shards_miss_no_member(spark, sf_dir, shards):
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet")
    for kind in ("xor", "bloom", "xor_plus"):
        fs = build_filter(orders, "o_orderkey", FilterSpec(kind), shards=shards)
        assert fs.frame.count() == shards
        for mode in ("udf", "shuffle"):
            assert probe(fs, orders, "o_orderkey", mode).where("maybe_member = 0").count() == 0
        other = spark.range(10_000_000, 10_050_000)
        share = prefilter(fs, other, "id", "udf").count() / 50_000
        assert share < (0.05 if kind == "bloom" else 0.007)
        assert surely_absent(fs, other, "id", "udf").count() + prefilter(fs, other, "id", "udf").count() == 50_000


def test_empty_and_null_sets(spark):
    nothing = spark.createDataFrame([(None,)], "k long")
    asked = spark.createDataFrame([(1,), (None,)], "k long")
    for spec in (FilterSpec("xor"), FilterSpec("bloom"), FilterSpec("cqf")):
        fs = build_filter(nothing, "k", spec)
        for mode in ("native", "udf", "shuffle"):
            if mode == "native" and spec.kind not in NATIVE:
                continue
            assert {r["k"]: r["maybe_member"] for r in probe(fs, asked, "k", mode).collect()} == {1: 0, None: None}


def test_kinds_of_keys(spark):
    rows = spark.sql("""
        select id, cast(id as string) s, cast(cast(id as string) as binary) b, date_add(date'2020-01-01', cast(id as int)) d, timestamp_micros(id * 1000) t,
               cast(id as decimal(10,2)) m, id / 7.0D f, array(id, id + 1) a, struct(id, 'x' as y) st, map('k', id) mp, cast(timestamp_micros(id) as timestamp_ntz) n,
               id % 2 = 0 bo from range(300)""")
    for column in rows.columns:
        fs = build_filter(rows.where("id < 200"), column, FilterSpec("xor"))
        got = probe(fs, rows, column, "udf").where("id < 200 and maybe_member = 0").count()
        assert got == 0, column
    fs = build_filter(rows.where("id < 200"), "s", FilterSpec("xor", hash_mode="md5"))
    assert probe(fs, rows, "s").where("id < 200 and maybe_member = 0").count() == 0


def test_pack_save_and_load(spark, sf_dir, tmp_path):
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet")
    for spec in (FilterSpec("xor"), FilterSpec("xor", 16), FilterSpec("xor_plus"), FilterSpec("bloom")):
        fs = build_filter(orders, "o_orderkey", spec, shards=3)
        path = f"file://{tmp_path}/{spec.kind}{spec.fp_bits}"
        fs.save(path)
        back = FilterSet.load(spark, path)
        key = lambda r: r["shard"]
        assert sorted(fs.frame.collect(), key=key) == sorted(back.frame.collect(), key=key)
        assert back.spec == spec
    packed = fs if fs.spec.kind == "xor" else build_filter(orders, "o_orderkey", FilterSpec("xor"))
    n, bits = packed.pack().selectExpr("sum(n_keys)", "sum(packed_bits)").first()
    assert abs(bits / n - 9.23) < 0.1


def test_confusion_counts(spark, sf_dir):
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet")
    fs = build_filter(orders.where("o_orderstatus = 'F'"), "o_orderkey", FilterSpec("bloom"))
    asked = orders.select(F.col("o_orderkey").alias("k64"), (F.col("o_orderstatus") == "F").cast("int").alias("is_member"), F.lit(0).alias("hit_pct"))
    row = confusion(fs, asked).first()
    assert row["n_false_neg"] == 0 and row["n_reported"] == row["n_true"] + row["n_false_pos"]


def test_static_map(spark):
    rows = spark.range(5000).selectExpr("id", "id * 37 % 251 as v")
    fs = build_static_map(rows, "id", "v", FilterSpec("xor", 8, shard_keys=2000))
    assert lookup_map(fs, rows, "id").where("value != v").count() == 0
