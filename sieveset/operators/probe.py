"""Asking filter sets: as columns, by Arrow functions, or by a co-partitioned join."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sieveset.functions.hashing import _lit, high32_col, low32_col, reduce_range_col, with_mix64
from sieveset.kernels import filters as K

from .build import with_key, with_shard
from .filterset import FilterSet, from_row
from .spec import ALTERNATE, CELL0, CELL1, CELL2, PLACE, PRINT, role_seed

#: Filters of up to so many bytes are sent to all tasks; their size is known, as it is kept with each shard.
BROADCAST_BYTES = 512 << 20
#: Kinds whose test is written as columns.
NATIVE = ("xor", "xor_plus", "bloom", "blocked_bloom", "cuckoo", "cuckoo_pow2")


def plan_mode(fs: FilterSet, mode: str = "auto") -> str:
    """``udf`` while the arrays as they are stored fit a broadcast, else ``shuffle``.

    ``native`` stays in generated code but drags the arrays beside each row: measured at 126 ns a key against 46 of ``udf``,
    so it is for those who ask for it, where no Python may run.
    """
    if mode != "auto":
        return mode
    return "shuffle" if fs.stored_bytes() > BROADCAST_BYTES else "udf"


def probe(fs: FilterSet, df: DataFrame, key: str, mode: str = "auto", out: str = "maybe_member") -> DataFrame:
    """``df`` with ``out``: 1 where the key may be a member, 0 where it surely is none, null where the key is null."""
    mode = plan_mode(fs, mode)
    if mode == "native":
        return _native(fs, df, key, out)
    if mode == "udf":
        return with_key(df, key, fs.spec.hash_mode, "_k64").withColumn(out, might_contain(fs)(F.col("_k64"))).drop("_k64")
    if mode == "shuffle":
        return _shuffled(fs, df, key, out)
    raise ValueError(f"unknown mode {mode!r}")


def prefilter(fs: FilterSet, df: DataFrame, key: str, mode: str = "auto") -> DataFrame:
    """Rows whose key may be a member."""
    return probe(fs, df, key, mode, "_maybe").where("_maybe = 1").drop("_maybe")


def surely_absent(fs: FilterSet, df: DataFrame, key: str, mode: str = "auto") -> DataFrame:
    """Rows whose key is no member; this side never errs."""
    return probe(fs, df, key, mode, "_maybe").where("_maybe = 0").drop("_maybe")


def _shards(fs: FilterSet) -> dict[int, K.Built]:
    """Shards as arrays; only for sets that fit a broadcast."""
    return {r["shard"]: from_row(r, fs.spec) for r in fs.frame.toPandas().to_dict("records")}


def might_contain(fs: FilterSet):
    """An Arrow function of a 64-bit key; register it for SQL with ``spark.udf.register``."""
    spark = fs.frame.sparkSession
    spec, shards = fs.spec, fs.shard_count
    _check_sendable(fs)
    sent = spark.sparkContext.broadcast(_shards(fs))

    @F.arrow_udf(T.IntegerType())
    def test(keys: pa.Array) -> pa.Array:
        import numpy as np

        from sieveset.functions.hashing import derived_seed, high32, mix64_np, reduce_range_np
        from sieveset.operators.spec import SHARD

        known = keys.is_valid().to_numpy(zero_copy_only=False)
        values = keys.fill_null(0).to_numpy().astype(np.int64)
        got = np.zeros(len(values), np.int32)
        if shards == 1:
            if 0 in sent.value:
                got = K.contains(sent.value[0], spec, values).astype(np.int32)
        else:
            shard = reduce_range_np(high32(mix64_np(values, derived_seed(spec.seed, 500 + SHARD))), shards)
            order = np.argsort(shard, kind="stable")
            for s, part in zip(*_split(shard[order], order), strict=True):
                if s in sent.value:
                    got[part] = K.contains(sent.value[s], spec, values[part])
        return pa.array(got, mask=~known)

    return test


def probe_groups(fs: FilterSet, k64: Column) -> Column:
    """Ids of the filters of a set built per group that report a 64-bit key, as an array; all filters are sent to all tasks."""
    spec = fs.spec
    _check_sendable(fs)
    sent = fs.frame.sparkSession.sparkContext.broadcast([(r["filter_id"], from_row(r, spec)) for r in fs.frame.orderBy("filter_id").toPandas().to_dict("records")])

    @F.arrow_udf(T.ArrayType(T.StringType()))
    def reported(keys: pa.Array) -> pa.Array:
        import numpy as np

        known = keys.is_valid().to_numpy(zero_copy_only=False)
        values = keys.fill_null(0).to_numpy().astype(np.int64)
        names = pa.array([name for name, _ in sent.value], pa.string())
        hit = np.stack([K.contains(b, spec, values) & known for _, b in sent.value] or [np.zeros(len(values), bool)], 1)
        ends = np.r_[0, np.cumsum(hit.sum(1))].astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(ends), names.take(pa.array(np.nonzero(hit)[1])) if len(names) else names)

    return reported(k64)


def _check_sendable(fs: FilterSet) -> None:
    if (size := fs.stored_bytes()) > BROADCAST_BYTES:
        raise ValueError(f"a set of {size} bytes is not sent to all tasks; use mode='shuffle'")


def _split(sorted_shards, order):
    import numpy as np

    starts = np.flatnonzero(np.r_[True, sorted_shards[1:] != sorted_shards[:-1]]) if len(order) else np.zeros(0, int)
    return sorted_shards[starts].tolist(), np.split(order, starts[1:]) if len(order) else []


def _shuffled(fs: FilterSet, df: DataFrame, key: str, out: str) -> DataFrame:
    """Keys meet their shard by a shuffle, once each: a key that fills a third of the rows is asked once and joined back."""
    spec = fs.spec
    rows = with_key(df, key, spec.hash_mode, "_k64")
    asked = with_shard(rows.select(F.col("_k64").alias("k64")).where("k64 is not null").distinct(), spec, fs.shard_count)
    schema = T.StructType([T.StructField("_k", T.LongType()), T.StructField("_said", T.IntegerType())])

    def run(key_: tuple, shard: pa.Table, keys: pa.Table) -> pa.Table:
        values = keys.column("k64").to_numpy()
        said = [0] * len(values)
        if shard.num_rows:
            row = {n: (c[0].values.to_numpy() if pa.types.is_list(c.type) else c[0].as_py()) for n, c in zip(shard.column_names, shard.columns, strict=True)}
            said = K.contains(from_row(row, spec), spec, values)
        return pa.table({"_k": pa.array(values, pa.int64()), "_said": pa.array(said).cast(pa.int32())})

    said = fs.frame.groupBy("shard").cogroup(asked.groupBy("shard")).applyInArrow(run, schema)
    return rows.join(said, F.col("_k64") == F.col("_k"), "left").withColumn(out, F.col("_said")).drop("_k64", "_k", "_said")


# --- as columns -------------------------------------------------------------------------------------------------------


def _cell(cells: Column, at: Column, bits: int) -> Column:
    return F.get(cells, at.cast("int")).cast("long").bitwiseAND(_lit((1 << bits) - 1))


def _bit(words: Column, at: Column) -> Column:
    word = F.get(words, F.shiftright(at, 6).cast("int"))
    return F.call_function("bit_get", word, at.bitwiseAND(F.lit(63).cast("long")).cast("int")) == 1


def _native(fs: FilterSet, df: DataFrame, key: str, out: str) -> DataFrame:
    """One shard, whose arrays come by a broadcast join of one row and are read in place inside generated code."""
    spec = fs.spec
    if spec.kind not in NATIVE:
        raise ValueError(f"{spec.kind} has no column form; use mode='udf'")
    if fs.shard_count != 1:
        raise ValueError("several shards have no common seed; use mode='udf' or 'shuffle'")
    _check_sendable(fs)
    meta = fs.frame.select("seed", "capacity", "seg1", "seg2", "n_keys", "num_hashes").first()
    keep = [c for c in df.columns if c != out]
    rows = with_key(df, key, spec.hash_mode, "_k64")
    if not meta["n_keys"]:
        return rows.withColumn(out, F.when(F.col("_k64").isNotNull(), F.lit(0))).select(*keep, out)
    seed = meta["seed"] % (1 << 64)
    roles = {"xor": (CELL0, CELL1, CELL2, PRINT), "xor_plus": (CELL0, CELL1, CELL2, PRINT), "bloom": (PLACE,), "blocked_bloom": (PLACE,)}.get(spec.kind, (PLACE, PRINT))
    rows = with_mix64(rows, "_k64", {f"_h{r}": role_seed(seed, r) for r in roles})
    h = lambda r: F.col(f"_h{r}")
    table = F.broadcast(fs.frame.select(F.col("cells").alias("_cells"), F.col("aux").alias("_aux")))
    cells, aux = F.col("_cells"), F.col("_aux")
    if spec.kind.startswith("xor"):
        seg1, seg2, c = meta["seg1"], meta["seg2"], meta["capacity"]
        at = [F.lit(lo).cast("long") + reduce_range_col(high32_col(h(r)), hi - lo) for r, lo, hi in ((CELL0, 0, seg1), (CELL1, seg1, seg2), (CELL2, seg2, c))]
        if spec.kind == "xor":
            third = _cell(cells, at[2], spec.fp_bits)
            rows = rows.crossJoin(table)
        else:
            rows, place = _ranked(rows.withColumn("_at", at[2] - F.lit(seg2)).crossJoin(table), c - seg2, spec.rank)
            third = F.when(_bit(aux, F.col("_at")), _cell(cells, F.lit(seg2).cast("long") + place, spec.fp_bits)).otherwise(F.lit(0).cast("long"))
        found = _cell(cells, at[0], spec.fp_bits).bitwiseXOR(_cell(cells, at[1], spec.fp_bits)).bitwiseXOR(third) == h(PRINT).bitwiseAND(_lit((1 << spec.fp_bits) - 1))
    elif spec.kind == "bloom":
        found = None
        for i in range(meta["num_hashes"]):  # the chain stops at the first unset bit
            one = _bit(aux, bloom_place(h(PLACE), i, meta["capacity"]))
            found = one if found is None else found & one
        rows = rows.crossJoin(table)
    elif spec.kind == "blocked_bloom":
        rows = rows.withColumn("_block", reduce_range_col(high32_col(h(PLACE)), meta["capacity"]) * 8).crossJoin(table)
        found = None
        for j in range(8):
            bit = block_bit(h(PLACE), j)
            one = F.call_function("bit_get", F.get(aux, (F.col("_block") + j).cast("int")), bit.cast("int")) == 1
            found = one if found is None else found & one
    else:
        rows = rows.withColumn("_f", F.greatest(h(PRINT).bitwiseAND(_lit((1 << spec.fp_bits) - 1)), F.lit(1).cast("long")))
        rows = with_mix64(rows, "_f", {"_ha": role_seed(seed, ALTERNATE)})
        rows = rows.withColumns(dict(zip(("_l1", "_l2"), cuckoo_buckets_cols(h(PLACE), F.col("_ha"), meta["capacity"], spec.kind.endswith("pow2")), strict=True))).crossJoin(table)
        found = F.lit(False)
        for bucket in ("_l1", "_l2"):
            for j in range(K.SLOTS):
                found = found | (_cell(cells, F.col(bucket) * K.SLOTS + j, spec.fp_bits) == F.col("_f"))
    return rows.withColumn(out, F.when(F.col("_k64").isNotNull(), found.cast("int"))).select(*keep, out)


def bloom_place(h: Column, i: int, bits: int) -> Column:
    """The i-th position of a key: first half and i times second half, modulo 2**32."""
    return reduce_range_col(low32_col(high32_col(h) + low32_col(h) * i), bits)


def block_bit(h: Column, j: int) -> Column:
    """The bit in word j: the low half times an odd number modulo 2**32, its five top bits; in limbs, as the product may pass 2**63."""
    m = K.BLOCK_MULTIPLIERS[j]
    low = low32_col(h)
    product = low * (m & 0xFFFF) + F.shiftleft((low * (m >> 16)).bitwiseAND(_lit(0xFFFF)), 16)
    return F.shiftrightunsigned(low32_col(product), 27)


def cuckoo_buckets_cols(place: Column, alternate: Column, buckets: int, pow2: bool) -> tuple[Column, Column]:
    l1, other = reduce_range_col(high32_col(place), buckets), reduce_range_col(high32_col(alternate), buckets)
    return l1, l1.bitwiseXOR(other) if pow2 else F.pmod(F.lit(buckets).cast("long") - l1 - other, F.lit(buckets).cast("long"))


def _ranked(rows: DataFrame, cells: int, rank: str) -> tuple[DataFrame, Column]:
    """How many cells of the last part are occupied before ``_at``, from words and counts in ``_aux``."""
    words = -(-max(1, cells) // 2048) * 32
    at, aux = F.col("_at"), F.col("_aux")
    word = F.shiftright(at, 6)
    # 2**n - 1 without an overflow at n = 63: all ones, shifted down
    mask = F.expr("case when (_at & 63) = 0 then 0L else shiftrightunsigned(-1L, cast(64 - (_at & 63) as int)) end")
    own = F.bit_count(F.get(aux, word.cast("int")).bitwiseAND(mask)).cast("long")
    if rank == "two_level":
        group, j = F.shiftright(word, 3), word.bitwiseAND(F.lit(7).cast("long"))
        absolute = F.get(aux, (F.lit(words) + group * 2).cast("int"))
        relative = F.get(aux, (F.lit(words) + group * 2 + 1).cast("int"))
        inside = F.when(j > 0, F.call_function("shiftright", relative, ((j - 1) * 9).cast("int")).bitwiseAND(_lit(511))).otherwise(F.lit(0).cast("long"))
        return rows, absolute + inside + own
    group = F.shiftright(word, 5)
    between = F.aggregate(F.slice(aux, (group * 32 + 1).cast("int"), (word - group * 32).cast("int")), F.lit(0).cast("long"), lambda a, w: a + F.bit_count(w).cast("long"))
    return rows, F.get(aux, (F.lit(words) + group).cast("int")) + between + own


def confusion(fs: FilterSet, queries: DataFrame, key: str = "k64", member: str = "is_member", by: tuple[str, ...] = ("hit_pct",), mode: str = "auto") -> DataFrame:
    """Counts for each hit ratio: n_queries, n_reported, n_true, n_false_pos, n_false_neg and the false-positive rate in parts per million."""
    said = probe(fs, queries, key, mode)
    yes, real = F.col("maybe_member") == 1, F.col(member) == 1
    count = lambda c: F.count(F.when(c, 1)).cast("long")
    out = said.groupBy(*by).agg(F.count("*").alias("n_queries"), count(yes).alias("n_reported"), count(real).alias("n_true"), count(yes & ~real).alias("n_false_pos"), count(~yes & real).alias("n_false_neg"))
    return out.withColumn("fpp_ppm", F.expr("case when n_queries > n_true then n_false_pos * 1000000 div (n_queries - n_true) else 0 end"))


def lookup_map(fs: FilterSet, df: DataFrame, key: str, out: str = "value") -> DataFrame:
    """Values of a static map."""
    spark, spec, shards = fs.frame.sparkSession, fs.spec, fs.shard_count
    _check_sendable(fs)
    sent = spark.sparkContext.broadcast(_shards(fs))

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        import numpy as np

        from sieveset.functions.hashing import derived_seed, high32, mix64_np, reduce_range_np
        from sieveset.operators.spec import SHARD

        for keys in batches:
            values = keys.fill_null(0).to_numpy().astype(np.int64)
            shard = reduce_range_np(high32(mix64_np(values, derived_seed(spec.seed, 500 + SHARD))), shards) if shards > 1 else np.zeros(len(values), int)
            got = np.zeros(len(values), np.int64)
            for s in np.unique(shard):
                own = shard == s
                got[own] = K.xor_values(sent.value[int(s)], spec, values[own])
            yield pa.array(got)

    look = F.arrow_udf(T.LongType())(_typed(run))
    return with_key(df, key, spec.hash_mode, "_k64").withColumn(out, look(F.col("_k64"))).drop("_k64")


def _typed(run):
    def iterate(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        return run(batches)

    iterate.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return iterate
