"""Queries of the methods, variants, baselines and measures, each with the SQL that checks it where SQL can say it."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sieveset.functions import hashing as H
from sieveset.functions import measures as S
from sieveset.operators import relational as R
from sieveset.operators.build import build_filter, build_static_map, merge_bloom
from sieveset.operators.filterset import FilterSet
from sieveset.operators.probe import confusion, lookup_map, probe
from sieveset.operators.spec import PLACE, FilterSpec, attempt_seed, capacity, role_seed
from sieveset.sources.staging import materialise, table

from . import oracle_text as O
from . import workloads as W

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
XOR8, XOR16 = FilterSpec("xor"), FilterSpec("xor", 16)
BLOOM8 = FilterSpec("bloom", bits_per_key=8)
SEED1 = H.derived_seed(42, 1)


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def orders(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders")


# --- hashing ----------------------------------------------------------------------------------------------------------

_MIX = H.mix64_sql("o_orderkey", SEED1)


@query("mix64_values", f"select o_orderkey, {H.signed_sql(_MIX)} as h from orders")
def _(spark, d):
    return H.with_mix64(orders(spark, d).select("o_orderkey"), "o_orderkey", {"h": SEED1})


@query("range_reduce_values", f"select o_orderkey, {H.reduce_sql(f'({_MIX}) >> 32', 1000)} as cell from orders")
def _(spark, d):
    return H.with_mix64(orders(spark, d).select("o_orderkey"), "o_orderkey", {"h": SEED1}).select("o_orderkey", H.reduce_range_col(H.high32_col(F.col("h")), 1000).alias("cell"))


@query("range_mod_values", f"select o_orderkey, ((({_MIX}) >> 32)::bigint % 1000) as cell from orders")
def _(spark, d):
    return H.with_mix64(orders(spark, d).select("o_orderkey"), "o_orderkey", {"h": SEED1}).select("o_orderkey", H.reduce_mod_col(H.high32_col(F.col("h")), 1000).alias("cell"))


def _cells_sql(select: str, spec: FilterSpec) -> str:
    return f"with m as ({O.MEMBERS}), cfg as (select {spec.slack_hundredths} * count(*) // 100 + {spec.extra} as c from m), x as (select k as k64, {O.cells('k', spec)} from m, cfg) {select}"


@query("project_cells", _cells_sql("select k64, c0, c1, c2 from x", XOR8))
def _(spark, d):
    m = W.members(spark, d)
    return R.cells_of(m, m.count(), XOR8).drop("fp")


@query("fingerprints", _cells_sql("select k64, fp from x", XOR16))
def _(spark, d):
    m = W.members(spark, d)
    return R.cells_of(m, m.count(), XOR16).select("k64", "fp")


@query("md5_keys", f"select page_id, {H.signed_sql(H.md5_key_sql('url') + '::uhugeint')} as k64 from pages")
def _(spark, d):
    return table(spark, d, "pages").select("page_id", H.canonical_key(F.col("url"), "string", "md5").alias("k64"))


# --- xor --------------------------------------------------------------------------------------------------------------


def _cell_rows(fs: FilterSet, bits: int) -> DataFrame:
    return fs.frame.select(F.posexplode("cells").alias("cell", "v")).select(F.col("cell").cast("long").alias("cell"), F.col("v").cast("long").bitwiseAND(F.lit((1 << bits) - 1).cast("long")).alias("val"))


for _name, _spec in (("xor8", XOR8), ("xor16", XOR16)):
    query(f"{_name}_cells", f"with recursive {O.xor_ctes(_spec)} select t.i as cell, coalesce(val, 0) as val from cfg, range(c) t(i) left join b on b.cell = t.i")(lambda spark, d, s=_spec: _cell_rows(W.standard_filter(spark, d, s), s.fp_bits))

for _name, _spec in W.COMPARED.items():
    if _spec.kind not in ("xor_plus", "morton"):
        query(f"{_name}_mix", O.mix_confusion(_spec))(lambda spark, d, s=_spec: W.mix_confusion(spark, d, s))


@query("xor8_peel_rounds", f"with recursive {O.xor_ctes(XOR8)} select round::bigint as round, count(*) as keys, sum(own)::bigint as own_sum from peeled group by round")
def _(spark, d):
    return R.peel_table(W.members(spark, d), XOR8).groupBy("round").agg(F.count("*").alias("keys"), F.sum("cell").alias("own_sum"))


_DEGREES = _cells_sql("select cell, count(*) as degree, bit_xor(k64) as mask from (select k64, unnest([c0, c1, c2]) as cell from x) group by cell", XOR8)


@query("cell_degree_xor", _DEGREES)
def _(spark, d):
    m = W.members(spark, d)
    return R.degrees(R.cells_of(m, m.count(), XOR8))


@query("xor8_degrees", f"select degree, count(*) as cells from ({_DEGREES}) group by degree")
def _(spark, d):
    m = W.members(spark, d)
    return R.degrees(R.cells_of(m, m.count(), XOR8)).groupBy("degree").agg(F.count("*").alias("cells"))


@query("xor8_empty_share", f"with m as ({O.MEMBERS}), x as (select count(*) as n, 123 * count(*) // 100 + 32 as c from m) select n as n_keys, c as capacity, c - n as empty, (c - n) * 1000000 // c as empty_ppm from x")
def _(spark, d):
    return W.standard_filter(spark, d, XOR8).totals().select("n_keys", "capacity", "empty", F.expr("empty * 1000000 div capacity").alias("empty_ppm"))


@query("xor_capacity_extra", f"with m as ({O.MEMBERS}) select extra, (123 * count(*) // 100 + extra)::bigint as capacity, (8 * (123 * count(*) // 100 + extra))::bigint as bits_total, 0::bigint as missed from m, (values (16), (32), (64)) t(extra) group by extra")
def _(spark, d):
    out = None
    for extra in (16, 32, 64):
        fs = build_filter(W.members(spark, d), "k64", FilterSpec("xor", extra=extra), shards=1)
        missed = probe(fs, W.members(spark, d), "k64").agg(F.count(F.when(F.col("maybe_member") == 0, 1)).alias("missed"))
        row = fs.totals().select(F.lit(extra).alias("extra"), "capacity", "bits_total").crossJoin(missed)
        out = row if out is None else out.unionByName(row)
    return out


@query("build_attempts", f"with m as ({O.MEMBERS}) select 'xor' as kind, count(*) as n_keys, 1::bigint as least_attempts, true as few from m")
def _(spark, d):
    """Attempts are geometric; the expected number is below 1.25 for any size."""
    return W.standard_filter(spark, d, XOR8).frame.groupBy("kind").agg(F.sum("n_keys").alias("n_keys"), F.lit(1).cast("long").alias("least_attempts"), (F.avg("attempts") < 8).alias("few"))


# --- xor+ -------------------------------------------------------------------------------------------------------------


def _plus_mix(fp_bits: int):
    def run(spark, d):
        rate = 1_000_000 / 2**fp_bits
        out = W.mix_confusion(spark, d, FilterSpec("xor_plus", fp_bits))
        return out.select("hit_pct", "n_queries", "n_true", "n_false_neg", (F.abs(F.col("n_false_pos") - (F.col("n_queries") - F.col("n_true")) * rate / 1e6) <= 5 * F.sqrt((F.col("n_queries") - F.col("n_true")) * rate / 1e6) + 3).cast("int").alias("in_band"))

    return run


for _bits in (8, 16):
    query(f"xorplus{_bits}_mix", f"with {O.query_mix()} select hit_pct, count(*) as n_queries, sum(is_member)::bigint as n_true, 0::bigint as n_false_neg, 1 as in_band from q group by hit_pct")(_plus_mix(_bits))


@query("xorplus_bits", f"with m as ({O.MEMBERS}) select unnest([8, 16]) as fp_bits, count(*) as n_keys, 1 as in_band from m")
def _(spark, d):
    out = None
    for bits in (8, 16):
        want = 1.0824 * bits + 0.5125
        row = W.standard_filter(spark, d, FilterSpec("xor_plus", bits)).totals().select(F.lit(bits).alias("fp_bits"), "n_keys", (F.abs(F.col("bits_total") / F.col("n_keys") - want) < 0.6).cast("int").alias("in_band"))
        out = row if out is None else out.unionByName(row)
    return out


@query("xorplus_last_third_in_band", f"with m as ({O.MEMBERS}) select count(*) as n_keys, 1 as in_band from m")
def _(spark, d):
    """About 36% of the last third is empty, against 24% without priority; small sets stray."""
    return W.standard_filter(spark, d, FilterSpec("xor_plus")).totals().select("n_keys", F.col("empty_last").__truediv__(F.col("last_cells")).between(0.33, 0.40).cast("int").alias("in_band"))


# --- compaction -------------------------------------------------------------------------------------------------------


@query("pack_sparse_bits", f"with m as ({O.MEMBERS}), x as (select count(*) as n, 123 * count(*) // 100 + 32 as c from m) select n as n_keys, 8 * c as plain_bits, c + 8 * n as packed_bits from x")
def _(spark, d):
    return W.standard_filter(spark, d, XOR8).pack().groupBy().agg(F.sum("n_keys").alias("n_keys"), F.sum("bits_total").alias("plain_bits"), F.sum("packed_bits").alias("packed_bits"))


@query("pack_roundtrip", f"with m as ({O.MEMBERS}) select count(*) as n_keys, 0::bigint as cells_changed from m")
def _(spark, d):
    from sieveset.operators.filterset import unpack

    fs = W.standard_filter(spark, d, XOR8)
    back = unpack(fs.pack(), XOR8).select("shard", F.posexplode("cells").alias("cell", "after"))
    was = fs.frame.select("shard", "n_keys", F.posexplode("cells").alias("cell", "before"))
    return was.join(back, ["shard", "cell"], "full_outer").agg(F.max("n_keys").alias("n_keys"), F.count(F.when(~F.col("before").eqNullSafe(F.col("after")), 1)).alias("cells_changed"))


_COMPACT_BITS = "(8 * n + c + case rank when 'two_level' then bits // 4 else bits // 32 end)::bigint"


@query("compact_full_probe", f"with recursive q as ({O.PROBES}), {O.reported_ctes(XOR8)}, size as (select count(*) as n, 123 * count(*) // 100 + 32 as c from ({O.MEMBERS})), w as (select n, c, (c + 2047) // 2048 * 2048 as bits from size), hit as (select count(*) as n_reported from reported) select rank, n as n_keys, {_COMPACT_BITS} as bits_total, n_reported from w, hit, (values ('two_level'), ('sparse_samples')) t(rank)")
def _(spark, d):
    """The whole array behind a rank structure, asked: answers are those of the plain filter, bits those that are written."""
    fs, out = W.standard_filter(spark, d, XOR8), None
    for rank in ("two_level", "sparse_samples"):
        small = fs.compact_full(rank)
        said = probe(small, W.probes(spark, d), "k64").agg(F.sum("maybe_member").cast("long").alias("n_reported"))
        row = small.totals().select(F.lit(rank).alias("rank"), "n_keys", "bits_total").crossJoin(said)
        out = row if out is None else out.unionByName(row)
    return out


@query("rank_prefix", f"with recursive {O.xor_ctes(XOR8)}, ones as (select cell // 64 as word_index, count(*) as n from b where cell >= 0 group by 1), words as (select t.i as word_index from cfg, range((c + 2047) // 2048 * 32) t(i)) select word_index, coalesce(sum(n) over (order by word_index rows between unbounded preceding and 1 preceding), 0)::bigint as ones_before from words left join ones using (word_index)")
def _(spark, d):
    """A rank structure as a running sum of popcounts."""
    words = W.standard_filter(spark, d, XOR8).frame.select("shard", F.posexplode("aux").alias("word_index", "word"))
    run = Window.partitionBy("shard").orderBy("word_index").rowsBetween(Window.unboundedPreceding, -1)
    return words.select(F.col("word_index").cast("long").alias("word_index"), F.coalesce(F.sum(F.bit_count("word")).over(run), F.lit(0)).cast("long").alias("ones_before"))


# --- Bloom ------------------------------------------------------------------------------------------------------------

_PLACE8 = O.mix("k", BLOOM8, PLACE)
_POS8 = f"((((h >> 32) + i::uhugeint * (h & {O.M32}::uhugeint)) & {O.M32}::uhugeint) * greatest(1, 8 * n)::uhugeint >> 32)::bigint"
_BITS8 = f"m as ({O.MEMBERS}), cfg as (select count(*) as n from m), hm as (select k, {_PLACE8} as h from m), bits as (select distinct {_POS8} as bit from hm, cfg, range({BLOOM8.hashes}) t(i))"


@query("bloom_bits_set", f"with {_BITS8} select n as n_keys, 8 * n as bits_total, (select count(*) from bits) as bits_set from cfg")
def _(spark, d):
    return W.standard_filter(spark, d, BLOOM8).frame.select("n_keys", "bits_total", F.aggregate("aux", F.lit(0).cast("long"), lambda a, w: a + F.bit_count(w)).alias("bits_set"))


@query("bloom_word_or", f"with {_BITS8} select bit // 64 as word_index, {H.signed_sql('bit_or(1::uhugeint << (bit % 64)::uhugeint)')} as word from bits group by 1")
def _(spark, d):
    m = W.members(spark, d)
    return R.bloom_words(m, m.count(), BLOOM8)


@query("bloom_probes_used", f"""with {O.query_mix()}, {_BITS8}, ha as (select distinct k, {_PLACE8} as h from q),
    seen as (select k, i, {_POS8} as bit from ha, cfg, range({BLOOM8.hashes}) t(i)),
    used as (select k, coalesce(min(case when bits.bit is null then i end) + 1, {BLOOM8.hashes}) as probes from seen left join bits using (bit) group by k)
    select hit_pct, count(*) as n_queries, sum(probes)::bigint as probes_used from q join used using (k) group by hit_pct""")
def _(spark, d):
    """Bloom filters read more for hits than for misses; the xor filter always reads three cells."""
    m, asked = W.members(spark, d), W.standard_mix(spark, d)
    n = m.count()
    used = R.bloom_probe(asked.select("k64").distinct(), R.bloom_words(m, n, BLOOM8), n, BLOOM8)
    return asked.join(used, "k64").groupBy("hit_pct").agg(F.count("*").alias("n_queries"), F.sum("probes_used").alias("probes_used"))


@query("bloom_forall_probe", f"with q as ({O.PROBES}), {O.reported_ctes(BLOOM8)} select count(*) as n_queries, count(r.k) as n_reported from q left join reported r on r.k = q.k")
def _(spark, d):
    """The probe as one higher-order function over an array of positions, each with its word of the filter.

    The filter is a scalar subquery, read in place; beside each row (a cross join) all of it would be copied once a key.
    """
    from sieveset.operators.probe import bloom_place

    fs = W.standard_filter(spark, d, BLOOM8)
    meta = fs.frame.select("capacity", "num_hashes", "seed").first()
    asked = H.with_mix64(W.probes(spark, d), "k64", {"h": role_seed(meta["seed"] % (1 << 64), PLACE)})
    words = fs.frame.select("aux").scalar()
    places = [bloom_place(F.col("h"), i, meta["capacity"]) for i in range(meta["num_hashes"])]
    asked = asked.select(F.array(*(F.struct(F.get(words, F.shiftright(p, 6).cast("int")).alias("word"), p.bitwiseAND(F.lit(63).cast("long")).cast("int").alias("at")) for p in places)).alias("read"))
    hit = F.forall("read", lambda x: F.call_function("bit_get", x["word"], x["at"]) == 1)
    return asked.select(hit.alias("hit")).agg(F.count("*").alias("n_queries"), F.count(F.when(F.col("hit"), 1)).alias("n_reported"))


_HALF = FilterSpec("bloom", bits_per_key=8, sized_for=10_000)


def _fixed_bits(members: str) -> str:
    return f"(select distinct ((((h >> 32) + i::uhugeint * (h & {O.M32}::uhugeint)) & {O.M32}::uhugeint) * 80000::uhugeint >> 32)::bigint as bit from (select {O.mix('k', _HALF, PLACE)} as h from ({members})), range({_HALF.hashes}) t(i))"


@query("bloom_merge", f"select count(*) as bits_set, (select count(*) from ({O.MEMBERS})) as n_keys, 0::bigint as missed from {_fixed_bits(O.MEMBERS)}")
def _(spark, d):
    m = W.members(spark, d)
    half = [build_filter(m.where(F.col("k64") % 2 == r), "k64", _HALF, shards=1) for r in (0, 1)]
    both = merge_bloom(*half)
    missed = probe(both, m, "k64").agg(F.count(F.when(F.col("maybe_member") == 0, 1)).alias("missed"))
    return both.frame.select(F.aggregate("aux", F.lit(0).cast("long"), lambda a, w: a + F.bit_count(w)).alias("bits_set"), "n_keys").crossJoin(missed)


@query("bloom_from_fpp", " union all ".join(f"select {inverse} as inverse_fpp, {math.ceil(math.log2(inverse))}::int as hashes, floor({math.log2(inverse) / math.log(2)!r}::double * count(*))::bigint as bits_total from ({O.MEMBERS})" for inverse in (10, 100, 1000)))
def _(spark, d):
    out = None
    for inverse in (10, 100, 1000):
        fs = W.standard_filter(spark, d, FilterSpec.from_fpp(1 / inverse))
        row = fs.frame.select(F.lit(inverse).alias("inverse_fpp"), F.col("num_hashes").alias("hashes"), "bits_total")
        out = row if out is None else out.unionByName(row)
    return out


_BLOCK = FilterSpec("blocked_bloom")


@query("blocked_words", f"with q as (select 0 as k where false), {O.reported_ctes(_BLOCK)} select block, word, sum(1::bigint << bit)::bigint as val from bits group by block, word")
def _(spark, d):
    m = W.members(spark, d)
    words = R.blocked_words(m, m.count(), _BLOCK)
    return words.unpivot("block", [f"w{j}" for j in range(8)], "name", "val").select("block", F.substring("name", 2, 1).cast("int").alias("word"), "val")


# --- cuckoo, GCS, quotient, Morton ------------------------------------------------------------------------------------

_C12 = FilterSpec("cuckoo", 12)


@query("cuckoo_involution", f"with m as ({O.MEMBERS}) select unnest(['cuckoo', 'cuckoo_pow2']) as kind, count(*) as n_keys, 0::bigint as broken, 0::bigint as out_of_range from m")
def _(spark, d):
    from sieveset.operators.spec import cuckoo_buckets

    m, out = W.members(spark, d), None
    n = m.count()
    for kind in ("cuckoo", "cuckoo_pow2"):
        spec = FilterSpec(kind, 12)
        buckets, e = cuckoo_buckets(n, spec), R.cuckoo_entries(m, n, spec)
        other = F.col("l1").bitwiseXOR(F.col("l2"))
        again = F.col("l2").bitwiseXOR(other) if kind.endswith("pow2") else F.pmod(F.lit(buckets) - F.col("l2") - F.pmod(F.lit(buckets) - F.col("l1") - F.col("l2"), F.lit(buckets)), F.lit(buckets))
        row = e.agg(F.count("*").alias("n_keys"), F.count(F.when(again != F.col("l1"), 1)).alias("broken"), F.count(F.when((F.col("l2") < 0) | (F.col("l2") >= buckets), 1)).alias("out_of_range")).select(F.lit(kind).alias("kind"), "*")
        out = row if out is None else out.unionByName(row)
    return out


@query("cuckoo12_relational", f"with q as ({O.PROBES}), {O.reported_ctes(_C12)} select k as k64 from reported")
def _(spark, d):
    m = W.members(spark, d)
    return R.cuckoo_members(W.probes(spark, d), m, m.count(), _C12)


@query("cuckoo_load_ablation", f"with m as ({O.MEMBERS}) select load, greatest(1, (100 * count(*) + 4 * load - 1) // (4 * load))::bigint as buckets, (48 * greatest(1, (100 * count(*) + 4 * load - 1) // (4 * load)))::bigint as bits_total, 0::bigint as missed from m, (values (80), (94), (95), (96)) t(load) group by load")
def _(spark, d):
    out = None
    for load in (80, 94, 95, 96):
        fs = W.standard_filter(spark, d, FilterSpec("cuckoo", 12, load=load / 100))
        missed = probe(fs, W.members(spark, d), "k64").agg(F.count(F.when(F.col("maybe_member") == 0, 1)).alias("missed"))
        row = fs.frame.select(F.lit(load).alias("load"), F.col("capacity").alias("buckets"), "bits_total").crossJoin(missed)
        out = row if out is None else out.unionByName(row)
    return out


_GCS = FilterSpec("gcs")


@query("gcs_deltas", f"with m as ({O.MEMBERS}), cfg as (select count(*) as n from m), v as (select {O.reduce(O.mix('k', _GCS, PLACE), 'n * 256')} as v from m, cfg) select v, v - lag(v, 1, 0) over (order by v) as delta from v")
def _(spark, d):
    """Sorted hashes and their differences; one stretch of the range a window, so that no task holds all."""
    m = W.members(spark, d)
    n = m.count()
    v = R.gcs_sorted(m, n, _GCS).select("v").withColumn("part", F.expr(f"v div {max(1, 65_536 << 8)}L"))
    edges = v.groupBy("part").agg(F.max("v").alias("hi"))
    before = edges.select("part", F.coalesce(F.last("hi", True).over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("prior"))
    inside = F.lag("v").over(Window.partitionBy("part").orderBy("v"))
    return v.withColumn("last", inside).join(before, "part").select("v", (F.col("v") - F.coalesce("last", "prior")).alias("delta"))


@query("gcs_bits", f"with m as ({O.MEMBERS}) select count(*) as n_keys, 1 as in_band from m")
def _(spark, d):
    return W.standard_filter(spark, d, _GCS).totals().select("n_keys", (F.col("bits_total") / F.col("n_keys")).between(9.8, 10.2).cast("int").alias("in_band"))


_CQF_N = "(select count(distinct l_orderkey) from lineitem)"
_CQF = FilterSpec("cqf")


@query("cqf_counts", f"""with n as (select {_CQF_N} as n), h as (select (({O.mix('l_orderkey', _CQF, PLACE)}) >> (64 - greatest(1, ceil(log2(greatest(2, n / 0.95)))::int) - 8)::uhugeint)::bigint as v from lineitem, n),
    by_value as (select v, count(*) as times from h group by v) select times, count(*) as values_held from by_value group by times""")
def _(spark, d):
    """The multiset side: how many stored values occur how often."""
    from sieveset.operators.spec import quotient_bits

    lines = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("k64"))
    q = quotient_bits(lines.agg(F.count_distinct("k64")).first()[0])
    h = H.with_mix64(lines, "k64", {"h": role_seed(attempt_seed(42, 0, 0), PLACE)})
    return h.groupBy(F.shiftrightunsigned("h", 64 - q - 8).alias("v")).agg(F.count("*").alias("times")).groupBy("times").agg(F.count("*").alias("values_held"))


@query("morton_members", f"with {O.query_mix()} select hit_pct, count(*) as n_queries, sum(is_member)::bigint as n_true, 0::bigint as n_false_neg, 1 as in_band from q group by hit_pct")
def _(spark, d):
    out = W.mix_confusion(spark, d, FilterSpec("morton"))
    return out.select("hit_pct", "n_queries", "n_true", "n_false_neg", (F.col("fpp_ppm") < 9000).cast("int").alias("in_band"))


# --- comparisons and measures -----------------------------------------------------------------------------------------

_CLOSED = {
    "blocked": "256 * greatest(1, (107 * n + 2559) // 2560)",
    "bloom8": "8 * n",
    "bloom12": "12 * n",
    "bloom16": "16 * n",
    "css13": "48 * greatest(1, (100 * n + 375) // 376)",
    "cuckoo12": "48 * greatest(1, (100 * n + 375) // 376)",
    "cuckoo16": "64 * greatest(1, (100 * n + 375) // 376)",
    "xor8": "8 * (123 * n // 100 + 32)",
    "xor16": "16 * (123 * n // 100 + 32)",
    "cuckoo12_pow2": "48 * (1::bigint << ceil(log2(greatest(1, (100 * n + 375) // 376)))::int)",
    "cuckoo16_pow2": "64 * (1::bigint << ceil(log2(greatest(1, (100 * n + 375) // 376)))::int)",
    "cqf": "(1::bigint << greatest(1, ceil(log2(greatest(2, n / 0.95)))::int)) * 10125 // 1000",
    "exact": "64 * n",
}


def _compare(pct: int):
    def run(spark, d):
        out, asked = None, W.standard_mix(spark, d, (pct,))
        asked = materialise(asked, "mix")
        for name in _CLOSED:
            fs = W.standard_filter(spark, d, W.COMPARED[name])
            row = confusion(fs, asked).select(F.lit(name).alias("filter"), "hit_pct", "n_queries", "n_reported", "n_false_pos", "n_false_neg").crossJoin(F.broadcast(fs.totals().select("n_keys", F.col("bits_total").cast("long").alias("bits_total"))))
            out = row if out is None else out.unionByName(row)
        return out

    return run


def _compare_sql(pct: int) -> str:
    parts = [f"""select '{name}' as filter, x.hit_pct, x.n_queries, x.n_reported, x.n_false_pos, x.n_false_neg, n.n as n_keys, ({bits})::bigint as bits_total
      from ({O.mix_confusion(W.COMPARED[name], (pct,))}) x, (select count(*) as n from ({O.MEMBERS})) n""" for name, bits in _CLOSED.items()]
    return " union all ".join(parts)


for _pct in (25, 100):
    query(f"filter_compare_{_pct}", _compare_sql(_pct))(_compare(_pct))


#: Bits per key as published or derived, and probability of a false positive, of each compared filter. Fixed values.
_EXPECTED = {
    "blocked": (10.7, 0.00929), "bloom8": (8.0, 0.02158), "bloom12": (12.0, 0.00314), "bloom16": (16.0, 0.00046), "css13": (12.77, 0.000918), "cuckoo12": (12.77, 0.00184),
    "cuckoo16": (17.02, 0.000115), "gcs8": (10.0, 0.0039), "xor8": (9.84, 0.0039), "xor16": (19.68, 0.0000153), "xorplus8": (9.17, 0.0039), "xorplus16": (17.82, 0.0000153), "morton": (11.72, 0.0039),
}


def _bands(pct: int):
    def run(spark, d):
        asked, out = materialise(W.standard_mix(spark, d, (pct,)), "mix"), None
        for name, (bits, fpp) in _EXPECTED.items():
            fs = W.standard_filter(spark, d, W.COMPARED[name])
            others = F.col("n_queries") - F.col("n_true")
            said = confusion(fs, asked).select("hit_pct", "n_queries", "n_false_neg", (F.abs(F.col("n_false_pos") - others * fpp) <= 5 * F.sqrt(others * fpp) + 0.1 * others * fpp + 3).cast("int").alias("fpp_in_band"))
            size = fs.totals().select((F.abs(F.col("bits_total") / F.col("n_keys") - bits) <= 0.1 + 2200 / F.col("n_keys")).cast("int").alias("bits_in_band"))
            row = said.select(F.lit(name).alias("filter"), "*").crossJoin(F.broadcast(size))
            out = row if out is None else out.unionByName(row)
        return out

    return run


for _pct in (25, 100):
    _names = ", ".join(f"'{name}'" for name in _EXPECTED)
    query(f"filter_bands_{_pct}", f"with {O.query_mix()} select unnest([{_names}]) as filter, hit_pct, count(*) as n_queries, 0::bigint as n_false_neg, 1 as fpp_in_band, 1 as bits_in_band from q where hit_pct = {_pct} group by hit_pct")(_bands(_pct))


_GRID = " union all ".join(f"select '{k}' as kind, i::int as log2_inverse_fpp, round(({a!r}::double * i + {b!r}::double) * 1000)::bigint as milli_bits from range(1, 33) t(i)" for k, (a, b) in S.CURVES.items())


@query("space_curve", f"with n as (select o_orderstatus, count(distinct o_orderkey) as n_keys from orders group by 1) select o_orderstatus, n_keys, kind, log2_inverse_fpp, milli_bits, n_keys * milli_bits // 1000 as bits from n, ({_GRID})")
def _(spark, d):
    """Bits per key, and of all orders of a status."""
    sets = orders(spark, d).groupBy("o_orderstatus").agg(F.count_distinct("o_orderkey").alias("n_keys"))
    return S.space_table(spark).crossJoin(F.broadcast(sets)).select("o_orderstatus", "n_keys", "kind", "log2_inverse_fpp", "milli_bits", F.expr("n_keys * milli_bits div 1000").alias("bits"))


_CROSSED = {("bloom", "cuckoo"): 0.004, ("cuckoo", "xor"): 5.6e-6, ("xor", "xor_plus"): 2 ** -(0.5125 / 0.1476)}


def _crossed_sql(one: str, other: str) -> str:
    """The pair, its thousandths of bits per key where the straight lines meet, and the band."""
    (a, b), (a2, b2) = S.CURVES[one], S.CURVES[other]
    return f"select '{one}' as one, '{other}' as other, round(1000 * ({a!r}::double * ({b2!r}::double - {b!r}::double) / ({a!r}::double - {a2!r}::double) + {b!r}::double))::bigint as milli"


@query("space_crossover", f"with n as (select o_orderstatus, count(distinct o_orderkey) as n_keys from orders group by 1) select o_orderstatus, one, other, n_keys, n_keys * milli // 1000 as bits, 1::int as in_band from n, ({' union all '.join(_crossed_sql(*pair) for pair in _CROSSED)})")
def _(spark, d):
    """Bits that the orders of a status need where two kinds take the same space. Bloom beats cuckoo from 0.4% on, cuckoo beats xor below 5.6e-6, xor+ beats xor from four bits on."""
    rows = []
    for (one, other), e in _CROSSED.items():
        at = S.crossover(one, other)
        rows.append((one, other, round(1000 * S.space_curve(one, at)), int(abs(math.log(at / e)) < 0.05)))
    sets = orders(spark, d).groupBy("o_orderstatus").agg(F.count_distinct("o_orderkey").alias("n_keys"))
    crossed = spark.createDataFrame(rows, "one string, other string, milli long, in_band int")
    return sets.crossJoin(F.broadcast(crossed)).select("o_orderstatus", "one", "other", "n_keys", F.expr("n_keys * milli div 1000").alias("bits"), "in_band")


#: Set sizes and their published success probabilities at 16, 32 and 64 cells more. Fixed values.
_SUCCESS = {
    3: (0.986, 0.994, 1.0), 9: (0.949, 0.986, 0.998), 27: (0.865, 0.965, 0.989), 81: (0.853, 0.944, 0.979), 243: (0.767, 0.959, 0.983), 729: (0.733, 0.9, 0.986), 2187: (0.712, 0.848, 0.978),
    6561: (0.815, 0.862, 0.953), 19683: (0.926, 0.948, 0.975), 59049: (0.997, 0.999, 0.999), 177147: (1.0, 1.0, 1.0), 531441: (1.0, 1.0, 1.0),
}
#: Keys that sets are drawn from together, at least: four times the largest set.
_POOL = 4 * max(_SUCCESS)


def line_keys(spark: SparkSession, d: str) -> DataFrame:
    """One key for each line of an order."""
    return table(spark, d, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("long").alias("k64")).distinct()


def _curve_sql() -> str:
    """Sets of each size that passes over all lines give: as many passes as make 1000, shared by the groups."""
    sizes, extras = (", ".join(f"({x})" for x in xs) for xs in (_SUCCESS, (16, 32, 64)))
    return f"""with k as (select distinct (l_orderkey * 8 + l_linenumber)::bigint as k64 from lineitem where l_orderkey is not null and l_linenumber is not null),
      g as (select greatest(1, count(*) // {_POOL}) as n_groups from k),
      p as (select n_groups, (({H.mix64_sql("k64", S.DEAL_SEED)}) >> 32)::bigint % n_groups as part, count(*) as n from k, g group by 1, 2),
      c as (select size, (n + size - 1) // size as n_sets, (999 + n_groups) // n_groups as need from p, (values {sizes}) s(size) where size <= n)
      select size::int as size, extra::int as extra, sum(n_sets * ((need + n_sets - 1) // n_sets))::bigint as trials, 1 as in_band from c, (values {extras}) e(extra) group by 1, 2"""


@query("success_curve", _curve_sql())
def _(spark, d):
    """All lines cut at random into sets of each size that they fill, 1000 sets or more; both samples err, so the band is five deviations of their difference and two hundredths."""
    got = S.success_curve(line_keys(spark, d), tuple(_SUCCESS), (16, 32, 64), 1000, _POOL)
    want = spark.createDataFrame([(size, extra, p) for size, ps in _SUCCESS.items() for extra, p in zip((16, 32, 64), ps, strict=True)], "size int, extra int, p double")
    gap = F.abs(F.col("successes") / F.col("trials") - F.col("p")) <= 5 * F.sqrt(F.col("p") * (1 - F.col("p")) * (1 / F.col("trials") + F.lit(0.001))) + 0.02
    return got.join(F.broadcast(want), ["size", "extra"]).select("size", "extra", "trials", gap.cast("int").alias("in_band"))


@query("pow2_vs_flexible", " union all ".join(f"select '{name}' as filter, count(*) as n_keys, ({_CLOSED[name]})::bigint as bits_total from (select count(*) as n from ({O.MEMBERS})), ({O.MEMBERS}) group by n" for name in ("cuckoo12", "cuckoo12_pow2", "cuckoo16", "cuckoo16_pow2")))
def _(spark, d):
    out = None
    for name in ("cuckoo12", "cuckoo12_pow2", "cuckoo16", "cuckoo16_pow2"):
        row = W.standard_filter(spark, d, W.COMPARED[name]).totals().select(F.lit(name).alias("filter"), "n_keys", F.col("bits_total").cast("long").alias("bits_total"))
        out = row if out is None else out.unionByName(row)
    return out


_FIT = "least(376 * (1::bigint << floor(log2(greatest(1, n / 3.76)))::int) // 100, n)"


@query("pow2_near_capacity", f"with c as (select count(*) as n from orders), k as (select {_FIT} as n_keys from c) select filter, n_keys, case filter when 'cuckoo12' then 48 * greatest(1, (100 * n_keys + 375) // 376) else 48 * (1::bigint << ceil(log2(greatest(1, (100 * n_keys + 375) // 376)))::int) end::bigint as bits_total from k, (values ('cuckoo12'), ('cuckoo12_pow2')) t(filter)")
def _(spark, d):
    """As many keys as just fit a power of two: both forms take the same space, up to a bucket."""
    keys, n = W.ranked(orders(spark, d).select(F.col("o_orderkey").alias("k64")))
    room = min(376 * (1 << int(math.floor(math.log2(max(1, n / 3.76))))) // 100, n)
    keys, out = keys.where(F.col("rank") <= room).select("k64"), None  # the size is what is measured
    for name in ("cuckoo12", "cuckoo12_pow2"):
        fs = build_filter(keys, "k64", W.COMPARED[name], shards=1)
        row = fs.totals().select(F.lit(name).alias("filter"), "n_keys", F.col("bits_total").cast("long").alias("bits_total"))
        out = row if out is None else out.unionByName(row)
    return out


@query("sequential_vs_mixed", f"with {O.query_mix()} select unnest(['sequential', 'mixed']) as keys, count(*) as n_queries, 0::bigint as n_false_neg, 1 as in_band from q where hit_pct = 25")
def _(spark, d):
    """The same experiment with keys as they come and with keys that were mixed first."""
    out = None
    for name in ("sequential", "mixed"):
        a, asked = W.members(spark, d), materialise(W.standard_mix(spark, d, (25,)), "mix")
        if name == "mixed":
            a = materialise(H.with_mix64(a, "k64", {"h": 42}).select(F.col("h").alias("k64")), "mixed-keys")
            asked = H.with_mix64(asked, "k64", {"h": 42}).drop("k64").withColumnRenamed("h", "k64")
        others = F.col("n_queries") - F.col("n_true")
        row = confusion(build_filter(a, "k64", XOR8, shards=1), asked).select(F.lit(name).alias("keys"), "n_queries", "n_false_neg", (F.abs(F.col("n_false_pos") - others / 256) <= 5 * F.sqrt(others / 256) + 3).cast("int").alias("in_band"))
        out = row if out is None else out.unionByName(row)
    return out


@query("mixed_keys_rate", f"with m as ({O.MEMBERS}) select count(*) as n_keys, 1 as same_rate from m")
def _(spark, d):
    """Mixed instead of sequential keys: no significant difference of the false-positive rates."""
    rates = []
    for mixed in (False, True):
        a, b = W.members(spark, d), W.others(spark, d)
        if mixed:
            a, b = (materialise(H.with_mix64(x, "k64", {"h": 42}).select(F.col("h").alias("k64")), "mixed-keys") for x in (a, b))
        fs = build_filter(a, "k64", XOR8, shards=1)
        rates.append(probe(fs, b, "k64").agg(F.sum("maybe_member").alias("hits"), F.count("*").alias("n")).select(F.lit(mixed).alias("mixed"), "hits", "n"))
    both = rates[0].unionByName(rates[1]).groupBy().agg(F.max(F.when(F.col("mixed"), F.col("hits"))).alias("a"), F.max(F.when(~F.col("mixed"), F.col("hits"))).alias("b"))
    n = W.members(spark, d).agg(F.count("*").alias("n_keys"))
    return n.crossJoin(both).select("n_keys", (F.abs(F.col("a") - F.col("b")) <= 5 * F.sqrt(F.col("a") + F.col("b")) + 3).cast("int").alias("same_rate"))


@query("construction_sizes", " union all ".join(f"select '{k}' as filter, n as n_keys, ({bits})::bigint as bits_total from (select count(distinct l_orderkey) as n from lineitem)" for k, bits in _CLOSED.items()))
def _(spark, d):
    keys, out = W.probes(spark, d), None
    for name in _CLOSED:
        row = build_filter(keys, "k64", W.COMPARED[name], shards=1).totals().select(F.lit(name).alias("filter"), "n_keys", F.col("bits_total").cast("long").alias("bits_total"))
        out = row if out is None else out.unionByName(row)
    return out


_ACCESSES = ("xor", "cuckoo", "blocked_bloom", "bloom")


@query("access_model", """with g as (select l_returnflag, count(*) as n_queries, count(case when o_orderstatus = 'F' then 1 end) as n_true from lineitem left join orders on o_orderkey = l_orderkey group by 1)
    select kind, l_returnflag, n_queries, n_true, ((n_true * hit + (n_queries - n_true) * miss) // (10000 * n_queries))::bigint as milli_accesses
    from g, (values ('xor', 30000000, 30000000), ('cuckoo', 20000000, 20000000), ('blocked_bloom', 10000000, 10000000), ('bloom', 80000000, 19921875)) t(kind, hit, miss)""")
def _(spark, d):
    """Modelled accesses of a probe at the share of hits that the lines of each return flag have; ten-millionths keep the model whole."""
    real = W.members(spark, d).select(F.col("k64").alias("l_orderkey"), F.lit(1).alias("real"))
    asked = table(spark, d, "lineitem").select("l_orderkey", "l_returnflag").join(real, "l_orderkey", "left")
    groups = asked.groupBy("l_returnflag").agg(F.count("*").alias("n_queries"), F.count("real").alias("n_true"))
    model = spark.createDataFrame([(k, *(round(10**7 * S.access_model(k, hit)) for hit in (1, 0))) for k in _ACCESSES], "kind string, hit long, miss long")
    return groups.crossJoin(F.broadcast(model)).select("kind", "l_returnflag", "n_queries", "n_true", F.expr("(n_true * hit + (n_queries - n_true) * miss) div (10000 * n_queries)").alias("milli_accesses"))


@query("static_map_lookup", "select count(*) as n_keys, 0::bigint as wrong from part")
def _(spark, d):
    parts = table(spark, d, "part").select("p_partkey", "p_size")
    fs = build_static_map(parts, "p_partkey", "p_size", XOR8)
    return lookup_map(fs, parts, "p_partkey").agg(F.count("*").alias("n_keys"), F.count(F.when(F.col("value") != F.col("p_size"), 1)).alias("wrong"))


@query("key128_collisions", "select count(*) as n_urls, count(distinct md5(url)) as n_keys from pages")
def _(spark, d):
    """Long keys as two 64-bit halves of an md5."""
    halves = table(spark, d, "pages").select(H.md5_key(F.col("url").cast("binary")).alias("hi"), H.md5_key(F.col("url").cast("binary"), 1).alias("lo"))
    return halves.agg(F.count("*").alias("n_urls"), F.count_distinct("hi", "lo").alias("n_keys"))


@query("sort_keys", f"select k as k64, row_number() over (order by k) as rank from ({O.MEMBERS})")
def _(spark, d):
    """The yardstick of building: all keys in order, which their ranks show; sorted inside slices of the range."""
    return W.ranked(W.members(spark, d))[0].select("k64", F.col("rank").cast("long").alias("rank"))


@query("cuckoo_failures")
def _(spark, d):
    """(load, trials, failures): how often tables of some 20,000 lines each, which hold all lines, fail to take their keys at the first seed. No SQL: evictions are drawn."""
    return S.cuckoo_failures(line_keys(spark, d), 20_000, (94, 95, 96, 98), 30)


assert capacity(10_000_000) == 12_300_032
