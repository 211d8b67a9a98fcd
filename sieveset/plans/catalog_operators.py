"""Queries of the operators around the filters, and of the applications."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sieveset.functions import hashing as H
from sieveset.operators.build import build_filter, build_filter_per_group, with_key
from sieveset.operators.joins import filtered_join, runs_to_read
from sieveset.operators.probe import probe_groups, might_contain, prefilter, probe, surely_absent
from sieveset.operators.relational import cells_of
from sieveset.operators.spec import FilterSpec
from sieveset.sources.staging import materialise, shared_dir, table

from . import oracle_text as O
from . import workloads as W

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
XOR8, BLOOM8 = FilterSpec("xor"), FilterSpec("bloom", bits_per_key=8)


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _orders(spark, d) -> DataFrame:
    return table(spark, d, "orders")


def _f(spark, d) -> DataFrame:
    return _orders(spark, d).where("o_orderstatus = 'F'")


REPORTED = f"with recursive q as ({O.PROBES}), {O.reported_ctes(XOR8)}"
BLOOMED = f"with q as ({O.PROBES}), {O.reported_ctes(BLOOM8)}"


# --- predicates, joins, subqueries ------------------------------------------------------------------------------------


@query("scan_keys", "select count(*) as n, count(distinct l_orderkey) as keys from lineitem")
def _(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey").agg(F.count("*").alias("n"), F.count_distinct("l_orderkey").alias("keys"))


@query("filter_maybe", f"{REPORTED} select k as k64 from reported")
def _(spark, d):
    return prefilter(W.standard_filter(spark, d, XOR8), W.probes(spark, d), "k64")


@query("filter_surely_absent", f"{REPORTED} select k as k64 from q anti join reported using (k)")
def _(spark, d):
    return surely_absent(W.standard_filter(spark, d, XOR8), W.probes(spark, d), "k64")


@query("filter_range_and_member", f"{REPORTED} select k as k64 from reported where k between 1000 and 9000")
def _(spark, d):
    return prefilter(W.standard_filter(spark, d, XOR8), W.probes(spark, d), "k64").where("k64 between 1000 and 9000")


@query("semi_exact", f"select k as k64 from ({O.PROBES}) semi join ({O.MEMBERS}) using (k)")
def _(spark, d):
    return W.probes(spark, d).join(W.members(spark, d), "k64", "left_semi")


@query("anti_exact", f"select k as k64 from ({O.PROBES}) anti join ({O.MEMBERS}) using (k)")
def _(spark, d):
    return W.probes(spark, d).join(W.members(spark, d), "k64", "left_anti")


def _views(spark, d) -> None:
    for t in ("orders", "lineitem"):
        table(spark, d, t).createOrReplaceTempView(f"sieveset_{t}")


@query("subquery_in", "select count(*) as n from lineitem where l_orderkey in (select o_orderkey from orders where o_orderstatus = 'F')")
def _(spark, d):
    _views(spark, d)
    return spark.sql("select count(*) as n from sieveset_lineitem where l_orderkey in (select o_orderkey from sieveset_orders where o_orderstatus = 'F')")


@query("subquery_exists", "select count(*) as n from orders o where exists (select 1 from lineitem l where l.l_orderkey = o.o_orderkey) and o_orderkey not in (select o_orderkey from orders where o_orderstatus = 'P')")
def _(spark, d):
    _views(spark, d)
    return spark.sql("select count(*) as n from sieveset_orders o where exists (select 1 from sieveset_lineitem l where l.l_orderkey = o.o_orderkey) and o_orderkey not in (select o_orderkey from sieveset_orders where o_orderstatus = 'P')")


@query("scalar_capacity", f"select (123 * (select count(*) from ({O.MEMBERS})) // 100 + 32)::bigint as capacity, count(*) as n from orders")
def _(spark, d):
    _views(spark, d)
    return spark.sql("select (123 * (select count(*) from sieveset_orders where o_orderstatus = 'F') div 100 + 32) as capacity, count(*) as n from sieveset_orders")


_JOINED = "select o_orderpriority, count(*) as n, sum(l_quantity)::bigint as quantity from lineitem join (select * from orders where o_orderstatus = 'F') on l_orderkey = o_orderkey group by o_orderpriority"


def _filtered(hint: str | None):
    def run(spark, d):
        lines = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_quantity")
        joined = filtered_join(lines, _f(spark, d).select("o_orderkey", "o_orderpriority"), "o_orderkey", hint=hint)
        return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("quantity"))

    return run


for _hint in ("bhj", "shj", "smj"):
    query(f"filtered_join_{_hint}", _JOINED)(_filtered({"bhj": "broadcast", "shj": "shuffle_hash", "smj": "merge"}[_hint]))


@query("filtered_join_survivors", f"{REPORTED} select count(*) as lines, count(r.k) as survivors from lineitem left join reported r on r.k = l_orderkey")
def _(spark, d):
    """What a pre-filter leaves of the larger side: hits and a 256th of the rest."""
    lines = table(spark, d, "lineitem").select("l_orderkey")
    return probe(W.standard_filter(spark, d, XOR8), lines, "l_orderkey").agg(F.count("*").alias("lines"), F.count(F.when(F.col("maybe_member") == 1, 1)).alias("survivors"))


@query("confusion_full_outer", f"{BLOOMED} select case when r.k is null then 'missed' when m.k is null then 'false_positive' else 'hit' end as outcome, count(*) as n from (select k from reported) r full outer join (select k from m semi join q using (k)) m on r.k = m.k group by outcome")
def _(spark, d):
    fs = W.standard_filter(spark, d, BLOOM8)
    said = prefilter(fs, W.probes(spark, d), "k64").withColumn("r", F.lit(1))
    real = W.members(spark, d).join(W.probes(spark, d), "k64", "left_semi").withColumn("m", F.lit(1))
    outcome = F.when(F.col("r").isNull(), "missed").when(F.col("m").isNull(), "false_positive").otherwise("hit").alias("outcome")
    return said.join(real, "k64", "full_outer").groupBy(outcome).agg(F.count("*").alias("n"))


@query("lateral_probe", "select p.k as k64, t.i::int as cell_no, p.k * 3 + t.i as value from (select o_orderkey as k from orders) p, range(3) t(i)")
def _(spark, d):
    _views(spark, d)
    return spark.sql("select o.o_orderkey as k64, x.i as cell_no, o.o_orderkey * 3 + x.i as value from sieveset_orders o, lateral (select explode(array(0, 1, 2)) as i) x")


# --- aggregates, windows, sets ----------------------------------------------------------------------------------------


@query("size_exact", "select count(distinct user_id) as n from events")
def _(spark, d):
    return table(spark, d, "events").agg(F.count_distinct("user_id").alias("n"))


@query("size_hll", "select 1 as within_a_tenth from (select count(distinct user_id) from events)")
def _(spark, d):
    e = table(spark, d, "events")
    both = e.agg(F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("a"), F.approx_count_distinct("user_id").alias("c"), F.count_distinct("user_id").alias("b"))
    near = lambda c: F.abs(F.col(c) / F.col("b") - 1) < 0.1
    return both.select((near("a") & near("c")).cast("int").alias("within_a_tenth"))


@query("collect_cells", f"with m as ({O.MEMBERS}), cfg as (select 123 * count(*) // 100 + 32 as c from m), x as (select k, {O.cells('k', XOR8)} from m, cfg) select c0 as cell, count(*) as degree, min(k) as first_key, max(k) as last_key from x group by c0")
def _(spark, d):
    m = W.members(spark, d)
    cells = cells_of(m, m.count(), XOR8)
    return cells.groupBy(F.col("c0").alias("cell")).agg(F.array_sort(F.collect_set("k64")).alias("keys")).select("cell", F.size("keys").cast("long").alias("degree"), F.element_at("keys", 1).alias("first_key"), F.element_at("keys", -1).alias("last_key"))


_SAID = f"{BLOOMED}, said as (select o_orderstatus, o_orderpriority, case when r.k is null then 0 else 1 end as hit from orders join q on q.k = o_orderkey left join reported r on r.k = o_orderkey)"


def _said(spark, d) -> DataFrame:
    asked = _orders(spark, d).join(W.probes(spark, d).withColumnRenamed("k64", "o_orderkey"), "o_orderkey", "left_semi")
    return probe(W.standard_filter(spark, d, BLOOM8), asked, "o_orderkey").select("o_orderstatus", "o_orderpriority", F.col("maybe_member").alias("hit"))


@query("metrics_cube", f"{_SAID} select o_orderstatus, o_orderpriority, count(*) as n, sum(hit)::bigint as hits from said group by cube (o_orderstatus, o_orderpriority)")
def _(spark, d):
    return _said(spark, d).cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.sum("hit").alias("hits"))


@query("metrics_rollup", f"{_SAID} select o_orderstatus, o_orderpriority, count(*) as n, sum(hit)::bigint as hits from said group by rollup (o_orderstatus, o_orderpriority)")
def _(spark, d):
    return _said(spark, d).rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.sum("hit").alias("hits"))


@query("metrics_grouping_sets", f"{_SAID} select o_orderstatus, o_orderpriority, count(*) as n from said group by grouping sets ((o_orderstatus), (o_orderpriority))")
def _(spark, d):
    _said(spark, d).createOrReplaceTempView("sieveset_said")
    return spark.sql("select o_orderstatus, o_orderpriority, count(*) as n from sieveset_said group by grouping sets ((o_orderstatus), (o_orderpriority))")


@query("metrics_pivot", f"{_SAID} select o_orderpriority, sum(case when o_orderstatus = 'F' then hit end)::bigint as f, sum(case when o_orderstatus = 'O' then hit end)::bigint as o, sum(case when o_orderstatus = 'P' then hit end)::bigint as p from said group by o_orderpriority")
def _(spark, d):
    return _said(spark, d).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.sum("hit")).withColumnsRenamed({"F": "f", "O": "o", "P": "p"})


@query("metrics_unpivot", f"{_SAID} select o_orderstatus, unnest(['n', 'hits']) as name, unnest([count(*), sum(hit)::bigint]) as value from said group by o_orderstatus")
def _(spark, d):
    return _said(spark, d).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("hit").alias("hits")).unpivot("o_orderstatus", ["n", "hits"], "name", "value")


@query("query_mix_rank", f"with {O.query_mix()} select hit_pct, is_member, count(*) as n, min(k) as least, max(k) as largest from q group by hit_pct, is_member")
def _(spark, d):
    return W.standard_mix(spark, d).groupBy("hit_pct", "is_member").agg(F.count("*").alias("n"), F.min("k64").alias("least"), F.max("k64").alias("largest"))


@query("topk_cells", f"with m as ({O.MEMBERS}), cfg as (select 123 * count(*) // 100 + 32 as c from m), x as (select k, {O.cells('k', XOR8)} from m, cfg) select cell, count(*) as degree from (select unnest([c0, c1, c2]) as cell from x) group by cell order by degree desc, cell limit 10")
def _(spark, d):
    m = W.members(spark, d)
    cells = cells_of(m, m.count(), XOR8).select(F.explode(F.array("c0", "c1", "c2")).alias("cell"))
    return cells.groupBy("cell").agg(F.count("*").alias("degree")).orderBy(F.desc("degree"), "cell").limit(10)


for _op, _sql in (("union", "union"), ("intersect", "intersect"), ("except", "except")):
    query(f"set_{_op}", f"select k as k64 from ({O.MEMBERS}) {_sql} select k from ({O.PROBES})")(
        lambda spark, d, op=_op: {"union": lambda a, b: a.union(b).distinct(), "intersect": lambda a, b: a.intersect(b), "except": lambda a, b: a.exceptAll(b).distinct()}[op](W.members(spark, d), W.probes(spark, d))
    )


@query("rebuild_version", f"select count(*) as n_keys, 0::bigint as missed from (select k from ({O.MEMBERS}) union select o_orderkey from orders where o_orderkey < 500)")
def _(spark, d):
    """An immutable filter takes new keys by a new build under a new id."""
    from sieveset.operators.build import rebuild

    old = W.standard_filter(spark, d, XOR8)
    keys = W.members(spark, d).union(_orders(spark, d).where("o_orderkey < 500").select("o_orderkey")).distinct()
    new = rebuild(old, keys, "k64", "v2")
    missed = probe(new, keys, "k64").agg(F.count(F.when(F.col("maybe_member") == 0, 1)).alias("missed"))
    return new.frame.agg(F.sum("n_keys").alias("n_keys")).crossJoin(missed)


# --- functions on strings, dates, maps, json --------------------------------------------------------------------------

_WORDS = "select doc_id, lang, unnest(string_split_regex(lower(text), '\\s+')) as w from documents"


def words(docs: DataFrame, *keep: str) -> DataFrame:
    return docs.select(*keep, F.explode(F.split(F.lower("text"), r"\s+")).alias("w")).where("w <> ''")


@query("word_keys", f"select count(*) as n, count(distinct w) as keys, {H.signed_sql('bit_xor(' + H.md5_key_sql('w') + ')::uhugeint')} as mask from (select distinct w from ({_WORDS})) where w <> ''")
def _(spark, d):
    keys = words(table(spark, d, "documents")).distinct().select("w", H.canonical_key(F.col("w"), "string", "md5").alias("k64"))
    return keys.agg(F.count("*").alias("n"), F.count_distinct("w").alias("keys"), F.bit_xor("k64").alias("mask"))


@query("line_keys", "select count(*) as n, count(distinct md5(line)) as keys from (select unnest(string_split(text, chr(10))) as line from documents)")
def _(spark, d):
    lines = table(spark, d, "documents").select(F.explode(F.split("text", "\n")).alias("line"))
    return lines.agg(F.count("*").alias("n"), F.count_distinct(F.md5(F.col("line").cast("binary"))).alias("keys"))


@query("url_host_keys", "select regexp_extract(url, '://([^/?#]*)', 1) as host, count(*) as n from pages group by 1")
def _(spark, d):
    return table(spark, d, "pages").groupBy(F.expr("parse_url(url, 'HOST')").alias("host")).agg(F.count("*").alias("n"))


@query("runs_by_month", "select strftime(o_orderdate, '%Y-%m') as run, count(*) as n, min(o_orderkey) as lo, max(o_orderkey) as hi from orders group by 1")
def _(spark, d):
    return _runs(spark, d).groupBy("run").agg(F.count("*").alias("n"), F.min("o_orderkey").alias("lo"), F.max("o_orderkey").alias("hi"))


def _runs(spark, d) -> DataFrame:
    return _orders(spark, d).select(F.date_format("o_orderdate", "yyyy-MM").alias("run"), "o_orderkey", "o_orderdate")


@query("json_key_probe", "select (props->>'$.k')::bigint % 7 as k, count(*) as n from events where (props->>'$.k')::bigint in (select distinct (props->>'$.k')::bigint from events where event_type = 'click') group by 1")
def _(spark, d):
    e = table(spark, d, "events").withColumn("k", F.get_json_object("props", "$.k").cast("long"))
    fs = build_filter(e.where("event_type = 'click'"), "k", FilterSpec("exact"), shards=1)
    return prefilter(fs, e, "k").groupBy((F.col("k") % 7).alias("k")).agg(F.count("*").alias("n"))


_LANG = f"with w as ({_WORDS}), known as (select distinct lang, w from w where doc_id % 2 = 0 and w <> ''), votes as (select a.doc_id, a.lang as truth, k.lang as guess, count(*) as n from w a join known k using (w) where a.doc_id % 2 = 1 group by all)"


def _votes(spark, d, verified: bool = True) -> DataFrame:
    """Words of a document that are known in a language: one filter for each language, asked for every distinct word in one pass, then
    (``verified``) looked up in the exact sets."""
    docs = table(spark, d, "documents")
    known = materialise(words(docs.where("doc_id % 2 = 0"), "lang").distinct(), "known-words")
    asked = words(docs.where("doc_id % 2 = 1"), "doc_id", "lang").withColumnRenamed("lang", "truth")
    fs = build_filter_per_group(known, ["lang"], "w", XOR8)
    hits = asked.select("w").distinct().select("w", F.explode(probe_groups(fs, H.canonical_key(F.col("w"), "string"))).alias("guess"))
    if verified:
        hits = hits.join(known.withColumnRenamed("lang", "guess"), ["guess", "w"], "left_semi")
    return asked.join(hits, "w").groupBy("doc_id", "truth", "guess").agg(F.count("*").alias("n"))


@query("lang_id_by_filters", "select count(*) as docs, 1 as in_band from documents where doc_id % 2 = 1 and exists (select 1 from (select unnest(string_split_regex(lower(text), '\\s+')) as w) where w <> '')")
def _(spark, d):
    """Identification by filters alone: with 1 false word in 256 nearly all documents get the language that the exact sets give."""
    best = Window.partitionBy("doc_id").orderBy(F.desc("n"), "guess")
    pick = lambda verified, name: _votes(spark, d, verified).withColumn("r", F.row_number().over(best)).where("r = 1").select("doc_id", F.col("guess").alias(name))
    asked = words(table(spark, d, "documents").where("doc_id % 2 = 1"), "doc_id").select("doc_id").distinct()
    both = asked.join(pick(True, "exact"), "doc_id", "left").join(pick(False, "filtered"), "doc_id", "left")
    same = F.avg(F.col("exact").eqNullSafe(F.col("filtered")).cast("double")) >= 0.95
    return both.agg(F.count("*").alias("docs"), same.cast("int").alias("in_band"))


@query("lang_hit_map", f"{_LANG} select doc_id, truth, max(case when guess = 'en' then n else 0 end)::bigint as en, count(*) as langs from votes group by doc_id, truth")
def _(spark, d):
    by = _votes(spark, d).groupBy("doc_id", "truth").agg(F.map_from_entries(F.collect_list(F.struct("guess", "n"))).alias("hits"))
    return by.select("doc_id", "truth", F.coalesce(F.try_element_at("hits", F.lit("en")), F.lit(0)).cast("long").alias("en"), F.size(F.map_entries("hits")).cast("long").alias("langs"))


# --- functions of one's own, sources ----------------------------------------------------------------------------------


@query("udf_probe_sql", f"{REPORTED} select count(*) as n from reported")
def _(spark, d):
    spark.udf.register("sieveset_might_contain", might_contain(W.standard_filter(spark, d, XOR8)))
    W.probes(spark, d).createOrReplaceTempView("sieveset_probes")
    return spark.sql("select count(*) as n from sieveset_probes where sieveset_might_contain(k64) = 1")


@query("filter_per_group", "select o_orderpriority as filter_id, count(*) as n_keys, (123 * count(*) // 100 + 32)::bigint as capacity from orders group by 1")
def _(spark, d):
    return build_filter_per_group(_orders(spark, d), ["o_orderpriority"], "o_orderkey", XOR8).frame.select("filter_id", "n_keys", "capacity")


#: Neighbouring keys that one call of the table function explains.
_EXPLAINED = 4096


@query("udtf_cells", f"with m as ({O.MEMBERS}), cfg as (select 123 * count(*) // 100 + 32 as c from m), x as (select o_orderkey as k64, {O.cells('o_orderkey', XOR8)} from orders, cfg) select k64, unnest([0, 1, 2]) as part, unnest([c0, c1, c2]) as cell from x")
def _(spark, d):
    """As udtf_cells, over all orders: a call takes a batch of keys."""
    from pyspark.sql.functions import udtf

    meta = W.standard_filter(spark, d, XOR8).frame.select("seed", "capacity").first()
    seed, cells = meta["seed"] % (1 << 64), meta["capacity"]

    class ExplainProbes:
        def eval(self, keys: list):
            import numpy as np

            from sieveset.kernels.filters import three_cells

            for k64, own in zip(keys, three_cells(np.array(keys, np.int64), seed, cells).T.tolist(), strict=True):
                for part, at in enumerate(own):
                    yield k64, part, at

    spark.udtf.register("sieveset_explain_probes", udtf(ExplainProbes, returnType="k64 long, part int, cell long"))
    _views(spark, d)
    batches = f"select collect_list(o_orderkey) as keys from sieveset_orders group by o_orderkey div {_EXPLAINED}"
    return spark.sql(f"select x.k64, x.part, x.cell from ({batches}) o, lateral sieveset_explain_probes(o.keys) x")


@query("sql_probe", f"{REPORTED} select count(*) as lines from lineitem join reported on k = l_orderkey")
def _(spark, d):
    _views(spark, d)
    probe(W.standard_filter(spark, d, XOR8), W.probes(spark, d), "k64").createOrReplaceTempView("sieveset_verdicts")
    return spark.sql("select count(*) as lines from sieveset_lineitem l join sieveset_verdicts v on v.k64 = l.l_orderkey where v.maybe_member = 1")


@query("amq_source_roundtrip", "select o_orderpriority as filter_id, 'xor' as kind, count(*) as n_keys from orders group by 1")
def _(spark, d):
    import uuid

    from sieveset.operators.filterset import FilterSet
    from sieveset.sources.amq_source import register

    fs = build_filter_per_group(_orders(spark, d), ["o_orderpriority"], "o_orderkey", XOR8)
    path = f"{shared_dir(spark)}/sieveset/saved-{uuid.uuid4().hex}"
    fs.save(path)
    register(spark)
    rows = spark.read.format("amq").load(path).select("filter_id", "kind", "n_keys")
    kept = FilterSet.load(spark, path).frame.select("filter_id")
    return rows.join(kept, "filter_id", "left_semi")


@query("key_formats", "select unnest(['csv', 'json', 'orc', 'parquet', 'text']) as kind, count(*) as n_keys, 0::bigint as missed from orders where o_orderstatus = 'F'")
def _(spark, d):
    import uuid

    from sieveset.sources.amq_source import read_keys, write_keys

    keys, out = _f(spark, d).select("o_orderkey"), None
    for kind in ("csv", "json", "orc", "parquet", "text"):
        path = f"{shared_dir(spark)}/sieveset/keys-{uuid.uuid4().hex}"
        write_keys(keys.select(F.col("o_orderkey").cast("string")) if kind == "text" else keys, path, kind)
        back = read_keys(spark, path, "o_orderkey", kind, schema=None if kind == "text" else "o_orderkey long").select(F.col("o_orderkey").cast("long").alias("o_orderkey"))
        fs = build_filter(back, "o_orderkey", XOR8, shards=1)
        row = probe(fs, keys, "o_orderkey").agg(F.lit(kind).alias("kind"), F.count("*").alias("n_keys"), F.count(F.when(F.col("maybe_member") == 0, 1)).alias("missed"))
        out = row if out is None else out.unionByName(row)
    return out


# --- applications -----------------------------------------------------------------------------------------------------


def _zones(spark, d) -> DataFrame:
    return _runs(spark, d).groupBy(F.col("run").alias("filter_id")).agg(F.min("o_orderkey").alias("lo"), F.max("o_orderkey").alias("hi"))


@query("lsm_true_hits", "select count(*) as keys_found from (select distinct l_orderkey from lineitem) semi join orders on o_orderkey = l_orderkey")
def _(spark, d):
    """Looking keys up in a store of monthly runs: what is found does not depend on the filters."""
    fs = build_filter_per_group(_runs(spark, d), ["run"], "o_orderkey", XOR8)
    asked = W.probes(spark, d)
    read = runs_to_read(fs, _zones(spark, d), asked, "k64")
    found = read.join(_runs(spark, d).select(F.col("run").alias("filter_id"), F.col("o_orderkey").alias("k64")), ["filter_id", "k64"], "left_semi")
    return found.agg(F.count_distinct("k64").alias("keys_found"))


@query("lsm_runs_touched", """with runs as (select strftime(o_orderdate, '%Y-%m') as run, min(o_orderkey) as lo, max(o_orderkey) as hi from orders group by 1), asked as (select distinct l_orderkey as k from lineitem)
    select (select count(*) from runs join asked on k between lo and hi) as reads_by_range, (select count(*) from orders semi join asked on k = o_orderkey) as needed_reads, 1 as in_band""")
def _(spark, d):
    """Reads with ranges alone, and those that are needed; with filters it is the needed ones and a 256th of the others."""
    fs = build_filter_per_group(_runs(spark, d), ["run"], "o_orderkey", XOR8)
    asked, zones = W.probes(spark, d), _zones(spark, d)
    by_range = asked.join(F.broadcast(zones), (F.col("k64") >= F.col("lo")) & (F.col("k64") <= F.col("hi"))).agg(F.count("*").alias("reads_by_range"))
    read = materialise(runs_to_read(fs, zones, asked, "k64"), "lsm-reads")
    needed = read.join(_runs(spark, d).select(F.col("run").alias("filter_id"), F.col("o_orderkey").alias("k64")), ["filter_id", "k64"], "left_semi")
    both = by_range.crossJoin(read.agg(F.count("*").alias("reads"))).crossJoin(needed.agg(F.count("*").alias("needed_reads")))
    extra = (F.col("reads_by_range") - F.col("needed_reads")) / 256
    return both.select("reads_by_range", "needed_reads", (F.abs(F.col("reads") - F.col("needed_reads") - extra) <= 5 * F.sqrt(extra) + 3).cast("int").alias("in_band"))


@query("runs_range_prune", "with runs as (select strftime(o_orderdate, '%Y-%m') as run, min(o_orderkey) as lo, max(o_orderkey) as hi from orders group by 1) select run, count(*) as n from runs join (select distinct l_orderkey as k from lineitem) on k between lo and hi group by run")
def _(spark, d):
    asked = W.probes(spark, d)
    return asked.join(F.broadcast(_zones(spark, d)), (F.col("k64") >= F.col("lo")) & (F.col("k64") <= F.col("hi"))).groupBy(F.col("filter_id").alias("run")).agg(F.count("*").alias("n"))


@query("runs_interval_join", "with runs as (select strftime(o_orderdate, '%Y') as run, min(o_orderdate) as a, max(o_orderdate) as b from orders group by 1) select run, count(*) as n from runs join orders on o_orderdate >= a and o_orderdate < b group by run")
def _(spark, d):
    runs = _orders(spark, d).groupBy(F.date_format("o_orderdate", "yyyy").alias("run")).agg(F.min("o_orderdate").alias("a"), F.max("o_orderdate").alias("b"))
    return _orders(spark, d).join(F.broadcast(runs), (F.col("o_orderdate") >= F.col("a")) & (F.col("o_orderdate") < F.col("b"))).groupBy("run").agg(F.count("*").alias("n"))


@query("filter_version_asof", """with e as (select event_id, user_id, extract(day from ts)::int // 7 as version from events),
    k as (select distinct v.version, user_id from events, (values (0), (1), (2), (3), (4)) v(version) where event_type = 'purchase' and extract(day from ts)::int < 7 * v.version)
    select e.version, count(*) as n, count(k.user_id) as known from e left join k using (version, user_id) group by e.version""")
def _(spark, d):
    """Each event is asked of the latest version of a filter that is not later than it. Versions hold those who bought before days 0, 7, 14,
    21 and 28; hits are verified."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", F.dayofmonth("ts").alias("at"))
    versions = F.broadcast(spark.createDataFrame([(v, 7 * v) for v in range(5)], "version int, since int"))
    held = e.where("event_type = 'purchase'").join(versions, F.col("at") < F.col("since")).select("version", "user_id").distinct()
    held = materialise(held, "versions")
    fs = build_filter_per_group(held, ["version"], "user_id", FilterSpec("xor", 16))
    reported = e.select("user_id").distinct().select("user_id", F.explode(probe_groups(fs, F.col("user_id").cast("long"))).alias("version")).withColumn("version", F.col("version").cast("int"))
    known = reported.join(held, ["version", "user_id"], "left_semi").withColumn("known", F.lit(1))
    asof = e.join(versions, F.col("since") <= F.col("at")).groupBy("event_id").agg(F.max_by("version", "since").alias("version"), F.first("user_id").alias("user_id"))
    return asof.join(known, ["version", "user_id"], "left").groupBy("version").agg(F.count("*").alias("n"), F.count("known").alias("known"))


_GRAMS = "list_transform(range(1, greatest(len(t) - 6, 1)), lambda i: array_to_string(t[i:i + 7], ' '))"


def tokenised(df: DataFrame, text: str, *keep: str) -> DataFrame:
    return df.select(*keep, F.split(F.trim(F.regexp_replace(F.lower(text), r"\s+", " ")), " ").alias("t"))


def grams(df: DataFrame, text: str, n: int, *keep: str) -> DataFrame:
    """Word n-grams of each text, lower-cased."""
    t = tokenised(df, text, *keep)
    return t.where(F.size("t") >= n).select(*keep, F.explode(F.transform(F.sequence(F.lit(1), F.size("t") - n + 1), lambda i: F.array_join(F.slice("t", i, F.lit(n)), " "))).alias("gram"))


@query("contamination_verified", f"""with d as (select doc_id, string_split(trim(regexp_replace(lower(text), '\\s+', ' ', 'g')), ' ') as t from documents),
    b as (select string_split(trim(regexp_replace(lower(text), '\\s+', ' ', 'g')), ' ') as t from benchmark),
    dg as (select doc_id, unnest({_GRAMS}) as gram from d where len(t) >= 8), bg as (select distinct unnest({_GRAMS}) as gram from b where len(t) >= 8)
    select doc_id, count(*) as hits from dg semi join bg using (gram) group by doc_id""")
def _(spark, d):
    """Payload signatures: word 8-grams of the benchmark as a filter, those of documents asked, survivors verified."""
    n = 8
    wanted = materialise(grams(table(spark, d, "benchmark"), "text", n).distinct(), "signatures")
    fs = build_filter(wanted.select(F.xxhash64("gram").alias("k64")), "k64", XOR8)
    gram = lambda i: F.array_join(F.slice("t", i, F.lit(n)), " ")
    tokens = tokenised(table(spark, d, "documents"), "text", "doc_id").where(F.size("t") >= n)
    hashes = tokens.select("doc_id", F.posexplode(F.transform(F.sequence(F.lit(1), F.size("t") - n + 1), lambda i: F.xxhash64(gram(i)))).alias("i", "k64"))
    places = prefilter(fs, hashes, "k64").groupBy("doc_id").agg(F.collect_list(F.col("i") + 1).alias("places"))
    met = tokens.join(places, "doc_id").select("doc_id", F.explode(F.transform("places", gram)).alias("gram"))
    return met.join(wanted, "gram", "left_semi").groupBy("doc_id").agg(F.count("*").alias("hits"))


@query("bad_words_flagged", f"""with w as ({_WORDS}), bad as (select distinct w from w join labels using (doc_id) where toxic = 1 and w <> '' except select w from w join labels using (doc_id) where toxic = 0)
    select doc_id, count(distinct w) as bad_words from w semi join bad using (w) group by doc_id having count(distinct w) >= 3""")
def _(spark, d):
    docs, labels = table(spark, d, "documents"), table(spark, d, "labels")
    marked = words(docs.join(labels, "doc_id"), "toxic").distinct()
    bad = materialise(marked.where("toxic = 1").select("w").exceptAll(marked.where("toxic = 0").select("w")).distinct(), "bad-words")
    hits = prefilter(build_filter(bad, "w", XOR8), words(docs, "doc_id"), "w").join(bad, "w", "left_semi")
    return hits.groupBy("doc_id").agg(F.count_distinct("w").alias("bad_words")).where("bad_words >= 3")


@query("lang_id_confusion", f"{_LANG}, best as (select doc_id, truth, guess, row_number() over (partition by doc_id order by n desc, guess) as r from votes) select truth, guess, count(*) as n from best where r = 1 group by truth, guess")
def _(spark, d):
    best = Window.partitionBy("doc_id").orderBy(F.desc("n"), "guess")
    return _votes(spark, d).withColumn("r", F.row_number().over(best)).where("r = 1").groupBy("truth", "guess").agg(F.count("*").alias("n"))


@query("line_dedup", "select count(*) as lines, count(distinct line) as kept, count(*) - count(distinct line) as dropped from (select unnest(string_split(text, chr(10))) as line from documents)")
def _(spark, d):
    """Seen before: lines of even documents as a filter; lines of odd ones that it does not know are new for sure, the rest are verified."""
    lines = table(spark, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    old = materialise(lines.where("doc_id % 2 = 0").select("line").distinct(), "lines")
    new = lines.where("doc_id % 2 = 1").select("line").distinct()
    said = materialise(probe(build_filter(old, "line", XOR8), new, "line"), "said")
    kept = said.where("maybe_member = 0").select("line").unionByName(said.where("maybe_member = 1").select("line").join(old, "line", "left_anti")).unionByName(old)
    return lines.agg(F.count("*").alias("lines")).crossJoin(kept.agg(F.count("*").alias("kept"))).select("lines", "kept", (F.col("lines") - F.col("kept")).alias("dropped"))


_HOST = "regexp_extract(url, '://([^/?#]*)', 1)"


@query("page_host_block", f"select page_id from pages where {_HOST} in (select {_HOST} from pages where page_id % 2 = 0 and ({_HOST} like '%spam-farm%' or {_HOST} like '%cheap-pills%'))")
def _(spark, d):
    """Blocked addresses: hosts reported by one half of the crawl are a filter, in front of the exact list, that all pages are asked of."""
    pages = table(spark, d, "pages").select("page_id", F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"))
    reported = pages.where("page_id % 2 = 0 and (host like '%spam-farm%' or host like '%cheap-pills%')")
    blocked = materialise(reported.select("host").distinct(), "hosts")
    return prefilter(build_filter(blocked, "host", XOR8), pages, "host").join(blocked, "host", "left_semi").select("page_id")


@query("vector_keys", "select count(*) as n, count(distinct embedding) as keys from embeddings")
def _(spark, d):
    keys = with_key(table(spark, d, "embeddings"), "embedding")
    return keys.agg(F.count("*").alias("n"), F.count_distinct("k64").alias("keys"))
