"""Sharding, packing and mixing: exact sizes, exact round trips, exact budgets."""

import math
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from sieveset.llm import mixing, packing, sharding

# --- sharding ---


def test_shards_are_exact(docs, rows, nothing):
    got = sharding.assign_shards(docs.withColumn("shard", F.lit("x")), 7).collect()
    want = Counter((r[0], len((r[1] or "").encode()) + 8, zlib.crc32((r[1] or "").encode())) for r in rows)
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == want
    by = defaultdict(list)
    for r in got:
        by[r["shard"]].append(r["slot"])
    assert set(by) == set(range(7)) and all(sorted(s) == list(range(len(s))) for s in by.values())
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
    assert sharding.assign_shards(nothing).count() == 0


def test_matrix_margins():
    blocks = [100, 1, 0, 2500, 77]
    m = sharding.communication_matrix(blocks, 24, 5)
    assert m.sum(1).tolist() == blocks
    assert set(m.sum(0).tolist()) <= {sum(blocks) // 24, sum(blocks) // 24 + 1}
    big = sharding.communication_matrix([3_000_000_000, 5_000_000_000], 3, 1)
    assert big.sum(1).tolist() == [3_000_000_000, 5_000_000_000] and (big > 0).all()


def test_two_levels_of_the_matrix(docs, rows, monkeypatch):
    """Blocks of few rows in several groups: sizes are exact, and the drawn rows add up."""
    monkeypatch.setattr(sharding, "BLOCK_ROWS", 2)
    monkeypatch.setattr(sharding, "GROUP_BLOCKS", 3)
    got = sharding.assign_shards(docs, 5).collect()
    by = Counter(r["shard"] for r in got)
    assert len(got) == len(rows) and max(by.values()) - min(by.values()) <= 1
    lacking = [7, 3, 5]
    drawn = sharding.draw_rows([4, 0, 6, 5], lacking, np.random.default_rng(2))
    assert drawn.sum(0).tolist() == lacking and drawn.sum(1).tolist() == [4, 0, 6, 5]


def test_hypergeometric_law():
    rng = np.random.default_rng(1)
    draws = [sharding.hypergeometric(rng, 30, 70, 20) for _ in range(20_000)]
    for k in range(2, 12):
        p = math.comb(30, k) * math.comb(70, 20 - k) / math.comb(100, 20)
        assert abs(draws.count(k) / 20_000 - p) < 5 * math.sqrt(p / 20_000)
    assert sharding.hypergeometric(rng, 5, 0, 3) == 3 and sharding.hypergeometric(rng, 0, 5, 3) == 0


# --- packing ---


def test_packing_round_trip(docs, rows, nothing):
    from tokenizers import Tokenizer

    inner = Tokenizer.from_file(packing.tokenizer_path())
    got = packing.pack(docs.withColumn("length", F.lit("x"))).toPandas()
    # repeated ids are left to their counts
    texts = defaultdict(list)
    for r in rows:
        texts[r[0]].append(r[1])
    assert got.length.sum() == sum(len(inner.encode(r[1] or "", add_special_tokens=False).ids) + 1 for r in rows)
    for doc, own in texts.items():
        if len(own) > 1:
            continue
        ids = np.array([*inner.encode(own[0] or "", add_special_tokens=False).ids, 2], "<u4")
        at = 0
        for p in got[got.doc_id == doc].sort_values("start").itertuples():
            assert p.start == at and p.length > 0 and p.doc_tokens == len(ids)
            assert p.ids_crc32 == zlib.crc32(ids[p.start : p.start + p.length].tobytes())
            at += p.length
        assert at == len(ids)
    fill = []
    for _, s in got.sort_values("offset").groupby("sequence_id"):
        assert s.offset.tolist() == [0, *s.length.cumsum().tolist()[:-1]]
        fill.append(int(s.length.sum()))
    assert max(fill) <= 4096 and all(f & (f - 1) == 0 for f in fill)
    assert packing.pack(nothing).count() == 0


def test_word_ids_equal_whole_text_ids():
    import pyarrow as pa
    from tokenizers import Tokenizer

    path = packing.tokenizer_path()
    inner, own = Tokenizer.from_file(path), packing.WordTokenizer(path)
    texts = ["", None, "Hello  WORLD\n\n it's. We'LL, 12,34 foo., *,. a. b.c", "é,́ ΣΑΣ İx <|endoftext|> y", "\t nb\x1c ok\x0b", "<|ENDOFTEXT|>", "word," * 50]
    for t, ids in zip(texts, own.ids_of(pa.array(texts, pa.string())), strict=True):
        assert ids.tolist() == inner.encode(t or "", add_special_tokens=False).ids


@pytest.mark.parametrize("demand", [{}, {5: 1}, {1: 1000}, {129: 10}, {200: 7, 56: 7}, {90: 40, 80: 35, 33: 60, 7: 11}, {i: i % 9 for i in range(1, 257)}])
def test_patterns_hold_the_demand(demand):
    d = np.zeros(256, np.int64)
    for c, n in demand.items():
        d[c - 1] = n
    plan = packing.rounded_patterns(d, 256)
    held = np.zeros(256, np.int64)
    for pattern, times in plan:
        assert times > 0 and sum(c * n for c, n in pattern.items()) <= 256
        for c, n in pattern.items():
            held[c - 1] += n * times
    assert (held == d).all()
    lower = math.ceil(sum(c * n for c, n in demand.items()) / 256)
    assert sum(t for _, t in plan) <= 1.12 * lower + 8 or max(demand) > 128
    at = defaultdict(int)
    for c, lo, hi, _, each in packing.layout(plan):
        assert lo == at[c] and (hi - lo) % each == 0
        at[c] = hi


def test_tail_sizes():
    for n in (0, 1, 5, 4095):
        assert sum(packing.powers(n)) == n


# --- mixing ---


def test_mixing_equals_its_sql(spark, docs, rows, nothing):
    plain = docs.where("doc_id < 900").dropDuplicates(["doc_id"])
    con = duckdb.connect()
    con.register("d", plain.toPandas())
    con.execute("create view documents as select doc_id::bigint as doc_id, text, lang, source from d")
    got = mixing.mix(mixing.with_domain(plain.withColumn("tokens", F.lit(7)))).select("doc_id", *mixing.LEVELS, "epoch", "tokens", "leaf_tokens", "leaf_budget", "taken_before")
    want = con.sql(mixing.oracle())
    key = lambda r: tuple(str(x) for x in r)
    names = sorted(got.columns)
    assert sorted(map(key, got.select(*names).collect())) == sorted(map(key, want.select(*names).fetchall()))
    assert mixing.mix(mixing.with_domain(nothing)).count() == 0


def test_budget_goes_to_siblings_first(spark):
    leaves = spark.createDataFrame([("a", "x", 10), ("a", "y", 1000), ("b", "z", 1000)], "domain string, source string, _tokens long")
    one = {"domain": F.lit(1).cast("long"), "source": F.lit(1).cast("long")}
    got = {r["source"]: r["leaf_budget"] for r in mixing.leaf_budgets(leaves.withColumn("_t", F.lit(0)).drop("_t"), one, ("domain", "source"), 500, 1).collect()}
    assert got == {"x": 10, "y": 492, "z": 502} or got["x"] == 10 and got["x"] + got["y"] == got["z"]
    # a domain that cannot take its share leaves the rest to the other one
    poor = spark.createDataFrame([("a", "x", 10), ("a", "y", 20), ("b", "z", 1000)], "domain string, source string, _tokens long")
    got = {r["source"]: r["leaf_budget"] for r in mixing.leaf_budgets(poor, one, ("domain", "source"), 500, 1).collect()}
    assert got == {"x": 10, "y": 20, "z": 485}


def test_many_leaves_go_by_a_shuffle(docs, monkeypatch):
    plain = sorted(map(str, mixing.mix(mixing.with_domain(docs)).collect()))
    monkeypatch.setattr(mixing, "BROADCAST_LEAVES", 0)
    assert sorted(map(str, mixing.mix(mixing.with_domain(docs)).collect())) == plain


def test_mixing_with_nulls_and_repeats(docs, rows):
    out = mixing.mix(mixing.with_domain(docs)).collect()
    spent = defaultdict(int)
    for r in out:
        assert r["tokens"] > 0
        spent[r["domain"], r["lang"], r["source"], r["leaf_budget"]] += r["tokens"]
    assert all(v <= k[3] for k, v in spent.items())


def test_programs_are_solved_after_a_spark_action(spark):
    """Large programs, in a process that has started Spark: they end soon, with no threaded linear algebra."""
    import time

    spark.range(10).count()
    begun = time.monotonic()
    demand = np.array([997 * i % 89 + 3 for i in range(1, 257)], np.int64)
    plan = packing.rounded_patterns(demand, 256)
    held = np.zeros(256, np.int64)
    for pattern, times in plan:
        for c, n in pattern.items():
            held[c - 1] += n * times
    assert (held == demand).all() and time.monotonic() - begun < 60
    matrix = np.random.default_rng(3).integers(0, 5, (40, 40)) + np.eye(40) * 9
    assert np.allclose((packing._inverse(matrix)[:, :, None] * matrix[None]).sum(1), np.eye(40))


def test_ids_that_do_not_fit_are_refused(monkeypatch):
    import pyarrow as pa

    class Wide:
        def ids_of(self, texts):
            return [np.array([70_000], np.uint32)]

    monkeypatch.setattr(packing, "_tokenizer", lambda path: Wide())
    batch = pa.RecordBatch.from_arrays([pa.array([1]), pa.array(["x"])], ["doc_id", "text"])
    with pytest.raises(ValueError, match="two bytes"):
        list(packing._tokenize("", 4096, 2)([batch]))
