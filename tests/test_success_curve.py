"""The success curve: all keys in sets of all sizes, each set peeled as by itself."""

import duckdb
import numpy as np

from sieveset.functions import measures as S
from sieveset.kernels.filters import three_cells
from sieveset.kernels.peel import peel_rounds
from sieveset.operators.spec import attempt_seed, capacity
from sieveset.plans import catalog_methods as C


def curve(keys, sizes, trials, group):
    return {r["size"]: (r["trials"], r["successes"]) for r in S.success_curve(keys, sizes, (32,), trials, group).collect()}


def test_sets_side_by_side_peel_as_each_alone():
    rng = np.random.default_rng(5)
    for size in (1, 3, 27, 2187):
        sets = rng.permutation(200_000)[: 90 * size].reshape(90, size)
        for extra in (1, 16):
            c = capacity(size, extra=extra)
            alone = [peel_rounds(three_cells(s, attempt_seed(9, extra, j), c), c) for j, s in enumerate(sets)]
            assert S.sets_peeled(sets, extra, 9) == sum(p is not None for p in alone)
        assert 0 < S.sets_peeled(sets, 16, 9)


def test_a_batch_takes_its_seeds_by_set(monkeypatch):
    sets = np.random.default_rng(6).permutation(5000)[:2700].reshape(100, 27)
    whole = S.sets_peeled(sets, 16, 9)
    monkeypatch.setattr(S, "PEEL_CELLS", 400)
    assert S.sets_peeled(sets, 16, 9) == whole < 100


def test_a_repeated_key_fails_its_own_set_alone():
    sets = np.arange(30).reshape(10, 3)
    sets[4, 1] = sets[4, 0]
    assert S.sets_peeled(sets, 64, 1) == 9


def test_all_keys_are_in_sets_of_each_size(spark):
    """Ten trials of three keys would leave 9,970 of 10,000 out; a size that does not divide them fills its last set up."""
    got = curve(spark.range(10_000).withColumnRenamed("id", "k64"), (3, 27, 729), 10, 20_000)
    assert {s: n for s, (n, _) in got.items()} == {3: 3334, 27: 371, 729: 14}
    assert all(0.8 * n <= ok <= n for n, ok in got.values())


def test_passes_are_repeated_until_trials_suffice(spark):
    got = curve(spark.range(10_000).withColumnRenamed("id", "k64"), (729, 6561), 100, 20_000)
    assert {s: n for s, (n, _) in got.items()} == {729: 8 * 14, 6561: 50 * 2}


def test_sets_have_the_size_they_are_counted_under(spark):
    """Groups hold sets of the largest size; a size that the table does not fill has no row, and null is no key."""
    keys = spark.range(20_000).selectExpr("id as k64").unionByName(spark.sql("select cast(null as bigint) as k64"))
    got = curve(keys, (6561, 19_683, 59_049), 20, 4 * 6561)
    assert {s: n for s, (n, _) in got.items()} == {6561: 20, 19_683: 20}
    grouped = curve(keys, (27,), 20, 5000)
    assert 20_000 // 27 <= grouped[27][0] <= 20_000 // 27 + 4


def test_the_query_has_all_published_sizes():
    con, sql = duckdb.connect(), C.ORACLES["success_curve"]
    con.execute("create table lineitem as select i // 4 as l_orderkey, i % 4 + 1 as l_linenumber from range(600000) t(i)")
    assert list(C._SUCCESS) == [3**i for i in range(1, 13)]
    got = con.sql(f"select size, min(trials) as least, min(trials * size) as keys from ({sql}) group by 1 order by 1").fetchall()
    assert [s for s, _, _ in got] == list(C._SUCCESS)
    assert all(n >= 1000 and keys >= 600_000 for _, n, keys in got)
