"""Streams: what is remembered, and for how long."""

import duckdb
import pytest

from sieveset.operators.spec import FilterSpec
from sieveset.streaming import queries as S


@pytest.mark.parametrize("bits", [16, 4])
def test_no_key_is_forgotten_or_mistaken(spark, tmp_path, monkeypatch, bits):
    """More keys than 64 generations in each shard hold, then all of them again; with 4 bits filters err often."""
    monkeypatch.setattr(S, "GENERATION", 8)
    for k in range(2):
        spark.range(5000).selectExpr("id * 7919 as user_id").coalesce(1).write.parquet(f"{tmp_path}/in/part={k}")
    stream = spark.readStream.schema("user_id long").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/part=*")
    out = S.run_to_end(S.seen_before(stream, "user_id", spec=FilterSpec("xor", bits)), "append")
    got = {(r["first"], r["count"]) for r in out.groupBy("first").count().collect()}
    assert got == {(1, 5000), (0, 5000)}
    assert out.where("first = 1").select("k64").distinct().count() == 5000


@pytest.mark.parametrize("name", ["stream_probe", "stream_tumbling", "stream_sliding", "stream_session", "stream_late", "stream_swap_version", "stream_keys_seen"])
def test_all_buyers_are_asked_for(spark, sf_dir, name):
    events = duckdb.connect()
    events.execute(f"create view events as select * from '{sf_dir}/events.parquet'")
    assert "%" not in S.ORACLES[f"{name}"]
    plain = lambda df: sorted(map(str, df[sorted(df.columns)].astype(str).values.tolist()))
    assert plain(S.QUERIES[f"{name}"](spark, sf_dir).toPandas()) == plain(events.sql(S.ORACLES[f"{name}"]).df())
