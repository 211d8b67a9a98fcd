"""Queries over whole tables, against their SQL."""

import duckdb
import pytest

from sieveset.plans import registry


@pytest.mark.parametrize(("name", "rows"), [("lateral_probe", 4500), ("udtf_cells", 4500), ("runs_range_prune", None)])
def test_whole_tables(spark, sf_dir, name, rows):
    con = duckdb.connect()
    for t in ("orders", "lineitem"):
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    got, want = registry.queries()[name](spark, sf_dir).toPandas(), con.sql(registry.oracle_sql()[name]).df()
    plain = lambda df: sorted(map(tuple, df[sorted(df.columns)].astype(str).values.tolist()))
    assert plain(got) == plain(want)
    if rows:
        assert len(got) == rows
