"""Joins that a filter makes cheaper, and picking files or runs by filter. Results are exact."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .build import build_filter, build_filter_per_group, with_key
from .filterset import FilterSet
from .probe import prefilter
from .spec import FilterSpec


def filtered_join(left: DataFrame, right: DataFrame, on: str, spec: FilterSpec | None = None, how: str = "inner", hint: str | None = None) -> DataFrame:
    """``left`` joined with ``right`` on one column, after rows of ``left`` that surely have no partner are gone.

    For inner and left_semi joins. Only hits and a few false positives of ``left`` reach the shuffle.
    """
    if how not in ("inner", "left_semi"):
        raise ValueError("a filter may only drop rows of inner and left_semi joins")
    fs = build_filter(right, on, spec or FilterSpec("xor"))
    return prefilter(fs, left, on).join(right.hint(hint) if hint else right, on, how)


def runs_with_filters(runs: DataFrame, run: str, key: str, spec: FilterSpec) -> FilterSet:
    """One filter for each run (or file) of a store."""
    return build_filter_per_group(runs, [run], key, spec)


def runs_to_read(fs: FilterSet, zones: DataFrame, asked: DataFrame, key: str) -> DataFrame:
    """(filter_id, key) pairs that must be read: the key lies in the run's range and the run's filter reports it.

    ``zones`` has filter_id, lo and hi of each run. The few runs are joined by range first, then keys are asked of the
    run's own filter in one grouped pass.
    """
    import pandas as pd

    from sieveset.kernels import filters as K

    from .filterset import from_row

    spec = fs.spec
    pairs = with_key(asked.select(key).distinct(), key, spec.hash_mode).join(F.broadcast(zones), (F.col("k64") >= F.col("lo")) & (F.col("k64") <= F.col("hi"))).select(*dict.fromkeys(("filter_id", key, "k64")))

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return right.iloc[:0][["filter_id", key]]
        said = K.contains(from_row(left.iloc[0], spec), spec, right["k64"].to_numpy())
        return right[said][["filter_id", key]]

    kind = asked.schema[key].dataType.simpleString()
    return fs.frame.groupBy("filter_id").cogroup(pairs.groupBy("filter_id")).applyInPandas(run, f"filter_id string, {key} {kind}")
