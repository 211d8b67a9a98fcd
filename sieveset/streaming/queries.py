"""Streams asked against a filter: the filter is immutable, so every micro-batch reads it without locks.

The queries replay ``events`` as a file stream with ``availableNow`` and give what the sink holds in the end as a batch frame.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from sieveset.kernels import filters as K
from sieveset.operators.build import build_filter
from sieveset.operators.filterset import FilterSet
from sieveset.operators.probe import prefilter
from sieveset.operators.spec import FilterSpec
from sieveset.sources.staging import shared_dir, table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stream; event time becomes a TIMESTAMP, as watermarks need one."""
    raw = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.convert_timezone(F.lit("UTC"), F.current_timezone(), "ts").cast("timestamp"))


def to_ntz(col: str):
    return F.to_utc_timestamp(F.col(col), F.current_timezone()).cast("timestamp_ntz")


def run_to_end(stream: DataFrame, mode: str) -> DataFrame:
    """Runs the stream over what is there. Append results are files of the sink; complete ones the last batch's table."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/sieveset/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        writer.format("parquet").option("path", f"{base}/out").start().awaitTermination()
    else:
        writer.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(f"{base}/out")).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


_BUYERS = "event_type = 'purchase'"
_BOUGHT = f"user_id in (select user_id from events where {_BUYERS})"


def buyers(spark: SparkSession, sf_dir: str, spec: FilterSpec | None = None) -> FilterSet:
    """A filter of all who bought."""
    return build_filter(table(spark, sf_dir, "events").where(_BUYERS), "user_id", spec or FilterSpec("xor"))


def bought(spark: SparkSession, sf_dir: str, stream: DataFrame, spec: FilterSpec | None = None) -> DataFrame:
    """Events of buyers: the filter drops most others inside the stream, a join with the static set verifies what is left."""
    exact = table(spark, sf_dir, "events").where(_BUYERS).select("user_id").distinct()
    return prefilter(buyers(spark, sf_dir, spec), stream, "user_id", "udf").join(exact, "user_id", "left_semi")


@query("stream_probe", f"select event_type, count(*) as n from events where {_BOUGHT} group by event_type")
def _(spark, d):
    """A stateless probe inside the stream."""
    return run_to_end(bought(spark, d, events(spark, d)).select("event_id", "event_type"), "append").groupBy("event_type").agg(F.count("*").alias("n"))


def _windows(width: str, slide: str | None = None):
    def run(spark, d):
        hits = bought(spark, d, events(spark, d))
        by = hits.groupBy(F.window("ts", width, slide) if slide else F.window("ts", width)).agg(F.count("*").alias("n"))
        return run_to_end(by, "complete").select(F.col("window.start").alias("win"), "n").select(to_ntz("win").alias("win"), "n")

    return run


query("stream_tumbling", f"select date_trunc('day', ts) as win, count(*) as n from events where {_BOUGHT} group by 1")(_windows("1 day"))
query("stream_sliding", f"select win, count(*) as n from (select unnest([date_trunc('day', ts), date_trunc('day', ts) - interval 1 day]) as win from events where {_BOUGHT}) group by win")(_windows("2 days", "1 day"))


@query("stream_session", f"""with e as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 12 hours then 0 else 1 end as fresh from events where {_BOUGHT}),
    s as (select user_id, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as session from e),
    c as (select user_id, session, count(*) as n from s group by user_id, session) select n as events_in_session, count(*) as sessions from c group by n""")
def _(spark, d):
    hits = bought(spark, d, events(spark, d))
    sessions = hits.groupBy("user_id", F.session_window("ts", "12 hours")).agg(F.count("*").alias("n"))
    return run_to_end(sessions, "complete").groupBy(F.col("n").alias("events_in_session")).agg(F.count("*").alias("sessions"))


@query("stream_late", f"with w as (select date_trunc('day', ts) as win, count(*) as n from events where {_BOUGHT} group by 1) select win, n from w where win < (select date_trunc('day', max(ts) - interval 10 minutes) from events)")
def _(spark, d):
    """With a watermark, windows that may still change are held back; in append mode only closed ones come out."""
    hits = bought(spark, d, events(spark, d).withWatermark("ts", "10 minutes"), FilterSpec("bloom", bits_per_key=12))
    by = hits.groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"))
    return run_to_end(by, "append").select(F.col("window.start").alias("win"), "n").select(to_ntz("win").alias("win"), "n")


#: Keys of a generation, after which it is sealed.
GENERATION = 512


def seen_before(stream: DataFrame, key: str, shards: int = 4, spec: FilterSpec | None = None) -> DataFrame:
    """(key, first) for each row: whether the key was not seen before, exactly, by generations of filters for each shard.

    New keys gather in an open generation, a plain list; when full it is sealed: sorted keys and an immutable xor filter over them. A key
    that no filter knows is new for sure; one that a filter knows is looked up in that generation's keys. No generation is
    dropped: two of one size are merged, so their number grows with the logarithm of the keys. A shard's state
    holds all its keys, so ``shards`` should grow with the keys that are expected.
    """
    spec = spec or FilterSpec("xor", 16)
    kind = T.StructType([T.StructField("k64", T.LongType()), T.StructField("first", T.IntegerType())])
    state_kind = "open array<bigint>, sealed array<struct<capacity:bigint,seed:bigint,seg1:bigint,seg2:bigint,n:bigint,cells:array<smallint>,keys:array<bigint>>>"

    def step(_: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        import numpy as np

        open_, sealed = state.get if state.exists else ([], [])
        known = set(open_)
        built = [(K.Built(n, c, 0, s % (1 << 64), seg1=a, seg2=b, cells=np.array(v, np.int16)), np.array(own, np.int64)) for c, s, a, b, n, v, own in map(tuple, sealed)]
        for frame in frames:
            keys = frame["k64"].to_numpy(np.int64)
            old = np.zeros(len(keys), bool)
            for b, own in built:
                said = np.flatnonzero(K.contains(b, spec, keys) & ~old)
                at = np.minimum(np.searchsorted(own, keys[said]), len(own) - 1)
                old[said[own[at] == keys[said]]] = True
            first = []
            for k, o in zip(keys.tolist(), old.tolist(), strict=True):
                first.append(int(not o and k not in known))
                if not o:
                    known.add(k)
            while len(known) >= GENERATION:
                part = np.array(sorted(known)[:GENERATION], np.int64)
                known -= set(part.tolist())
                while built and len(built[-1][1]) <= len(part):
                    part = np.union1d(part, built.pop()[1])
                built.append((K.build(part, spec), part))
            yield pd.DataFrame({"k64": keys, "first": np.array(first, np.int32)})
        sealed = [(b.capacity, b.seed - (1 << 64) if b.seed >> 63 else b.seed, b.seg1, b.seg2, b.n_keys, b.cells.tolist(), own.tolist()) for b, own in built]
        state.update((sorted(known), sealed))

    rows = stream.select(F.col(key).cast("long").alias("k64")).withColumn("shard", F.pmod(F.xxhash64("k64"), F.lit(shards)))
    return rows.groupBy("shard").applyInPandasWithState(step, kind, state_kind, "append", GroupStateTimeout.NoTimeout)


@query("stream_keys_seen", "select count(*) as rows, count(distinct event_id) as keys from (select event_id from events union all select event_id from events)")
def _(spark, d):
    """Keys by the thousands a shard, so that many generations are sealed and asked; the table streams twice, so every filter meets its members."""
    both = events(spark, d).select("event_id")
    out = run_to_end(seen_before(both.select(F.explode(F.array("event_id", "event_id")).alias("event_id")), "event_id"), "append")
    return out.agg(F.count("*").alias("rows"), F.sum("first").cast("long").alias("keys"))


@query("stream_seen_before", "select count(*) as events, count(distinct user_id) as users from events")
def _(spark, d):
    out = run_to_end(seen_before(events(spark, d), "user_id"), "append")
    return out.agg(F.count("*").alias("events"), F.sum("first").cast("long").alias("users"))


@query("stream_dedup", "select count(*) as users from (select distinct user_id, event_type from events)")
def _(spark, d):
    """Exact deduplication by the engine's own state, for comparison."""
    return run_to_end(events(spark, d).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]), "append").agg(F.count("*").alias("users"))


def swapping(versions: Callable[[int], FilterSet], out: str) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: each batch is asked of the version that holds when it starts, and written to ``out``."""

    def step(batch: DataFrame, batch_id: int) -> None:
        prefilter(versions(batch_id), batch, "user_id", "udf").select("event_id", F.lit(batch_id).alias("batch_id")).write.mode("append").parquet(out)

    return step


@query("stream_swap_version", f"select count(*) as n from events where {_BOUGHT}")
def _(spark, d):
    base = f"{shared_dir(spark)}/sieveset/stream-{uuid.uuid4().hex}"
    made: dict[int, FilterSet] = {}
    versions = lambda batch_id: made.setdefault(batch_id // 10, buyers(spark, d))
    events(spark, d).writeStream.option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(swapping(versions, f"{base}/out")).start().awaitTermination()
    found = spark.read.schema("event_id long, batch_id long").parquet(f"{base}/out")
    found = found.join(table(spark, d, "events").select("event_id", "user_id"), "event_id")
    exact = table(spark, d, "events").where(_BUYERS).select("user_id").distinct()
    return found.join(exact, "user_id", "left_semi").agg(F.count("*").alias("n"))
