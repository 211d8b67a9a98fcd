"""Shared helpers: table access, lineage cuts in the shared folder, hot-key joins."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

_LOCAL: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share.

    It is what ``spark.checkpoint.dir`` names. Only where that is unset and the
    master is local does a temporary folder of this machine take its place.
    """
    given = spark.conf.get("spark.checkpoint.dir", None)
    if given:
        return given.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    app = spark.sparkContext.applicationId
    if app not in _LOCAL:
        _LOCAL[app] = tempfile.mkdtemp(prefix="sieveset-")
        atexit.register(shutil.rmtree, _LOCAL[app], ignore_errors=True)
    return f"file://{_LOCAL[app]}"


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it again.

    It cuts the lineage: whatever executors are lost later, the rows and the order in
    which they were numbered stay. Unlike a checkpoint of rows it keeps column pruning.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/sieveset/{spark.sparkContext.applicationId}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def lower_ascii(col: Column) -> Column:
    """Lower-case A-Z and nothing else."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


_BATCH_KEY, _BATCH_DEFAULT, _BATCH = "spark.sql.execution.arrow.maxBytesPerBatch", "67108864b", "4m"


def small_batches(spark: SparkSession) -> None:
    """Bound the bytes that go to Python at once, since rows here are whole texts.

    This is a runtime setting; one that the user chose stays.
    """
    if spark.conf.get(_BATCH_KEY, _BATCH_DEFAULT) == _BATCH_DEFAULT:
        spark.conf.set(_BATCH_KEY, _BATCH)


def to_python(df: DataFrame, function: Callable, schema: T.StructType) -> DataFrame:
    """``mapInArrow`` with batches of bounded bytes; workers give freed memory back after each task, as they live on idle."""
    small_batches(df.sparkSession)

    def run(batches: Iterator) -> Iterator:
        yield from function(batches)
        release_memory()

    return df.mapInArrow(run, schema)


def release_memory() -> None:
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


#: A key counts as hot from this share of all rows on, so that hot keys number 1024 at most
#: and a table of them can always be broadcast.
HOT_SHARE = 1024


def attach(rows: DataFrame, stats: DataFrame, keys: list[str], n_rows: int, size: str = "group_size") -> DataFrame:
    """Inner join of ``rows`` with one row per key, safe for keys that hold a third of all rows.

    ``stats`` must have each key once, with its number of rows in ``size``. Keys of over a 1024th of
    ``n_rows`` are at most 1024 in number, so their table is broadcast and their rows stay where they
    are; all other keys are joined by a shuffle in which none can weigh much.
    """
    limit = max(1, n_rows // HOT_SHARE)
    # written before it is used, so its keys number at most HOT_SHARE
    hot = stats.where(F.col(size) > limit)
    cold = stats.where(F.col(size) <= limit)
    of_hot = rows.join(F.broadcast(hot), keys, "inner")
    of_cold = rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti").join(cold, keys, "inner")
    return of_hot.unionByName(of_cold)


def lead(doc_id: str, raw: str) -> Column:
    """The row of the least doc_id; null ids come after all others, equal ids by ``raw``."""
    return F.min(F.struct(F.col(doc_id).isNull().alias("none"), F.col(doc_id).alias("doc_id"), F.col(raw).alias("raw")))


#: Rows of a key from which on it is dealt in blocks, about; every SAMPLED-th member is counted to tell.
CELL_ROWS, SAMPLED = 4096, 64


def dealt_cells(rows: DataFrame, members: DataFrame, spread: Callable[[DataFrame], DataFrame], key: str, member: str, size: int | None = None) -> DataFrame:
    """``rows`` with i and j, partitioned by key, i and j, so that every two rows of a key meet in some cell of bounded size.

    A key of about ``size`` (CELL_ROWS) rows or more is cut into blocks by a hash of ``member``, and each row goes to all pairs of its block and
    another one. Which keys those are is told from a sample of ``members``, which ``spread`` turns into rows; a wrong guess costs time and
    changes no result.
    """
    size = size or CELL_ROWS
    few = members.where(F.pmod(F.xxhash64(F.lit(5), member), F.lit(SAMPLED)) == 0)
    hot = spread(few).groupBy(key).agg(F.count("*").alias("_seen")).where(F.col("_seen") * SAMPLED >= size)
    hot = materialise(hot.withColumn("_blocks", F.ceil(F.col("_seen") * SAMPLED / size).cast("int") + 1).drop("_seen"), "hot-keys")
    if hot.isEmpty():
        out = rows.withColumns({"i": F.lit(0), "j": F.lit(0)})
    else:
        out = rows.join(hot, key, "left").withColumn("_blocks", F.coalesce("_blocks", F.lit(1)))
        out = out.withColumn("_own", F.pmod(F.xxhash64(F.lit(6), member), F.col("_blocks")).cast("int"))
        out = out.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_blocks") - 1)))
        out = out.withColumns({"i": F.least("_own", "_other"), "j": F.greatest("_own", "_other")}).drop("_blocks", "_own", "_other")
    return out.repartition(key, "i", "j")


LONG, STRING, BINARY, INT = T.LongType(), T.StringType(), T.BinaryType(), T.IntegerType()
LONGS = T.ArrayType(LONG)


def fields(**kinds: T.DataType) -> T.StructType:
    """Schema from keyword arguments, in their order."""
    return T.StructType([T.StructField(k, v) for k, v in kinds.items()])
