"""Filter sets: one row per shard, kept as a table."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sieveset.kernels import filters as K
from sieveset.kernels.rank import to_words
from sieveset.kernels.sparse import pack_sparse, packed_bits, unpack_sparse

from sieveset.sources.staging import materialise

from .spec import FilterSpec, SchemaMismatch

_CELLS = {np.int8: T.ByteType(), np.int16: T.ShortType(), np.int32: T.IntegerType(), np.int64: T.LongType()}


def cell_type(spec: FilterSpec) -> T.DataType:
    bits = max(spec.fp_bits, 9) if spec.kind.startswith(("cuckoo", "cqf")) else spec.fp_bits
    return _CELLS[K._cell_type(bits)]


def schema(spec: FilterSpec) -> T.StructType:
    long, integer = T.LongType(), T.IntegerType()
    kinds = {
        "filter_id": T.StringType(), "kind": T.StringType(), "shard": integer, "shard_count": integer, "n_keys": long, "fp_bits": integer, "capacity": long,
        "seg1": long, "seg2": long, "seed": long, "attempts": integer, "num_hashes": integer, "cells": T.ArrayType(cell_type(spec), False),
        "aux": T.ArrayType(long, False), "bits_total": long, "empty": long, "empty_last": long,
    }
    return T.StructType([T.StructField(k, v) for k, v in kinds.items()])


def to_row(built: K.Built, spec: FilterSpec, filter_id: str, shard: int, shard_count: int) -> dict:
    return {
        "filter_id": filter_id, "kind": spec.kind, "shard": shard, "shard_count": shard_count, "n_keys": built.n_keys, "fp_bits": spec.fp_bits, "capacity": built.capacity,
        "seg1": built.seg1, "seg2": built.seg2, "seed": built.seed - (1 << 64) if built.seed >> 63 else built.seed, "attempts": built.attempts, "num_hashes": built.num_hashes,
        "cells": built.cells, "aux": built.aux, "bits_total": built.bits_total, "empty": built.empty, "empty_last": built.empty_last,
    }


def from_row(row, spec: FilterSpec) -> K.Built:
    kind = {T.ByteType: np.int8, T.ShortType: np.int16, T.IntegerType: np.int32, T.LongType: np.int64}[type(cell_type(spec))]
    of = lambda name: int(row[name])
    return K.Built(of("n_keys"), of("capacity"), of("bits_total"), of("seed") % (1 << 64), of("attempts"), of("seg1"), of("seg2"), of("num_hashes"), np.asarray(row["cells"], kind), np.asarray(row["aux"], np.int64), of("empty"), of("empty_last"))


@dataclass(frozen=True)
class FilterSet:
    """A filter is immutable: new keys mean a new set under a new id."""

    frame: DataFrame
    spec: FilterSpec
    shard_count: int

    def totals(self) -> DataFrame:
        """One row per filter_id: n_keys, bits_total, capacity, empty, empty_last, last_cells, attempts."""
        last = F.sum(F.col("capacity") - F.col("seg2")).alias("last_cells")
        return self.frame.groupBy("filter_id").agg(*(F.sum(c).alias(c) for c in ("n_keys", "bits_total", "capacity", "empty", "empty_last")), last, F.sum("attempts").alias("attempts"))

    def bits_total(self) -> int:
        return self.frame.agg(F.coalesce(F.sum("bits_total"), F.lit(0))).first()[0]

    def stored_bytes(self) -> int:
        """Bytes of the arrays as they are kept, which may be more than the bits that the structure needs."""
        width = {T.ByteType: 1, T.ShortType: 2, T.IntegerType: 4, T.LongType: 8}[type(cell_type(self.spec))]
        return self.frame.agg(F.coalesce(F.sum(F.size("cells").cast("long") * width + F.size("aux").cast("long") * 8), F.lit(0))).first()[0]

    def bits_per_key(self) -> float:
        n, bits = self.frame.agg(F.sum("n_keys"), F.sum("bits_total")).first()
        return bits / n if n else float("nan")

    def empty_share(self) -> float:
        empty, cells = self.frame.agg(F.sum("empty"), F.sum("capacity")).first()
        return empty / cells if cells else float("nan")

    def save(self, path: str, mode: str = "overwrite") -> None:
        """Parquet by filter_id; xor filters in the compact form, without empty cells."""
        out = self.pack() if self.spec.kind == "xor" else self.frame
        out.withColumn("spec", F.lit(self.spec.to_json())).write.mode(mode).partitionBy("filter_id").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> FilterSet:
        frame = spark.read.parquet(path)
        if "spec" not in frame.columns or "bits_total" not in frame.columns:
            raise SchemaMismatch(f"{path} holds no filter set")
        first = frame.select("spec", "shard_count").first()
        if first is None:
            raise SchemaMismatch(f"{path} is empty")
        spec = FilterSpec.from_json(first["spec"])
        frame = frame.drop("spec").withColumn("filter_id", F.col("filter_id").cast("string"))
        frame = unpack(frame, spec) if spec.kind == "xor" else frame.select(*(f.name for f in schema(spec)))
        return cls(frame, spec, first["shard_count"])

    def pack(self) -> DataFrame:
        """For sending: a bitmap and the occupied cells in place of ``cells``; packed_bits counts both."""
        if self.spec.kind != "xor":
            raise ValueError("only plain xor filters have empty cells to leave out")
        spec = self.spec
        names = [f.name for f in schema(spec) if f.name not in ("cells", "aux")]
        kinds = T.StructType([f for f in schema(spec) if f.name in names] + [T.StructField("bitmap", T.BinaryType()), T.StructField("occupied", T.BinaryType()), T.StructField("packed_bits", T.LongType())])

        def run(frames):
            import pandas as pd

            for pdf in frames:
                rows = []
                for row in pdf.to_dict("records"):
                    b = from_row(row, spec)
                    bits = np.unpackbits(b.aux.view(np.uint8), count=b.capacity, bitorder="little").astype(bool)
                    bitmap, values = pack_sparse(b.cells, bits)
                    rows.append({n: row[n] for n in names} | {"bitmap": bitmap, "occupied": values, "packed_bits": packed_bits(b.capacity, b.n_keys, spec.fp_bits)})
                yield pd.DataFrame(rows, columns=kinds.names)

        return self.frame.mapInPandas(run, kinds)

    def compact_full(self, rank: str = "two_level") -> FilterSet:
        """The run-time form that keeps occupied cells only and finds all three by rank over the whole table; asked like any other set."""
        if self.spec.kind != "xor":
            raise ValueError("only plain xor filters have empty cells to leave out")
        old, spec = self.spec, replace(self.spec, kind="xor_compact", rank=rank)
        kinds = schema(spec)

        def run(frames):
            import pandas as pd

            for pdf in frames:
                made = [to_row(K.compacted(from_row(r, old), spec), spec, r["filter_id"], r["shard"], r["shard_count"]) for r in pdf.to_dict("records")]
                yield pd.DataFrame(made, columns=kinds.names)

        return FilterSet(materialise(self.frame.mapInPandas(run, kinds), "filter"), spec, self.shard_count)


def unpack(packed: DataFrame, spec: FilterSpec) -> DataFrame:
    """The frame of a packed xor filter set, cell for cell as it was."""
    kinds = schema(spec)
    cell = {T.ByteType: np.int8, T.ShortType: np.int16, T.IntegerType: np.int32, T.LongType: np.int64}[type(cell_type(spec))]

    def run(frames):
        import pandas as pd

        for pdf in frames:
            rows = []
            for row in pdf.to_dict("records"):
                cells, occupied = unpack_sparse(row["bitmap"], row["occupied"], row["capacity"], cell)
                rows.append({n: row[n] for n in kinds.names if n in row} | {"cells": cells, "aux": to_words(occupied).view(np.int64)})
            yield pd.DataFrame(rows, columns=kinds.names)

    return packed.mapInPandas(run, kinds)
