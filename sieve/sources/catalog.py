"""Keeping, shipping and refreshing filters."""

from __future__ import annotations

import io
import json

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema

from sieve.operators.build import Filter, build, key_table
from sieve.schema import FILTERS, Spec


def save(f: Filter, path: str, mode: str = "overwrite") -> None:
    """One Parquet folder a filter id; other filters under ``path`` stay."""
    f.table.drop("filter_id").write.mode(mode).parquet(f"{path}/filter_id={f.filter_id}")


def load(spark: SparkSession, path: str, filter_id: str = "f", family: str | None = None) -> Filter:
    """Reads a filter back; a probe's hash family must be the builder's."""
    table = spark.read.schema(FILTERS).parquet(f"{path}/filter_id={filter_id}").withColumn("filter_id", F.lit(filter_id))
    first = table.select("params", "shard_bits").first()
    if first is None:
        raise ValueError(f"no filter {filter_id}")
    s = Spec(**json.loads(first["params"]["spec"]))
    if family and family != s.family:
        raise ValueError(f"filter {filter_id} hashes with {s.family}, not {family}")
    return Filter(table.select(*[x.name for x in FILTERS]), s, first["shard_bits"], filter_id)


def to_bytes(f: Filter) -> DataFrame:
    """(filter_id, shard, blob): every shard as one self-contained Arrow stream."""
    schema = to_arrow_schema(FILTERS)

    def run(batches):
        for batch in batches:
            table = pa.Table.from_batches([batch]).cast(schema)
            blobs = []
            for i in range(len(table)):
                sink = io.BytesIO()
                with pa.ipc.new_stream(sink, schema) as out:
                    out.write_table(table.slice(i, 1))
                blobs.append(sink.getvalue())
            yield pa.RecordBatch.from_arrays([table.column("filter_id").combine_chunks(), table.column("shard").combine_chunks(), pa.array(blobs, pa.binary())], ["filter_id", "shard", "blob"])

    return f.table.mapInArrow(run, "filter_id string, shard int, blob binary")


def from_bytes(blobs: DataFrame) -> Filter:
    """A filter from its shards' blobs."""

    def run(batches):
        for batch in batches:
            for blob in batch.column(0).to_pylist():
                yield from pa.ipc.open_stream(blob).read_all().to_batches()

    table = blobs.select("blob").mapInArrow(run, FILTERS)
    first = table.select("params", "shard_bits", "filter_id").first()
    return Filter(table, Spec(**json.loads(first["params"]["spec"])), first["shard_bits"], first["filter_id"])


def refresh(f: Filter, all_keys: DataFrame, delta: DataFrame, keys: str | list[str], seed: int = 1) -> Filter:
    """``f`` over ``all_keys`` after ``delta`` changed: only the shards it touches are rebuilt.

    Give the delta's added and removed keys; shards that no key of it falls in keep their rows.
    """
    names = [keys] if isinstance(keys, str) else list(keys)
    touched = key_table(delta, names, f.shard_bits, f.spec.family).select("shard").distinct()
    from sieve.functions.keys import key64, shard

    at = shard(key64(*names, family=f.spec.family), f.shard_bits)
    rows = all_keys.select(*names).withColumn("__at", at).join(F.broadcast(touched.withColumnRenamed("shard", "__at")), "__at", "left_semi")  # at most one row a shard
    how = {k: v for k, v in vars(f.spec).items() if k != "kind"}
    new = build(rows, names, f.spec.kind, seed=seed, shard_bits=f.shard_bits, filter_id=f.filter_id, **how)
    kept = f.table.join(F.broadcast(touched), "shard", "left_anti").select(*[x.name for x in FILTERS])
    return Filter(kept.unionByName(new.table), f.spec, f.shard_bits, f.filter_id)


def occupancy(cells: list[int] | np.ndarray, seg_len: int) -> list[tuple[int, int, int]]:
    """(segment, used, empty) of a fuse array."""
    x = np.asarray(cells) != 0
    return [(k, int(x[k * seg_len : (k + 1) * seg_len].sum()), int((~x[k * seg_len : (k + 1) * seg_len]).sum())) for k in range(len(x) // seg_len)]
