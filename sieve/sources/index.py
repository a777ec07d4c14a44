"""A file-skipping index: one filter a file, asked before the file is opened."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sieve.functions.keys import key64
from sieve.operators.build import _record, _row
from sieve.operators.contains import Loaded
from sieve.plans.scratch import materialize
from sieve.schema import FILTERS, Spec, spec


#: Looked-up values that the index is asked for at most; with more, every file is likely to hold one.
MOST_VALUES = 1_000_000


def build_index(spark: SparkSession, path: str, key: str, kind: str = "fuse3", seed: int = 1, **how) -> DataFrame:
    """One filter row for every file under ``path``; filter_id is the file.

    A file's distinct keys are gathered in one task: the file's size bounds them.
    """
    s = spec(kind, **how)
    rows = spark.read.parquet(path).select(F.col("_metadata.file_path").alias("file"), key64(key).alias("key64")).filter("key64 IS NOT NULL").distinct()

    def one(table: pa.Table) -> pa.Table:
        return _record(_row(table.column(1).to_numpy().astype(np.int64), 0, s, seed, table.column(0)[0].as_py(), 0))

    return materialize(rows.groupBy("file").applyInArrow(one, FILTERS), "file-index")


def candidates(index: DataFrame, values: DataFrame, key: str, most: int = MOST_VALUES) -> DataFrame | None:
    """(file) of all files that may hold one of the values; None with more than ``most`` values.

    The distinct values, 8 bytes each, go to the tasks that read the index, one pass over it.
    """
    first = index.select("params").first()
    if first is None:
        return index.select("filter_id")
    s = Spec(**json.loads(first["params"]["spec"]))
    asked = values.select(key64(key).alias("k")).filter("k IS NOT NULL").distinct().limit(most + 1).toArrow()
    if len(asked) > most:
        return None
    shared = index.sparkSession.sparkContext.broadcast(asked.column(0).to_numpy().astype(np.int64).tobytes())
    names = [f.name for f in FILTERS if f.name not in ("params", "filter_id")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        k = np.frombuffer(shared.value, np.int64)
        for batch in batches:
            files = batch.column(0).to_pylist()
            rows = ({n: batch.column(i + 1)[at].as_py() for i, n in enumerate(names)} for at in range(len(files)))
            yield pa.RecordBatch.from_arrays([pa.array([x for x, row in zip(files, rows, strict=True) if Loaded(row, s).contains(k).any()], pa.string())], ["filter_id"])

    return index.select("filter_id", *names).mapInArrow(run, "filter_id string")


def read_skipping(spark: SparkSession, path: str, index: DataFrame, values: DataFrame, key: str, most: int = MOST_VALUES) -> DataFrame:
    """The rows of ``path`` whose key is among ``values``, opening only candidate files.

    With more than ``most`` values all files are read: the exact join is the same.
    """
    found = candidates(index, values, key, most)
    data = spark.read.parquet(path)
    if found is not None:
        files = [r[0] for r in found.collect()]  # file names, as many as the reader lists
        if not files:
            return data.limit(0)
        data = spark.read.schema(data.schema).parquet(*files)
    return data.join(values.select(key).distinct(), key, "left_semi")
