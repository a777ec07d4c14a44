"""Scratch tables in the cluster's shared folder.

Iterative plans cut their lineage by writing a Parquet table below the folder
that ``spark.checkpoint.dir`` names; any executor can read it again, so a lost
executor costs a task retry and no recomputation of the rounds before.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_RUN = uuid.uuid4().hex[:12]


def scratch_root(spark: SparkSession) -> str:
    """The shared folder. Under a local master that names none, a temporary one is set."""
    sc = spark.sparkContext
    root = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not root:
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        root = tempfile.mkdtemp(prefix="sieve-scratch-")
        sc.setCheckpointDir(root)
        root = f"file://{root}"
    return f"{root.rstrip('/')}/sieve-{_RUN}"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as a scratch table and return a reader of it."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex[:8]}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def clear(spark: SparkSession) -> None:
    """Delete every scratch table of this driver process."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(scratch_root(spark))
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
