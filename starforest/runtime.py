"""Session helpers: lineage cuts in the shared folder, and nothing machine-local on a cluster."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyarrow import fs as pafs
from pyspark.sql import Column, DataFrame, Observation, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's ``spark.checkpoint.dir``.

    Only a local session without that setting (tests, laptops) gets a temporary folder.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="starforest-"))
    return sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` reliably and forget how it was made (one job; survives lost executors)."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def cut_state(df: DataFrame) -> DataFrame:
    """The state of a loop as a table in the shared folder, read again.

    Checkpoints keep a link to the plan they came from, and describing such plans takes time that doubles with
    every reference; a written table starts afresh, in columns, and with a size the planner knows.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/state-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def cut_observing(df: DataFrame, **measures: Column) -> tuple[DataFrame, dict]:
    """:func:`cut_state`, and aggregates over the rows from the same job."""
    seen = Observation()
    out = cut_state(df.observe(seen, *[c.alias(n) for n, c in measures.items()]))
    return out, seen.get


def open_store(uri: str) -> tuple[pafs.FileSystem, str]:
    """The Arrow file system of an address and the path in it (file, hdfs, s3, gs)."""
    return pafs.FileSystem.from_uri(re.sub(r"^file:/+", "file:///", uri))


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
