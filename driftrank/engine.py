"""Execution helpers: lineage cuts in the shared folder, and the choice of an executor."""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BROADCAST_EDGES = 40_000_000  # arcs that a local kernel may hold: 16 bytes each, 640 MB


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir. A local master, as in tests, may do without one."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if not found.isDefined() and not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir has to name a folder that all executors share")
        root = found.get() if found.isDefined() else "/tmp/checkpoints"
    return root.rstrip("/")


def cut_lineage(df: DataFrame, name: str = "state") -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back; survives lost executors."""
    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def choose(edges: DataFrame) -> str:
    """'kernel' where the whole graph fits into each worker by a checked count, else 'rounds'."""
    return "kernel" if edges.count() <= BROADCAST_EDGES else "rounds"


BROADCAST_ROWS = 1_000_000  # of three numbers each: 24 MB


def side_hint(batch: DataFrame):
    """F.broadcast where ``batch`` is under BROADCAST_ROWS by a count, else no hint; also for what has no more rows."""
    return F.broadcast if batch.count() <= BROADCAST_ROWS else lambda df: df
