"""Lineage and broadcast decisions shared by the iterative operators."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of ids that are broadcast at most. A row is a few longs, so this bounds a broadcast to some tens of MB.
BROADCAST_ROWS = 200_000


def shared_dir(spark: SparkSession) -> str:
    """The folder for checkpoints and written levels: the one that spark.checkpoint.dir names. A local session without it gets a scratch
    folder; on a cluster the setting is required, since executors don't share local folders."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        where = spark.conf.get("spark.checkpoint.dir", None)
        if where is None and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(where or f"file:///tmp/checkpoints/{os.getpid()}")
    return sc._jsc.sc().getCheckpointDir().get()


def delete(spark: SparkSession, path: str) -> None:
    """Removes what a run wrote, if it is there."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def cut(df: DataFrame) -> DataFrame:
    """The same rows, written to the shared folder; later plans start from there, and a lost executor costs no recomputation."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def gated(df: DataFrame, rows: int, most: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint if a count has shown that the table is small; the plain table otherwise."""
    return F.broadcast(df) if rows <= most else df


_MEMO: dict[tuple, object] = {}


def memo(spark: SparkSession, key: tuple, make):
    """One result per application and key; what it holds are written tables, not data."""
    full = (spark.sparkContext.applicationId, *key)
    if full not in _MEMO:
        for old in [k for k in _MEMO if k[0] != full[0]]:
            del _MEMO[old]
        _MEMO[full] = make()
    return _MEMO[full]
