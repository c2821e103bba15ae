"""Cutting lineage in a folder that all executors share.

The cluster names that folder in ``spark.checkpoint.dir``.  A session on one
machine that names none gets a temporary one; on a cluster that is an error, as
executors do not share local folders.
"""

from __future__ import annotations

import gc
import re
import tempfile
import time

from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder, set to a temporary one where a session on one machine has none."""
    context = spark.sparkContext
    current = context._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.fullmatch(r"local(\[.*\])?", context.master):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    context.setCheckpointDir(named or tempfile.mkdtemp(prefix="sparsegrid-checkpoint-"))
    return context._jsc.sc().getCheckpointDir().get()


def cut_lineage(df: DataFrame) -> DataFrame:
    """Writes ``df`` to the shared checkpoint folder and returns what was written.

    Tables derived from it twice are not computed twice, and a lost executor
    costs no recomputation of what lies before it.
    """
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def cut_and_release(df: DataFrame, rounds: int = 1) -> DataFrame:
    """``cut_lineage`` for methods of many jobs: what is no longer needed is deleted."""
    out = cut_lineage(df)
    del df  # its shuffles are among what is no longer needed
    release(out.sparkSession, every=2.0 if rounds == 1 else 0.0, rounds=rounds)
    return out


_released = [0.0]


def release(spark: SparkSession, every: float = 0.0, rounds: int = 1) -> None:
    """Lets Spark delete the shuffle and checkpoint files of tables that are no longer referred to.

    Its cleaner acts when the driver collects garbage, which a driver with few
    objects seldom does; a method of many small jobs would keep the files of all,
    and the driver's heap would grow with the plans of all.  What the last job
    has used is free only after three collections within about a second: ask for
    as many ``rounds`` after a job of large shuffles.  Nothing happens where the
    last time was less than ``every`` seconds ago.
    """
    if time.monotonic() - _released[0] < every:
        return
    for k in range(rounds):
        time.sleep(0.35 if k else 0.0)
        gc.collect()
        spark.sparkContext._jvm.System.gc()
    _released[0] = time.monotonic()


def drop_folder(spark: SparkSession, path: str) -> None:
    """Deletes a folder of intermediate tables, on whatever file system it is."""
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)
