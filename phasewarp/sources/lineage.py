"""Lineage cuts: a result that several stages read is checkpointed into the shared folder, so that
plans stay small and a lost executor costs no recomputation."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame


def cut(df: DataFrame) -> DataFrame:
    """``df`` after a reliable checkpoint, in the folder that the session names.  Where none is
    named, a temporary one is set once if the session runs on this machine alone; on a cluster that
    is an error, since executors would not see each other's files."""
    spark = df.sparkSession
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and (not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="phasewarp-"))
    return df.checkpoint()
