"""Cutting lineage in the shared checkpoint folder."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame


def cut(df: DataFrame) -> DataFrame:
    """``df.checkpoint()`` in the folder of ``spark.checkpoint.dir``; only a local session without one gets a folder of its own."""
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        at = sc.getConf().get("spark.checkpoint.dir")
        if not at and not sc.master.startswith("local["):
            at = f"{df.sparkSession.conf.get('spark.sql.warehouse.dir').rstrip('/')}/checkpoints"
        sc.setCheckpointDir(at or tempfile.mkdtemp(prefix="tablemill-"))
    return df.checkpoint()
