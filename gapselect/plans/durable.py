"""Lineage cuts that survive lost executors."""

from __future__ import annotations

import tempfile
import uuid

from pyspark import SparkContext
from pyspark.sql import DataFrame


def _shared(sc: SparkContext) -> str:
    """The folder of ``spark.checkpoint.dir``. Where the session names none, a ``local`` one
    gets a temporary folder of this machine; a cluster has to name one."""
    if sc.getCheckpointDir() is None:
        found = sc.getConf().get("spark.checkpoint.dir")
        if not found and not sc.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir is not set: name a folder that driver and executors share")
        sc.setCheckpointDir(found or tempfile.mkdtemp(prefix="shared-"))
    return sc.getCheckpointDir()


def durable(df: DataFrame) -> DataFrame:
    """``df`` written once below ``spark.checkpoint.dir``."""
    _shared(df.sparkSession.sparkContext)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """``df`` written once as compressed columns below ``spark.checkpoint.dir``: for rows of
    tables, of which a checkpoint keeps every one in full width. What was shuffled to make
    them is let go at once, not when the driver next collects its garbage."""
    folder = f"{_shared(df.sparkSession.sparkContext)}/rows-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(folder)
    df.sparkSession.sparkContext._jvm.java.lang.System.gc()
    return df.sparkSession.read.schema(df.schema).parquet(folder)
