"""Reading and writing files of other formats with explicit schemas."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder below the shared checkpoint folder."""
    from gapselect.plans.durable import durable

    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        durable(spark.range(1))
    return f"{sc.getCheckpointDir()}/{name}-{uuid.uuid4().hex}"


def roundtrip(df: DataFrame, fmt: str) -> DataFrame:
    """``df`` written as ``fmt`` and read back with its own schema (nothing is inferred)."""
    folder = scratch(df.sparkSession, fmt)
    df.write.format(fmt).options(**({"header": "true"} if fmt == "csv" else {})).save(folder)
    return df.sparkSession.read.format(fmt).schema(df.schema).options(**({"header": "true"} if fmt == "csv" else {})).load(folder)
