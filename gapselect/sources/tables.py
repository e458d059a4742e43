"""Tables of a data folder, read lazily with the columns and filters of the query."""

from __future__ import annotations

import re
from urllib.parse import unquote, urlparse

from pyarrow import parquet
from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _row_groups(files: list[str]) -> int:
    """Row groups of local files, each of which one task reads alone; of others, the files."""
    paths = [unquote(urlparse(f).path) for f in files if urlparse(f).scheme in ("", "file")]
    return sum(parquet.ParquetFile(p).num_row_groups for p in paths) if len(paths) == len(files) else len(files)


def spread(df: DataFrame) -> DataFrame:
    """``df`` dealt to all cores where it lies in fewer files and row groups: one task would
    read such a group alone. Larger tables are read in parallel as they lie, unshuffled."""
    cores, files = df.sparkSession.sparkContext.defaultParallelism, df.inputFiles()
    return df if len(files) >= cores or _row_groups(files) >= cores else df.repartition(cores)


def sql(spark: SparkSession, sf_dir: str, text: str, **frames: DataFrame) -> DataFrame:
    """``text`` with ``{name}`` standing for the folder's table or a given frame."""
    names = set(re.findall(r"\{(\w+)\}", text))
    return spark.sql(text, **{n: frames[n] if n in frames else table(spark, sf_dir, n) for n in names})
