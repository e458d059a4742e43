"""What the corpus operators share: reading tables, and cutting lineage durably."""

from __future__ import annotations

import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Characters that separate words and are folded in normalised texts: fixed values.
SPACES = r"[\x20\x09-\x0D]+"
WORDS = r"[^\x20\x09-\x0D]+"
#: Bytes of rows, as they lie in memory, up to which a written table may be broadcast.
SENT_BYTES = 8 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the
    session. Where that is unset a temporary one is made if the session is ``local``
    (tests on one machine); a cluster has to name one."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir()
    if found is None:
        found = sc.getConf().get("spark.checkpoint.dir")
        if not found and not sc.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir is not set: name a folder that driver and executors share")
        sc.setCheckpointDir(found or tempfile.mkdtemp(prefix="shared-"))
        found = sc.getCheckpointDir()
    return found


def durable(df: DataFrame) -> DataFrame:
    """``df`` written once to the shared folder: later reads survive lost executors and
    see the same rows in the same partitions."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def _bytes_of(df: DataFrame):
    """Bytes of the rows of ``df`` as a hash table holds them, about."""
    fixed = F.lit(32 + 16 * len(df.columns)).cast("long")
    for f in df.schema.fields:
        if isinstance(f.dataType, (T.StringType, T.BinaryType)):
            fixed = fixed + F.coalesce(F.octet_length(F.col(f.name)), F.lit(0))
        elif isinstance(f.dataType, T.ArrayType):
            fixed = fixed + F.coalesce(8 * F.greatest(F.size(F.col(f.name)), F.lit(0)), F.lit(0))
    return F.coalesce(F.sum(fixed), F.lit(0))


def few(df: DataFrame, rows: int, a_task: int = 20_000) -> DataFrame:
    """``df`` of ``rows`` rows at most in no more tasks than these need, but one a core. An
    exchange deals a small table out over as many tasks as a large one, and each costs its
    start and a file; large tables stay in the tasks that they are in."""
    return df.coalesce(max(df.sparkSession.sparkContext.defaultParallelism, rows // a_task + 1))


def written(df: DataFrame) -> DataFrame:
    return counted(df)[0]


def counted(df: DataFrame) -> tuple[DataFrame, int]:
    """``df`` as a table in the shared folder, removed when the session's JVM ends, and its rows. Other
    than :func:`durable` it forgets how rows were dealt out, so that a later join by a hot
    key exchanges them anew and adaptive execution can split them.

    Spark would judge by the size of the files whether to broadcast it. Repeated values
    take little there and all of their room on the driver, so rows are measured while they
    are written and tables beyond ``SENT_BYTES`` are joined by merging."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/table-{uuid.uuid4().hex}"
    seen = Observation()
    df.observe(seen, _bytes_of(df).alias("bytes"), F.count(F.lit(1)).alias("rows")).write.parquet(path)
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(where)
    out = spark.read.schema(df.schema).parquet(path)
    return out.hint("merge") if seen.get["bytes"] > SENT_BYTES else out, seen.get["rows"]


def distinct_ids(docs: DataFrame, id_col: str) -> bool:
    """Whether no id, null included, is in two rows; reads the ids alone."""
    return docs.groupBy(id_col).agg(F.count(F.lit(1)).alias("n")).filter("n > 1").isEmpty()


def numbered(docs: DataFrame) -> tuple[DataFrame, str]:
    """``docs`` written once with a number for every row, so that rows that repeat an id
    can be told apart, and the name of that column, which no other one has."""
    name = "__row"
    while name in docs.columns:
        name += "_"
    return written(docs.withColumn(name, F.monotonically_increasing_id())), name


def release(spark: SparkSession) -> None:
    """Lets Spark delete shuffle files of steps whose frames are gone: its cleaner acts
    when the driver's JVM collects garbage, which may be long after."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def as_text(name: str = "text"):
    return F.coalesce(F.col(name).cast("string"), F.lit(""))
