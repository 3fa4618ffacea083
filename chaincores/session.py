"""Places for intermediate tables that every executor can reach."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder named in ``spark.checkpoint.dir``. Only where it is unset and Spark runs in one process, as in tests, a temporary one."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        base = tempfile.gettempdir() + "/chaincores-shared"
    return base.rstrip("/")


#: Tasks for each core, at least, where groups are worked on by Python: small rows may be long work.
TASKS = 8


def dealt(df: DataFrame, *keys: str) -> DataFrame:
    """``df`` dealt by ``keys`` to a fixed number of tasks, which Spark doesn't join for their few bytes."""
    n = max(TASKS * df.sparkSession.sparkContext.defaultParallelism, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return df.repartition(n, *keys)


#: Files of an intermediate table for each core, at most; a task takes its partitions one after the other.
FILES = 4


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once as Parquet in the shared folder and read it back: cuts the lineage and survives lost executors.

    The files don't grow in number with the partitions: on a local disk Hadoop starts processes for each file (``chmod``).
    """
    path = f"{shared_dir(df.sparkSession)}/chaincores/{name}-{uuid.uuid4().hex}"
    schema = df.schema
    df.coalesce(FILES * df.sparkSession.sparkContext.defaultParallelism).write.parquet(path)
    out = df.sparkSession.read.schema(schema).parquet(path)
    out._chaincores_path = path
    return out


def release(df: DataFrame) -> None:
    """Delete a table made by :func:`materialise` once nothing lazy reads it any more."""
    path = getattr(df, "_chaincores_path", None)
    if path:
        jvm = df.sparkSession._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(p, True)
