"""Tables that cut lineage: Parquet in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, as in tests on one machine, a folder of our own. A cluster must name one."""
    context = spark.sparkContext
    base = context.getConf().get("spark.checkpoint.dir")
    if not base and (known := context._jsc.sc().getCheckpointDir()).isDefined():
        base = known.get()
    if not base:
        if not context.master.startswith("local") or context.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = tempfile.mkdtemp(prefix="checkpoints-")
        context.setCheckpointDir(base)
    return base


def written(df: DataFrame, name: str, *by: str) -> DataFrame:
    """The rows, written (in a folder for each value of ``by``) and read again; a lost executor costs nothing that came before."""
    path = f"{shared_dir(df.sparkSession).rstrip('/')}/tables/{name}-{uuid.uuid4().hex}"
    df.write.partitionBy(*by).parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    back._written = path
    return back


def drop(*tables: DataFrame | None) -> None:
    """Deletes what ``written`` wrote for these; other tables are left alone. Nothing unwritten may read them any more."""
    for df in tables:
        if path := getattr(df, "_written", None):
            there = df.sparkSession._jvm.org.apache.hadoop.fs.Path(path)
            there.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(there, True)
