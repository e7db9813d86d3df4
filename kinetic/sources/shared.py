"""The folder that all executors share."""

from __future__ import annotations

import gc
import uuid

from pyspark.sql import DataFrame, SparkSession


def checkpoint_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder: spark.checkpoint.dir; one is set only where none is and all runs on one machine (tests)."""
    sc = spark.sparkContext
    own = sc._jsc.sc().getCheckpointDir()
    if own.isDefined():
        return own.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir has to name a folder that all executors share")
        import tempfile

        named = "file://" + tempfile.mkdtemp(prefix="kinetic-checkpoint-")
    sc.setCheckpointDir(named)
    return named


def kept(df: DataFrame, name: str = "table") -> DataFrame:
    """df as a Parquet table in the shared folder, reread: lineage ends here, executors can be lost, and its size is known to later joins."""
    path = f"{checkpoint_folder(df.sparkSession).rstrip('/')}/kinetic-{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def dropped(spark: SparkSession, path: str) -> None:
    """Deletes a folder that this session has written below the shared folder, and what its shuffles left on disk."""
    if not path.startswith(checkpoint_folder(spark).rstrip("/") + "/"):
        raise ValueError(f"{path} is not below the shared folder")
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    gc.collect()
    jvm.System.gc()  # shuffle files go with the tables that made them
