"""Tables in the folder all executors share, where derived facts are spilled."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, a local folder of our own, on a local master only (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = held.get() if held.isDefined() else None
    if not base:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="rulepush-")
        spark.sparkContext.setCheckpointDir(base)
    return base


def spill(df: DataFrame, name: str) -> DataFrame:
    """df written once and read back: a snapshot that later inserts don't touch, with no lineage."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._spilled_to = path
    return out


def discard(*dfs: DataFrame) -> None:
    """Deletes the folders of spilled tables that nothing will read again; other frames are left alone."""
    for df in dfs:
        if path := getattr(df, "_spilled_to", None):
            jvm, conf = df.sparkSession._jvm, df.sparkSession._jsc.hadoopConfiguration()
            folder = jvm.org.apache.hadoop.fs.Path(path)
            folder.getFileSystem(conf).delete(folder, True)


def stored_bytes(df: DataFrame) -> int:
    """Bytes on disk of a spilled table."""
    if not (path := getattr(df, "_spilled_to", None)):
        return 0
    jvm, conf = df.sparkSession._jvm, df.sparkSession._jsc.hadoopConfiguration()
    folder = jvm.org.apache.hadoop.fs.Path(path)
    return int(folder.getFileSystem(conf).getContentSummary(folder).getLength())
