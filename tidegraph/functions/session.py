"""Session helpers shared by iterative operators."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a fresh one where it is unset (tests)."""
    sc = spark.sparkContext
    configured = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if configured:
        if not sc.getCheckpointDir():
            sc.setCheckpointDir(configured)
        return configured
    if not sc.getCheckpointDir():
        if sc.master != "local" and not sc.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="tidegraph-"))
    return sc.getCheckpointDir()


_scratch: dict[str, list[str]] = {}  # application id -> folders written by stored


def scratch_path(spark: SparkSession, label: str) -> str:
    """A fresh folder below the shared one, on the list that release_scratch deletes."""
    path = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    _scratch.setdefault(spark.sparkContext.applicationId, []).append(path)
    return path


def stored(df: DataFrame, label: str) -> DataFrame:
    """Write a table to the shared folder and read it back: compressed, columnar, prunable, of known size (so joins can
    be planned by it). Cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def dropped(df: DataFrame) -> None:
    """Deletes a stored table that nothing reads any more."""
    path, spark = df._scratch_path, df.sparkSession
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
    _scratch[spark.sparkContext.applicationId].remove(path)


def cut(df: DataFrame) -> DataFrame:
    """Cut lineage through a written table."""
    return stored(df, "cut")


def release_scratch(spark: SparkSession) -> int:
    """Deletes the intermediate tables of this session and returns their number. The caller of an operator owns
    them: a lazy result reads them, so call this once results are written."""
    paths = _scratch.pop(spark.sparkContext.applicationId, [])
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for p in paths:
        at = hadoop(p)
        at.getFileSystem(conf).delete(at, True)
    return len(paths)
