"""Folder that driver and executors share, for written intermediate tables."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's checkpoint folder. Where none is named, a local session gets a folder of its own, removed at exit; a cluster must name one."""
    conf = spark.conf.get("spark.checkpoint.dir", None)
    if conf:
        return conf.rstrip("/")
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("name a folder that driver and executors share in spark.checkpoint.dir")
        folder = tempfile.mkdtemp(prefix="blockwright-")
        atexit.register(shutil.rmtree, folder, True)
        sc.setCheckpointDir("file://" + folder)
    return sc._jsc.sc().getCheckpointDir().get().rstrip("/")


def _own(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/blockwright-{spark.sparkContext.applicationId}"


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{_own(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """`df` written to the shared folder and read again: lineage ends, and lost executors cost nothing already done."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def drop(df: DataFrame) -> None:
    """Remove a table that `cut` wrote, once nothing lazy reads it any more; other files are never touched."""
    own = _own(df.sparkSession).split("://")[-1].removeprefix("file:")
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if own.rstrip("/") in folder:
            _delete(df.sparkSession, folder)


def clear(spark: SparkSession) -> None:
    """Remove all intermediate tables of this application, when its results are written."""
    _delete(spark, _own(spark))
