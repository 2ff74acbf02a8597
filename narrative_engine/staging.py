"""Tables written to the folder that driver and executors share, to end lineage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; one of our own only where none is named and everything runs in this process."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if spark.sparkContext.master.split("[")[0] != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"file://{tempfile.gettempdir()}/narrative_engine_shared"


def _path(spark: SparkSession, path: str):
    jvm = spark._jvm
    found = jvm.org.apache.hadoop.fs.Path(path)
    return found.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()), found


def kept_until_exit(spark: SparkSession, path: str) -> str:
    """``path``, which its file system deletes when the driver ends."""
    fs, found = _path(spark, path)
    fs.deleteOnExit(found)
    return path


def staged(df: DataFrame, parts: int | None = None) -> DataFrame:
    """``df`` written and read back: what follows reads it instead of computing it, and lost executors cost nothing.

    ``parts`` merges the last stage's partitions for tables known to be small.  The table goes when
    the driver ends, or before with :func:`release`.
    """
    df = df if parts is None else df.coalesce(parts)
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/staged-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(kept_until_exit(spark, path))


def spread_out(df: DataFrame) -> DataFrame:
    """``df`` dealt to all cores in turn: rows that are small to move but long to work on, which adaptive plans would merge into a few tasks."""
    spark = df.sparkSession
    return df.repartition(max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))))


def release(df: DataFrame) -> None:
    """Deletes the staged tables that ``df`` reads, once nothing needs it any more."""
    spark, top = df.sparkSession, shared_dir(df.sparkSession).rstrip("/")
    for folder in {f.rpartition("/")[0] for f in df.inputFiles()}:
        if "/staged-" in folder and folder.split(":", 1)[-1].lstrip("/").startswith(top.split(":", 1)[-1].lstrip("/")):
            fs, found = _path(spark, folder)
            fs.delete(found, True)
