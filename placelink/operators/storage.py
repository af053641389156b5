"""Cut lineage in the folder that driver and executors share, and free what is no longer needed."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors see: spark.checkpoint.dir. Without one, a local master gets a temporary folder; a cluster is an error."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not at:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="placelink-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        at = "file://" + folder
        spark.sparkContext.setCheckpointDir(at)
    return at


def _home(spark: SparkSession) -> str:
    """One folder per application, so that all it wrote can go at once."""
    return f"{shared_dir(spark)}/placelink-{spark.sparkContext.applicationId}"


def stored(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Writes df in the shared folder and reads it back: lineage is cut, and a lost executor costs only its running tasks."""
    at = f"{_home(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", codec).parquet(at)
    out = df.sparkSession.read.schema(df.schema).parquet(at)
    out._stored_at = at
    return out


def _delete(spark: SparkSession, at: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(at)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def forget(*frames: DataFrame | None) -> None:
    """Deletes the files of stored frames that nothing reads any more."""
    for df in frames:
        at = getattr(df, "_stored_at", None)
        if at:
            _delete(df.sparkSession, at)


def release(spark: SparkSession) -> None:
    """Deletes all that this application has stored. Call it when no result of its queries will be read again."""
    _delete(spark, _home(spark))
