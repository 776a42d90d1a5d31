"""Where state and logs are written: a folder that the driver and all executors share."""

from __future__ import annotations

import atexit
import shutil
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; where it is unset a folder of this machine, in local mode only."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    return "file:///tmp/checkpoints"


_made: list[str] = []
_intermediate: list[str] = []


def fresh_dir(spark: SparkSession, tag: str) -> str:
    """A folder's path that no one else uses; ``release`` deletes what this application has written."""
    path = f"{shared_dir(spark)}/skipsketch-{tag}-{uuid.uuid4().hex}"
    _made.append(path)
    return path


def release(spark: SparkSession) -> None:
    """Delete the folders that this application has made; frames that still read them can't be used any more."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    while _made:
        path = jvm.org.apache.hadoop.fs.Path(_made.pop())
        path.getFileSystem(conf).delete(path, True)


@atexit.register
def _release_intermediates() -> None:
    """At the end of the driver, intermediate tables whose folder it can reach itself; logs, states and catalogs stay."""
    for path in _intermediate:
        shutil.rmtree(path.removeprefix("file://"), ignore_errors=True)


def stored(df: DataFrame, tag: str) -> DataFrame:
    """Write once and read back: cuts lineage, and outlives lost executors."""
    path = fresh_dir(df.sparkSession, tag)
    _intermediate.append(path)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
