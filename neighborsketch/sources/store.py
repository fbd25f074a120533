"""Tables shared by several steps, written once to the folder that all executors see."""

from __future__ import annotations

import gc
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session, or where that is unset and all runs on
    one machine, a new folder."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if at:
        return at.rstrip("/")
    known = spark.sparkContext.getCheckpointDir()
    if known is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
        known = spark.sparkContext.getCheckpointDir()
    return known.rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


SETTLE_S = 5.0  # at most so often
_settled = 0.0


def settle(spark: SparkSession) -> None:
    """Lets go of what finished steps left behind: their shuffle files and broadcasts stay,
    and the driver's heap grows, until the driver happens to collect its garbage."""
    global _settled
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    _settled = time.monotonic()


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once and read back: its lineage ends here, so a lost executor
    costs no more than a reread. Every few seconds the steps before are let go."""
    path = new_folder(df.sparkSession, name)
    df.write.parquet(path)
    if time.monotonic() - _settled >= SETTLE_S:
        settle(df.sparkSession)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_stored(df: DataFrame) -> None:
    """Deletes a table that ``stored`` made, once nothing reads it any more."""
    jvm = df.sparkSession.sparkContext._jvm
    for file in df.inputFiles()[:1]:
        folder = jvm.org.apache.hadoop.fs.Path(file).getParent()
        folder.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)


def rows_bounded(df: DataFrame, most: int) -> bool:
    """Whether a frame has at most so many rows: what decides if it may be broadcast."""
    return df.limit(most + 1).count() <= most
