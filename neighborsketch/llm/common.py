"""What the training-data operators share: tables, shared storage, key packing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.store import shared_dir, stored

__all__ = ["WS", "drop_stored", "free_name", "hash_share", "input_bytes", "join_hot", "row_salt", "salts_for", "shared_dir", "stored", "table", "whole"]

#: The white space of every contract here: blank and U+0009 to U+000D.
WS = " \t\n\x0b\x0c\r"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def whole(text: Column | str) -> Column:
    """The text as a string; null counts as empty."""
    return F.coalesce((F.col(text) if isinstance(text, str) else text).cast("string"), F.lit(""))


def drop_stored(spark: SparkSession, df: DataFrame) -> None:
    """Deletes a table that ``stored`` made, once nothing reads it any more."""
    jvm = spark.sparkContext._jvm
    for file in df.inputFiles()[:1]:
        folder = jvm.org.apache.hadoop.fs.Path(file).getParent()
        folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)


def free_name(df: DataFrame, stem: str) -> str:
    """A column name that ``df`` doesn't have."""
    taken = {c.lower() for c in df.columns}
    while stem in taken:
        stem += "_"
    return stem


def input_bytes(df: DataFrame) -> int:
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def salts_for(df: DataFrame, least: int = 32) -> int:
    """A number of salts that grows with the input: one a GiB, ``least`` at least."""
    return min(max(least, input_bytes(df) >> 30), 1 << 20)


def join_hot(left: DataFrame, right: DataFrame, key: str, weight: str, most: int) -> DataFrame:
    """``left`` joined to ``right`` (a row per key, written; ``weight``: how many rows
    of ``left`` have it). The keys of greatest weight, at most ``most``, are broadcast
    and so never meet in one task; the others join through a shuffle."""
    step = F.floor(F.log2(F.greatest(F.col(weight), F.lit(1)))).cast("int")
    sizes = {r.step: r.k for r in right.groupBy(step.alias("step")).agg(F.count(F.lit(1)).alias("k")).collect()}  # at most 64 rows
    least, held = 64, 0
    for s in sorted(sizes, reverse=True):
        if held + sizes[s] > most:
            break
        least, held = s, held + sizes[s]
    met = left.join(F.broadcast(right.where(step >= least)), key)
    return met if held == sum(sizes.values()) else met.unionByName(left.join(right.where(step < least), key))


def row_salt(column: str, salts: int) -> Column:
    """A salt that a row's own id decides, so that a rerun deals rows alike."""
    return F.pmod(F.xxhash64(F.col(column)), F.lit(salts)).cast("int")


def hash_share(column: str, share: Column | float) -> Column:
    """Whether a row's hash lies in the lowest ``share`` of all hashes: ahead of a
    top-k by hash this leaves about that share of the rows of every task."""
    share = share if isinstance(share, Column) else F.lit(float(share))
    return F.xxhash64(column).cast("double") <= F.lit(-(2.0**63)) + F.lit(2.0**64) * share
