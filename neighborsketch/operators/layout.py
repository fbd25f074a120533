"""Layouts of a sketch's counters: dense arrays, sparse maps, packed bytes."""

from __future__ import annotations

import json
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.params import SketchParams
from .grid import Sketch, unpack

WIDTHS = {8: "tinyint", 16: "smallint", 32: "int"}
KEY_BYTES = 4  # of a flat offset into the counters


def counter_profile(sketch: Sketch) -> DataFrame:
    """``max_count, nonzero, zero_fraction, width_bits``: one row."""
    largest = F.coalesce(F.max(F.abs("n")), F.lit(0)).cast("long")
    total = F.lit(sketch.params.counters).cast("double")
    return sketch.cells.agg(largest.alias("max_count"), F.count(F.lit(1)).alias("nonzero")).select(
        "max_count", "nonzero", (F.lit(1.0) - F.col("nonzero") / total).alias("zero_fraction"),
        F.when(F.col("max_count") < 128, 8).when(F.col("max_count") < 32768, 16).otherwise(32).cast("int").alias("width_bits"))


def _fits(width_bits: int) -> int:
    return (1 << (width_bits - 1)) - 1


def _checked(n, width_bits: int):
    """The counter at its stored width; one that doesn't fit is an error."""
    return F.when(F.abs(n) <= _fits(width_bits), n).otherwise(F.raise_error(F.concat(F.lit(f"a counter needs more than {width_bits} bits: "), n.cast("string")))).cast(WIDTHS[width_bits])


def to_sparse(sketch: Sketch, width_bits: int = 16) -> DataFrame:
    """``row, col, rep, counts``: a map from bucket to counter by collision array."""
    entry = F.struct(F.col("bucket").cast("int").alias("bucket"), _checked(F.col("n"), width_bits).alias("n"))
    return unpack(sketch.cells, sketch.params).groupBy("row", "col", "rep").agg(F.map_from_entries(F.sort_array(F.collect_list(entry))).alias("counts"))


def to_dense(sketch: Sketch, width_bits: int = 16) -> DataFrame:
    """``row, col, rep, counts``: all buckets of every collision array."""
    p = sketch.params
    arrays = sketch.cells.sparkSession.range(p.arrays).select(
        F.floor(F.col("id") / (p.cols * p.reps)).cast("long").alias("row"), (F.floor(F.col("id") / p.reps) % p.cols).cast("long").alias("col"), (F.col("id") % p.reps).cast("long").alias("rep"))
    zero = F.lit(0).cast(WIDTHS[width_bits])
    filled = F.transform(F.sequence(F.lit(0), F.lit(p.slots - 1)), lambda b: F.coalesce(F.try_element_at(F.col("counts"), b), zero))
    joined = arrays.join(to_sparse(sketch, width_bits), ["row", "col", "rep"], "left").withColumn("counts", F.coalesce("counts", F.map_from_arrays(F.array().cast("array<int>"), F.array().cast(f"array<{WIDTHS[width_bits]}>"))))
    return joined.select("row", "col", "rep", filled.alias("counts"))


def from_layout(table: DataFrame, p: SketchParams) -> Sketch:
    """A sketch from its dense or sparse table."""
    base = ((F.col("row") * p.cols + F.col("col")) * p.reps + F.col("rep")) * F.lit(p.slots).cast("long")
    pos = "posexplode" if dict(table.dtypes)["counts"].startswith("array") else "explode"
    rows = table.select(base.alias("base"), getattr(F, pos)("counts").alias("bucket", "n"))
    return Sketch(rows.where("n != 0").select((F.col("base") + F.col("bucket")).alias("cell"), F.col("n").cast("long").alias("n")), p)


def pack_bytes(sketch: Sketch, width_bits: int = 16) -> DataFrame:
    """``row, col, rep, data``: the dense counters as little-endian bytes, as a device would send them."""
    kind = {8: "<i1", 16: "<i2", 32: "<i4"}[width_bits]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data = [np.array(x, kind).tobytes() for x in b.column(3).to_pylist()]
            yield pa.record_batch([b.column(0), b.column(1), b.column(2), pa.array(data, pa.binary())], ["row", "col", "rep", "data"])

    return to_dense(sketch, width_bits).mapInArrow(run, "row long, col long, rep long, data binary")


def save_sketch(sketch: Sketch, path: str, *, layout: str = "sparse", width_bits: int = 16) -> None:
    """Writes the counters, partitioned by row, and one row of parameters."""
    spark = sketch.cells.sparkSession
    table = to_dense(sketch, width_bits) if layout == "dense" else to_sparse(sketch, width_bits)
    table.write.mode("overwrite").partitionBy("row").parquet(f"{path}/counters")
    spark.createDataFrame([(json.dumps(sketch.params.as_dict()),)], "params string").coalesce(1).write.mode("overwrite").parquet(f"{path}/params")


def load_sketch(spark: SparkSession, path: str) -> Sketch:
    p = SketchParams(**json.loads(spark.read.parquet(f"{path}/params").first().params))
    table = spark.read.parquet(f"{path}/counters").withColumn("row", F.col("row").cast("long"))
    return from_layout(table, p)


def sketch_bytes(sketch: Sketch, layout: str, width_bits: int = 16) -> DataFrame:
    """``bytes``: dense has every counter; sparse a key and a counter for each that isn't zero, and an offset per array."""
    p, width = sketch.params, width_bits // 8
    if layout == "dense":
        return sketch.cells.sparkSession.createDataFrame([(p.counters * width,)], "bytes long")
    return sketch.cells.agg((F.count(F.lit(1)) * (KEY_BYTES + width) + 4 * p.rows).cast("long").alias("bytes"))
