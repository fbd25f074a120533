"""Edge lists of graphs from common formats, and back."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE = "src long, dst long"


def read_edges(spark: SparkSession, path: str, fmt: str = "text") -> DataFrame:
    """``src, dst``. text: two numbers a line, with blanks or tabs between and comments
    after #; csv, json, orc and parquet: two columns of these names."""
    if fmt == "text":
        parts = F.split(F.trim(F.split("value", "#")[0]), r"[\s,]+")
        rows = spark.read.text(path).select(F.try_element_at(parts, F.lit(1)).try_cast("long").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("dst"))
        return rows.where("src is not null and dst is not null")
    return spark.read.format(fmt).schema(EDGE).load(path)


def adjacency(edges: DataFrame) -> DataFrame:
    """``id, elements``: each node with its neighbours."""
    return edges.where("src is not null and dst is not null").groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_set("dst")).alias("elements"))


def edges_of(sets: DataFrame) -> DataFrame:
    return sets.select(F.col("id").alias("src"), F.explode("elements").alias("dst"))


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet") -> None:
    edges.select("src", "dst").write.mode("overwrite").format(fmt).save(path)
