"""Applications of the density sketch: a robust cache, outliers, overlap of two corpora."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.params import SketchParams
from .decode import estimate_measurements, query_cells, read_counters
from .grid import Sketch, build_sketch, kde_params


def kde_sketch(items: DataFrame, p: SketchParams, **more) -> Sketch:
    if p.rows != 1 or p.cols != 1:
        raise ValueError("a density sketch has one cell")
    return build_sketch(items, p, **more)


def kde_estimate(sketch: Sketch, queries: DataFrame, *, groups: int = 1) -> DataFrame:
    """``qid, est``: the estimated sum of kernel values over all items."""
    y = estimate_measurements(read_counters(sketch, query_cells(queries, sketch.params)), groups=groups)
    return y.select("qid", F.col("y").alias("est"))


def cache_hits(sketch: Sketch, probes: DataFrame, tau: float, *, groups: int = 1) -> DataFrame:
    """``qid, est, hit``: whether something close to the probe is cached."""
    return kde_estimate(sketch, probes, groups=groups).withColumn("hit", F.col("est") >= tau)


def roc(estimates: DataFrame, positives: DataFrame, taus: list[float]) -> DataFrame:
    """``tau, hit_rate, false_rate`` of estimates against the ids (qid) that should hit."""
    asked = estimates.sparkSession.createDataFrame([(float(t),) for t in taus], "tau double")
    marked = estimates.join(positives.select("qid").distinct().withColumn("should", F.lit(1)), "qid", "left").crossJoin(F.broadcast(asked))  # a few thresholds
    hit = (F.col("est") >= F.col("tau")).cast("int")
    return marked.groupBy("tau").agg(F.avg(F.when(F.col("should") == 1, hit)).alias("hit_rate"), F.avg(F.when(F.col("should").isNull(), hit)).alias("false_rate"))


def density_anomalies(sketch: Sketch, items: DataFrame, k: int, *, groups: int = 1) -> DataFrame:
    """The k items of least density (a top-k report), ties by id."""
    return kde_estimate(sketch, items, groups=groups).orderBy("est", "qid").limit(k)


__all__ = ["cache_hits", "density_anomalies", "kde_estimate", "kde_params", "kde_sketch", "roc"]
