"""Accuracy, size and cost measures of the experiments."""

from __future__ import annotations

import time
from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..sources.store import drop_stored, stored
from . import scan

ID_BYTES = 4


def recall_at(top: DataFrame, truth: DataFrame, num: int, den: int, *, v: int = 20, denom: str = "all", average: str = "macro") -> DataFrame:
    """``queries, recall``: the share of a query's true neighbours (similarity of at
    least num / den) among its first v answers, averaged over the queries that have
    any. denom ``capped`` divides by min(v, true); average ``micro`` pools all pairs."""
    true = truth.where((F.col("id") != F.col("qid")) & (F.col("inter") * den >= F.col("uni") * num)).select("qid", "id")
    found = top.where(F.col("rank") <= v).select("qid", "id", F.lit(1).alias("hit"))
    each = true.join(found, ["qid", "id"], "left").groupBy("qid").agg(F.count(F.lit(1)).alias("true"), F.count("hit").alias("hits"))
    size = F.least(F.col("true"), F.lit(v)) if denom == "capped" else F.col("true")
    if average == "micro":
        return each.agg(F.count(F.lit(1)).alias("queries"), F.try_divide(F.sum("hits"), F.sum(size)).alias("recall"))
    return each.agg(F.count(F.lit(1)).alias("queries"), F.avg(F.try_divide("hits", size)).alias("recall"))


def fixed(value: Column | str, digits: int = 6) -> Column:
    """Rounded by steps that every engine takes alike: rounding functions differ where a
    value lies just between two results."""
    x = F.col(value) if isinstance(value, str) else value
    return F.floor(x.cast("double") * F.lit(10.0**digits) + F.lit(0.5)).cast("double") / F.lit(10.0**digits)


def recall_at_each(top: DataFrame, truth: DataFrame, thresholds: Iterable[tuple[int, int]], *, v: int = 20) -> DataFrame:
    """``threshold, queries, recall`` (9 digits) for several thresholds from one join."""
    steps = list(thresholds)
    found = top.where(F.col("rank") <= v).select("qid", "id", F.lit(1).alias("hit"))
    met = truth.where("id != qid").select("qid", "id", "inter", "uni").join(found, ["qid", "id"], "left")
    near = [F.col("inter") * den >= F.col("uni") * num for num, den in steps]
    sums = [F.struct(F.lit(num / den).alias("threshold"), F.count_if(c).alias("near"), F.count_if(c & F.col("hit").isNotNull()).alias("hits")) for c, (num, den) in zip(near, steps)]
    each = met.groupBy("qid").agg(F.array(*sums).alias("x")).select(F.explode("x").alias("x")).select("x.*").where("near > 0")
    known = each.groupBy("threshold").agg(F.count(F.lit(1)).alias("queries"), F.avg(F.col("hits") / F.col("near")).alias("recall"))
    asked = top.sparkSession.createDataFrame([(num / den,) for num, den in steps], "threshold double")
    return asked.join(F.broadcast(known), "threshold", "left").select("threshold", F.coalesce("queries", F.lit(0)).cast("long").alias("queries"), fixed("recall", 9).alias("recall"))


def recall_by_band(top: DataFrame, truth: DataFrame, v: int = 20) -> DataFrame:
    """``band, pairs, recall`` by tenths of similarity."""
    found = top.where(F.col("rank") <= v).select("qid", "id", F.lit(1).alias("hit"))
    band = F.least(F.floor(F.col("inter") * 10 / F.col("uni")), F.lit(9)).cast("int")
    pairs = truth.where("id != qid").withColumn("band", band).join(found, ["qid", "id"], "left")
    return pairs.groupBy("band").agg(F.count(F.lit(1)).alias("pairs"), (F.count("hit") / F.count(F.lit(1))).alias("recall"))


def uncompressed_bytes(items: DataFrame, mode: str = "csr") -> DataFrame:
    """``bytes`` of the items as 32-bit ids: csr has one offset an item, coo two ids an entry."""
    nnz, n = F.coalesce(F.sum(F.size("elements")), F.lit(0)), F.count(F.lit(1))
    return items.agg((nnz * 2 * ID_BYTES if mode == "coo" else nnz * ID_BYTES + (n + 1) * ID_BYTES).cast("long").alias("bytes"))


def smallest_bytes(items: DataFrame) -> DataFrame:
    """``bytes`` of the items by the smallest unsigned type that holds their elements,
    one entry each, with no offsets."""
    most = F.coalesce(F.max(F.array_max("elements")), F.lit(0))
    width = F.when(most < 1 << 8, 1).when(most < 1 << 16, 2).when(most < 1 << 32, 4).otherwise(8)
    return items.agg((F.coalesce(F.sum(F.size("elements")), F.lit(0)) * width).cast("long").alias("bytes"))


def sample_bytes(sample: DataFrame) -> DataFrame:
    return uncompressed_bytes(sample)


def projection_bytes(m: int, n_items: int) -> int:
    return 4 * m * n_items


def size_ratio(compressed: Column, uncompressed: Column) -> Column:
    """Compressed by uncompressed: smaller is better; its inverse is the compression factor."""
    return F.try_divide(compressed, uncompressed)


def pareto(points: DataFrame, size: str, quality: str, by: list[str]) -> DataFrame:
    """The points that no smaller one beats, by method."""
    ties = [c for c in ("setting",) if c in points.columns]
    ahead = Window.partitionBy(*by).orderBy(size, F.desc(quality), *ties).rowsBetween(Window.unboundedPreceding, -1)
    return points.withColumn("__best", F.max(quality).over(ahead)).where(F.col("__best").isNull() | (F.col(quality) > F.col("__best"))).drop("__best")


def bytes_at_recall(points: DataFrame, target: float, by: list[str], size: str = "bytes", quality: str = "recall") -> DataFrame:
    """The least bytes at which each method reaches the target; null if it never does."""
    return points.groupBy(*by).agg(F.min(F.when(F.col(quality) >= target, F.col(size))).alias("bytes"))


def advantage(points: DataFrame, target: float, a: str, b: str) -> DataFrame:
    """``factor``: bytes that method b needs, by those of method a."""
    least = bytes_at_recall(points, target, ["method"])
    wide = least.groupBy().pivot("method", [a, b]).agg(F.first("bytes"))
    return wide.select(F.try_divide(F.col(f"`{b}`"), F.col(f"`{a}`")).alias("factor"))


def advantages(points: DataFrame, target: float, method: str) -> DataFrame:
    """``against, threshold, factor``: the same against every other method."""
    least = bytes_at_recall(points, target, ["method", "threshold"])
    own = least.where(F.col("method") == method).select("threshold", F.col("bytes").alias("own"))
    return least.where(F.col("method") != method).join(own, "threshold").select(F.col("method").alias("against"), "threshold", F.try_divide("bytes", "own").alias("factor"))


def dataset_stats(items: DataFrame) -> DataFrame:
    """``nodes, nonzeros, mean_edges, mean_similarity`` (over all pairs of two items; of
    pairs that share nothing only the number counts)."""
    kept = stored(scan.sized(items), "similarity-items")
    known = kept if kept.where("id is null").isEmpty() else stored(kept.where("id is not null"), "similarity-items")
    pairs = scan.scan_stored(known, known, "s double", scan.lower_sums, "similarity-sums").agg(F.coalesce(F.sum("s"), F.lit(0.0)).alias("s"))
    flat = stored(kept.agg(F.count(F.lit(1)).alias("nodes"), F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("nonzeros")), "similarity-nodes")
    for used in {id(kept): kept, id(known): known}.values():
        drop_stored(used)
    return flat.crossJoin(pairs).select("nodes", "nonzeros", F.try_divide("nonzeros", "nodes").alias("mean_edges"), F.try_divide(F.col("s"), F.col("nodes") * (F.col("nodes") - 1) / 2).alias("mean_similarity"))  # one row each


def estimator_error(estimates: DataFrame, exact: DataFrame) -> DataFrame:
    """``qid, bias, variance, mse`` of estimates (qid, seed, est) against (qid, s)."""
    met = estimates.join(exact, "qid", "left").withColumn("e", F.col("est") - F.coalesce("s", F.lit(0.0)))
    return met.groupBy("qid").agg(F.avg("e").alias("bias"), F.var_pop("est").alias("variance"), F.avg(F.col("e") * F.col("e")).alias("mse"))


def recovery_error(scores: DataFrame, kernel: DataFrame, eps: float) -> DataFrame:
    """``pairs, worst, within, below``: over all (query, id) scores."""
    met = scores.join(kernel, ["qid", "id"], "left").withColumn("e", F.col("score") - F.coalesce("s", F.lit(0.0)))
    return met.agg(F.count(F.lit(1)).alias("pairs"), F.max(F.abs("e")).alias("worst"), F.avg((F.abs("e") <= eps / 2).cast("int")).alias("within"), F.avg((F.col("e") < -1e-9).cast("int")).alias("below"))


def all_found_rate(top: DataFrame, exact: DataFrame, v: int) -> DataFrame:
    """``queries, all_found, each_found``: the share of queries of which all v nearest
    are reported, and the share of single neighbours."""
    found = top.where(F.col("rank") <= v).select("qid", "id", F.lit(1).alias("hit"))
    met = exact.where(F.col("rank") <= v).join(found, ["qid", "id"], "left").groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.count("hit").alias("hits"))
    return met.agg(F.count(F.lit(1)).alias("queries"), F.avg((F.col("n") == F.col("hits")).cast("int")).alias("all_found"), F.try_divide(F.sum("hits"), F.sum("n")).alias("each_found"))


def communication_bytes(grouped: DataFrame, keys: list[str], width_bits: int = 16) -> DataFrame:
    """``keys..., bytes`` that each site sends as sparse counters."""
    return grouped.groupBy(*keys).agg((F.count(F.lit(1)) * (ID_BYTES + width_bits // 8)).cast("long").alias("bytes"))


def timed(df: DataFrame) -> float:
    """Seconds to compute a frame in full without keeping it."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def mean_similarity_estimate(items: DataFrame, reps: int = 32) -> DataFrame:
    """``nodes, mean_similarity`` without comparing pairs: over ``reps`` MinHash codes
    (not re-hashed) the sum of squared counts is N plus twice the sum of J, on average."""
    from ..functions.hashing import constants
    from ..functions.lsh import minhash_code
    from ..functions.params import SketchParams

    c = constants(SketchParams(1, 1, reps, buckets=1))
    pairs = [F.struct(F.lit(o).alias("rep"), minhash_code(F.col("elements"), F.lit(int(c["alpha"][0, 0, o, 0])).cast("long"), F.lit(int(c["beta"][0, 0, o, 0])).cast("long")).alias("code")) for o in range(reps)]
    counts = items.where("size(elements) > 0").select(F.explode(F.array(*pairs)).alias("x")).groupBy("x.rep", "x.code").agg(F.count(F.lit(1)).alias("n"))
    by_rep = counts.groupBy("rep").agg(F.sum("n").alias("nodes"), F.sum(F.col("n") * F.col("n")).alias("sq"))
    return by_rep.agg(F.max("nodes").alias("nodes"), F.avg(F.try_divide(F.col("sq") - F.col("nodes"), F.col("nodes") * (F.col("nodes") - 1))).alias("mean_similarity"))
