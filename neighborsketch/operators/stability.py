"""How hard a query is: gap, tail, norms, and what follows from them.

A kernel is ``qid, id, p``: collision probabilities of one hash, for the pairs where
they are not zero (an item that shares nothing has p = 0 and adds nothing to any sum).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..functions import theory
from . import scan
from .exact import jaccard


def kernel(similarities: DataFrame) -> DataFrame:
    return similarities.where("id != qid").select("qid", "id", jaccard().alias("p"))


def stability_stats(k: DataFrame, v: int, n_items: int) -> DataFrame:
    """``qid, p_v, p_next, gap, tail, norm1, norm_tilde, status``: gap is p_{v+1} / p_v and
    tail the sum of the square roots of the others over that of the next one, at one
    hash. status: ok, unstable_tie (gap 1), empty_tail (nothing after rank v) or
    few_neighbors (fewer than v items share anything)."""
    order = Window.partitionBy("qid").orderBy(F.desc("p"), "id")
    ranked = k.withColumn("rank", F.row_number().over(order))
    at = lambda r: F.max(F.when(F.col("rank") == r, F.col("p")))
    stats = ranked.groupBy("qid").agg(
        at(v).alias("p_v"), at(v + 1).alias("p_next"),
        F.sum(F.when(F.col("rank") > v, F.sqrt("p"))).alias("root_tail"), F.sum("p").alias("norm1"), F.sum(F.sqrt("p")).alias("norm_tilde"),
    )
    return _described(stats, n_items)


def _described(stats: DataFrame, n_items: int) -> DataFrame:
    gap = F.coalesce("p_next", F.lit(0.0)) / F.col("p_v")
    status = F.when(F.col("p_v").isNull(), "few_neighbors").when(F.col("p_next").isNull(), "empty_tail").when(gap >= 1, "unstable_tie").otherwise("ok")
    return stats.select(
        "qid", "p_v", "p_next", gap.alias("gap"), F.try_divide(F.col("root_tail"), F.sqrt("p_next")).alias("tail"), "norm1", "norm_tilde", status.alias("status"), F.lit(n_items).cast("long").alias("n_items"))


def scanned_stats(items: DataFrame, queries: DataFrame, v: int, n_items: int) -> DataFrame:
    """``stability_stats`` of the MinHash kernel, without a row a pair."""
    parts = scan.scan(items, queries, scan.SUMS, scan.sums(v + 1), "kernel-stats")
    each = parts.groupBy("qid").agg(F.reverse(F.array_sort(F.flatten(F.collect_list("best")))).alias("best"), F.sum("norm1").alias("norm1"), F.sum("norm_tilde").alias("norm_tilde"))
    ahead = F.aggregate(F.slice("best", 1, v), F.lit(0.0), lambda s, p: s + F.sqrt(p))
    stats = each.select("qid", F.get("best", F.lit(v - 1)).alias("p_v"), F.get("best", F.lit(v)).alias("p_next"), (F.col("norm_tilde") - ahead).alias("root_tail"), "norm1", "norm_tilde")
    return _described(stats, n_items)


def with_hashes(stats: DataFrame) -> DataFrame:
    """Adds ``hashes``: the number of hashes that makes the query's kernel sparse."""
    return stats.withColumn("hashes", F.when(F.col("status") == "empty_tail", 1).when(F.col("status") == "few_neighbors", F.lit(None)).otherwise(theory.choose_hashes_column(F.col("tail"), F.col("gap"))).cast("int"))


def check_sparsity(k: DataFrame, hashed: DataFrame, v: int) -> DataFrame:
    """``qid, hashes, top_p, tail_sum, norm1, norm_tilde`` at each query's own number of
    hashes, and whether the three conclusions hold."""
    order = Window.partitionBy("qid").orderBy(F.desc("p"), "id")
    own = k.withColumn("rank", F.row_number().over(order)).join(hashed.where("hashes is not null").select("qid", "hashes"), "qid").withColumn("s", F.pow("p", F.col("hashes")))
    sums = own.groupBy("qid", "hashes").agg(
        F.max(F.when(F.col("rank") == v, F.col("s"))).alias("top_p"), F.coalesce(F.sum(F.when(F.col("rank") > v, F.col("s"))), F.lit(0.0)).alias("tail_sum"),
        F.sum("s").alias("norm1"), F.sum(F.sqrt("s")).alias("norm_tilde"))
    eps = 1e-9
    return sums.select("*", (F.col("top_p") >= F.col("tail_sum") - eps).alias("tail_below"), (F.col("norm1") <= v + 1 + eps).alias("norm1_bounded"), (F.col("norm_tilde") <= v + 1 + eps).alias("tilde_bounded"))


def kernel_norms(k: DataFrame, hashes: int) -> DataFrame:
    s = F.pow("p", F.lit(hashes))
    return k.groupBy("qid").agg(F.sum(s).alias("norm1"), F.sum(F.sqrt(s)).alias("norm_tilde"))


def variance_bound(k: DataFrame, hashes: int) -> DataFrame:
    """``qid, bound``: the counter's variance is at most the square of the root norm."""
    return kernel_norms(k, hashes).select("qid", (F.col("norm_tilde") * F.col("norm_tilde")).alias("bound"))


def hashes_tradeoff(k: DataFrame, v: int, most: int, n_items: int, delta: float = 0.01) -> DataFrame:
    """``qid, hashes, norm1, norm_tilde, eps, arrays``: more hashes make the kernel
    sparser, but the gap to tell apart smaller."""
    order = Window.partitionBy("qid").orderBy(F.desc("p"), "id")
    each = k.withColumn("rank", F.row_number().over(order)).withColumn("hashes", F.explode(F.sequence(F.lit(1), F.lit(most)))).withColumn("s", F.pow("p", F.col("hashes")))
    at = lambda r: F.coalesce(F.max(F.when(F.col("rank") == r, F.col("s"))), F.lit(0.0))
    sums = each.groupBy("qid", "hashes").agg(F.sum("s").alias("norm1"), F.sum(F.sqrt("s")).alias("norm_tilde"), (at(v) - at(v + 1)).alias("eps"))
    return sums.withColumn("arrays", theory.arrays_needed_column(F.col("norm1"), F.col("norm_tilde"), F.col("eps"), delta, F.lit(float(n_items))))


def is_unstable(k: DataFrame, n_items: int, eps: float, most: float = 0.5) -> DataFrame:
    """``qid, near, unstable``: the share of items within (1 + eps) times the least
    distance 1 - p; unstable if that is most of them. Items that share nothing are at
    distance 1."""
    closest = k.groupBy("qid").agg(F.min(1 - F.col("p")).alias("d0"), F.count(F.lit(1)).alias("sharing"))
    reach = (1 + eps) * F.col("d0") + theory.GUARD
    met = k.join(closest, "qid").groupBy("qid", "d0", "sharing").agg(F.sum(F.when(1 - F.col("p") <= reach, 1).otherwise(0)).alias("near"))
    total = F.col("near") + F.when(reach >= 1, F.lit(n_items - 1) - F.col("sharing")).otherwise(0)
    share = total / F.lit(float(max(1, n_items - 1)))
    return met.select("qid", share.alias("near"), (share > most).alias("unstable"))


def with_exponent(stats: DataFrame, code_range: int) -> DataFrame:
    """Adds ``b``, and whether it promises sublinear memory."""
    b = theory.memory_exponent_column(F.col("p_v"), code_range, F.col("gap"))
    return stats.withColumn("b", b).withColumn("sublinear", F.coalesce(F.col("b") < 1, F.lit(False)))


def coverage(with_b: DataFrame, values: list[float]) -> DataFrame:
    """``b, covered, guaranteed``: how many queries a committed exponent covers."""
    spark = with_b.sparkSession
    asked = spark.createDataFrame([(float(x),) for x in values], "committed double")
    joined = with_b.select("b").crossJoin(F.broadcast(asked))  # a few values
    return joined.groupBy("committed").agg(F.sum(F.when(F.col("b") <= F.col("committed"), 1).otherwise(0)).alias("guaranteed"), F.count(F.lit(1)).alias("queries")).select("committed", "guaranteed", "queries", (F.col("guaranteed") / F.col("queries")).alias("covered"))


def geometry_class(stats: DataFrame, flat: float = 0.5) -> DataFrame:
    """Adds ``geometry``: equidistant (the tail is nearly as long as the data), sparse
    (it is short), or between."""
    share = F.col("tail") / F.col("n_items")
    return stats.withColumn("geometry", F.when(F.col("tail").isNull() | (share < 0.01), "sparse").when(share >= flat, "equidistant").otherwise("between"))
