"""Exact answers from the stored data: the naive scan, and the ground truth."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..sources.store import stored
from . import scan
from .decode import SEARCHED, SENT, best, nearest_of, query_blocks

SALTS = 16
PREFIX_SHARES = 4
QUERY_BLOCK = 4096


def overlaps(items: DataFrame, queries: DataFrame) -> DataFrame:
    """``qid, id, inter, uni`` of all pairs that share an element (set form on both
    sides). An inverted index: both sides meet by element; an element that many items
    have is dealt out over salts on the item side and copied on the query side, which
    is a stated set."""
    left = queries.select(F.col("id").alias("qid"), F.size("elements").alias("nq"), F.explode("elements").alias("element"), F.sequence(F.lit(0), F.lit(SALTS - 1)).alias("salts"))
    left = left.select("qid", "nq", "element", F.explode("salts").alias("salt"))
    right = items.select("id", F.size("elements").alias("ni"), F.explode("elements").alias("element")).withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(SALTS)).cast("int"))
    shared = right.join(left, ["element", "salt"]).groupBy("qid", "id").agg(F.count(F.lit(1)).alias("inter"), F.first("nq").alias("nq"), F.first("ni").alias("ni"))
    return shared.select("qid", "id", "inter", (F.col("nq") + F.col("ni") - F.col("inter")).cast("long").alias("uni"))


def set_classes(items: DataFrame) -> DataFrame:
    """``head, elements`` of the distinct sets, and each item's head: equal sets, told by
    128 bits of hash and their size, are one class with the smallest id as its head."""
    marked = items.select("id", "elements", F.xxhash64("elements").alias("s1"), F.xxhash64(F.lit(1), "elements").alias("s2"))
    return marked.groupBy("s1", "s2", F.size("elements").alias("n")).agg(F.min("id").alias("head"), F.count(F.lit(1)).alias("members"))


def close_classes(items: DataFrame, num: int, den: int) -> tuple[DataFrame, DataFrame]:
    """Pairs of different sets with Jaccard of at least num / den (``a, b, inter, uni``
    by class heads, both directions), and membership (``id, head, members``). Classes
    are linear in the input however many copies a set has; ``close_pairs`` expands them.

    Only the rarest elements of each set, as many as a close pair must share
    ``PREFIX_SHARES`` of (all, if it may share fewer), are counted against each other
    (prefix and size filters); survivors are compared exactly. Elements that a single
    class has match nothing and are dropped before anything is ordered."""
    classes = stored(set_classes(items), "set-classes")
    marked = items.select("id", "elements", F.xxhash64("elements").alias("s1"), F.xxhash64(F.lit(1), "elements").alias("s2"), F.size("elements").alias("n"))
    members = stored(marked.join(classes, ["s1", "s2", "n"]).select("id", "head", "members", F.when(F.col("id") == F.col("head"), F.col("elements")).alias("elements")), "set-members")
    heads = members.where("id = head").select("id", "elements", F.size("elements").alias("n"))
    each = heads.select("id", "n", F.explode("elements").alias("element"))
    counts = each.groupBy("element").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    shared = each.join(counts, "element").groupBy("id", "n").agg(F.sort_array(F.collect_list(F.struct("df", "element"))).alias("own"))
    # elements of a single set come first in its order and match nothing: only their number counts
    first = F.col("n") - F.ceil(F.col("n") * num / den - 1e-9) + PREFIX_SHARES - (F.col("n") - F.size("own"))
    prefix = shared.where(first > 0).select("id", "n", F.transform(F.slice("own", F.lit(1), first.cast("int")), lambda x: x["element"]).alias("elements"))
    candidates = scan.scan(prefix, prefix, "a long, b long", scan.sharing_several(num, den, PREFIX_SHARES), "close-candidates").distinct()
    one, two = heads.select(F.col("id").alias("a"), F.col("elements").alias("x")), heads.select(F.col("id").alias("b"), F.col("elements").alias("y"))
    inter = F.size(F.array_intersect("x", "y"))
    both = candidates.join(one, "a").join(two, "b").select("a", "b", inter.cast("long").alias("inter"), (F.size("x") + F.size("y") - inter).cast("long").alias("uni"))
    close = stored(both.where(F.col("inter") * den >= F.col("uni") * num), "close-classes")
    return close.unionByName(close.select(F.col("b").alias("a"), F.col("a").alias("b"), "inter", "uni")), members.select("id", "head", "members", "elements")


def close_pairs(items: DataFrame, num: int, den: int) -> DataFrame:
    """``qid, id, inter, uni`` with Jaccard of at least num / den, in both directions.
    Expands the classes: for m equal sets these are m * (m - 1) rows."""
    close, members = close_classes(items, num, den)
    mine, other = members.select(F.col("id").alias("qid"), F.col("head").alias("a")), members.select("id", F.col("head").alias("b"))
    across = close.join(mine, "a").join(other, "b").select("qid", "id", "inter", "uni")
    copied = members.where("members > 1")
    size = copied.where("id = head").select(F.col("head").alias("b"), F.size("elements").cast("long").alias("inter"))
    within = copied.select(F.col("id").alias("qid"), F.col("head").alias("a")).join(copied.select("id", F.col("head").alias("b")), F.col("a") == F.col("b")).where("id != qid").join(size, "b").select("qid", "id", "inter", F.col("inter").alias("uni"))
    return across.unionByName(within)


def close_items(items: DataFrame, num: int, den: int) -> DataFrame:
    """``id, links``: the items with another at least that similar, and how many: a row
    an item, however many copies a set has."""
    close, members = close_classes(items, num, den)
    sizes = members.where("id = head").select(F.col("head").alias("b"), F.col("members").alias("k"))
    links = close.join(sizes, "b").groupBy(F.col("a").alias("head")).agg(F.sum("k").alias("others"))
    return members.join(links, "head", "left").select("id", (F.coalesce("others", F.lit(0)) + F.col("members") - 1).alias("links")).where("links > 0")


def jaccard(inter: Column | str = "inter", uni: Column | str = "uni") -> Column:
    column = lambda c: F.col(c) if isinstance(c, str) else c
    return F.try_divide(column(inter), column(uni))


def exact_top(similarities: DataFrame, v: int, *, exclude_own: bool = True) -> DataFrame:
    """``qid, rank, id, inter, uni``: the v most similar items, ties by id. Fractions of
    integers below 2**26 that differ are different doubles, and equal ones equal."""
    found = similarities.where("id != qid") if exclude_own else similarities
    order = Window.partitionBy("qid").orderBy(F.desc(F.col("inter") / F.col("uni")), "id")
    return found.withColumn("rank", F.row_number().over(order).cast("long")).where(F.col("rank") <= v).select("qid", "rank", "id", "inter", "uni")


def dot_products(vectors: DataFrame, queries: DataFrame) -> DataFrame:
    """``qid, id, score``: inner products of the stated set of queries with all vectors."""
    dot = F.aggregate(F.zip_with("q", "elements", lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda s, x: s + x)
    return meet_blocks(vectors, queries).where("id != qid").select("qid", "id", dot.alias("score"))


def top_products(vectors: DataFrame, queries: DataFrame, v: int) -> DataFrame:
    """``qid, rank, id, score``: the v largest inner products of whole-number vectors,
    exactly, ties by id. The queries go out in blocks; numpy multiplies whole batches."""
    out = vectors.sparkSession.createDataFrame([], "qid long, id long, score long")
    for block in query_blocks(queries, "id", "elements", SENT):
        shipped = vectors.sparkSession.sparkContext.broadcast(block)

        def run(batches: Iterable[pa.RecordBatch], shipped=shipped) -> Iterator[pa.RecordBatch]:
            q, y = shipped.value
            for batch in batches:
                if not batch.num_rows:
                    continue
                own = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
                x = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(len(own), -1)
                if float(np.abs(x).max(initial=0)) * float(np.abs(y).max(initial=0)) * x.shape[1] >= 2**53:
                    raise ValueError("these products are not exact as 64-bit floats")
                x, place = x.astype(np.float64), {i: at for at, i in enumerate(own.tolist())}
                for begin in range(0, len(q), SEARCHED):
                    some = q[begin : begin + SEARCHED]
                    far = -(y[begin : begin + SEARCHED] @ x.T)
                    mine = [(at, place[i]) for at, i in enumerate(some.tolist()) if i in place]
                    if mine:
                        far[tuple(np.array(mine).T)] = np.inf
                    found = nearest_of(some, own, far, v)
                    yield pa.record_batch([found.column(0), found.column(1), found.column(2).cast(pa.int64())], ["qid", "id", "score"])

        out = out.unionByName(vectors.select(F.col("id").cast("long").alias("id"), "elements").mapInArrow(run, "qid long, id long, score long"))
    return best(out, v)


def meet_blocks(vectors: DataFrame, queries: DataFrame) -> DataFrame:
    """``id, elements, qid, q``: every vector beside every query. Up to ``QUERY_BLOCK``
    queries are broadcast; more are dealt out in blocks of about that size, and a copy
    of the vectors goes to each."""
    left = stored(queries.select(F.col("id").alias("qid"), F.col("elements").alias("q")), "queries")
    n_blocks = -(-left.count() // QUERY_BLOCK)
    if n_blocks <= 1:
        return vectors.select("id", "elements").crossJoin(F.broadcast(left))  # at most QUERY_BLOCK rows
    dealt = left.withColumn("block", F.pmod(F.xxhash64("qid"), F.lit(n_blocks)).cast("int"))
    copies = vectors.select("id", "elements", F.explode(F.sequence(F.lit(0), F.lit(n_blocks - 1))).alias("block"))
    return copies.join(dealt, "block").drop("block")


def top_similar(items: DataFrame, queries: DataFrame, v: int) -> DataFrame:
    """``exact_top`` of ``overlaps``, of which only each query's v best are written."""
    return exact_top(scan.scan(items, queries, scan.TOP, scan.top_similar(v), "similar"), v)


def kernel_sums(items: DataFrame, queries: DataFrame, hashes: int) -> DataFrame:
    """``exact_kde`` of ``overlaps`` with other items, without a row a pair."""
    return scan.scan(items, queries, "qid long, s double", scan.powers(hashes), "kernel-sums").groupBy("qid").agg(F.sum("s").alias("s"))


def exact_kernel(similarities: DataFrame, hashes: int) -> DataFrame:
    """``qid, id, s``: the kernel values of the pairs that are not zero (MinHash: p = J)."""
    return similarities.select("qid", "id", F.pow(jaccard(), F.lit(hashes)).alias("s"))


def exact_kde(similarities: DataFrame, hashes: int) -> DataFrame:
    """``qid, s``: the exact sum of kernel values over all items."""
    return exact_kernel(similarities, hashes).groupBy("qid").agg(F.sum("s").alias("s"))


def rerank(reported: DataFrame, items: DataFrame, queries: DataFrame) -> DataFrame:
    """Reported neighbours in the order of their exact similarity, where items exist."""
    pairs = reported.select("qid", "id").join(queries.select(F.col("id").alias("qid"), F.col("elements").alias("q")), "qid").join(items.select("id", "elements"), "id")
    inter = F.size(F.array_intersect("q", "elements")).cast("long")
    return exact_top(pairs.select("qid", "id", inter.alias("inter"), (F.size("q") + F.size("elements") - inter).alias("uni")), 1 << 30, exclude_own=False)
