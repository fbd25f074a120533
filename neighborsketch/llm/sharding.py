"""Sharding by a minimax contiguous partition.

Equal texts form atomic groups. The groups lie in one fixed order (by digest)
and each shard takes a contiguous run of them; the smallest capacity for which
a greedy walk needs no more than the given number of shards is found by binary
search, and the cuts are set within it, as evenly as it allows.

The walk runs on the driver, which knows the first and the last group start of each
cell of ``total / (shards * resolution)`` bytes. What lies between these is unknown:
cuts at known starts alone bound the capacity from above, cuts anywhere between
them from below. While the bounds differ, only the cells that a cut could fall into
are cut finer, so each round fetches about ``shards * resolution`` rows at most and
the result is the optimum over all groups.

Nothing unbounded meets in a task: a group is counted in salted parts, prefix
sums run per bucket of about ``BUCKET_ROWS`` parts, below them over the totals of the
buckets with the same first digits and then over those digits' totals, and rows are
numbered within their own (group, salt).

Edge cases: null text counts as empty with 8 bytes; rows that repeat stay in one
group and get slots of their own; null ids sort first in their group; an empty
table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from bisect import bisect_left, bisect_right
from itertools import accumulate

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import row_salt, salts_for, stored, table, whole

SHARDS = 24
RESOLUTION = 4096
BUCKET_ROWS = 20_000
TOP_DIGITS = 4


def greedy_cuts(sizes: list[int], capacity: int) -> list[int]:
    """Where a greedy walk opens its shards: indexes of their first units."""
    cuts, used = [0], 0
    for i, size in enumerate(sizes):
        if used + size > capacity and used:
            cuts.append(i)
            used = 0
        used += size
    return cuts


def minimax_cuts(sizes: list[int], shards: int) -> tuple[int, list[int]]:
    """The smallest feasible capacity over the ordered sizes, and its cuts."""
    if not sizes:
        return 0, [0]
    low, high = max(max(sizes), -(-sum(sizes) // shards)), sum(sizes)
    while low < high:
        middle = (low + high) // 2
        if len(greedy_cuts(sizes, middle)) <= shards:
            high = middle
        else:
            low = middle + 1
    return low, even_cuts(sizes, shards, low)


def even_cuts(sizes: list[int], shards: int, capacity: int) -> list[int]:
    """Cuts that keep the capacity and lie nearest to equal shares of what is left: a
    plain greedy walk fills its first shards and leaves the last one short."""
    ends = [0, *accumulate(sizes)]
    n, earliest, i = len(sizes), [0] * (shards + 1), len(sizes)
    for j in range(shards - 1, 0, -1):  # from where the shards j and later can hold the rest
        used = 0
        while i and used + sizes[i - 1] <= capacity:
            used += sizes[i - 1]
            i -= 1
        earliest[j] = i
    cuts = [0]
    for j in range(1, shards):
        last = cuts[-1]
        aim = ends[last] + (ends[n] - ends[last]) / (shards - j + 1)
        near = bisect_left(ends, aim)
        if near and aim - ends[near - 1] < ends[near] - aim:
            near -= 1
        furthest = bisect_right(ends, ends[last] + capacity) - 1
        cut = min(max(near, earliest[j], last + 1), furthest)
        if cut >= n:
            break
        cuts.append(cut)
    return cuts


def walk(ends: list[int], between: list[bool], shards: int, capacity: int, anywhere: bool) -> tuple[bool, list[int]]:
    """Whether a greedy walk fits, and its cuts. ``between[i]``: starts that aren't
    known may lie after ``ends[i]``; ``anywhere``: a cut may fall on any byte there."""
    at, cuts = 0, []
    for _ in range(shards):
        if at + capacity >= ends[-1]:
            return True, cuts
        i = bisect_right(ends, at + capacity) - 1
        to = at + capacity if anywhere and between[i] else ends[i]
        if to <= at:
            break
        at = to
        cuts.append(at)
    return False, cuts


def least_capacity(ends: list[int], between: list[bool], shards: int, anywhere: bool) -> int:
    low, high = -(-ends[-1] // shards), ends[-1]
    while low < high:
        middle = (low + high) // 2
        if walk(ends, between, shards, middle, anywhere)[0]:
            high = middle
        else:
            low = middle + 1
    return low


def open_gaps(ends: list[int], between: list[bool], shards: int, low: int, high: int) -> list[int]:
    """The unknown stretches that a cut of a capacity from low to high may fall into."""
    first, last = walk(ends, between, shards, low, False)[1], walk(ends, between, shards, high, True)[1]
    found = set()
    for k, a in enumerate(first):
        b = last[k] if k < len(last) else ends[-1]
        found.update(i for i in range(bisect_right(ends, a) - 1, bisect_right(ends, b)) if i < len(between) and between[i])
    return sorted(found)


def exact_cuts(placed: DataFrame, total: int, shards: int, resolution: int) -> list[tuple[int, int]]:
    """``(start, row)`` of each shard's first group."""
    cells = shards * resolution
    cell = max(1, total // cells)
    edges = [f("group_start") for f in (F.min, F.max)] + [f("group_row") for f in (F.min, F.max)]
    held = placed.withColumn("cell", F.floor(F.col("group_start") / F.lit(cell)))
    units = held.groupBy("cell").agg(*edges).collect()  # at most shards * resolution + 1 rows, whatever the input
    if not units:
        return [(0, 0)]
    row_of, unknown = {}, set()

    def learn(found: list[tuple[int, int, int, int]]) -> None:
        for a, b, row_a, row_b in found:
            row_of[a], row_of[b] = row_a, row_b
            if b > a + 1:
                unknown.add(a)

    learn([tuple(u)[1:] for u in units])
    while True:
        ends = [*sorted(row_of), total]
        between = [a in unknown for a in ends[:-1]]
        low, high = (least_capacity(ends, between, shards, anywhere) for anywhere in (True, False))
        if low == high:
            break
        gaps = open_gaps(ends, between, shards, low, high)
        parts = max(2, cells // len(gaps))
        rows = [(ends[i] // cell, ends[i], ends[i + 1], -(-(ends[i + 1] - ends[i]) // parts)) for i in gaps]
        table_ = F.broadcast(placed.sparkSession.createDataFrame(rows, "cell long, a long, b long, width long"))
        inside = held.join(table_, "cell").where("group_start > a and group_start < b")
        found = inside.groupBy("a", F.floor((F.col("group_start") - F.col("a")) / F.col("width")).alias("part")).agg(*edges).collect()  # at most about shards * resolution rows
        unknown -= {ends[i] for i in gaps}
        learn([tuple(u)[2:] for u in found])
    sizes = [b - a for a, b in zip(ends, ends[1:])]
    return [(ends[i], row_of[ends[i]]) for i in even_cuts(sizes, shards, low)]


def _ahead(totals: DataFrame, digits: int) -> DataFrame:
    """``bucket, bytes_ahead, rows_ahead`` of ``bucket, b, k``: what lies before each
    bucket. One task orders at most ``16 ** TOP_DIGITS`` rows, whatever the input."""
    sums = lambda w: [F.coalesce(F.sum(c).over(w.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) for c in ("b", "k")]
    if digits <= TOP_DIGITS:
        b, k = sums(Window.partitionBy(F.lit(0)))
        return totals.select("bucket", b.alias("bytes_ahead"), k.alias("rows_ahead"))
    top = F.substring("bucket", 1, digits - TOP_DIGITS)
    above = _ahead(totals.groupBy(top.alias("bucket")).agg(F.sum("b").alias("b"), F.sum("k").alias("k")), digits - TOP_DIGITS)
    above = above.select(F.col("bucket").alias("top"), F.col("bytes_ahead").alias("bytes_above"), F.col("rows_ahead").alias("rows_above"))
    b, k = sums(Window.partitionBy("top"))
    return totals.withColumn("top", top).select("bucket", "top", b.alias("b"), k.alias("k")).join(above, "top").select("bucket", (F.col("b") + F.col("bytes_above")).alias("bytes_ahead"), (F.col("k") + F.col("rows_above")).alias("rows_ahead"))


def assign(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", shards: int = SHARDS, resolution: int = RESOLUTION, salts: int | None = None) -> DataFrame:
    """``doc_id, size, text_crc32, law, shard, slot, grown_shard`` for each row."""
    text = whole(text_col)
    rows = docs.select(
        F.col(id_col).alias("doc_id"), (F.octet_length(text) + 8).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"), F.md5(text.cast("binary")).alias("group"), row_salt(id_col, salts or salts_for(docs)).alias("salt"),
    )
    parts = stored(rows.groupBy("group", "salt").agg(F.sum("size").alias("bytes"), F.count(F.lit(1)).alias("n")), "shard-parts")
    n_parts, total = parts.agg(F.count(F.lit(1)), F.coalesce(F.sum("bytes"), F.lit(0))).first()
    digits = 2
    while 16**digits * BUCKET_ROWS < n_parts:
        digits += 1
    parts = parts.withColumn("bucket", F.substring("group", 1, digits))
    totals = _ahead(parts.groupBy("bucket").agg(F.sum("bytes").alias("b"), F.sum("n").alias("k")), digits)
    inside = Window.partitionBy("bucket").orderBy("group", "salt").rowsBetween(Window.unboundedPreceding, -1)
    placed = parts.join(totals, "bucket").withColumns({
        "start": F.col("bytes_ahead") + F.coalesce(F.sum("bytes").over(inside), F.lit(0)),
        "row0": F.col("rows_ahead") + F.coalesce(F.sum("n").over(inside), F.lit(0)),
    })
    placed = stored(placed.withColumns({
        "group_start": F.min("start").over(Window.partitionBy("bucket", "group")),
        "group_row": F.min("row0").over(Window.partitionBy("bucket", "group")),
    }).select("group", "salt", "row0", "group_start", "group_row", "bytes"), "shard-places")
    firsts = exact_cuts(placed, total, shards, resolution)
    starts = F.array(*[F.lit(int(b)).cast("long") for b, _ in firsts])
    first_rows = F.array(*[F.lit(int(r)).cast("long") for _, r in firsts])
    shard = F.size(F.filter(starts, lambda x: x <= F.col("group_start"))) - 1
    where = placed.select("group", "salt", "row0", shard.alias("shard")).withColumn("row0", F.col("row0") - F.element_at(first_rows, F.col("shard") + 1))
    rank = F.row_number().over(Window.partitionBy("group", "salt").orderBy("doc_id")) - 1
    return rows.join(where, ["group", "salt"]).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"),
        (F.col("row0") + rank).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"),
    )


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return assign(table(spark, sf_dir, "documents"))
