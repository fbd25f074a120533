r"""Benchmark decontamination in built-in expressions.

A document is contaminated by a benchmark item if some window of the item's
number of words has a weighted shingle similarity of at least ``NUMERATOR /
DENOMINATOR`` with it: shingles of five words (of all words, if the item has
fewer), weighted by how often they occur, sum of minima over sum of maxima. Words
are runs of letters and digits in lower case, so case and punctuation don't count.

1. *Windows.* A window has as many words as some item. One that reaches the
   similarity has at least ``need`` of its shingle positions in common with that
   item, so the longest run of these is at least ``least_run`` long: looking up every
   ``stride``-th shingle of a document, the stride being the least such run over all
   items, finds every document that can match. Around the hits all positions are
   looked up, and the windows of an item length with at least ``need`` positions whose
   shingle *some item of that length* has are kept. This prefilter knows lengths only,
   not items, and loses nothing.
2. *Fingerprints.* Every distinct window and every item gets a 128-bit SimHash of its
   shingles, the copies of one shingle numbered, so that distance follows the weighted
   similarity however often shingles repeat.
3. *Multi-index search.* Fingerprints are cut into eight blocks of 16 bits. Two within
   ``RADIUS`` bits differ in at most ``t`` bits in some block, where the ``t`` of all
   blocks, plus one each, add up to ``RADIUS + 1``. A window looks itself up with all
   ways to flip ``t // 2`` bits of a block, among the items of its length with all ways
   to flip the rest, so the join by block value finds every pair within the radius;
   its condition counts all bits. A random pair agrees in some block with a chance of
   18 %. What the index doesn't find is never compared. At the least similarity a bit
   differs with a chance of 0.151, so that a pair is lost with one of 4e-5 (binomial
   law), and in the worst case, four shingles against an item of five, of 5e-3.
4. *Verification* compares the numbered shingles of window and item.

The items' shingles and block values, and the documents with hits, are broadcast only
if there are at most ``BROADCAST_ROWS``; beyond that they meet by shuffle joins, whose
skewed keys are split at run time.

Edge cases: a null or empty text, or one without words, is clean; items without
words or with a null id never match; a document shorter than an item is held
against it whole; equal items all match, as do the texts of a repeated item id;
repeated rows get equal results; texts are read whole; an empty table on either side
gives clean rows or none; other columns, whatever their names, are not read by
:func:`report` and come back untouched from :func:`drop_contaminated`.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import cache

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import free_name, stored, table, whole

WORDS = 5
NUMERATOR, DENOMINATOR = 4, 5
RADIUS = 35
BLOCKS, BLOCK_BITS = 8, 16
BROADCAST_ROWS = 500_000


def words(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), "")


def shingle_words(n_words: Column) -> Column:
    """The words of a shingle of an item of so many words."""
    return F.least(F.lit(WORDS), n_words)


def least_run(n_shingles: int) -> int:
    """The shortest possible longest run of shared shingle positions."""
    need = -(-2 * NUMERATOR * n_shingles // (NUMERATOR + DENOMINATOR))
    return max(1, -(-need // (n_shingles - need + 1)))


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of an array, which inner functions share: without the name that an
    array of one element gives it they would compute it anew for each element."""
    return F.flatten(F.transform(F.array(value), body))


def _hashes(tokens: Column, k: Column | int, stride: int = 1) -> Column:
    """``at, hash`` of every ``stride``-th run of k words; none if there are fewer words."""
    k = F.lit(k) if isinstance(k, int) else k
    last = F.size(tokens) - k
    runs = F.transform(F.sequence(F.lit(0), F.greatest(last, F.lit(0)), F.lit(stride)), lambda i: F.struct(i.alias("at"), F.xxhash64(F.array_join(F.slice(tokens, i + 1, k), " ")).alias("hash")))
    return F.when((last >= 0) & (k > 0), runs).otherwise(F.array().cast("array<struct<at:int,hash:long>>"))


def numbered(hashes: Column) -> Column:
    """Features of a bag of shingles: each with the number of its copy (0, 1, ...), so
    that two bags share as many features as the sum of their minima."""
    return _let(F.array_sort(hashes), lambda hs: F.transform(hs, lambda h, i: F.xxhash64(h, i - F.array_position(hs, h).cast("int") + 1)))


def with_prints(rows: DataFrame, keys: list[str], lane: int = 16) -> DataFrame:
    """``keys..., print_a, print_b`` of rows with ``features``: 128 bits, each the
    majority of the features' hash bits. A long adds up the votes on ``64 / lane`` bits
    at once, in lanes of ``lane`` bits; a lane holds up to ``2 ** (lane - 1)`` votes."""
    group, full = 64 // lane, (1 << lane) - 1
    factor, ones = sum(1 << i * (lane - 1) for i in range(group)), sum(1 << i * lane for i in range(group))
    each = rows.select(*keys, F.explode("features").alias("f")).select(*keys, "f", F.xxhash64("f", F.lit(1)).alias("g"))
    votes = [F.expr(f"sum(((shiftrightunsigned({h}, {j * group}) & {(1 << group) - 1}L) * {factor}L) & {ones}L) AS {h}{j}") for h in "fg" for j in range(lane)]
    sums = each.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), *votes)

    def majority(h: str) -> Column:
        count = lambda b: f"(shiftrightunsigned({h}{b // group}, {lane * (b % group)}) & {full}L)"
        return F.expr(" | ".join(f"if(2 * {count(b)} > n, shiftleft(1L, {b}), 0L)" for b in range(64)))

    return sums.select(*keys, majority("f").alias("print_a"), majority("g").alias("print_b"))


def block_bounds(radius: int = RADIUS) -> list[int]:
    """The most bits t in which a block differs, for all blocks: two fingerprints that
    differ in more in every block are more than ``radius`` apart."""
    return [(radius + 1) // BLOCKS + (i < (radius + 1) % BLOCKS) - 1 for i in range(BLOCKS)]


@cache
def flip_masks(most: int) -> list[int]:
    return [m for m in range(1 << BLOCK_BITS) if m.bit_count() <= most]


def block_keys(n_words: Column, flips: list[int]) -> Column:
    """A key for each block and each way to flip at most so many of its bits."""
    def near(i: int, most: int) -> Column:
        masks = F.expr(f"array({', '.join(f'{m}L' for m in flip_masks(most))})")
        own = F.shiftrightunsigned(F.col("print_a" if i < BLOCKS // 2 else "print_b"), BLOCK_BITS * (i % (BLOCKS // 2))).bitwiseAND(F.lit((1 << BLOCK_BITS) - 1).cast("long"))
        place = (n_words.cast("long") * BLOCKS + i) * (1 << BLOCK_BITS) + own
        return _let(place, lambda p: F.transform(masks, lambda m: p.bitwiseXOR(m)))

    return F.flatten(F.array(*[near(i, most) for i, most in enumerate(flips)]))


def _items(benchmark: DataFrame, item_col: str, text_col: str) -> DataFrame:
    own = benchmark.select(F.col(item_col).cast("long").alias("item_id"), words(whole(text_col)).alias("tokens")).where("item_id is not null and size(tokens) > 0")
    hashed = own.select("item_id", F.size("tokens").alias("n_words"), F.transform(_hashes(F.col("tokens"), shingle_words(F.size("tokens"))), lambda s: s["hash"]).alias("hashes"))
    return hashed.withColumn("features", numbered(F.col("hashes"))).withColumn("item_key", F.xxhash64("item_id", "n_words", "features")).dropDuplicates(["item_key"])


def _bounded(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def _piece(tokens: Column, w: Column) -> Column:
    """The words that the windows of one length around the hits cover, and how many
    starts these have."""
    spread = w["n_words"] - shingle_words(w["n_words"])
    end = F.greatest(F.size(tokens) - w["n_words"], F.lit(0))
    low = F.least(F.greatest(w["first"] - spread, F.lit(0)), end)
    high = F.least(w["last"], end)
    return F.struct(w["n_words"].alias("n_words"), low.alias("low"), (high - low).alias("room"), F.slice(tokens, low + 1, high - low + w["n_words"]).alias("tokens"))


def _starts() -> Column:
    """The starts of all windows of a piece with enough known positions: those that
    hold some ``need`` known positions in a row."""
    n = F.col("n_words") - shingle_words(F.col("n_words")) + 1
    need = F.ceil(F.lit(NUMERATOR) * (n + F.least(n, F.size("hashes"))) / F.lit(NUMERATOR + DENOMINATOR)).cast("int")

    def around(i: Column) -> Column:
        first, last = F.get("known", i), F.get("known", i + need - 1)
        low, high = F.greatest(last - n + 1, F.lit(0)), F.least(first, F.col("room"))
        return F.when(low <= high, F.sequence(low, F.greatest(low, high))).otherwise(F.array().cast("array<int>"))

    some = F.size("known") - need
    return F.when(some >= 0, F.array_distinct(F.flatten(F.transform(F.sequence(F.lit(0), F.greatest(some, F.lit(0))), around)))).otherwise(F.array().cast("array<int>"))


def windows(docs: DataFrame, items: DataFrame, lengths: dict[int, int], *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, row_key, n_words, start, features``: all windows worth a fingerprint.
    lengths: how many items have so many words."""
    index = items.select("n_words", F.explode(F.array_distinct("hashes")).alias("hash")).distinct()
    index = _bounded(index, sum(n * k for n, k in lengths.items()))
    keyed = docs.select(F.col(id_col).cast("long").alias("doc_id"), whole(text_col).alias("text")).withColumn("row_key", F.xxhash64("text"))
    split = keyed.select("doc_id", "row_key", words(F.col("text")).alias("tokens"))
    strides = {k: min(least_run(n - k + 1) for n in lengths if min(WORDS, n) == k) for k in sorted({min(WORDS, n) for n in lengths})}
    looked = F.concat(*[_hashes(F.col("tokens"), k, stride) for k, stride in strides.items()])
    hits = split.select("doc_id", "row_key", F.explode(looked).alias("s")).select("doc_id", "row_key", "s.at", "s.hash").join(index, "hash")
    hits = hits.groupBy("doc_id", "row_key", "n_words").agg(F.min("at").alias("first"), F.max("at").alias("last"))
    held = hits.groupBy("doc_id", "row_key").agg(F.collect_list(F.struct("n_words", "first", "last")).alias("held"))
    held = stored(held.withColumnsRenamed({"doc_id": "hit_id", "row_key": "hit_key"}), "benchmark-hits")
    met = keyed.join(_bounded(held, held.agg(F.coalesce(F.sum(F.size("held")), F.lit(0))).first()[0]), F.col("doc_id").eqNullSafe(F.col("hit_id")) & (F.col("row_key") == F.col("hit_key")))
    placed = met.select("doc_id", "row_key", words(F.col("text")).alias("tokens"), "held")
    pieces = placed.select("doc_id", "row_key", F.explode(F.transform("held", lambda w: _piece(F.col("tokens"), w))).alias("w")).select("doc_id", "row_key", "w.*")
    each = pieces.select("doc_id", "row_key", "n_words", "low", "room", F.explode(_hashes(F.col("tokens"), shingle_words(F.col("n_words")))).alias("s"))
    marked = each.select("doc_id", "row_key", "n_words", "low", "room", "s.at", "s.hash").join(index.withColumn("own", F.lit(True)), ["n_words", "hash"], "left")
    back = marked.groupBy("doc_id", "row_key", "n_words", "low", "room").agg(F.sort_array(F.collect_set(F.struct("at", "hash", "own"))).alias("s"))  # one text at most
    ready = back.select("doc_id", "row_key", "n_words", "low", "room", F.transform("s", lambda x: x["hash"]).alias("hashes"), F.transform(F.filter("s", lambda x: x["own"]), lambda x: x["at"]).alias("known"))
    n = F.col("n_words") - shingle_words(F.col("n_words")) + 1
    cut = F.transform(_starts(), lambda s: F.struct((F.col("low") + s).alias("start"), numbered(F.slice("hashes", s + 1, n)).alias("features")))
    return ready.select("doc_id", "row_key", "n_words", F.explode(cut).alias("w")).select("doc_id", "row_key", "n_words", "w.start", "w.features")


def near_pairs(window_prints: DataFrame, item_prints: DataFrame, n_items: int) -> DataFrame:
    """``n_words, w1, w2, item_key``: all windows and items of one length whose
    fingerprints are at most ``RADIUS`` bits apart."""
    bounds = block_bounds()
    own, other = [t // 2 for t in bounds], [t - t // 2 for t in bounds]
    ways = sum(len(flip_masks(f)) for f in other)
    left = window_prints.select("n_words", "w1", "w2", "print_a", "print_b", F.explode(block_keys(F.col("n_words"), own)).alias("key"))
    right = item_prints.select("item_key", F.col("print_a").alias("item_a"), F.col("print_b").alias("item_b"), F.explode(block_keys(F.col("n_words"), other)).alias("key"))
    apart = F.bit_count(F.col("print_a").bitwiseXOR(F.col("item_a"))) + F.bit_count(F.col("print_b").bitwiseXOR(F.col("item_b")))
    met = left.join(_bounded(right, n_items * ways).withColumnRenamed("key", "item_block"), (F.col("key") == F.col("item_block")) & (apart <= RADIUS))
    return met.select("n_words", "w1", "w2", "item_key").distinct()


def matches(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """``doc_id, row_key, item_id, inter, uni``: the best window of each matching pair."""
    items = stored(_items(benchmark, item_col, item_text_col), "benchmark-items")
    lengths = {r.n_words: r.k for r in items.groupBy("n_words").agg(F.count(F.lit(1)).alias("k")).collect()}  # a row per item length
    if not lengths:
        return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(whole(text_col)).alias("row_key"), F.lit(0).cast("long").alias("item_id"), F.lit(0).alias("inter"), F.lit(0).alias("uni")).where(F.lit(False))
    lane = 16 if max(lengths) < 1 << 15 else 32
    item_prints = stored(with_prints(items, ["item_key", "n_words"], lane), "item-prints")
    found = windows(docs, items, lengths, id_col=id_col, text_col=text_col)
    found = stored(found.withColumns({"w1": F.xxhash64("features"), "w2": F.xxhash64(F.lit(1), "features")}), "item-windows")
    own = ["n_words", "w1", "w2"]
    prints = stored(with_prints(found.select(*own, "features").dropDuplicates(own), own, lane), "window-prints")
    near = stored(near_pairs(prints, item_prints, sum(lengths.values())), "near-pairs")
    other = items.select("item_key", "item_id", F.col("features").alias("item_features"))
    pairs = found.select(*own, "features").join(near, own).dropDuplicates([*own, "item_key"]).join(other, "item_key")
    checked = pairs.withColumn("inter", F.size(F.array_intersect("features", "item_features"))).withColumn("uni", F.size("features") + F.size("item_features") - F.col("inter"))
    alike = stored(checked.where(DENOMINATOR * F.col("inter") >= NUMERATOR * F.col("uni")).select(*own, "item_id", "inter", "uni"), "window-matches")
    best = F.max(F.struct(F.try_divide("inter", "uni").alias("s"), "inter", "uni")).alias("best")
    return found.drop("features").join(alike, own).groupBy("doc_id", "row_key", "item_id").agg(best).select("doc_id", "row_key", "item_id", "best.inter", "best.uni")


def report(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, contaminated, n_items, item_ids, similarity`` for each row."""
    found = matches(docs, benchmark, id_col=id_col, text_col=text_col).groupBy("doc_id", "row_key").agg(F.sort_array(F.collect_set("item_id")).alias("item_ids"), F.max(F.try_divide("inter", "uni")).alias("similarity"))
    found = found.withColumnsRenamed({"doc_id": "hit_id", "row_key": "hit_key"})
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(whole(text_col)).alias("row_key"))
    both = rows.join(found, F.col("doc_id").eqNullSafe(F.col("hit_id")) & (F.col("row_key") == F.col("hit_key")), "left")
    return both.select(
        "doc_id", F.col("item_ids").isNotNull().alias("contaminated"), F.coalesce(F.size("item_ids"), F.lit(0)).cast("long").alias("n_items"),
        F.coalesce("item_ids", F.array().cast("array<long>")).alias("item_ids"), F.coalesce("similarity", F.lit(0.0)).alias("similarity"),
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The clean rows, with all their columns."""
    hit_id, hit_key = (free_name(docs, stem) for stem in ("hit_id", "hit_key"))
    found = stored(matches(docs, benchmark, id_col=id_col, text_col=text_col).select(F.col("doc_id").alias(hit_id), F.col("row_key").alias(hit_key)).distinct(), "contaminated")
    return docs.join(_bounded(found, found.count()), F.col(id_col).cast("long").eqNullSafe(F.col(hit_id)) & (F.xxhash64(whole(text_col)) == F.col(hit_key)), "left_anti")


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
