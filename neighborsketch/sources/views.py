"""Item views of the given tables: sets of codes, as pairs or as arrays.

Long form is ``id, element`` without repeats; set form is ``id, elements`` with a
sorted array. Texts are read whole; empty and null payloads give no item.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import code
from ..functions.params import PRIME
from .store import stored

#: Fixed values of the planted copies: P, two multipliers, and the salts.
TWIN_ID, TWIN_ELEMENT, TWIN_SALT, DROP_SALT = 48271, 1000003, 17, 11


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(r"[^\s]+"), F.lit(0))


def shingle_codes(words: Column, k: int = 3) -> Column:
    """Distinct codes of all runs of k tokens; of all tokens, if there are fewer. The
    tokens should be a column of their own, or each run splits the text again."""
    n = F.size(words)
    runs = F.transform(F.sequence(F.lit(1), F.greatest(n - k + 1, F.lit(1))), lambda i: code(F.array_join(F.slice(words, i, k), " ")))
    return F.when(n == 0, F.array().cast("array<long>")).otherwise(F.array_distinct(runs))


def visible_text(html: Column) -> Column:
    """Markup replaced by blanks, scripts and styles with their content."""
    return F.regexp_replace(F.regexp_replace(html, r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), r"(?s)<[^>]*>", " ")


def with_twins(pairs: DataFrame) -> DataFrame:
    """Plants a thinned copy of every item whose hash is 0 mod 5: the copy keeps
    about 95 % of the elements. Copies get ids above the largest one."""
    h = (F.lit(TWIN_SALT * TWIN_ELEMENT + DROP_SALT).cast("long") + F.col("id") * TWIN_ID) % PRIME
    stays = ((h * TWIN_ELEMENT + F.col("element") * TWIN_ID + DROP_SALT) % PRIME) % 100 >= 5
    top = pairs.agg(F.max("id").alias("top"))
    twins = pairs.where(h % 5 == 0).where(stays).crossJoin(F.broadcast(top)).select((F.col("id") + F.col("top") + 1).alias("id"), "element")  # one row
    return pairs.unionByName(twins)


def twin_sets(sets: DataFrame) -> DataFrame:
    """``with_twins`` of the set form."""
    h = (F.lit(TWIN_SALT * TWIN_ELEMENT + DROP_SALT).cast("long") + F.col("id") * TWIN_ID) % PRIME
    stays = lambda e: ((h * TWIN_ELEMENT + e * TWIN_ID + DROP_SALT) % PRIME) % 100 >= 5
    top = sets.agg(F.max("id").alias("top"))
    thinned = sets.where(h % 5 == 0).withColumn("elements", F.filter("elements", stays))  # by the old id, so ahead of the new one
    twins = thinned.crossJoin(F.broadcast(top)).select((F.col("id") + F.col("top") + 1).alias("id"), "elements")  # one row
    return sets.unionByName(twins)


def perturbed(pairs: DataFrame, salt: int = 29) -> DataFrame:
    """The items with about a tenth of their elements dropped."""
    h = (F.lit(salt * TWIN_ELEMENT + DROP_SALT).cast("long") + F.col("id") * TWIN_ID) % PRIME
    return pairs.where(((h * TWIN_ELEMENT + F.col("element") * TWIN_ID + DROP_SALT) % PRIME) % 100 >= 10)


SPREAD_BYTES = 16 << 20


def spread(df: DataFrame) -> DataFrame:
    """Deals a small input out over all cores: a file of a few row groups would keep
    just as many of them busy. Inputs that fill the cores anyway stay as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return df.repartition(cores) if size < cores * SPREAD_BYTES else df


def _texts(df: DataFrame, row_id: Column, text: Column, k: int = 3) -> DataFrame:
    # one() keeps filters on the codes from being pushed into the lambda above the tokens
    dealt = spread(df.select(row_id.alias("id"), text.alias("text")))
    words = dealt.select("id", one(tokens(F.col("text"))).alias("words")).where("size(words) > 0")
    return words.select("id", one(F.sort_array(shingle_codes(F.col("words"), k))).alias("elements"))


def one(value: Column) -> Column:
    """The value itself, computed once: the optimizer does not move predicates on a
    generator's output below it, nor copy the value into other expressions."""
    return F.explode(F.array(value))


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem")


def _customer_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = _lines(spark, sf_dir).select("l_orderkey", "l_partkey")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey).select(F.col("o_custkey").alias("id"), F.col("l_partkey").alias("element"))


def _supplied_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _lines(spark, sf_dir).select(F.col("l_partkey").alias("id"), F.col("l_suppkey").alias("element"))


#: Views with planted copies: their pairs, which may repeat.
TWINNED = {"basket_twins": _customer_lines, "part_suppliers": _supplied_lines}


def basket_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _customer_lines(spark, sf_dir).distinct()


def _pairs(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    if name == "basket_customer":
        return basket_customer(spark, sf_dir)
    if name == "basket_twins":
        return with_twins(basket_customer(spark, sf_dir))
    if name == "basket_order":
        return _lines(spark, sf_dir).select(F.col("l_orderkey").alias("id"), F.col("l_partkey").alias("element")).distinct()
    if name == "part_suppliers":
        return with_twins(_supplied_lines(spark, sf_dir).distinct())
    if name == "user_events":
        events = table(spark, sf_dir, "events")
        hour = F.hour(F.col("ts"))
        return events.select(F.col("user_id").alias("id"), code(F.concat_ws(":", "event_type", hour.cast("string"))).alias("element")).distinct()
    raise KeyError(name)


#: Table, id and text of the text views.
TEXTS = {
    "doc_shingles": ("documents", lambda f: f.col("doc_id"), lambda f: f.col("text")),
    "page_tokens": ("pages", lambda f: f.col("page_id"), lambda f: visible_text(f.col("html"))),
    "turn_shingles": ("conversations", lambda f: f.shiftleft(f.col("conv_id"), 20) + f.col("turn"), lambda f: f.col("text")),
    "benchmark_shingles": ("benchmark", lambda f: f.col("item_id"), lambda f: f.col("text")),
}


def _sets(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    source, row_id, text = TEXTS[name]
    return _texts(table(spark, sf_dir, source), row_id(F), text(F))


PAIR_VIEWS = ("basket_customer", "basket_twins", "basket_order", "part_suppliers", "user_events")
SET_VIEWS = ("doc_shingles", "page_tokens", "turn_shingles", "benchmark_shingles")
VIEWS = PAIR_VIEWS + SET_VIEWS
#: Views whose elements are plain keys and get mixed before hashing.
RAW = ("basket_customer", "basket_twins", "basket_order", "part_suppliers")


def pairs(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Long form of a view. A row of the source is one item of a text view."""
    if name in PAIR_VIEWS:
        return _pairs(name, spark, sf_dir)
    return _sets(name, spark, sf_dir).select("id", F.explode("elements").alias("element"))


def sets(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Set form of a view. Sets of pairs are made once and written, copies from them."""
    if name in TWINNED:
        base = stored(TWINNED[name](spark, sf_dir).groupBy("id").agg(F.sort_array(F.collect_set("element")).alias("elements")), name)
        return twin_sets(base).where("size(elements) > 0")
    if name in PAIR_VIEWS:
        return stored(to_sets(_pairs(name, spark, sf_dir)), name)
    return _sets(name, spark, sf_dir)


def to_sets(pairs_df: DataFrame) -> DataFrame:
    return pairs_df.where("element is not null").groupBy("id").agg(F.sort_array(F.collect_set("element")).alias("elements"))


def ids(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The ids of a view's items, without making their elements."""
    if name in PAIR_VIEWS:
        return _pairs(name, spark, sf_dir).select("id").distinct()
    source, row_id, text = TEXTS[name]
    return table(spark, sf_dir, source).where(text(F).rlike(r"[^\s]")).select(row_id(F).alias("id"))


def items(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Set form whose elements are codes, ready for hashing."""
    found = sets(spark, sf_dir, name)
    return stored(found.withColumn("elements", F.transform("elements", code)), name) if name in RAW else found


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("elements"))


def rounded_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The vectors in millionths, for exact integer sums."""
    return vectors(spark, sf_dir).select("id", F.transform("elements", lambda x: F.round(x.cast("double") * 1_000_000).cast("long")).alias("elements"))
