r"""Exact deduplication by skew-safe combining.

Texts are equal when identical after every character of ``[\x20\x09-\x0D]`` is
deleted. Copies are combined in three steps, each of which compares the whole
normalised text beside its digest:

1. each map task combines its own copies (the partial aggregate);
2. each (digest, salt) group combines those of all tasks, where a row's id
   decides the salt, so that no task gets more than a share of a hot text;
3. the salts' winners of a digest, at most ``salts`` rows, combine globally.

The classes go back to the rows by (digest, salt), again a share of a hot text
at a time. Should two texts share a digest, their rows take their class by the
text instead; no such pair of texts is known, so that path is joined in only
when the stored class table has one.

Edge cases: a null text counts as empty, so null, empty and blank texts are one
class; a null id loses every tie; where ids repeat, the row with the most code
points stays among them, of equally long ones the text of least hash, and of rows
that repeat id and text just one, whichever its other columns; an empty table
gives an empty result; other columns, whatever their names, are not read by
:func:`report` and come back untouched from :func:`drop_copies`.
"""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import WS, free_name, row_salt, salts_for, stored, table, whole

# Rank of a row as one decimal, greatest wins: the number of code points, then
# the smaller id. Decimals keep the aggregate on the hash path.
_ID_SPAN = Decimal(10**20)
_TOP = Decimal(2**63)


def normalised(text: Column) -> Column:
    return F.translate(text, WS, "")


def _rank(length: Column, row_id: Column) -> Column:
    tie = F.coalesce(F.lit(_TOP).cast("decimal(20,0)") - row_id.cast("decimal(20,0)"), F.lit(0).cast("decimal(20,0)"))
    return (length.cast("decimal(18,0)") * F.lit(_ID_SPAN).cast("decimal(21,0)") + tie).cast("decimal(38,0)")


def _rank_id(rank: Column) -> Column:
    tie = F.pmod(rank, F.lit(_ID_SPAN).cast("decimal(38,0)"))
    return F.when(tie != 0, (F.lit(_TOP).cast("decimal(20,0)") - tie).cast("long"))


def _keyed(docs: DataFrame, id_col: str, text_col: str, salts: int) -> DataFrame:
    text = whole(text_col)
    return docs.select(
        F.col(id_col).cast("long").alias("row_id"), row_salt(id_col, salts).alias("salt"),
        F.length(text).alias("length"), F.xxhash64(text).alias("mark"), normalised(text).alias("content"),
    ).withColumn("digest", F.unhex(F.sha2("content", 256)))


def classes(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", salts: int | None = None) -> DataFrame:
    """One row per (class, salt) with the class's winner and size. ``content``
    is null unless another text shares the digest."""
    keyed = _keyed(docs, id_col, text_col, salts or salts_for(docs))
    salted = keyed.groupBy("digest", "salt", "content").agg(F.max(_rank(F.col("length"), F.col("row_id"))).alias("rank"), F.count(F.lit(1)).alias("n"))
    alike = Window.partitionBy("digest", "content")
    same = Window.partitionBy("digest")
    return (
        salted.repartition("digest")
        .withColumn("winner", F.max("rank").over(alike)).withColumn("size", F.sum("n").over(alike))
        .withColumn("texts", F.min("content").over(same) != F.max("content").over(same))
        .select("digest", "salt", _rank_id(F.col("winner")).alias("keep_id"), "size", F.when(F.col("texts"), F.col("content")).alias("content"))
    )


def _marked(docs: DataFrame, id_col: str, text_col: str, salts: int | None) -> DataFrame:
    """``row_id, keep_id, size, kept, digest, mark, repeats``, one row per input row."""
    salts = salts or salts_for(docs)
    found = stored(classes(docs, id_col=id_col, text_col=text_col, salts=salts), "copy-classes")
    keyed = _keyed(docs, id_col, text_col, salts)
    plain = found.where("content is null").drop("content")
    joined = keyed.drop("content").join(plain, ["digest", "salt"])
    shared = found.where("content is not null")
    if not shared.isEmpty():
        joined = joined.unionByName(keyed.join(shared.withColumnRenamed("content", "own"), ["digest", "salt"]).where("content = own").drop("content", "own"))
    own = Window.partitionBy("digest", "salt", "keep_id", "row_id")  # the salt is the id's, so all rows of an id are here
    first = F.row_number().over(own.orderBy(F.desc("length"), "mark")) == 1
    return joined.select(
        "row_id", "keep_id", "size", (F.col("row_id").eqNullSafe(F.col("keep_id")) & first).alias("kept"), "digest", "mark",
        F.count(F.lit(1)).over(own).alias("repeats"),
    )


def report(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", salts: int | None = None) -> DataFrame:
    """``doc_id, keep_id, group_size, kept, text_sha256``, one row per input row."""
    return _marked(docs, id_col, text_col, salts).select(
        F.col("row_id").alias("doc_id"), "keep_id", F.col("size").alias("group_size"), "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def drop_copies(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows that stay, one of each class, with all their columns. Of the winners
    only ids and hashes travel; the texts meet them once."""
    names = [free_name(docs, stem) for stem in ("kept_id", "kept_digest", "kept_mark")]
    kept = stored(_marked(docs, id_col, text_col, None).where("kept").select(*[F.col(c).alias(n) for c, n in zip(("row_id", "digest", "mark"), names)], (F.col("repeats") > 1).alias("again")), "copies-kept")
    digest = F.unhex(F.sha2(normalised(whole(text_col)), 256))

    def meet(winners: DataFrame) -> DataFrame:
        same = F.col(id_col).cast("long").eqNullSafe(F.col(names[0])) & (digest == F.col(names[1])) & (F.xxhash64(whole(text_col)) == F.col(names[2]))
        return docs.join(winners.drop("again"), same, "left_semi")

    out = meet(kept.where("not again"))
    again = kept.where("again")
    return out if again.isEmpty() else out.unionByName(meet(again).dropDuplicates([id_col, text_col]))


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return report(table(spark, sf_dir, "documents"))


ORACLE = r"""
WITH d AS (
  SELECT doc_id, length(coalesce(text, '')) AS n,
         sha256(regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g')) AS text_sha256
  FROM documents
), c AS (
  SELECT *, first_value(doc_id) OVER (PARTITION BY text_sha256 ORDER BY n DESC, doc_id) AS keep_id,
         count(*) OVER (PARTITION BY text_sha256) AS group_size
  FROM d
)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, text_sha256 FROM c
"""
