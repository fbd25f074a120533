r"""Reversible line deduplication: cuckoo filters over exact reference counts.

A line's key is the line without ``[\x20\x09-\x0D]`` at both ends, with A-Z in
lower case. The *reference-count table* says for each key (by 16 bytes of its
SHA-256) in how many documents it is; it is exact, and inserting or deleting
documents only adds to or subtracts from it. Keys in at least ``threshold``
documents also stand in a *cuckoo filter*, sharded by the digest; keys that cross
the threshold in either direction are inserted into or deleted from their
shard's filter, so an index after a deletion equals one that never saw those
documents.

To clean documents, all their lines are held against the filters, and the few
that may be common against the exact table. The filters travel to the executors
if all shards together are below ``FILTER_BYTES``; beyond that the lines' digests
travel to their shard's filter, a shard's lines dealt over ``SALTS`` copies of it. Of
the exact rows the most frequent ones, at most ``BROADCAST_KEYS``, are broadcast and
the others join through a shuffle. An index that grows beyond twice its number of
shards is dealt out anew.

Edge cases: a null or empty text is one empty line, whose key has no code point
and never goes; blank lines stay too; repeated rows count as documents of their
own; deleting documents that were never inserted is an error; null ids are fine; lines of any length and texts of any number of lines are
handled whole; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import WS, join_hot, stored, table, whole

THRESHOLD = 10
SHARD_KEYS = 16_384
SALTS = 32
SLOTS = 4
FILTER_BYTES = 32 << 20
BROADCAST_KEYS = 100_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


class CuckooFilter:
    """Sixteen-bit fingerprints in buckets of four, two buckets a key."""

    def __init__(self, buckets: int):
        assert buckets & (buckets - 1) == 0
        self.table = np.zeros((buckets, SLOTS), np.uint16)

    @classmethod
    def sized(cls, keys: int) -> CuckooFilter:
        return cls(1 << max(4, int(np.ceil(np.log2(max(1, keys) / (SLOTS * 0.6))))))

    @classmethod
    def from_bytes(cls, data: bytes) -> CuckooFilter:
        found = np.frombuffer(data, np.uint16).reshape(-1, SLOTS)
        out = cls(len(found))
        out.table = found.copy()
        return out

    def to_bytes(self) -> bytes:
        return self.table.tobytes()

    def _places(self, digests: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """digests: rows of 16 bytes. Bytes 0-3 deal out shards, 4-7 buckets, 8-9 fingerprints."""
        words = np.ascontiguousarray(digests).view("<u4").reshape(-1, 4)
        mask = np.uint32(len(self.table) - 1)
        mark = (words[:, 2] & np.uint32(0xFFFF)).astype(np.uint32)
        mark[mark == 0] = 1
        first = words[:, 1] & mask
        return mark.astype(np.uint16), first, first ^ ((mark * np.uint32(0x5BD1E995)) >> np.uint32(7)) & mask

    def _other(self, mark: int, at: int) -> int:
        return at ^ (((mark * 0x5BD1E995) & 0xFFFFFFFF) >> 7) & (len(self.table) - 1)

    def contains(self, digests: np.ndarray) -> np.ndarray:
        mark, a, b = self._places(digests)
        return (self.table[a] == mark[:, None]).any(1) | (self.table[b] == mark[:, None]).any(1)

    def insert(self, digests: np.ndarray) -> bool:
        """False if some key found no place: then build a larger filter."""
        for mark, a, b in zip(*[x.tolist() for x in self._places(digests)]):
            if not self._put(mark, a, b):
                return False
        return True

    def _put(self, mark: int, a: int, b: int) -> bool:
        for at in (a, b):
            free = np.flatnonzero(self.table[at] == 0)
            if len(free):
                self.table[at, free[0]] = mark
                return True
        at = b
        for kick in range(500):
            slot = (kick + at) % SLOTS
            mark, self.table[at, slot] = int(self.table[at, slot]), mark
            at = self._other(mark, at)
            free = np.flatnonzero(self.table[at] == 0)
            if len(free):
                self.table[at, free[0]] = mark
                return True
        return False

    def delete(self, digests: np.ndarray) -> None:
        for mark, a, b in zip(*[x.tolist() for x in self._places(digests)]):
            for at in (a, b):
                held = np.flatnonzero(self.table[at] == mark)
                if len(held):
                    self.table[at, held[0]] = 0
                    break


def line_key(line: Column) -> Column:
    return F.translate(F.btrim(line, F.lit(WS)), UPPER, LOWER)


def line_digests(text: Column) -> Column:
    """By line: 16 bytes of the key's digest; null where the key is empty."""
    key = lambda line: F.when(F.length(line_key(line)) > 0, F.substring(F.unhex(F.sha2(line_key(line), 256)), 1, 16))
    return F.transform(F.split(text, "\n"), key)


def reference_counts(docs: DataFrame, *, text_col: str = "text") -> DataFrame:
    """``digest, n_docs`` for all keys of the documents."""
    keys = docs.select(F.explode(F.array_distinct(line_digests(whole(text_col)))).alias("digest"))
    return keys.where("digest is not null").groupBy("digest").agg(F.count(F.lit(1)).alias("n_docs"))


def _shard(n_shards: int) -> Column:
    return F.pmod(F.conv(F.hex(F.substring("digest", 1, 4)), 16, 10).cast("long"), F.lit(n_shards)).cast("int")


def _digests(column: Iterable[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(column), np.uint8).reshape(-1, 16)


def _filled(digests: np.ndarray, least: int = 0) -> CuckooFilter:
    found = CuckooFilter.sized(max(len(digests), least))
    while not found.insert(digests):
        found = CuckooFilter(2 * len(found.table))
    return found


@dataclass
class LineIndex:
    """Reference counts of all keys, and filters of those at the threshold."""

    counts: DataFrame  # digest binary, n_docs long
    filters: DataFrame  # shard int, data binary
    n_shards: int
    threshold: int

    @classmethod
    def build(cls, docs: DataFrame, *, text_col: str = "text", threshold: int = THRESHOLD) -> LineIndex:
        return cls.of(stored(reference_counts(docs, text_col=text_col), "line-counts"), threshold)

    @classmethod
    def of(cls, counts: DataFrame, threshold: int = THRESHOLD) -> LineIndex:
        """An index from its exact table, with as many shards as that needs."""
        common = counts.where(F.col("n_docs") >= threshold)
        n_shards = max(1, -(-common.count() // SHARD_KEYS))

        def fill(pdf: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"shard": [int(pdf["shard"].iloc[0])], "data": [_filled(_digests(pdf["digest"])).to_bytes()]})

        # a group has about SHARD_KEYS keys whatever the data's size
        filters = common.select("digest", _shard(n_shards).alias("shard")).groupBy("shard").applyInPandas(fill, "shard int, data binary")
        return cls(counts, stored(filters, "line-filters"), n_shards, threshold)

    def _changed(self, docs: DataFrame, sign: int, text_col: str) -> LineIndex:
        delta = reference_counts(docs, text_col=text_col).select("digest", (sign * F.col("n_docs")).alias("n_docs"))
        delta = stored(delta, "line-delta")
        counts = stored(self.counts.unionByName(delta).groupBy("digest").agg(F.sum("n_docs").alias("n_docs")).where("n_docs != 0"), "line-counts")
        if sign < 0 and not counts.where("n_docs < 0").isEmpty():
            raise ValueError("some of these documents are not in the index")
        if counts.where(F.col("n_docs") >= self.threshold).count() > 2 * self.n_shards * SHARD_KEYS:
            return LineIndex.of(counts, self.threshold)
        before, after = F.coalesce(F.col("b.n_docs"), F.lit(0)), F.coalesce(F.col("a.n_docs"), F.lit(0))
        crossed = (
            delta.alias("d").join(self.counts.alias("b"), F.col("d.digest") == F.col("b.digest"), "left").join(counts.alias("a"), F.col("d.digest") == F.col("a.digest"), "left")
            .select(F.col("d.digest").alias("digest"), (before >= self.threshold).alias("was"), (after >= self.threshold).alias("now")).where("was != now")
            .select("digest", "now", _shard(self.n_shards).alias("shard"))
        )
        threshold_keys = counts.where(F.col("n_docs") >= self.threshold).select("digest", _shard(self.n_shards).alias("shard"))

        def update(key, old: pd.DataFrame, new: pd.DataFrame) -> pd.DataFrame:
            goes, comes = _digests(new.loc[~new["now"], "digest"]), _digests(new.loc[new["now"], "digest"])
            held = CuckooFilter.from_bytes(old["data"].iloc[0]) if len(old) else CuckooFilter.sized(len(comes))
            held.delete(goes)
            full = not held.insert(comes)
            return pd.DataFrame({"shard": [int(key[0])], "data": [None if full else held.to_bytes()]})

        moved = stored(self.filters.groupBy("shard").cogroup(crossed.groupBy("shard")).applyInPandas(update, "shard int, data binary"), "line-filters")
        full = moved.where("data is null").select("shard")

        def refill(pdf: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"shard": [int(pdf["shard"].iloc[0])], "data": [_filled(_digests(pdf["digest"]), 2 * len(pdf)).to_bytes()]})

        again = threshold_keys.join(full, "shard").groupBy("shard").applyInPandas(refill, "shard int, data binary")
        return LineIndex(counts, stored(moved.where("data is not null").unionByName(again), "line-filters"), self.n_shards, self.threshold)

    def insert(self, docs: DataFrame, *, text_col: str = "text") -> LineIndex:
        return self._changed(docs, 1, text_col)

    def delete(self, docs: DataFrame, *, text_col: str = "text") -> LineIndex:
        return self._changed(docs, -1, text_col)

    def maybe_common(self, lines: DataFrame) -> DataFrame:
        """The lines whose digest some filter may hold: all that are common, and few others."""
        size = self.filters.agg(F.coalesce(F.sum(F.length("data")), F.lit(0))).first()[0]
        if size > FILTER_BYTES:
            return self._by_shard(lines)
        shipped = lines.sparkSession.sparkContext.broadcast({r.shard: r.data for r in self.filters.collect()})
        n_shards = self.n_shards

        def probe(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = {k: CuckooFilter.from_bytes(v) for k, v in shipped.value.items()}
            for batch in batches:
                digests = _digests(batch.column(batch.schema.get_field_index("digest")).to_pylist())
                shard = np.ascontiguousarray(digests[:, :4]).view(">u4").ravel().astype(np.int64) % n_shards
                hit = np.zeros(len(digests), bool)
                for k, f in held.items():
                    own = np.flatnonzero(shard == k)
                    if len(own):
                        hit[own] = f.contains(digests[own])
                yield batch.filter(pa.array(hit))

        return lines.mapInArrow(probe, lines.schema)


    def _by_shard(self, lines: DataFrame) -> DataFrame:
        """The same where the filters don't fit: in every (shard, salt) the filter comes
        first, then the digests that are held against it, one batch at a time."""
        names = lines.columns
        salt = F.pmod(F.xxhash64(*[c for c in names if c != "digest"]), F.lit(SALTS)).cast("int")
        given = lines.select("*", _shard(self.n_shards).alias("shard"), salt.alias("salt"), F.lit(None).cast("binary").alias("data"))
        empty = [F.lit(None).cast(lines.schema[c].dataType).alias(c) for c in names]
        copies = self.filters.select(*empty, "shard", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"), "data")
        dealt = given.unionByName(copies).repartition("shard", "salt").sortWithinPartitions("shard", "salt", F.col("data").isNull())

        def probe(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, own = None, None
            for batch in batches:
                data, shards = batch.column("data"), batch.column("shard").to_numpy(zero_copy_only=False)
                digests, hit, at = batch.column("digest"), np.zeros(batch.num_rows, bool), 0
                for to in [*np.flatnonzero(data.is_valid().to_numpy(zero_copy_only=False)).tolist(), batch.num_rows]:
                    if held is not None and to > at:
                        hit[at:to] = held.contains(_digests(digests.slice(at, to - at).to_pylist())) & (shards[at:to] == own)
                    if to < batch.num_rows:
                        held, own, at = CuckooFilter.from_bytes(data[to].as_py()), shards[to], to + 1
                yield batch.filter(pa.array(hit)).select(names)

        return dealt.mapInArrow(probe, lines.schema)


def clean(docs: DataFrame, index: LineIndex, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_lines, n_dropped, kept`` with the text that stays."""
    keyed = docs.select(F.col(id_col).cast("long").alias("doc_id"), whole(text_col).alias("text")).withColumn("row_key", F.xxhash64("text"))
    lines = keyed.select("doc_id", "row_key", F.posexplode(line_digests(F.col("text"))).alias("pos", "digest")).where("digest is not null")
    exact = index.counts.where(F.col("n_docs") >= index.threshold)
    dropped = join_hot(index.maybe_common(lines), exact, "digest", "n_docs", BROADCAST_KEYS).groupBy("doc_id", "row_key").agg(F.collect_set("pos").alias("dropped"))
    dropped = dropped.withColumnsRenamed({"doc_id": "drop_id", "row_key": "drop_key"})
    both = keyed.join(dropped, F.col("doc_id").eqNullSafe(F.col("drop_id")) & (F.col("row_key") == F.col("drop_key")), "left").select("doc_id", "text", "dropped")

    def rewrite(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole_batch in batches:
            for at in range(0, whole_batch.num_rows, 1000):
                batch = whole_batch.slice(at, 1000)
                n_lines, n_dropped, kept = [], [], []
                for text, gone in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                    parts, gone = text.split("\n"), set(gone or ())
                    n_lines.append(len(parts))
                    n_dropped.append(len(gone))
                    kept.append("\n".join(p for i, p in enumerate(parts) if i not in gone) if gone else text)
                yield pa.record_batch([batch.column(0), pa.array(n_lines, pa.int64()), pa.array(n_dropped, pa.int64()), pa.array(kept, pa.string())], ["doc_id", "n_lines", "n_dropped", "kept"])

    return both.mapInArrow(rewrite, "doc_id long, n_lines long, n_dropped long, kept string")


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return clean(docs, LineIndex.build(docs)).select("doc_id", "n_lines", "n_dropped", F.sha2("kept", 256).alias("kept_sha256"))


ORACLE = r"""
WITH l AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents
), k AS (
  SELECT doc_id, pos, line,
         translate(trim(line, chr(9) || chr(10) || chr(11) || chr(12) || chr(13) || ' '), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM l
), c AS (
  SELECT key FROM k WHERE length(key) > 0 GROUP BY key HAVING count(DISTINCT doc_id) >= 10
), m AS (
  SELECT k.*, c.key IS NOT NULL AS dropped FROM k LEFT JOIN c ON k.key = c.key
)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (WHERE dropped))::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT dropped), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""
