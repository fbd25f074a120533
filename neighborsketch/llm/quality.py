"""Quality classifier: histogram gradient-boosted trees over document statistics.

The statistics come from whole texts with array operations. The trees are fitted
on the driver from at most ``TRAIN_ROWS`` labelled rows (those with the smallest
hash of their id, so the sample is the same at every run) and are flattened into
arrays: every tree is a complete binary tree, and scoring walks all rows and all
trees down one level at a time.

Labels, language, source and id are never inputs of a score.

Edge cases: null text counts as empty and gets a score as any text; rows without
a label, with a null one or with a null id are scored only; several labels of an
id count as their maximum, and of an id's several texts that of least statistics is
learned from; without any label every score is 0.5; repeated rows
get equal scores; an empty table gives an empty result; texts are read whole;
other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .byte_bpe import _rows
from .common import hash_share, table

TRAIN_ROWS = 20_000
TREES, DEPTH, BINS, RATE, SMOOTH = 80, 4, 64, 0.15, 5.0
KEEP_AT = 0.3

FEATURES = [
    "log_chars", "log_words", "log_lines", "letters", "uppers", "digits", "spaces", "marks", "symbols", "bars", "bangs",
    "word_length", "longest_word", "words_a_line", "distinct_words", "distinct_lines", "top_word", "ends_with_stop", "non_ascii", "short_words", "commas", "odd_ends", "distinct_pairs",
]

# Code points by kind.
_STOPS, _COMMAS, _BANGS, _BARS = ".?", ",;", "!", "|"
_SYMBOLS = "#$%&*+<=>@\\^_`~{}[]/"
UPPER, LOWER, DIGIT, SPACE, STOP, COMMA, BANG, BAR, SYMBOL, ELSE = range(10)


@cache
def _kinds() -> np.ndarray:
    out = np.full(0x110000, ELSE, np.uint8)
    for c in range(0x110000):
        x = chr(c)
        if x.isalpha():
            out[c] = UPPER if x.isupper() else LOWER
        elif x.isdigit():
            out[c] = DIGIT
        elif x.isspace():
            out[c] = SPACE
    for kind, chars in ((STOP, _STOPS), (COMMA, _COMMAS), (BANG, _BANGS), (BAR, _BARS), (SYMBOL, _SYMBOLS)):
        out[[ord(x) for x in chars]] = kind
    return out


def statistics(texts: list[str]) -> np.ndarray:
    """One row of FEATURES for each text."""
    n = len(texts)
    out = np.zeros((n, len(FEATURES)), np.float32)
    size = np.array([len(t) for t in texts], np.int64)
    points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
    owner = np.repeat(np.arange(n), size)
    kinds = _kinds()[points]
    counts = np.bincount(owner * 10 + kinds, minlength=10 * n).reshape(n, 10).astype(np.float64)
    ascii_no = np.bincount(owner, weights=points > 127, minlength=n)
    chars = np.maximum(size, 1)
    letters = np.maximum(counts[:, UPPER] + counts[:, LOWER], 1)
    rest = np.zeros((n, 12))
    for i, t in enumerate(texts):
        words, lines = t.split(), t.split("\n")
        if not words:
            rest[i, 1] = len(lines)
            continue
        k, m = len(words), len(lines)
        lengths = list(map(len, words))
        distinct = set(words)
        seen: dict[str, int] = {}
        for w in words:
            seen[w] = seen.get(w, 0) + 1
        pairs = set(zip(words, words[1:]))
        rest[i] = (
            k, m, sum(lengths) / k, max(lengths), k / m, len(distinct) / k, len(set(lines)) / m, max(seen.values()) / k,
            t.rstrip()[-1] in ".!?", sum(x <= 2 for x in lengths) / k, sum(not w[-1].isalnum() for w in words) / k, (len(pairs) + 1) / k,
        )
    out[:, 0], out[:, 1], out[:, 2] = np.log1p(size), np.log1p(rest[:, 0]), np.log1p(rest[:, 1])
    out[:, 3] = letters / chars
    out[:, 4] = counts[:, UPPER] / letters
    for at, kind in ((5, DIGIT), (6, SPACE), (7, STOP), (8, SYMBOL), (9, BAR), (10, BANG), (20, COMMA)):
        out[:, at] = counts[:, kind] / chars
    out[:, 11], out[:, 12], out[:, 13] = rest[:, 2], np.log1p(rest[:, 3]), np.log1p(rest[:, 4])
    out[:, 14], out[:, 15], out[:, 16], out[:, 17] = rest[:, 5], rest[:, 6], rest[:, 7], rest[:, 8]
    out[:, 18], out[:, 19], out[:, 21], out[:, 22] = ascii_no / chars, rest[:, 9], rest[:, 10], rest[:, 11]
    return out


@dataclass
class Forest:
    """Complete binary trees of one depth: node i has children 2i+1 and 2i+2."""

    feature: np.ndarray  # (trees, inner nodes)
    threshold: np.ndarray  # (trees, inner nodes): go right if greater
    leaf: np.ndarray  # (trees, leaves)
    base: float

    def raw(self, x: np.ndarray) -> np.ndarray:
        trees, inner = self.feature.shape
        total = np.full(len(x), self.base)
        if not trees:
            return total
        node, tree = np.zeros((len(x), trees), np.int64), np.arange(trees)[None, :]
        row = np.arange(len(x))[:, None]
        for _ in range(int(np.log2(inner + 1))):
            node = 2 * node + 1 + (x[row, self.feature[tree, node]] > self.threshold[tree, node])
        return total + self.leaf[tree, node - inner].sum(axis=1)

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-self.raw(x)))


def fit(x: np.ndarray, y: np.ndarray, *, trees: int = TREES, depth: int = DEPTH, bins: int = BINS, rate: float = RATE, smooth: float = SMOOTH) -> Forest:
    """Log-loss boosting on binned features, one level of a tree at a time."""
    inner = 2**depth - 1
    if not len(y) or y.min() == y.max():
        mean = (y.sum() + 1) / (len(y) + 2)
        return Forest(np.zeros((0, inner), np.int64), np.zeros((0, inner), np.float32), np.zeros((0, inner + 1)), float(np.log(mean / (1 - mean))))
    n, width = x.shape
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(width)]
    binned = np.stack([np.searchsorted(e, x[:, j], side="left") for j, e in enumerate(edges)], 1)
    flat = binned + np.arange(width) * bins
    base = float(np.log(y.mean() / (1 - y.mean())))
    f = np.full(n, base)
    feature, threshold, leaf = np.zeros((trees, inner), np.int64), np.full((trees, inner), np.inf, np.float32), np.zeros((trees, inner + 1))
    for t in range(trees):
        p = 1 / (1 + np.exp(-f))
        g, h = y - p, np.maximum(p * (1 - p), 1e-9)
        node = np.zeros(n, np.int64)
        for level in range(depth):
            first, k = 2**level - 1, 2**level
            key = ((node - first)[:, None] * (width * bins) + flat).ravel()
            shape = (k, width, bins)
            gs = np.bincount(key, np.repeat(g, width), k * width * bins).reshape(shape).cumsum(2)
            hs = np.bincount(key, np.repeat(h, width), k * width * bins).reshape(shape).cumsum(2)
            gt, ht = gs[:, :1, -1:], hs[:, :1, -1:]
            gain = gs**2 / (hs + smooth) + (gt - gs) ** 2 / (ht - hs + smooth) - gt**2 / (ht + smooth)
            gain[(hs < 1) | (ht - hs < 1)] = 0
            best = gain.reshape(k, -1).argmax(1)
            for i in range(k):
                j, b = divmod(int(best[i]), bins)
                if gain[i, j, b] > 1e-9 and b < len(edges[j]):
                    feature[t, first + i], threshold[t, first + i] = j, edges[j][b]
            node = 2 * node + 1 + (x[np.arange(n), feature[t, node]] > threshold[t, node])
        at = node - inner
        leaf[t] = rate * np.bincount(at, g, inner + 1) / (np.bincount(at, h, inner + 1) + smooth)
        f += leaf[t, at]
    return Forest(feature, threshold, leaf, base)


def held_out(row_id: Column) -> Column:
    return F.crc32(row_id.cast("string").cast("binary")) % 5 == 0


def _training_rows(docs: DataFrame, labels: DataFrame, rows: int) -> DataFrame:
    usable = labels.where("doc_id is not null and quality is not null").where(~held_out(F.col("doc_id")))
    share = min(1.0, 2 * rows / max(1, usable.count()))  # so that no task sends more than it need
    chosen = (
        usable.where(hash_share("doc_id", share))
        .groupBy("doc_id").agg(F.max("quality").alias("label")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
        .select(F.col("doc_id").alias("labelled"), F.col("label").cast("double").alias("label"))
    )
    # at most `rows` ids and labels are broadcast
    return docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("labelled")).select("labelled", "label", "text")


def train(docs: DataFrame, labels: DataFrame, *, rows: int = TRAIN_ROWS) -> Forest:
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row_id, texts in _rows(batches):
            yield pa.record_batch([row_id, pa.array(list(statistics(texts)), pa.list_(pa.float32()))], ["row", "x"])

    chosen = _training_rows(docs, labels, rows)
    each = chosen.select(F.struct("labelled", "label").alias("row"), "text").mapInArrow(run, "row struct<labelled:long,label:double>, x array<float>")
    got = each.groupBy("row").agg(F.min("x").alias("x")).select("row.label", "x").toArrow()  # at most `rows` rows
    y = np.asarray(got.column("label").to_pylist(), np.float64)
    x = np.asarray(got.column("x").to_pylist(), np.float32).reshape(len(y), len(FEATURES))
    order = np.lexsort((y, *x.T))  # the rows' order of arrival must not matter
    return fit(x[order], (y[order] > 0).astype(np.float64))


def score(docs: DataFrame, forest: Forest, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, held_out, score, predicted`` for each row."""
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, texts in _rows(batches):
            yield pa.record_batch([ids, pa.array(forest.score(statistics(texts)), pa.float64())], ["doc_id", "score"])

    scored = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= KEEP_AT).cast("int").alias("predicted"))


def keep(docs: DataFrame, forest: Forest) -> DataFrame:
    """The rows that the classifier accepts, with all their columns."""
    import pyarrow.compute as pc

    at = docs.columns.index("text")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in range(0, batch.num_rows, 1000):
                part = batch.slice(begin, 1000)
                flags = np.concatenate([np.zeros(0, bool), *[forest.score(statistics(texts)) >= KEEP_AT for _, texts in _rows([pa.record_batch([part.column(at), part.column(at)], ["i", "t"])])]])
                yield part.filter(pc.fill_null(pa.array(flags, pa.bool_()), False))

    return docs.mapInArrow(run, docs.schema)


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score(docs, train(docs, table(spark, sf_dir, "labels")))
