"""Language identification with error-correcting output codes.

Each language has a codeword of bits; one binary logistic classifier over hashed
n-grams of code points (1 to 3) predicts each bit. Decoding adds, for every
codeword, the bits' logistic losses weighted by how far each classifier beats
chance on its training rows, and takes the codeword of least loss; a small lead
over the next one flags the text as ambiguous.

With up to five languages the code is exhaustive (all splits); beyond that it has
``15 * ceil(log2 languages)`` random bits, drawn a number of times to keep the
code with the largest least distance.

Training takes at most ``TRAIN_ROWS`` rows, shared evenly among the languages, of
which the ``LANGUAGES`` most frequent ones are learned: those with the smallest hash
of their id. Whole texts are read, for learning and
for prediction. Language, source and id are never inputs of a prediction.

Edge cases: a null text or one without a letter is ``und`` with score 0, as is
every text if there is nothing to learn from; with one language, texts with
letters are that; rows with a null language aren't learned from; repeated rows
get equal results; null ids count as not held out; an empty table gives an empty
result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import cache
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from .byte_bpe import _rows
from .common import hash_share, table

TRAIN_ROWS = 2000
LANGUAGES = 256
DIMS = 2048
STEPS, RATE, RIDGE = 200, 0.05, 1e-3
AMBIGUOUS = 0.2
UNKNOWN = "und"


@cache
def _folded() -> np.ndarray:
    """Letters in lower case; everything else is a blank."""
    out = np.full(0x110000, 0x20, np.uint32)
    for c in range(0x110000):
        x = chr(c)
        if x.isalpha():
            low = x.lower()
            out[c] = ord(low[0])
    return out


def grams(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Square roots of hashed n-gram counts, each row of length 1; and whether
    the text has a letter."""
    n = len(texts)
    size = np.array([len(t) for t in texts], np.int64)
    points = _folded()[np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)]
    base = np.repeat(np.arange(n, dtype=np.int64) * DIMS, size)
    letters = np.bincount(base // DIMS, weights=points != 0x20, minlength=n) > 0
    counts = np.zeros(n * DIMS)
    code = points.astype(np.uint64)
    for k in (1, 2, 3):
        if k > 1:
            code = code[:-1] * np.uint64(0x9E3779B97F4A7C15) + points[k - 1 :]
        first = base[: len(code)]
        inside = first == base[k - 1 :]  # the n-gram lies in one text
        mixed = (code ^ (code >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9 + 2 * k)
        slot = (mixed >> np.uint64(64 - 11)).astype(np.int64)
        counts += np.bincount((first + slot)[inside], minlength=n * DIMS)
    x = np.sqrt(counts.reshape(n, DIMS)).astype(np.float32)
    norm = np.sqrt((x**2).sum(1, keepdims=True))
    return x / np.maximum(norm, 1e-9), letters


def codewords(k: int) -> np.ndarray:
    """(languages, bits) of -1 and 1; no bit is the same for all languages."""
    if k <= 1:
        return np.ones((k, 0))
    if k <= 5:
        splits = [s for r in range(1, k) for s in combinations(range(k), r) if 0 in s]
        return np.array([[1.0 if i in s else -1.0 for s in splits] for i in range(k)])
    rng, best, most = np.random.default_rng(7), None, -1
    for _ in range(64):
        code = np.where(rng.random((k, 15 * int(np.ceil(np.log2(k))))) < 0.5, 1.0, -1.0)
        code = code[:, np.abs(code.sum(0)) < k]
        agree = code @ code.T
        apart = int(code.shape[1] - agree[~np.eye(k, dtype=bool)].max()) // 2
        if apart > most:
            best, most = code, apart
    return best


@dataclass
class Model:
    languages: list[str]
    code: np.ndarray
    weights: np.ndarray  # (DIMS, bits)
    bias: np.ndarray
    trust: np.ndarray  # by bit

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language, score, and whether the lead is small, for each text."""
        x, letters = grams(texts)
        known = letters & bool(self.languages)
        if not self.languages:
            return [UNKNOWN] * len(texts), np.zeros(len(texts)), np.zeros(len(texts), bool)
        margins = x @ self.weights + self.bias
        loss = (np.logaddexp(0, -margins[:, None, :] * self.code[None]) * self.trust).sum(2)
        share = np.exp(loss.min(1, keepdims=True) - loss)
        share /= share.sum(1, keepdims=True)
        best = loss.argmin(1)
        top = np.sort(share, 1)
        lead = top[:, -1] - top[:, -2] if len(self.languages) > 1 else np.ones(len(texts))
        names = [self.languages[b] if k else UNKNOWN for b, k in zip(best, known)]
        return names, np.where(known, share[np.arange(len(texts)), best], 0.0), known & (lead < AMBIGUOUS)


def fit(x: np.ndarray, names: list[str]) -> Model:
    languages = sorted(set(names))
    code = codewords(len(languages))
    target = code[[languages.index(n) for n in names]] if names else np.zeros((0, 0))
    bits = code.shape[1]
    w, b = np.zeros((DIMS, bits)), np.zeros(bits)
    if bits:
        m, v = np.zeros((DIMS + 1, bits)), np.zeros((DIMS + 1, bits))
        scale = 8.0
        x = x.astype(np.float64) * scale
        for step in range(1, STEPS + 1):
            slope = -target / (1 + np.exp(np.clip(target * (x @ w + b), -30, 30))) / len(x)
            grad = np.vstack([x.T @ slope + RIDGE * w, slope.sum(0)])
            m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
            move = RATE * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-9)
            w, b = w - move[:-1], b - move[-1]
        right = ((x @ w + b) * target > 0).mean(0)
        trust = np.maximum(2 * right - 1, 0.01)
        w = w * scale
    else:
        trust = np.zeros(0)
    return Model(languages, code, w.astype(np.float32), b, trust)


def held_out(row_id: Column) -> Column:
    return F.crc32(row_id.cast("string").cast("binary")) % 3 == 1


def train(docs: DataFrame, *, rows: int = TRAIN_ROWS) -> Model:
    usable = docs.where("text is not null and lang is not null and doc_id is not null").where(~held_out(F.col("doc_id")))
    counts = usable.groupBy("lang").agg(F.count(F.lit(1)).alias("texts")).orderBy(F.desc("texts"), "lang").limit(LANGUAGES)
    each = max(1, rows // max(1, counts.count()))
    shares = counts.select("lang", F.least(F.lit(1.0), F.lit(2.0 * each) / F.col("texts")).alias("share"))
    by_hash = Window.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id")
    near = usable.select("doc_id", "lang").join(F.broadcast(shares), "lang").where(hash_share("doc_id", F.col("share")))
    chosen = near.withColumn("at", F.row_number().over(by_hash)).where(F.col("at") <= each).select(F.col("doc_id").alias("own"), F.col("lang").alias("name"))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows_, texts in _rows(batches):
            x, letters = grams(texts)
            part = pa.record_batch([rows_, pa.array([r.tobytes() for r in x], pa.binary()), pa.array(letters)], ["row", "x", "letters"])
            yield part.filter(part.column(2)).select(["row", "x"])

    # at most `rows` ids are broadcast and as many vectors come back: one for each id
    learned = docs.select("doc_id", "text").join(F.broadcast(chosen.distinct()), F.col("doc_id") == F.col("own")).select(F.struct("own", "name").alias("row"), "text")
    each = learned.mapInArrow(run, "row struct<own:long,name:string>, x binary").groupBy("row").agg(F.min("x").alias("x"))
    got = each.select("row.name", "x").toArrow()
    found = sorted(zip(got.column("name").to_pylist(), got.column("x").to_pylist()))
    return fit(np.array([np.frombuffer(v, np.float32) for _, v in found]).reshape(len(found), DIMS), [n for n, _ in found])


def identify(docs: DataFrame, model: Model, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, held_out, lang_pred, score, ambiguous`` for each row."""
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, texts in _rows(batches):
            names, scores, unsure = model.predict(texts)
            yield pa.record_batch([ids, pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(unsure, pa.bool_())], ["doc_id", "lang_pred", "score", "ambiguous"])

    found = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, lang_pred string, score double, ambiguous boolean")
    return found.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "lang_pred", "score", "ambiguous")


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return identify(docs, train(docs))
