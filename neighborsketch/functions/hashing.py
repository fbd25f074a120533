"""Universal hashes and their seeded constants.

Every constant is the leading 32 bits of an MD5 digest of ``kind:seed:...``, so any
engine that has MD5 and 64-bit integers computes the same sketch.
"""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .params import PRIME, SketchParams


def digest_int(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16)


def multiplier(text: str) -> int:
    return 1 + digest_int(text) % (PRIME - 1)


def offset(text: str) -> int:
    return digest_int(text) % PRIME


def code(value: Column) -> Column:
    """A string or number as a code below PRIME; consecutive keys land far apart."""
    return F.conv(F.substring(F.md5(value.cast("string").cast("binary")), 1, 8), 16, 10).cast("long") % F.lit(PRIME)


def mix_elements(elements: Column) -> Column:
    """Codes of an array's elements: a linear hash is biased on consecutive keys."""
    return F.transform(elements, code)


def row_constants(params: SketchParams, row: int) -> tuple[int, int]:
    return multiplier(f"a:{params.seed}:{row}"), offset(f"b:{params.seed}:{row}")


def column_hash(row_id: Column, row: int, params: SketchParams) -> Column:
    """The column of an item in a row of the grid, from its id alone."""
    if params.mixer == "murmur3":
        return F.pmod(F.hash(row_id, F.lit(params.seed * 1009 + row)), F.lit(params.cols)).cast("long")
    if params.mixer == "xxhash64":
        return F.pmod(F.xxhash64(row_id, F.lit(params.seed * 1009 + row)), F.lit(params.cols)).cast("long")
    a, b = row_constants(params, row)
    return F.pmod(F.pmod(row_id.cast("long"), F.lit(PRIME).cast("long")) * F.lit(a).cast("long") + F.lit(b).cast("long"), F.lit(PRIME).cast("long")) % F.lit(params.cols)


def murmur_array(words: list[np.ndarray], length: int, seed: np.ndarray | int) -> np.ndarray:
    """The 32-bit Murmur hash (third version) of rows of 32-bit words."""
    turned = lambda x, n: (x << np.uint32(n)) | (x >> np.uint32(32 - n))
    h = np.broadcast_to(np.asarray(seed, np.uint32), words[0].shape)
    for w in words:
        h = turned(h ^ (turned(w * np.uint32(0xCC9E2D51), 15) * np.uint32(0x1B873593)), 13) * np.uint32(5) + np.uint32(0xE6546B64)
    h = h ^ np.uint32(length)
    h = (h ^ (h >> np.uint32(16))) * np.uint32(0x85EBCA6B)
    h = (h ^ (h >> np.uint32(13))) * np.uint32(0xC2B2AE35)
    return h ^ (h >> np.uint32(16))


def column_hash_array(ids: np.ndarray, row: int, params: SketchParams) -> np.ndarray:
    """The column hash over an array of ids, by the portable mixer or Murmur."""
    if params.mixer == "murmur3":
        own = ids.astype(np.int64).view(np.uint64)
        first = murmur_array([(own & np.uint64(0xFFFFFFFF)).astype(np.uint32), (own >> np.uint64(32)).astype(np.uint32)], 8, 42)
        word = np.full(len(own), (params.seed * 1009 + row) & 0xFFFFFFFF, np.uint32)
        return np.mod(murmur_array([word], 4, first).view(np.int32).astype(np.int64), params.cols)
    a, b = row_constants(params, row)
    return (np.mod(ids, PRIME) * a + b) % PRIME % params.cols


def sign_hash(row_id: Column, row: int, params: SketchParams) -> Column:
    """-1 or 1, from the id alone: the coefficients of the signed measurement."""
    a, b = multiplier(f"sa:{params.seed}:{row}"), offset(f"sb:{params.seed}:{row}")
    h = F.pmod(F.pmod(row_id.cast("long"), F.lit(PRIME).cast("long")) * F.lit(a).cast("long") + F.lit(b).cast("long"), F.lit(PRIME).cast("long"))
    return F.when(h % 2 == 0, F.lit(1)).otherwise(F.lit(-1)).cast("long")


@lru_cache(maxsize=16)
def constants(params: SketchParams) -> dict[str, np.ndarray]:
    """alpha, beta, gamma by [row, col, rep, k]; shared coordinates repeat values."""
    shape = (params.rows, params.cols, params.reps, params.hashes)
    out = {n: np.zeros(shape, np.int64) for n in ("alpha", "beta", "gamma")}
    made: dict[tuple, tuple[int, int, int]] = {}
    for row in range(params.rows):
        for col in range(params.cols):
            for rep in range(params.reps):
                owner = params.shared(row, col, rep)
                for k in range(params.hashes):
                    if (owner, k) not in made:
                        tail = ":".join(map(str, (params.seed, *owner, k)))
                        made[owner, k] = multiplier(f"alpha:{tail}"), offset(f"beta:{tail}"), multiplier(f"gamma:{tail}")
                    for name, value in zip(("alpha", "beta", "gamma"), made[owner, k]):
                        out[name][row, col, rep, k] = value
    return out


def hash_params(spark: SparkSession, params: SketchParams) -> DataFrame:
    """``row, col, rep, alpha, beta, gamma``: arrays over k, one row per collision
    array; rows * cols * reps rows, a number that no data changes."""
    c = constants(params)
    made = [
        (i, j, o, *(c[n][i, j, o].tolist() for n in ("alpha", "beta", "gamma")))
        for i in range(params.rows) for j in range(params.cols) for o in range(params.reps)
    ]
    return spark.createDataFrame(made, "row long, col long, rep long, alpha array<long>, beta array<long>, gamma array<long>")
