"""Locality-sensitive hash families.

Each family says how a payload becomes codes and how likely two payloads collide at
a similarity; that chance is monotone, which is all that the sketch needs.

minhash            sets            p = J                  codes below PRIME
onebit_minhash     sets            p = (1 + J) / 2        codes 0, 1
signed_projection  vectors         p = 1 - angle / pi     codes 0, 1
euclidean_grid     vectors         falls with distance    cell numbers mod PRIME
bit_sample         sets as bits    p = 1 - hamming / dim  codes 0, 1

Vectors are projected on hash-generated sign planes: coordinate c of plane
(row, col, rep, k) is +-1 by the parity of a universal hash of c.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .params import PRIME, SketchParams

BIT_DIMS = 1 << 16  # coordinates that bit_sample draws from, unless told otherwise
GRID_SCALE = 1_000_000  # vectors are rounded to this for exact integer sums


def _lin(a: Column, x: Column, b: Column) -> Column:
    return (a * x + b) % F.lit(PRIME)


def minhash_code(elements: Column, alpha: Column, beta: Column) -> Column:
    """The least hash of a set's elements (codes below PRIME); null for no elements."""
    return F.array_min(F.transform(elements, lambda e: _lin(alpha, e, beta)))


def projection_sum(vector: Column, alpha: Column, beta: Column) -> Column:
    """The exact sum of a rounded vector's coordinates under hash-generated signs."""
    signed = F.transform(vector, lambda x, c: F.when(_lin(alpha, (c + 1).cast("long"), beta) % 2 == 0, F.round(x.cast("double") * GRID_SCALE).cast("long")).otherwise(-F.round(x.cast("double") * GRID_SCALE).cast("long")))
    return F.aggregate(signed, F.lit(0).cast("long"), lambda s, x: s + x)


def one_code(payload: Column, alpha: Column, beta: Column, params: SketchParams) -> Column:
    """One hash value of a payload."""
    if params.family == "minhash":
        return minhash_code(payload, alpha, beta)
    if params.family == "onebit_minhash":
        return minhash_code(payload, alpha, beta) % 2
    if params.family == "signed_projection":
        return F.when(projection_sum(payload, alpha, beta) >= 0, F.lit(1)).otherwise(F.lit(0)).cast("long")
    if params.family == "euclidean_grid":
        step = int(params.width * GRID_SCALE)
        shifted = projection_sum(payload, alpha, beta) + F.pmod(beta, F.lit(step))
        return F.pmod(F.floor(shifted / F.lit(step)).cast("long"), F.lit(PRIME))
    return F.array_contains(payload, alpha % F.lit(BIT_DIMS)).cast("long")


def concat_codes(codes: Column, code_range: int) -> Column:
    """K codes below code_range as one number below code_range ** K."""
    return F.aggregate(codes, F.lit(0).cast("long"), lambda acc, c: acc * F.lit(code_range) + c)


def rehash(codes: Column, gamma: Column, buckets: int) -> Column:
    """K codes to one of the buckets; each product is reduced before it is added."""
    products = F.zip_with(codes, gamma, lambda c, g: (c * g) % F.lit(PRIME))
    return F.aggregate(products, F.lit(0).cast("long"), lambda acc, x: (acc + x) % F.lit(PRIME)) % F.lit(buckets)


def bucket(payload: Column, alpha: Column, beta: Column, gamma: Column, params: SketchParams) -> Column:
    """The slot of a payload in one collision array (alpha, beta, gamma: over k)."""
    codes = F.transform(F.arrays_zip(alpha.alias("a"), beta.alias("b")), lambda z: one_code(payload, z["a"], z["b"], params))
    if params.buckets is None:
        return concat_codes(codes, params.code_range)
    return rehash(codes, gamma, params.buckets)


def collision_probability(similarity: float, params: SketchParams) -> float:
    """Chance that one code of two payloads agrees. similarity: Jaccard, cosine,
    share of equal bits, or for the grid the distance."""
    if params.family == "minhash":
        return similarity
    if params.family == "onebit_minhash":
        return (1 + similarity) / 2
    if params.family == "signed_projection":
        return 1 - math.acos(max(-1.0, min(1.0, similarity))) / math.pi
    if params.family == "bit_sample":
        return similarity
    r = params.width / max(similarity, 1e-12)
    normal = 0.5 * math.erfc(r / math.sqrt(2))
    return 1 - 2 * normal - 2 / (math.sqrt(2 * math.pi) * r) * (1 - math.exp(-r * r / 2))


# numpy forms, for the Arrow engine -------------------------------------------------------


def codes_array(values: np.ndarray, starts: np.ndarray, lengths: np.ndarray, alpha: np.ndarray, beta: np.ndarray, params: SketchParams) -> np.ndarray:
    """One code per item. values: all items' payloads one after the other (codes of
    elements, or rounded coordinates); alpha, beta: one per item, or one for all."""
    if params.family in ("minhash", "onebit_minhash"):
        h = values * (alpha if np.ndim(alpha) == 0 else np.repeat(alpha, lengths))
        h += beta if np.ndim(beta) == 0 else np.repeat(beta, lengths)
        np.remainder(h, PRIME, out=h)
        least = np.minimum.reduceat(h, starts)
        return least % 2 if params.family == "onebit_minhash" else least
    alpha, beta = np.broadcast_to(alpha, len(lengths)), np.broadcast_to(beta, len(lengths))
    place = np.arange(len(values)) - np.repeat(starts, lengths)
    if params.family == "bit_sample":
        hit = values == np.repeat(alpha % BIT_DIMS, lengths)
        return np.add.reduceat(hit.astype(np.int64), starts).clip(0, 1)
    h = ((place + 1) * np.repeat(alpha, lengths) + np.repeat(beta, lengths)) % PRIME
    total = np.add.reduceat(np.where(h % 2 == 0, values, -values), starts)
    if params.family == "signed_projection":
        return (total >= 0).astype(np.int64)
    step = int(params.width * GRID_SCALE)
    return np.floor_divide(total + np.mod(beta, step), step) % PRIME


def buckets_array(codes: list[np.ndarray], gamma: np.ndarray, params: SketchParams) -> np.ndarray:
    """codes: one array per k; gamma: (items, k)."""
    out = np.zeros(len(codes[0]), np.int64)
    for k, c in enumerate(codes):
        out = out * params.code_range + c if params.buckets is None else (out + c * gamma[:, k] % PRIME) % PRIME
    return out if params.buckets is None else out % params.buckets
