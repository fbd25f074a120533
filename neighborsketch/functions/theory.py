"""Calculators of the sketch's guarantees, as Columns over per-query statistics and as
plain numbers. Constants hidden by big-O are the parameter ``const``."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

GUARD = 1e-9  # against floating error just above an integer


def choose_hashes(tail: float, gap: float) -> int | None:
    """The least number of concatenated hashes that makes the kernel vector sparse:
    ceil(2 ln B / ln(1 / gap)), one at least. None for a tie (gap = 1)."""
    if gap >= 1:
        return None
    if gap <= 0 or tail <= 1:
        return 1
    return max(1, math.ceil(2 * math.log(tail) / math.log(1 / gap) - GUARD))


def choose_hashes_column(tail: Column, gap: Column) -> Column:
    raw = F.ceil(2 * F.log(F.greatest(tail, F.lit(1.0))) / F.log(1 / F.when((gap > 0) & (gap < 1), gap)) - GUARD).cast("int")
    return F.when(gap >= 1, F.lit(None).cast("int")).when((gap <= 0) | gap.isNull() | (tail <= 1), F.lit(1)).otherwise(F.greatest(raw, F.lit(1)))


def memory_exponent(p_v: float, code_range: int, gap: float) -> float:
    """b of N^b log^3 N bits: (6 |ln p_v| + 2 ln r) / ln(1 / gap)."""
    return (6 * abs(math.log(p_v)) + 2 * math.log(code_range)) / math.log(1 / gap)


def memory_exponent_column(p_v: Column, code_range: int, gap: Column) -> Column:
    usable = F.when((gap > 0) & (gap < 1), gap)
    return (6 * F.abs(F.log(F.when(p_v > 0, p_v))) + 2 * math.log(code_range)) / F.log(1 / usable)


def repetitions_needed(measurements: int, norm_tilde: float, eps: float, delta: float, const: float = 1.0) -> float:
    """Arrays for all measurements within eps with probability 1 - delta."""
    return const * measurements * norm_tilde**2 / eps**2 * math.log(measurements / delta)


def arrays_needed(norm1: float, norm_tilde: float, eps: float, delta: float, n: int, const: float = 1.0) -> float:
    """Arrays for every recovered value within eps / 2."""
    deep = math.log(n / delta)
    return const * norm_tilde**2 * norm1 / eps**3 * math.log(max(norm1 / (eps * delta) * deep, math.e)) * deep


def arrays_needed_column(norm1: Column, norm_tilde: Column, eps: Column, delta: float, n: Column, const: float = 1.0) -> Column:
    deep = F.log(n / delta)
    inner = F.greatest(norm1 / (F.when(eps > 0, eps) * delta) * deep, F.lit(math.e))
    return const * norm_tilde * norm_tilde * norm1 / F.pow(F.when(eps > 0, eps), F.lit(3)) * F.log(inner) * deep


def sketch_bits(n: int, b: float) -> float:
    return n**b * math.log(n) ** 3


def sketch_time(n: int, b: float) -> float:
    return n ** (b + 1) * math.log(n) ** 3


def array_bits(code_range: int, hashes: int, n: int, buckets: int | None = None) -> float:
    """Bits of one collision array, without and with a re-hash."""
    return (code_range**hashes if buckets is None else buckets) * math.log2(n)


def sketch_bits_from_norms(norm1: float, norm_tilde: float, eps: float, delta: float, n: int, code_range: int, hashes: int, buckets: int | None = None) -> float:
    """The direct way when the norms are simply bounded: arrays times bits of each."""
    return arrays_needed(norm1, norm_tilde, eps, delta, n) * array_bits(code_range, hashes, n, buckets)


def error_budget(eps: float, share: float = 0.5, norm1: float = 1.0) -> tuple[float, float]:
    """How a total error splits: (relative error of the cells, absolute error of the counters)."""
    return eps * share / norm1, eps * (1 - share)


def suggest_params(p_v: float, gap: float, tail: float, n: int, budget_bytes: int, width_bits: int = 16) -> list[dict]:
    """Grids of the usual ranges that fit a byte budget, largest first."""
    hashes = choose_hashes(tail, gap)
    wanted = [1, 2] if hashes is None else sorted({1, min(2, hashes)})
    out = []
    for rows in (2, 3, 4, 5):
        for cols in (100, 200, 500, 1000):
            for reps in (2, 4, 8):
                for buckets in (100, 300, 1000):
                    size = rows * cols * reps * buckets * width_bits // 8
                    if size <= budget_bytes:
                        out += [{"rows": rows, "cols": cols, "reps": reps, "hashes": k, "buckets": buckets, "bytes": size, "load": n / cols} for k in wanted]
    return sorted(out, key=lambda x: (-x["bytes"], x["hashes"], x["rows"]))


def cost_counters(p, n_items: int, n_queries: int, mean_size: float) -> dict[str, float]:
    """Hash evaluations, counter updates, reads and decoded rows, by phase."""
    touched = p.rows * p.reps
    asked = {"cell": p.arrays, "row": p.rows * p.reps, "rep": p.reps}[p.sharing]
    return {
        "build_hashes": n_items * touched * p.hashes * mean_size, "build_updates": n_items * touched,
        "query_hashes": n_queries * asked * p.hashes * mean_size, "query_reads": n_queries * p.arrays, "decoded": n_queries * n_items * p.rows,
    }
