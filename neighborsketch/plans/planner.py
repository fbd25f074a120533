"""Choices that depend on sizes: layout, engine, how counters are read, how scores decode."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..functions.params import SketchParams
from ..operators import decode
from ..operators.grid import Sketch, build_sketch


@dataclass(frozen=True)
class Plan:
    engine: str  # sql or arrow
    read: str  # broadcast or shuffle
    decode: str  # full, threshold or arrow
    layout: str  # dense or sparse
    reason: str


def choose(p: SketchParams, *, n_items: int, n_queries: int, nonzero: int | None = None, width_bits: int = 16) -> Plan:
    """nonzero: counters that aren't zero; by default at most one per item and array it enters."""
    nonzero = min(p.counters, n_items * p.rows * p.reps) if nonzero is None else nonzero
    plain = p.measurement == "cms" and p.mixer == "portable"
    read = "broadcast" if p.counters <= decode.BROADCAST_COUNTERS else "shuffle"
    layout = "dense" if p.counters * width_bits // 8 <= nonzero * (4 + width_bits // 8) else "sparse"
    engine = "arrow" if plain else "sql"
    how = "arrow" if engine == "arrow" and p.counters <= decode.FLAT_COUNTERS else ("threshold" if p.measurement == "cms" and n_items > 64 * p.cols else "full")
    return Plan(engine, read, how, layout, f"{p.counters} counters, {nonzero} not zero, {n_queries} queries on {n_items} items")


def report_neighbors(items: DataFrame, queries: DataFrame, p: SketchParams, v: int, *, groups: int = 1, hold_out: str = "none", n_items: int | None = None) -> DataFrame:
    """Builds, queries and decodes by the plan. ``qid, rank, id, score``."""
    n_items = items.count() if n_items is None else n_items
    plan = choose(p, n_items=n_items, n_queries=queries.count())
    sketch: Sketch = build_sketch(items, p, engine=plan.engine)
    if plan.decode == "arrow":
        ys = decode.measure_arrow(sketch, queries, groups=groups, hold_out=hold_out)
        return decode.top_arrow(ys, items.select("id"), p, v, exclude_own=hold_out != "none")
    return decode.top_neighbors(sketch, queries, items.select("id"), v, groups=groups, hold_out=hold_out, decode=plan.decode)
