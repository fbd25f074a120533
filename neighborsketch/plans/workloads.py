"""The experiments: query sets, hold-out protocols, sweeps and headline figures."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.params import SketchParams
from ..operators import baselines, decode, exact, layout, measures
from ..operators.grid import build_sketch
from ..sources.store import stored

POINT = "method string, setting string, bytes long, ratio double, threshold string, queries long, recall double"
THRESHOLDS = ((8, 10), (9, 10))


def close_queries(items: DataFrame, num: int, den: int) -> tuple[DataFrame, DataFrame]:
    """The items that have another at least that similar, and all such pairs, which are
    found once and written."""
    pairs = stored(exact.close_pairs(items, num, den), "close-pairs")
    return items.join(pairs.select(F.col("qid").alias("id")).distinct(), "id", "left_semi"), pairs


def sketch_top(items: DataFrame, queries: DataFrame, p: SketchParams, v: int = 20, *, groups: int = 1, protocol: str = "decrement_one") -> DataFrame:
    """Neighbours by the sketch. protocol: how the query itself is kept out:
    ``decrement_one`` (its own counts taken off), ``holdout_all`` (no query is in the
    sketch) or ``exclude_at_decode`` (it is only left out of the answer)."""
    kept = items.join(queries.select("id"), "id", "left_anti") if protocol == "holdout_all" else items
    sketch = build_sketch(kept, p, engine="arrow")
    ys = decode.measure(sketch, queries, groups=groups, hold_out="decrement_one" if protocol == "decrement_one" else "none")
    return decode.top_arrow(ys, kept.select("id"), p, v, exclude_own=True)


def _recalls(top: DataFrame, truth: DataFrame) -> list[tuple[str, int, float]]:
    rows = measures.recall_at_each(top, truth, THRESHOLDS).orderBy("threshold").collect()  # a row a threshold
    return [(f"{r.threshold:.1f}", r.queries, float(r.recall or 0.0)) for r in rows]


def sweep(items: DataFrame, *, grid: Iterable[SketchParams] = (), projections: Iterable[int] = (), fractions: Iterable[float] = (), groups: int = 1, uncompressed: int | None = None) -> DataFrame:
    """Points of every method: the sketch in both layouts for each grid, projections and
    samples, these two with Euclidean search. Truth and query set are found once; the
    projections are made once and cut to prefixes; each point is a job of its own.
    uncompressed: bytes of the data, by default of 32-bit ids in rows."""
    spark = items.sparkSession
    items = stored(items, "sweep-items")
    queries, truth = close_queries(items, *THRESHOLDS[0])
    queries = stored(queries, "sweep-queries")
    n, full = items.count(), measures.uncompressed_bytes(items).first().bytes if uncompressed is None else uncompressed
    points = []

    def add(method: str, setting: str, size: int, found: list[tuple[str, int, float]]) -> None:
        points.extend((method, setting, int(size), size / max(full, 1), t, q, r) for t, q, r in found)

    for p in grid:
        sketch = build_sketch(items, p, engine="arrow")
        sketch.cells = stored(sketch.cells, "sweep-cells")
        ys = decode.measure(sketch, queries, groups=min(groups, p.reps), hold_out="decrement_one")
        found = _recalls(decode.top_arrow(ys, items.select("id"), p, 20, exclude_own=True), truth)
        for kind in ("dense", "sparse"):
            add(f"sketch_{kind}", setting_of(p), layout.sketch_bytes(sketch, kind).first().bytes, found)
    wanted = sorted(projections)
    if wanted:
        vectors = stored(baselines.random_projection(items, wanted[-1], scaled=False), "sweep-projections")
        asked = vectors.join(queries.select("id"), "id", "left_semi")
        for m in wanted:
            top = baselines.projection_top(vectors, asked, 20, prefix=m)
            add("projections", f"m={m}", measures.projection_bytes(m, n), _recalls(top, truth))
    for f in fractions:
        sample = baselines.sample_items(items, max(1, int(f * n + 0.5)))
        add("sampling", f"fraction={f}", measures.sample_bytes(sample).first().bytes, _recalls(baselines.sample_top(sample, queries, 20, "euclidean"), truth))
    return spark.createDataFrame(points, POINT)


def setting_of(p: SketchParams) -> str:
    return f"rows={p.rows},cols={p.cols},reps={p.reps},hashes={p.hashes},buckets={p.slots}"


def frontier(points: DataFrame) -> DataFrame:
    return measures.pareto(points, "bytes", "recall", ["method", "threshold"])


def headline(points: DataFrame, target: float = 0.8) -> DataFrame:
    """``method, threshold, bytes``: bytes that each method needs for the target recall."""
    return measures.bytes_at_recall(points, target, ["method", "threshold"])


def mutual_pairs(top: DataFrame) -> DataFrame:
    """``a, b``: pairs that report each other."""
    one = top.select(F.col("qid").alias("a"), F.col("id").alias("b"))
    return one.join(one.select(F.col("a").alias("b"), F.col("b").alias("a")), ["a", "b"]).where("a < b")
