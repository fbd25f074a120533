"""Collision arrays and the neighbour sketch: build, merge, subtract, group.

A counter's place is one number, ``cell = ((row * cols + col) * reps + rep) * slots +
bucket``. Building is a narrow projection of items to cells and one aggregation by
that number, so what is shuffled is at most the non-zero counters of each map task.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import hashing, lsh
from ..functions.params import PRIME, SketchParams


@dataclass
class Sketch:
    """``cells``: cell, n for the counters that aren't zero."""

    cells: DataFrame
    params: SketchParams
    n_items: int | None = None


def pack(row: Column, col: Column, rep: Column, bucket: Column, p: SketchParams) -> Column:
    return (((row * p.cols + col) * p.reps + rep) * F.lit(p.slots).cast("long") + bucket).cast("long")


def unpack(cells: DataFrame, p: SketchParams) -> DataFrame:
    """``row, col, rep, bucket, n`` from packed cells."""
    array = F.floor(F.col("cell") / F.lit(p.slots)).cast("long")
    whole = lambda x, n: F.floor(x / F.lit(n)).cast("long")
    return cells.select(
        whole(array, p.cols * p.reps).alias("row"), (whole(array, p.reps) % p.cols).alias("col"), (array % p.reps).alias("rep"), (F.col("cell") % F.lit(p.slots)).alias("bucket"), "n")


def usable(items: DataFrame, id_col: str = "id", payload_col: str = "elements") -> DataFrame:
    """Items with an id and at least one element that isn't null: the others have no hash."""
    payload = F.filter(F.col(payload_col), lambda x: x.isNotNull())
    return items.withColumn(payload_col, payload).where(F.col(id_col).isNotNull() & (F.size(payload_col) > 0))


def _cells_of(row_id: Column, p: SketchParams) -> Column:
    """The (row, col, weight) that an item enters."""
    one = F.lit(1).cast("long")
    if p.measurement == "bernoulli":
        made = []
        for i in range(p.rows):
            for j in range(p.cols):
                a, b = hashing.multiplier(f"ba:{p.seed}:{i}:{j}"), hashing.offset(f"bb:{p.seed}:{i}:{j}")
                h = F.pmod(F.pmod(row_id.cast("long"), F.lit(PRIME).cast("long")) * F.lit(a).cast("long") + F.lit(b).cast("long"), F.lit(PRIME).cast("long"))
                made.append(F.struct(F.lit(i).cast("long").alias("row"), F.lit(j).cast("long").alias("col"), (h % 2).cast("long").alias("w")))
        return F.filter(F.array(*made), lambda x: x["w"] != 0)
    sign = (lambda i: hashing.sign_hash(row_id, i, p)) if p.measurement == "signed" else (lambda i: one)
    return F.array(*[F.struct(F.lit(i).cast("long").alias("row"), hashing.column_hash(row_id, i, p).alias("col"), sign(i).alias("w")) for i in range(p.rows)])


def touched(items: DataFrame, p: SketchParams, *, id_col: str = "id", payload_col: str = "elements", weight_col: str | None = None, keep: list[str] | None = None, engine: str = "sql") -> DataFrame:
    """``keep..., cell, w``: one row per counter that an item adds to."""
    keep = keep or []
    weight = F.col(weight_col).cast("double") if weight_col else None
    rows = usable(items, id_col, payload_col).select(*keep, F.col(id_col).cast("long").alias("__id"), F.col(payload_col).alias("__payload"), *([weight.alias("__w")] if weight_col else []))
    if engine == "arrow":
        if p.measurement != "cms" or p.mixer == "xxhash64" or weight_col or keep:
            raise ValueError("the Arrow engine builds plain sketches, by the portable mixer or Murmur")
        return _touched_arrow(rows, p)
    constants = hashing.hash_params(items.sparkSession, p)
    placed = rows.select("*", F.explode(_cells_of(F.col("__id"), p)).alias("__c")).select("*", F.col("__c.row").alias("row"), F.col("__c.col").alias("col"), F.col("__c.w").alias("__sign")).drop("__c")
    joined = placed.join(F.broadcast(constants), ["row", "col"])  # rows * cols * reps rows, whatever the data
    cell = pack(F.col("row"), F.col("col"), F.col("rep"), lsh.bucket(F.col("__payload"), F.col("alpha"), F.col("beta"), F.col("gamma"), p), p)
    return joined.select(*keep, cell.alias("cell"), (F.col("__sign") * F.col("__w") if weight_col else F.col("__sign")).alias("w"))


def _flat(batch: pa.RecordBatch, name: str, p: SketchParams) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    column = batch.column(batch.schema.get_field_index(name))
    lengths = column.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    values = column.flatten().to_numpy(zero_copy_only=False)
    if p.family in ("signed_projection", "euclidean_grid"):
        values = np.sign(values) * np.floor(np.abs(values.astype(np.float64)) * lsh.GRID_SCALE + 0.5)
    return values.astype(np.int64), np.cumsum(lengths) - lengths, lengths


def _touched_arrow(rows: DataFrame, p: SketchParams) -> DataFrame:
    """Vectorised: each batch gives its cells already counted."""
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = hashing.constants(p)
        for whole in batches:
            for at in range(0, whole.num_rows, 2000):
                batch = whole.slice(at, 2000)
                ids = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
                values, starts, lengths = _flat(batch, "__payload", p)
                found = []
                for i in range(p.rows):
                    cols = hashing.column_hash_array(ids, i, p)
                    for o in range(p.reps):
                        codes = [lsh.codes_array(values, starts, lengths, c["alpha"][i, cols, o, k], c["beta"][i, cols, o, k], p) for k in range(p.hashes)]
                        found.append(((i * p.cols + cols) * p.reps + o) * p.slots + lsh.buckets_array(codes, c["gamma"][i, cols, o], p))
                cells, counts = np.unique(np.concatenate(found), return_counts=True)
                yield pa.record_batch([pa.array(cells), pa.array(counts.astype(np.int64))], ["cell", "w"])

    return rows.mapInArrow(run, "cell long, w long")


def build_sketch(items: DataFrame, p: SketchParams, *, id_col: str = "id", payload_col: str = "elements", weight_col: str | None = None, engine: str = "sql") -> Sketch:
    """One pass over the items; weights (any real numbers) replace the ones."""
    cells = touched(items, p, id_col=id_col, payload_col=payload_col, weight_col=weight_col, engine=engine)
    summed = cells.groupBy("cell").agg(F.sum("w").alias("n"))
    return Sketch(summed.where("n != 0") if p.measurement == "signed" or weight_col else summed, p)


def build_grouped(items: DataFrame, p: SketchParams, groups: list[str], *, how: str = "group", id_col: str = "id", payload_col: str = "elements") -> DataFrame:
    """``groups..., cell, n``: one sketch per site, day or language. how: ``group``,
    or ``rollup`` / ``cube`` for the merged parents as well (null group columns)."""
    cells = touched(items, p, id_col=id_col, payload_col=payload_col, keep=groups)
    keys = [*groups, "cell"]
    if how == "group":
        return cells.groupBy(*keys).agg(F.sum("w").alias("n"))
    first = cells.groupBy(*keys).agg(F.sum("w").alias("w"))  # the parents add up counters, not items
    sets = [groups[:i] for i in range(len(groups) + 1)] if how == "rollup" else [[g for j, g in enumerate(groups) if m >> j & 1] for m in range(1 << len(groups))]
    return first.groupingSets([[F.col(c) for c in [*s, "cell"]] for s in sets], *[F.col(k) for k in keys]).agg(F.sum("w").alias("n"), F.grouping_id().alias("level"))


def _same(sketches: Iterable[Sketch]) -> SketchParams:
    found = {s.params for s in sketches}
    if len(found) != 1:
        raise ValueError("only sketches of equal parameters combine")
    return found.pop()


def merge_sketches(*sketches: Sketch) -> Sketch:
    """The sketch of the union of disjoint data; ids must be unique over all of it."""
    p = _same(sketches)
    cells = reduce(DataFrame.unionByName, [s.cells.select("cell", "n") for s in sketches])
    return Sketch(cells.groupBy("cell").agg(F.sum("n").alias("n")).where("n != 0"), p)


def subtract(a: Sketch, b: Sketch) -> Sketch:
    p = _same((a, b))
    return merge_sketches(a, Sketch(b.cells.select("cell", (-F.col("n")).alias("n")), p))


def remove_items(sketch: Sketch, items: DataFrame, **columns: str) -> Sketch:
    """Deletes items whose payloads are at hand."""
    return subtract(sketch, build_sketch(items, sketch.params, **columns))


def differences(a: Sketch, b: Sketch) -> DataFrame:
    """Counters in which two sketches differ; none if they are equal."""
    joined = a.cells.select("cell", F.col("n").alias("left_n")).join(b.cells.select("cell", F.col("n").alias("right_n")), "cell", "full")
    return joined.where(F.coalesce("left_n", F.lit(0)) != F.coalesce("right_n", F.lit(0)))


def kde_params(reps: int, **more) -> SketchParams:
    return SketchParams(rows=1, cols=1, reps=reps, **more)


def collision_array(items: DataFrame, *, family: str = "minhash", hashes: int = 1, buckets: int | None = 100, seed: int = 42, weight_col: str | None = None) -> DataFrame:
    """``bucket, n``: a single collision array over all items."""
    p = SketchParams(1, 1, 1, hashes=hashes, buckets=buckets, family=family, seed=seed)
    return build_sketch(items, p, weight_col=weight_col).cells.select(F.col("cell").alias("bucket"), "n")


def with_seed(p: SketchParams, seed: int) -> SketchParams:
    return replace(p, seed=seed)
