"""Sketches over streams: running counters, windows, snapshots, retractions."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.params import SketchParams
from ..operators.grid import touched
from ..sources.store import rows_bounded

BROADCAST_ROWS = 1_000_000
EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def file_stream(spark: SparkSession, path: str, schema: str, *, pattern: str | None = None, per_trigger: int | None = None) -> DataFrame:
    """A stream of Parquet files as they arrive."""
    reader = spark.readStream.schema(schema)
    if pattern:
        reader = reader.option("pathGlobFilter", pattern)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    return reader.parquet(path)


def rate_stream(spark: SparkSession, rows_per_second: int = 1000) -> DataFrame:
    """``id, ts, elements``: an endless stream of synthetic items, for load tests."""
    source = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    parts = F.transform(F.sequence(F.lit(0), F.lit(4)), lambda i: F.pmod(F.xxhash64("value", i), F.lit(10_000)))
    return source.select(F.col("value").alias("id"), F.col("timestamp").alias("ts"), F.array_distinct(parts).alias("elements"))


def with_event_time(events: DataFrame, column: str = "ts") -> DataFrame:
    """The event time as a timestamp: watermarks don't take one without a zone."""
    return events.withColumn(column, F.col(column).cast("timestamp"))


def once(stream: DataFrame, keys: list[str], time_col: str, delay: str) -> DataFrame:
    """Each key counts once within the watermark."""
    return stream.withWatermark(time_col, delay).dropDuplicatesWithinWatermark(keys)


def running_sketch(items: DataFrame, p: SketchParams) -> DataFrame:
    """``cell, n`` of all items so far. The state is the counters that aren't zero, so
    its size has a bound that no stream exceeds."""
    return touched(items, p).groupBy("cell").agg(F.sum("w").alias("n"))


def windowed_sketch(items: DataFrame, p: SketchParams, *, time_col: str, size: str, slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """``start, end, cell, n``: one sketch per tumbling or sliding window, emitted when
    the watermark passes it; later rows are dropped and counted by the query."""
    cells = touched(items.withWatermark(time_col, delay), p, keep=[time_col])
    return cells.groupBy(F.window(time_col, size, slide) if slide else F.window(time_col, size), "cell").agg(F.sum("w").alias("n")).select("window.start", "window.end", "cell", "n")


def session_sets(events: DataFrame, *, key: str, element: str, time_col: str, gap: str, delay: str | None = None) -> DataFrame:
    """``key, start, end, elements``: the set of each visit, closed by a gap."""
    source = events.withWatermark(time_col, delay) if delay else events
    return source.groupBy(key, F.session_window(time_col, gap)).agg(F.sort_array(F.collect_set(element)).alias("elements")).select(key, "session_window.start", "session_window.end", "elements")


def keep_running(stream: DataFrame, merge: Callable[[DataFrame, int], None], checkpoint: str):
    """Runs a stream to its present end, handing each batch with its id to ``merge``,
    which must ignore an id that it has merged before."""
    return stream.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def stored_merge(path: str, p: SketchParams) -> Callable[[DataFrame, int], None]:
    """A merge that writes every batch's counters under its id: writing one again
    changes nothing, and the sketch is the sum over the folder."""

    def merge(batch: DataFrame, batch_id: int) -> None:
        touched(batch, p).groupBy("cell").agg(F.sum("w").alias("n")).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return merge


def stored_sketch(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).groupBy("cell").agg(F.sum("n").alias("n"))


def as_of(queries: DataFrame, snapshots: DataFrame, *, query_time: str = "at", snapshot_time: str = "taken", bucket: str = "hour") -> DataFrame:
    """Each query with the last snapshot that is not after it (null if none): both
    sides in one ordered pass within each ``bucket`` of time, and the last snapshot of
    earlier buckets carried over by a table with a row a bucket."""
    from pyspark.sql import Window

    left = queries.select(F.col(query_time).alias("__t"), F.lit(1).alias("__kind"), F.struct(*queries.columns).alias("__q"), F.lit(None).cast(snapshots.schema[snapshot_time].dataType).alias("__s"))
    right = snapshots.select(F.col(snapshot_time).alias("__t"), F.lit(0).alias("__kind"), F.lit(None).cast(left.schema["__q"].dataType).alias("__q"), F.col(snapshot_time).alias("__s"))
    both = left.unionByName(right).withColumn("__bucket", F.date_trunc(bucket, "__t"))
    inside = both.withColumn("__last", F.last("__s", ignorenulls=True).over(Window.partitionBy("__bucket").orderBy("__t", "__kind")))
    buckets = inside.groupBy("__bucket").agg(F.max("__s").alias("m"))
    carried = buckets.withColumn("__before", F.max("m").over(Window.orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1))).select("__bucket", "__before")
    carried = F.broadcast(carried) if not inside.isStreaming and rows_bounded(carried, BROADCAST_ROWS) else carried
    return inside.where("__kind = 1").join(carried, "__bucket").select("__q.*", F.coalesce("__last", "__before").alias("snapshot"))


def interval_sketch(daily: DataFrame, intervals: DataFrame) -> DataFrame:
    """``interval_id, cell, n``: the sum of the days from first to last, inclusive. Days
    are enumerated, so the join is by equality."""
    days = intervals.select("interval_id", F.explode(F.sequence("first", "last")).alias("day"))
    few = not daily.isStreaming and rows_bounded(days, BROADCAST_ROWS)
    return daily.join(F.broadcast(days) if few else days, "day").groupBy("interval_id", "cell").agg(F.sum("n").alias("n"))


def retracting_items(stream: DataFrame, *, key: str = "id", element: str = "element") -> DataFrame:
    """An edge stream as signed item versions: ``id, elements, sign``. When an item's set
    grows, its old version leaves (-1) and the new one enters (+1), so the running sum
    over versions is the sketch of the present sets."""

    def update(k: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = list(state.get[0]) if state.exists else []
        new = sorted(set(held) | {int(e) for part in parts for e in part[element].dropna()})
        if new != held:
            state.update((new,))
            rows = [(int(k[0]), new, 1)] + ([(int(k[0]), held, -1)] if held else [])
            yield pd.DataFrame(rows, columns=["id", "elements", "sign"])

    return stream.groupBy(key).applyInPandasWithState(update, "id long, elements array<long>, sign int", "elements array<long>", "append", GroupStateTimeout.NoTimeout)


def retracted_sketch(versions: DataFrame, p: SketchParams) -> DataFrame:
    return touched(versions, p, weight_col="sign").groupBy("cell").agg(F.sum("w").cast("long").alias("n"))


def answer_stream(queries: DataFrame, cells: DataFrame, p: SketchParams) -> DataFrame:
    """``qid, row, col, rep, n`` of a query stream against a stored sketch."""
    from ..operators.decode import read_counters, query_cells
    from ..operators.grid import Sketch

    return read_counters(Sketch(cells, p), query_cells(queries, p))
