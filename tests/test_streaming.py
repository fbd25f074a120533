"""Streams against batches."""

import datetime as dt
import time

from pyspark.sql import functions as F

from neighborsketch.functions.params import SketchParams
from neighborsketch.operators import grid
from neighborsketch.streaming import stream

P = SketchParams(2, 5, 2)
T0 = dt.datetime(2024, 1, 1)
SCHEMA = "id long, ts timestamp, elements array<long>"


def run(df, name, mode, folder):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", str(folder)).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def write(spark, rows, path):
    spark.createDataFrame(rows, SCHEMA).coalesce(1).write.mode("append").parquet(str(path))


def rows_of(n, start=0, hours=1):
    return [(i, T0 + dt.timedelta(hours=hours * i), [i % 7 + 1, i % 3 + 10]) for i in range(start, start + n)]


def test_running_equals_batch_and_duplicates_count_once(spark, tmp_path):
    write(spark, rows_of(20), tmp_path / "in")
    write(spark, rows_of(10), tmp_path / "in")  # sent again
    source = stream.once(stream.file_stream(spark, str(tmp_path / "in"), SCHEMA), ["id"], "ts", "60 days")
    run(stream.running_sketch(source, P), "once_sketch", "update", tmp_path / "c")
    got = spark.table("once_sketch").groupBy("cell").agg(F.max("n").alias("n"))
    want = grid.build_sketch(spark.createDataFrame(rows_of(20), SCHEMA), P)
    assert grid.differences(grid.Sketch(got, P), want).count() == 0


def test_windows_drop_late_rows(spark, tmp_path):
    write(spark, rows_of(72), tmp_path / "in")
    time.sleep(1.1)  # files are taken by age
    write(spark, rows_of(1, 72), tmp_path / "in")
    time.sleep(1.1)
    write(spark, [(500, T0, [1, 2])], tmp_path / "in")  # after its window closed
    source = stream.file_stream(spark, str(tmp_path / "in"), SCHEMA, per_trigger=1)
    q = run(stream.windowed_sketch(source, P, time_col="ts", size="1 day", delay="1 hour"), "window_sketch", "append", tmp_path / "c")
    assert sum(s.numRowsDroppedByWatermark for p in q.recentProgress for s in p.stateOperators) > 0
    per_day = spark.table("window_sketch").groupBy("start").agg(F.sum("n").alias("n")).collect()
    assert {r.n for r in per_day} == {24 * P.rows * P.reps} and len(per_day) >= 2


def test_stored_merge_is_idempotent(spark, tmp_path):
    write(spark, rows_of(15), tmp_path / "in")
    merge = stream.stored_merge(str(tmp_path / "out"), P)
    stream.keep_running(stream.file_stream(spark, str(tmp_path / "in"), SCHEMA), merge, str(tmp_path / "c")).awaitTermination()
    merge(spark.createDataFrame(rows_of(15), SCHEMA), 0)
    want = grid.build_sketch(spark.createDataFrame(rows_of(15), SCHEMA), P)
    assert grid.differences(grid.Sketch(stream.stored_sketch(spark, str(tmp_path / "out")), P), want).count() == 0


def test_retractions(spark, tmp_path):
    for part in ([(1, 5), (2, 6)], [(1, 7), (2, 6)]):
        spark.createDataFrame(part, "id long, element long").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    versions = stream.retracting_items(stream.file_stream(spark, str(tmp_path / "in"), "id long, element long", per_trigger=1))
    run(versions, "versions", "append", tmp_path / "c")
    got = stream.retracted_sketch(spark.table("versions"), P).where("n != 0")
    want = grid.build_sketch(spark.createDataFrame([(1, [5, 7]), (2, [6])], "id long, elements array<long>"), P)
    assert grid.differences(grid.Sketch(got, P), want).count() == 0


def test_as_of(spark):
    queries = spark.createDataFrame([(1, T0), (2, T0 + dt.timedelta(days=40)), (3, T0 - dt.timedelta(days=1)), (4, T0 + dt.timedelta(minutes=90))], "q long, at timestamp")
    snaps = spark.createDataFrame([(T0,), (T0 + dt.timedelta(hours=1),)], "taken timestamp")
    got = {r.q: r.snapshot for r in stream.as_of(queries, snaps).collect()}
    assert got == {1: T0, 2: T0 + dt.timedelta(hours=1), 3: None, 4: T0 + dt.timedelta(hours=1)}


def test_query_stream_against_stored_sketch(spark, tmp_path):
    items = spark.createDataFrame(rows_of(20), SCHEMA)
    cells = grid.build_sketch(items, P).cells
    cells.write.parquet(str(tmp_path / "cells"))
    write(spark, rows_of(3), tmp_path / "in")
    answers = stream.answer_stream(stream.file_stream(spark, str(tmp_path / "in"), SCHEMA), spark.read.parquet(str(tmp_path / "cells")), P)
    run(answers, "answers", "append", tmp_path / "c")
    assert spark.table("answers").count() == 3 * P.arrays


def test_event_stream_of_one_file_or_of_part_files(spark, tmp_path):
    from neighborsketch.catalog_experiments import stream_sketch_equals_batch

    rows = spark.sql("SELECT id AS event_id, TIMESTAMP_NTZ '2024-01-01 00:00:00' AS ts, id % 7 AS user_id, 'a' AS event_type, 0.5D AS value, '' AS props FROM range(60)")
    rows.repartition(3).write.parquet(str(tmp_path / "parts" / "events.parquet"))
    rows.coalesce(1).write.parquet(str(tmp_path / "one"))
    (tmp_path / "file").mkdir()
    next((tmp_path / "one").glob("part-*")).rename(tmp_path / "file" / "events.parquet")
    parts, file = (sorted(map(tuple, stream_sketch_equals_batch(spark, str(tmp_path / d)).collect())) for d in ("parts", "file"))
    assert parts == file and sum(n for _, n in parts) == 60 * 2 * 2
