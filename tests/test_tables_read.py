"""The calculators take their sizes from the given tables."""

import math

import pytest

from neighborsketch import catalog


@pytest.fixture()
def folder(spark, tmp_path):
    lines = [(o, p, p % 2) for o in range(5) for p in range(o, o + 4)]
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(o, 11 * (o % 3)) for o in range(5)], "o_orderkey long, o_custkey long").write.parquet(f"{tmp_path}/orders.parquet")
    spark.sql("SELECT event_id, event_id % 3 AS user_id, 'view' AS event_type, timestamp'2024-01-01 05:00:00' AS ts FROM (SELECT id AS event_id FROM range(9))").write.parquet(f"{tmp_path}/events.parquet")
    return str(tmp_path)


def test_calculators_take_sizes_from_tables(spark, folder):
    run = lambda name: catalog.QUERIES[name](spark, folder).collect()
    assert {r.load * r.cols for r in run("suggested_params")} == {5.0}
    assert all(math.isclose(r.bits, (r.buckets or r.code_range**r.hashes) * math.log2(5), abs_tol=1e-3) for r in run("array_bits"))
    assert {(r.key, r.n) for r in run("cms_sizes")} == {("l_orderkey", 5), ("l_partkey", 8), ("l_suppkey", 2)}
    assert {r.norm1 for r in run("error_budgets") if r.view == "user_events"} == {3.0}  # three users of one set


def test_columns_hold_the_customers(spark, folder):
    found = catalog.QUERIES["ids_by_column"](spark, folder).collect()
    assert sorted((r.row, r.id) for r in found) == [(row, i) for row in range(3) for i in (0, 11, 22)]
