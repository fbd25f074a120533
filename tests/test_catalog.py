"""Every query with SQL against DuckDB on the smallest tables, and a smoke run of entry()."""

from pathlib import Path

import duckdb
import numpy as np
import pandas as pd
import pytest

import __spark_entry__ as entry_point
from neighborsketch import catalog
from neighborsketch.operators import baselines
from neighborsketch.sources import views

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
pytestmark = pytest.mark.skipif(not Path(SF).exists(), reason="no test tables here")


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def plain(value):
    if value is None or value is pd.NaT or value != value:
        return None
    if hasattr(value, "item"):
        value = value.item()
    return round(value, 5) + 0.0 if isinstance(value, float) else value


def rows(frame: pd.DataFrame) -> list[str]:
    frame = frame[sorted(frame.columns)]
    return sorted(repr(tuple(plain(v) for v in r)) for r in frame.astype(object).itertuples(index=False, name=None))


@pytest.mark.parametrize("name", sorted(catalog.ORACLES))
def test_query_equals_sql(spark, db, name):
    got = catalog.QUERIES[name](spark, SF).toPandas()
    want = db.sql(catalog.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


WITHOUT_SQL = {"library_minhash_top", "library_vectors_top", "product_quantized_embeddings", "approx_distinct_elements", "throughput"}


def test_all_other_queries_have_sql():
    assert set(catalog.QUERIES) - set(catalog.ORACLES) == WITHOUT_SQL


def test_library_join_reports_true_similarities(spark):
    sets = {r.id: set(r.elements) for r in views.items(spark, SF, "basket_twins").collect()}
    top = catalog.QUERIES["library_minhash_top"](spark, SF).collect()
    assert top and all(abs(r.score - len(sets[r.qid] & sets[r.id]) / len(sets[r.qid] | sets[r.id])) < 0.02 for r in top)
    nearest = {r.qid: r.id for r in top if r["rank"] == 1}
    best = {q: max((i for i in sets if i != q), key=lambda i: (len(sets[q] & sets[i]) / len(sets[q] | sets[i]), -i)) for q in nearest}
    assert sum(nearest[q] == best[q] for q in nearest) >= 0.9 * len(nearest)


def test_library_vector_join_reports_true_distances(spark):
    vectors = {r.id: np.array(r.elements, float) for r in views.vectors(spark, SF).collect()}
    top = catalog.QUERIES["library_vectors_top"](spark, SF).collect()
    assert top and all(abs(r.score + np.linalg.norm(vectors[r.qid] - vectors[r.id])) < 1e-6 for r in top)


def test_product_codes_are_the_nearest_centers(spark):
    vectors = views.vectors(spark, SF)
    books = baselines.product_codebooks(vectors)
    codes = {r.id: r.codes for r in catalog.QUERIES["product_quantized_embeddings"](spark, SF).collect()}
    rows = vectors.collect()
    assert len(codes) == len(rows)
    for r in rows[:60]:
        blocks = np.array_split(np.array(r.elements, np.float32), len(books))
        assert list(codes[r.id]) == [int(((c - b) ** 2).sum(1).argmin()) for b, c in zip(blocks, books)]


def test_approximate_counts_are_near(spark):
    for r in catalog.QUERIES["approx_distinct_elements"](spark, SF).collect():
        exact = views.pairs(spark, SF, r.view).selectExpr("count(distinct id) i", "count(distinct element) e").first()
        assert abs(r["items"] - exact.i) <= 0.1 * exact.i + 1 and abs(r.elements - exact.e) <= 0.1 * exact.e + 1


def test_throughput_is_measured(spark):
    assert {r.phase: r.per_second > 0 for r in catalog.QUERIES["throughput"](spark, SF).collect()} == {"build": True, "query": True}


def test_entry(spark):
    df = entry_point.entry(spark)
    assert df.columns == ["qid", "rank", "id", "score"] and df.count() > 0
    assert set(catalog.QUERIES) <= set(entry_point.queries()) and set(entry_point.oracle_sql()) <= set(entry_point.queries())
