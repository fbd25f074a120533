"""The guarantees: closed forms, the sparsity rule exactly, the estimator statistically."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from neighborsketch.functions import theory
from neighborsketch.functions.params import SketchParams
from neighborsketch.operators import cms, decode, exact, grid, measures, stability


def test_closed_forms():
    assert theory.choose_hashes(4, 0.5) == 4
    assert theory.choose_hashes(100, 0.5) == 14
    assert theory.choose_hashes(5, 1.0) is None and theory.choose_hashes(0.5, 0.5) == 1
    assert theory.memory_exponent(0.9, 2, 0.05) == pytest.approx(0.6738, abs=1e-4)
    assert theory.memory_exponent(0.9, 100, 0.05) == pytest.approx(3.2855, abs=1e-4)
    assert theory.sketch_bits(1000, 0.5) == pytest.approx(math.sqrt(1000) * math.log(1000) ** 3)
    assert theory.sketch_time(1000, 0.5) == pytest.approx(1000 * theory.sketch_bits(1000, 0.5))
    assert theory.array_bits(2, 5, 1024) == 320 and theory.array_bits(2, 5, 1024, 100) == 1000
    assert theory.arrays_needed(2, 2, 0.1, 0.01, 1000) < theory.arrays_needed(2, 2, 0.05, 0.01, 1000)
    assert theory.error_budget(1.0, 0.5, 2.0) == (0.25, 0.5)
    assert all(s["bytes"] <= 10**6 for s in theory.suggest_params(0.9, 0.1, 50, 10**5, 10**6))


@pytest.fixture(scope="module")
def kernel(spark):
    rng = np.random.default_rng(5)
    rows = [(q, i, float(p)) for q in range(30) for i, p in enumerate(np.sort(np.append(rng.uniform(0.6, 1, 2), rng.uniform(0.01, 0.5, rng.integers(1, 60)))))]
    rows += [(100, i, 0.5) for i in range(10)] + [(101, 0, 0.9)]
    return spark.createDataFrame(rows, "qid long, id long, p double").cache()


def test_sparsity_rule_holds(kernel):
    stats = stability.stability_stats(kernel, 1, 1000)
    status = {r.qid: r.status for r in stats.collect()}
    assert status[100] == "unstable_tie" and status[101] == "empty_tail"
    found = stability.check_sparsity(kernel, stability.with_hashes(stats), 1).collect()
    assert len(found) == 31 and all(r.tail_below and r.norm1_bounded and r.tilde_bounded for r in found)


def test_more_hashes_cost_more_arrays(kernel):
    rows = stability.hashes_tradeoff(kernel.where("qid = 3"), 1, 6, 1000).orderBy("hashes").collect()
    assert [r.norm1 for r in rows] == sorted((r.norm1 for r in rows), reverse=True)


def test_counter_is_unbiased_and_bounded(spark):
    rng = np.random.default_rng(9)
    base = rng.integers(0, 2**31 - 1, 40)
    rows = [(i, sorted({int(x) for x in np.append(base[: rng.integers(5, 40)], rng.integers(0, 2**31 - 1, 15))})) for i in range(40)]
    items, query = spark.createDataFrame(rows, "id long, elements array<long>"), spark.createDataFrame([(99, [int(x) for x in base])], "id long, elements array<long>")
    seeds = 400
    p = SketchParams(1, 1, seeds, buckets=1 << 20)
    reads = decode.read_counters(grid.build_sketch(items, p, engine="arrow"), decode.query_cells(query, p))
    got = np.array([r.n for r in reads.collect()], float)
    true = [r.s for r in exact.exact_kernel(exact.overlaps(items, query), 1).collect()]
    bound = sum(math.sqrt(s) for s in true) ** 2
    assert abs(got.mean() - sum(true)) < 4 * got.std() / math.sqrt(seeds)
    assert got.var() <= bound * 1.2
    few, many = (np.array([g.mean() for g in got.reshape(-1, k)]) for k in (4, 40))
    assert many.std() < few.std()


def test_exact_cells_never_read_below(spark, kernel):
    p = SketchParams(3, 20, 1)
    s = kernel.withColumnRenamed("p", "s")
    scores = cms.exact_cell_scores(s, kernel.select("id").distinct(), p)
    assert measures.recovery_error(scores, s, 1.0).first().below == 0


def test_coverage_and_geometry(kernel):
    with_b = stability.with_exponent(stability.stability_stats(kernel, 1, 1000), 2)
    rows = {r.committed: r.guaranteed for r in stability.coverage(with_b, [0.5, 1.0, 50.0]).collect()}
    assert rows[0.5] <= rows[1.0] <= rows[50.0]
    flat = with_b.sparkSession.createDataFrame([(1, i, 0.9 if i == 0 else 0.5) for i in range(100)], "qid long, id long, p double")
    assert stability.geometry_class(stability.stability_stats(flat, 1, 100)).first().geometry == "equidistant"
    assert stability.is_unstable(flat.withColumn("p", F.lit(0.5)), 101, 0.1).first().unstable
