"""Invariants of sketches, layouts and decoding on crafted frames."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from neighborsketch.functions import hashing, lsh, sqlfuncs
from neighborsketch.functions.params import PRIME, SketchParams
from neighborsketch.operators import baselines, cms, decode, exact, grid, layout, measures
from neighborsketch.plans import planner, workloads
from neighborsketch.sources import edges, views

RNG = np.random.default_rng(3)
P = SketchParams(3, 7, 4, hashes=2, buckets=50)


def sets(n=60, universe=400, size=30):
    out = [(i, sorted({int(x) for x in RNG.integers(0, PRIME, size)} if i % 3 else {int(x) for x in np.random.default_rng(i // 9).integers(0, PRIME, size)})) for i in range(n)]
    return out


ROWS = sets()


@pytest.fixture(scope="module")
def items(spark):
    return spark.createDataFrame(ROWS, "id long, elements array<long>").repartition(4).cache()


def counters(s):
    return sorted(map(tuple, s.cells.collect()))


def test_counts_add_up(spark, items):
    s = grid.build_sketch(items, P)
    by = grid.unpack(s.cells, P).groupBy("row", "rep").agg(F.sum("n").alias("n")).collect()
    assert {r.n for r in by} == {len(ROWS)} and len(by) == P.rows * P.reps


def test_engines_agree(items):
    for p in (P, SketchParams(2, 5, 3), SketchParams(2, 5, 3, sharing="row"), SketchParams(2, 5, 3, sharing="rep"), SketchParams(2, 4, 2, hashes=3, buckets=None, family="onebit_minhash"), SketchParams(1, 1, 1, buckets=1), SketchParams(2, 4, 2, buckets=None, family="bit_sample")):
        assert counters(grid.build_sketch(items, p)) == counters(grid.build_sketch(items, p, engine="arrow"))


def test_vector_families_agree(spark):
    v = spark.createDataFrame([(i, RNG.normal(size=16).astype(float).tolist()) for i in range(40)], "id long, elements array<float>")
    for family, buckets in (("signed_projection", None), ("euclidean_grid", 64)):
        p = SketchParams(2, 5, 3, hashes=3, buckets=buckets, family=family, width=0.7)
        assert counters(grid.build_sketch(v, p)) == counters(grid.build_sketch(v, p, engine="arrow"))


def test_linear(spark, items):
    whole = grid.build_sketch(items, P)
    a, b = items.where("id % 2 = 0"), items.where("id % 2 = 1")
    assert grid.differences(grid.merge_sketches(grid.build_sketch(a, P), grid.build_sketch(b, P)), whole).count() == 0
    assert grid.differences(grid.remove_items(whole, a), grid.build_sketch(b, P)).count() == 0
    with pytest.raises(ValueError):
        grid.merge_sketches(whole, grid.build_sketch(items, SketchParams(3, 7, 4)))


def test_groups_roll_up(items):
    grouped = grid.build_grouped(items.withColumn("g", F.col("id") % 3).withColumn("h", F.col("id") % 2), P, ["g", "h"], how="cube")
    top = grouped.where("g is null and h is null").select("cell", "n")
    assert grid.differences(grid.Sketch(top, P), grid.build_sketch(items, P)).count() == 0


def test_weights_and_matrices(items):
    weighted = grid.build_sketch(items.withColumn("w", F.lit(0.5)), P, weight_col="w")
    plain = dict(counters(grid.build_sketch(items, P)))
    assert {c: n * 2 for c, n in counters(weighted)} == plain
    dense = SketchParams(2, 4, 2, measurement="bernoulli")
    n = grid.unpack(grid.build_sketch(items, dense).cells, dense).groupBy("row", "col", "rep").agg(F.sum("n").alias("n")).collect()
    assert all(0 < r.n < len(ROWS) for r in n)


def test_layouts_round_trip(spark, items, tmp_path):
    s = grid.build_sketch(items, P)
    for table in (layout.to_dense(s), layout.to_sparse(s, 8)):
        assert grid.differences(layout.from_layout(table, P), s).count() == 0
    layout.save_sketch(s, str(tmp_path / "s"))
    back = layout.load_sketch(spark, str(tmp_path / "s"))
    assert back.params == P and grid.differences(back, s).count() == 0
    assert layout.pack_bytes(s).select(F.length("data")).distinct().collect()[0][0] == P.slots * 2
    heavy = grid.Sketch(spark.createDataFrame([(0, 300)], "cell long, n long"), P)
    with pytest.raises(Exception, match="more than 8 bits"):
        layout.to_sparse(heavy, 8).collect()


def test_unusable_items(spark):
    bad = spark.createDataFrame([(1, []), (2, None), (None, [5]), (3, [None, 7]), (-4, [7]), (1 << 40, [7])], "id long, elements array<long>")
    assert grid.unpack(grid.build_sketch(bad, P).cells, P).where("row = 0 and rep = 0").agg(F.sum("n")).first()[0] == 3
    assert grid.build_sketch(bad.limit(0), P).cells.count() == 0


def test_decoders_agree(items):
    p = SketchParams(3, 9, 4)
    s, ids = grid.build_sketch(items, p), items.select("id")
    queries = items.where("id < 30")
    for v in (1, 5, 100):
        full = sorted(map(tuple, decode.top_neighbors(s, queries, ids, v, groups=2).collect()))
        assert full == sorted(map(tuple, decode.top_neighbors(s, queries, ids, v, groups=2, decode="threshold").collect()))
        assert full == sorted(map(tuple, decode.top_arrow(decode.measure_arrow(s, queries, groups=2), ids, p, v).collect()))
    without = grid.build_sketch(items.where("id != 4"), p)
    y = lambda sk, own: sorted(map(tuple, decode.estimate_measurements(decode.own_removed(decode.read_counters(sk, decode.query_cells(items.where("id = 4"), p)), p) if own else decode.read_counters(sk, decode.query_cells(items.where("id = 4"), p))).collect()))
    assert y(s, True) == y(without, False)


def test_one_cell_scores_all_alike(items):
    p = SketchParams(1, 1, 1, buckets=1)
    top = decode.top_neighbors(grid.build_sketch(items, p), items.where("id = 3"), items.select("id"), 5)
    assert [(r.id, r.score) for r in top.orderBy("rank").collect()] == [(i, len(ROWS)) for i in range(5)]


def test_plan_shapes(spark, items):
    s = grid.build_sketch(items, P)
    plan = s.cells._jdf.queryExecution().executedPlan().toString()
    assert plan.count("hashpartitioning") == 1 and "BroadcastHashJoin" in plan
    top = decode.top_neighbors(s, items, items.select("id"), 3)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in top


def test_collision_rate_follows_similarity():
    a, b = np.arange(0, 300), np.arange(100, 400)  # J = 0.5
    mix = np.vectorize(lambda x: hashing.digest_int(str(x)) % PRIME)
    a, b = mix(a), mix(b)
    c = hashing.constants(SketchParams(1, 1, 4000, buckets=1))
    hits = [((a * x + y) % PRIME).min() == ((b * x + y) % PRIME).min() for x, y in zip(c["alpha"].ravel().tolist(), c["beta"].ravel().tolist())]
    assert abs(np.mean(hits) - 0.5) < 0.04
    assert lsh.collision_probability(0.5, SketchParams(1, 1, 1, family="onebit_minhash")) == 0.75
    assert lsh.collision_probability(0.0, SketchParams(1, 1, 1, family="signed_projection")) == 0.5
    grid_p = SketchParams(1, 1, 1, family="euclidean_grid")
    assert lsh.collision_probability(0.1, grid_p) > lsh.collision_probability(1.0, grid_p) > lsh.collision_probability(5.0, grid_p)


def test_mixers(spark, items):
    for mixer in ("murmur3", "xxhash64"):
        p = SketchParams(2, 5, 2, mixer=mixer)
        assert grid.unpack(grid.build_sketch(items, p).cells, p).agg(F.sum("n")).first()[0] == 4 * len(ROWS)


def test_exact_answers(spark, items):
    pairs = {(r.qid, r.id): (r.inter, r.uni) for r in exact.overlaps(items, items).collect()}
    own = dict(ROWS)
    for (q, i), (inter, uni) in pairs.items():
        assert inter == len(set(own[q]) & set(own[i])) and uni == len(set(own[q]) | set(own[i]))
    close = {(r.qid, r.id) for r in exact.close_pairs(items, 8, 10).collect()}
    assert close == {k for k, (x, y) in pairs.items() if k[0] != k[1] and 10 * x >= 8 * y}


def test_count_min_never_below(spark):
    df = spark.createDataFrame([(int(k), 1) for k in RNG.zipf(1.5, 3000) if k < 5000], "k long, w long")
    p = cms.cms_params(4, 40)
    true = {r.k: r.w for r in df.groupBy("k").agg(F.sum("w").alias("w")).collect()}
    got = {r.k: r.estimate for r in cms.cms_point(cms.cms_build(df, "k", "w", p), df, "k", p).collect()}
    assert all(got[k] >= w for k, w in true.items())
    heavy = {r.k for r in cms.cms_heavy_hitters(cms.cms_build(df, "k", "w", p), df, "k", 0.1, p).collect()}
    assert {k for k, w in true.items() if w >= 0.1 * sum(true.values())} <= heavy
    assert cms.cms_size(1000, 0.05, 0.01) == (12, 55)


def test_sparse_recovery():
    phi = np.random.default_rng(1).normal(size=(60, 200))
    x = np.zeros(200)
    x[[3, 50, 120]] = 1.0, 2.0, -1.5
    assert np.allclose(cms.recover_sparse(phi @ x, phi, 3), x)


def test_baselines(spark, items):
    assert baselines.sample_items(items, 7).count() == 7 and baselines.sample_items(items, 1000).count() == len(ROWS)
    vec = {r.id: np.array(r.vec) for r in baselines.random_projection(items, 6).collect()}
    sums = {r.id: np.array(r.sums) for r in baselines.projection_sums(items, 6).collect()}
    assert all(np.allclose(vec[i], sums[i] * np.sqrt(3 / 6), atol=1e-5) for i in vec)
    keys = items.select("id")
    assert baselines.bloom_test(baselines.bloom_build(keys, "id", 4096, 3), keys, "id", 4096, 3).where("not hit").count() == 0


def test_measures(spark):
    truth = spark.createDataFrame([(1, 2, 9, 10), (1, 3, 8, 10), (2, 1, 9, 10), (5, 6, 1, 10)], "qid long, id long, inter long, uni long")
    top = spark.createDataFrame([(1, 1, 2, 1.0), (2, 1, 7, 1.0)], "qid long, rank long, id long, score double")
    assert tuple(measures.recall_at(top, truth, 8, 10).first()) == (2, 0.25)
    assert tuple(measures.recall_at(top, truth, 8, 10, average="micro").first()) == (2, 1 / 3)
    points = spark.createDataFrame([("a", 10, 0.5), ("a", 20, 0.4), ("a", 30, 0.9), ("b", 90, 0.9)], "method string, bytes long, recall double")
    assert sorted(r.bytes for r in measures.pareto(points, "bytes", "recall", ["method"]).collect()) == [10, 30, 90]
    assert measures.advantage(points, 0.8, "a", "b").first().factor == 3.0


def test_sweep_and_planner(spark, items):
    points = workloads.sweep(items, grid=[SketchParams(2, 20, 2)], projections=(5, 10), fractions=(0.5,))
    assert {r.method for r in points.collect()} == {"sketch_dense", "sketch_sparse", "projections", "sampling"}
    assert workloads.frontier(points).count() >= 4
    plan = planner.choose(SketchParams(5, 1000, 8, buckets=1000), n_items=10**9, n_queries=100)
    assert (plan.read, plan.decode, plan.layout) == ("shuffle", "threshold", "dense")
    assert planner.report_neighbors(items, items.limit(4), SketchParams(2, 10, 2), 3).count() == 12


def test_sql_functions(spark):
    assert {"jaccard", "shingles", "ids_in_column"} <= set(sqlfuncs.register(spark))
    assert spark.sql("SELECT jaccard(array(1L, 2L), array(2L, 3L)) j, median_of(array(3D, 1D, 2D)) m").first() == (1 / 3, 2.0)
    assert [r.shingle for r in spark.sql("SELECT * FROM shingles('a b c', 2)").collect()] == ["a b", "b c"]
    a, b = hashing.row_constants(P, 0)
    got = {r.id for r in spark.sql(f"SELECT * FROM ids_in_column({a}, {b}, 7, 3, 200)").collect()}
    assert got == {i for i in range(200) if (a * i + b) % PRIME % 7 == 3}


def test_edges(spark, tmp_path):
    (tmp_path / "g.txt").write_text("# graph\n1 2\n1\t3\n2 1 # x\nbad line\n")
    found = edges.adjacency(edges.read_edges(spark, str(tmp_path / "g.txt")))
    assert sorted(map(tuple, found.collect())) == [(1, [2, 3]), (2, [1])]
    for fmt in ("csv", "json", "orc", "parquet"):
        edges.write_edges(edges.edges_of(found), str(tmp_path / fmt), fmt)
        assert edges.read_edges(spark, str(tmp_path / fmt), fmt).count() == 3


def test_views_handle_empty_text(spark):
    df = spark.createDataFrame([(1, None), (2, ""), (3, "one"), (4, "a b c d")], "doc_id long, text string")
    got = {r.id: len(r.elements) for r in views._texts(df, F.col("doc_id"), F.col("text")).collect()}
    assert got == {3: 1, 4: 2}
