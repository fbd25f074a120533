"""The pair scan and the grouped decoding against brute force, over several blocks."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from neighborsketch import catalog
from neighborsketch.functions.params import SketchParams
from neighborsketch.operators import baselines, cms, decode, exact, grid, measures, scan, stability
from neighborsketch.sources import store, views

SF = "/root/testdata/sf0.001"


def some_sets(n: int, words: int) -> dict[int, list[int]]:
    rng = random.Random(5)
    made = {i * 7: sorted(rng.sample(range(words), rng.randint(1, 12))) for i in range(n)}
    return made | {i * 7 + 3: made[i * 7][: max(1, len(made[i * 7]) - 1)] for i in range(0, n, 4)}


def frame(spark, sets):
    return spark.createDataFrame(list(sets.items()), "id long, elements array<long>")


def similar(sets, q):
    pairs = [(i, len(set(sets[q]) & set(sets[i])), len(set(sets[q]) | set(sets[i]))) for i in sets if i != q]
    return sorted((p for p in pairs if p[1]), key=lambda p: (-p[1] / p[2], p[0]))


@pytest.fixture(params=[40, 2000], ids=["dense", "lists"])
def sets(request, monkeypatch):
    monkeypatch.setattr(scan, "BLOCK_ENTRIES", 150)
    monkeypatch.setattr(scan, "SLICE_PAIRS", 60)
    return some_sets(80, request.param) | {5: [3, 4, 10**9 + 1], 6: list(range(3, 900)) if request.param > 40 else [1, 2]}


def test_similar_items_and_sums_over_blocks(spark, sets, monkeypatch):
    monkeypatch.setattr(exact, "overlaps", lambda *a: pytest.fail("a row a pair"))
    items = frame(spark, sets)
    queries = items.where("id % 2 = 0")
    got = {(r.qid, r["rank"]): (r.id, r.inter, r.uni) for r in exact.top_similar(items, queries, 4).collect()}
    asked = [q for q in sets if q % 2 == 0]
    assert got == {(q, k + 1): p for q in asked for k, p in enumerate(similar(sets, q)[:4])}
    stats = {r.qid: r for r in stability.scanned_stats(items, queries, 1, len(sets)).collect()}
    sums = {r.qid: r.s for r in exact.kernel_sums(items, queries, 2).collect()}
    for q in asked:
        p = [a / b for _, a, b in similar(sets, q)]
        assert (q in stats) == bool(p) == (q in sums)
        if p:
            assert np.isclose(sums[q], sum(x * x for x in p)) and stats[q].p_v == p[0] and stats[q].p_next == (p[1] if len(p) > 1 else None)
            assert np.isclose(stats[q].norm_tilde, sum(x**0.5 for x in p))
            assert stats[q].tail is None if len(p) < 2 else np.isclose(stats[q].tail, sum(x**0.5 for x in p[1:]) / p[1] ** 0.5)


def test_close_pairs_lose_none(spark, sets):
    got = {(r.qid, r.id, r.inter, r.uni) for r in exact.close_pairs(frame(spark, sets), 8, 10).collect()}
    assert got == {(q, *p) for q in sets for p in similar(sets, q) if 10 * p[1] >= 8 * p[2]}


def test_euclidean_sample_search_over_blocks(spark, sets):
    got = {(r.qid, r["rank"]): (r.id, r.score) for r in baselines.sample_top(frame(spark, sets), frame(spark, sets).where("id % 3 = 0"), 5, "euclidean").collect()}
    for q in (q for q in sets if q % 3 == 0):
        far = sorted((len(set(sets[q]) ^ set(s)), i) for i, s in sets.items() if i != q)[:5]
        assert [got[q, k + 1] for k in range(5)] == [(i, -float(d)) for d, i in far]


def test_sample_is_not_put_in_order_as_a_whole(spark):
    items = spark.range(5000).select("id", F.array("id").alias("elements"))
    plan = baselines.sample_items(items, 1500)._jdf.queryExecution().executedPlan().toString()
    assert "limit=1500" not in plan
    rank = {r.id: r.rank for r in items.select("id", baselines.sample_rank(F.col("id"), 42).alias("rank")).collect()}
    for k in (0, 1, 1500, 5000, 9999):
        assert {r.id for r in baselines.sample_items(items, k).collect()} == set(sorted(rank, key=lambda i: (rank[i], i))[:k])


@pytest.mark.parametrize("p", [SketchParams(3, 5, 2), SketchParams(2, 40, 2, buckets=10), SketchParams(1, 6, 1)], ids=str)
def test_decoding_keeps_queries_where_they_are(spark, p, monkeypatch):
    monkeypatch.setattr(decode, "ID_BLOCK", 60)
    monkeypatch.setattr(decode, "query_blocks", lambda *a: pytest.fail("queries came to the driver"))
    made = some_sets(100, 60)
    items = frame(spark, made)
    sketch = grid.build_sketch(items, p, engine="arrow")
    queries = items.where("id % 5 = 0")
    ys = decode.measure_arrow(sketch, queries)
    got = [tuple(r) for r in decode.top_arrow(ys, items.select("id"), p, 6, exclude_own=True).orderBy("qid", "rank").collect()]
    y = decode.estimate_measurements(decode.read_counters(sketch, decode.query_cells(queries, p)))
    full = decode.recover_scores(y, items.select("id"), p).where("id != qid")
    assert got == [tuple(r) for r in decode.best(full, 6).orderBy("qid", "rank").collect()]


def test_copies_of_sets_are_those_of_pairs(spark):
    for name in ("basket_twins", "part_suppliers"):
        one = {r.id: r.elements for r in views.sets(spark, SF, name).collect()}
        assert one == {r.id: r.elements for r in views.to_sets(views.pairs(spark, SF, name)).collect()}


def test_products_are_exact_and_ties_go_by_id(spark):
    rng = np.random.default_rng(3)
    x = rng.integers(-10**6, 10**6, (300, 8))
    x[7] = x[250]
    vectors = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, elements array<long>")
    got = {(r.qid, r["rank"]): (r.id, r.score) for r in exact.top_products(vectors, vectors.where("id % 50 = 0"), 3).collect()}
    dots = x @ x.T
    for q in range(0, 300, 50):
        want = sorted((-int(dots[q, i]), i) for i in range(300) if i != q)[:3]
        assert [got[q, k + 1] for k in range(3)] == [(i, -d) for d, i in want]


def test_cell_scores_are_not_shuffled(spark, sets, monkeypatch):
    p = SketchParams(3, 11, 1)
    monkeypatch.setattr(cms, "ID_BLOCK", 30)
    monkeypatch.setattr(cms, "OUT_ROWS", 7)
    items = frame(spark, sets)
    queries = items.where("id % 3 = 0")
    kernel = exact.exact_kernel(exact.overlaps(items, queries).where("id != qid"), 1)
    want = {(r.qid, r.id): r.score for r in cms.exact_cell_scores(kernel, items.select("id"), p).collect()}
    monkeypatch.setattr(exact, "overlaps", lambda *a: pytest.fail("a row a pair"))
    found = cms.scanned_cell_scores(items, queries, 1, p)
    got = {(r.qid, r.id): r.score for r in found.collect()}
    assert len(want) > 200 and got.keys() == want.keys() and all(np.isclose(got[k], want[k]) for k in want)


def test_exact_cell_decode_makes_no_row_a_pair(spark, monkeypatch):
    monkeypatch.setattr(exact, "overlaps", lambda *a: pytest.fail("a row a pair"))
    assert catalog.QUERIES["exact_cell_decode"](spark, SF).count()


def test_library_vector_search_equals_the_library_join(spark, monkeypatch):
    from pyspark.ml.feature import BucketedRandomProjectionLSH, BucketedRandomProjectionLSHModel
    from pyspark.ml.functions import array_to_vector

    rng = np.random.default_rng(8)
    x = rng.normal(size=(400, 6)).round(2)
    x[9], x[50] = x[311], x[17]
    vectors = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, elements array<float>")
    ready = vectors.select("id", array_to_vector(F.col("elements").cast("array<double>")).alias("f"))
    model = BucketedRandomProjectionLSH(inputCol="f", outputCol="h", bucketLength=0.5, numHashTables=3, seed=42).fit(ready)
    joined = model.approxSimilarityJoin(ready, ready.where("id % 10 = 0"), 2.0, distCol="d")
    pairs = joined.select(F.col("datasetB.id").alias("qid"), F.col("datasetA.id").alias("id"), (-F.col("d")).alias("score")).where("id != qid")
    want = [tuple(r) for r in decode.best(pairs, 7).orderBy("qid", "rank").collect()]
    monkeypatch.setattr(baselines, "SENT", 16)
    monkeypatch.setattr(baselines, "SEARCHED", 5)
    monkeypatch.setattr(BucketedRandomProjectionLSHModel, "approxSimilarityJoin", lambda *a, **b: pytest.fail("a row a pair"))
    got = [tuple(r) for r in baselines.library_vectors_top(vectors, vectors.where("id % 10 = 0"), 7, width=0.5, tables=3, most_distance=2.0).orderBy("qid", "rank").collect()]
    assert len(want) > 100 and got == want


def test_statistics_write_the_items_once(spark, sets, monkeypatch):
    written, dropped = [], []
    for module in (scan, measures):
        monkeypatch.setattr(module, "stored", lambda df, name: written.append(name) or store.stored(df, name))
        monkeypatch.setattr(module, "drop_stored", lambda df: dropped.append(df.inputFiles()) or store.drop_stored(df))
    r = measures.dataset_stats(frame(spark, sets)).first()
    total = sum(sum(a / b for _, a, b in similar(sets, q)) for q in sets) / 2
    assert (r.nodes, r.nonzeros) == (len(sets), sum(map(len, sets.values()))) and np.isclose(r.mean_similarity, total / (len(sets) * (len(sets) - 1) / 2))
    assert len([x for x in written if x.endswith("items")]) == 1 and len(dropped) == 1


def test_finished_steps_are_let_go(spark, monkeypatch):
    settled = []
    monkeypatch.setattr(store, "_settled", float("-inf"))
    monkeypatch.setattr(store, "settle", lambda s: settled.append(s))
    store.stored(spark.range(3), "some")
    assert settled == [spark]
    monkeypatch.setattr(store, "_settled", store.time.monotonic())
    store.stored(spark.range(3), "some")
    assert len(settled) == 1


def test_a_block_is_made_of_rows_in_any_order():
    made = some_sets(300, 90)
    order = random.Random(2).sample(sorted(made), len(made))
    rows = pa.table({"id": order, "n": [len(made[i]) for i in order], "elements": pa.array([made[i] for i in order], pa.list_(pa.int64()))})
    block = scan._block(rows)
    assert block.ids.tolist() == sorted(made) and block.sizes.tolist() == [len(made[i]) for i in sorted(made)]
    assert block.elements.tolist() == sorted({e for s in made.values() for e in s})
    for e, begin, end in zip(block.elements.tolist(), block.starts[:-1], block.starts[1:]):
        assert block.ids[block.owners[begin:end]].tolist() == [i for i in sorted(made) if e in made[i]]
    empty = scan._block(rows.slice(0, 0))
    assert len(empty.ids) == 0 and empty.starts.tolist() == [0]


@pytest.mark.parametrize("whole", [True, False])
def test_projections_of_many_queries_ship_items(spark, whole, monkeypatch):
    """Beyond one broadcast of queries, what is written is a block's v best of each
    query, not a batch's; the answers are those of brute force, ties by id."""
    monkeypatch.setattr(baselines, "SENT", 10)
    monkeypatch.setattr(baselines, "BLOCK_VALUES", 300, raising=False)
    monkeypatch.setattr(baselines, "PIECE", 16, raising=False)
    rng = np.random.default_rng(4)
    x = rng.integers(-2, 3, (150, 4)).astype(np.float32) * (1 if whole else 0.37)
    ids = rng.permutation(1000)[:150]
    items = spark.createDataFrame([(int(i), a.tolist()) for i, a in zip(ids, x)], "id long, vec array<float>")
    monkeypatch.setattr(baselines, "nearest_of", lambda *a: pytest.fail("items stay where they are"))
    got = {(r.qid, r["rank"]): (r.id, r.score) for r in baselines.projection_top(items, items.where("id % 3 = 0"), 5, prefix=3).collect()}
    y = x[:, :3].astype(np.float64)
    for k, q in enumerate(ids.tolist()):
        if q % 3 == 0:
            far = np.round((y[k] ** 2).sum() - 2 * y @ y[k] + (y**2).sum(1), 6)
            want = sorted((d, i) for d, i in zip(far.tolist(), ids.tolist()) if i != q)[:5]
            assert [got[q, n + 1] for n in range(5)] == [(i, -d) for d, i in want]


def test_listed_elements_are_found():
    rng = np.random.default_rng(2)
    elements = np.unique(rng.integers(-(2**62), 2**62, 400))
    values = np.concatenate([rng.choice(elements, 50), rng.integers(-(2**62), 2**62, 500)])
    hit, places = scan.Listed(elements).find(values)
    assert hit.tolist() == np.flatnonzero(np.isin(values, elements)).tolist() and (elements[places] == values[hit]).all()
    assert len(scan.Listed(elements[:0]).find(values)[0]) == 0


def test_equal_counts_by_cells_and_by_sorting():
    key = np.random.default_rng(1).integers(0, 50, 400)
    for most in (50, 10**9):
        assert [x.tolist() for x in scan._counted(key, most)] == [x.tolist() for x in np.unique(key, return_counts=True)]


@pytest.mark.parametrize("top", [10**6, 2**62])
def test_entries_by_element_and_owner(top):
    rng = np.random.default_rng(3)
    elements, owners = rng.integers(0, top, 500) // (top // 40), rng.integers(0, 30, 500).astype(np.int32)
    elements = elements * (top // 40)
    order = np.lexsort((owners, elements))
    got = scan._in_order(elements, owners, 30)
    assert got[0].tolist() == elements[order].tolist() and got[1].tolist() == owners[order].tolist()


def test_codes_of_one_hash_for_all_items():
    from neighborsketch.functions import lsh
    rng = np.random.default_rng(6)
    lengths = rng.integers(1, 9, 40)
    values, starts = rng.integers(0, 2**31 - 1, lengths.sum()), np.cumsum(lengths) - lengths
    for family in ("minhash", "onebit_minhash", "signed_projection"):
        p = SketchParams(1, 1, 1, family=family)
        each = lsh.codes_array(values, starts, lengths, np.full(40, 12345), np.full(40, 678), p)
        assert lsh.codes_array(values, starts, lengths, 12345, 678, p).tolist() == each.tolist()
