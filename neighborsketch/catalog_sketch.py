"""Queries over hash families, sketches, readings, decoding and Count-Min sketches."""

from __future__ import annotations

from pyspark.sql import functions as F

from .functions import hashing, lsh
from .functions.params import SketchParams
from .operators import cache, cms, decode, grid, layout, measures
from .operators.measures import fixed
from .oracles import blocks as sql
from .plans import workloads
from .sources import views

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

SMALL = SketchParams(2, 10, 2)  # documents
TWINS = SketchParams(2, 12, 3)  # baskets
KDE = SketchParams(1, 1, 5)
V = 20


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = sql.stable(oracle)
        return f

    return add


def _docs(spark, sf_dir):
    return views.items(spark, sf_dir, "doc_shingles")


def _doc_ids(spark, sf_dir):
    return views.ids(spark, sf_dir, "doc_shingles")


def _unseen(spark, sf_dir):
    return views.items(spark, sf_dir, "benchmark_shingles")


def _baskets(spark, sf_dir):
    return views.items(spark, sf_dir, "basket_twins")


def _close(items):
    return workloads.close_queries(items, 9, 10)[0]


# hash families ---------------------------------------------------------------------------


@query("minhash_codes_docs", f"""WITH items AS ({sql.items('doc_shingles')}), {sql.constants(1, 1, 3, 1)}
    SELECT s.id, q.rep, min((q.alpha * s.element + q.beta) % {sql.P}) AS code FROM items s, par q GROUP BY s.id, q.rep""")
def minhash_codes_docs(spark, sf_dir):
    c = hashing.constants(SketchParams(1, 1, 3))
    each = [F.struct(F.lit(o).cast("long").alias("rep"), lsh.minhash_code(F.col("elements"), F.lit(int(c["alpha"][0, 0, o, 0])).cast("long"), F.lit(int(c["beta"][0, 0, o, 0])).cast("long")).alias("code")) for o in range(3)]
    return _docs(spark, sf_dir).select("id", F.explode(F.array(*each)).alias("x")).select("id", "x.rep", "x.code")


@query("minhash_concat_rehash", f"WITH items AS MATERIALIZED ({sql.items('doc_shingles')}), {sql.constants(1, 1, 3, 2)}, {sql.touched('items', 1, 1, 3, 2, 100)} SELECT id, rep, cell % 100 AS bucket FROM hits")
def minhash_concat_rehash(spark, sf_dir):
    p = SketchParams(1, 1, 3, hashes=2)
    return grid.touched(_docs(spark, sf_dir), p, keep=["id"]).select("id", F.floor(F.col("cell") / 100).cast("long").alias("rep"), (F.col("cell") % 100).alias("bucket"))


@query("srp_codes_embeddings", f"""WITH {sql.constants(1, 1, 8, 1)}, e AS (SELECT vec_id AS id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS c FROM embeddings)
    SELECT id, rep, CASE WHEN sum(CASE WHEN ((alpha * c + beta) % {sql.P}) % 2 = 0 THEN 1 ELSE -1 END * CAST(round(CAST(x AS DOUBLE) * 1000000) AS BIGINT)) >= 0 THEN 1 ELSE 0 END::BIGINT AS bit
    FROM e, par GROUP BY id, rep""")
def srp_codes_embeddings(spark, sf_dir):
    p = SketchParams(1, 1, 8, family="signed_projection", buckets=None)
    return grid.touched(views.vectors(spark, sf_dir), p, keep=["id"]).select("id", F.floor(F.col("cell") / 2).cast("long").alias("rep"), (F.col("cell") % 2).alias("bit"))


# sketches --------------------------------------------------------------------------------


@query("collision_array_docs", f"WITH {sql.sketch('doc_shingles', 1, 1, 1, 1, 100)} SELECT cell AS bucket, n FROM sketch")
def collision_array_docs(spark, sf_dir):
    return grid.collision_array(_docs(spark, sf_dir))


@query("weighted_collision_array", f"""WITH {sql.sketch('doc_shingles', 1, 1, 1, 1, 100)}
    SELECT cell AS bucket, sum(k)::DOUBLE AS n FROM hits JOIN (SELECT id, count(*) AS k FROM items GROUP BY id) USING (id) GROUP BY cell""")
def weighted_collision_array(spark, sf_dir):
    return grid.collision_array(_docs(spark, sf_dir).withColumn("k", F.size("elements")), weight_col="k")


@query("kde_sketch_docs", f"WITH {sql.sketch('doc_shingles', 1, 1, 5, 1, 100)} SELECT cell, n FROM sketch")
def kde_sketch_docs(spark, sf_dir):
    return cache.kde_sketch(_docs(spark, sf_dir), KDE).cells


_UNSEEN = f"unseen AS MATERIALIZED ({sql.items('benchmark_shingles')})"
_KDE_READ = f"WITH {sql.sketch('doc_shingles', 1, 1, 5, 1, 100)}, {_UNSEEN}, {sql.asked('unseen', 1, 5, 100)}, {sql.readings()}"


@query("kde_estimates_docs", f"{_KDE_READ}, {sql.measured(5)} SELECT qid, y AS est FROM y")
def kde_estimates_docs(spark, sf_dir):
    return cache.kde_estimate(cache.kde_sketch(_docs(spark, sf_dir), KDE), _unseen(spark, sf_dir), groups=5)


for _key, _view in (("docs", "doc_shingles"), ("baskets", "basket_twins"), ("orders", "basket_order")):
    QUERIES[f"sketch_build_{_key}"] = lambda spark, sf_dir, v=_view: grid.build_sketch(views.items(spark, sf_dir, v), SMALL, engine="arrow").cells
    ORACLES[f"sketch_build_{_key}"] = f"WITH {sql.sketch(_view, 2, 10, 2, 1, 100)} SELECT cell, n FROM sketch"


@query("sketch_build_sql_engine", ORACLES["sketch_build_docs"])
def sketch_build_sql_engine(spark, sf_dir):
    return grid.build_sketch(_docs(spark, sf_dir), SMALL).cells


def _sourced(spark, sf_dir):
    sources = views.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "source")
    return _docs(spark, sf_dir).join(sources, "id")


@query("sketch_merge_by_source", ORACLES["sketch_build_docs"])
def sketch_merge_by_source(spark, sf_dir):
    """Sketches of all sources, merged: equal to the sketch of all documents."""
    by_source = grid.build_grouped(_sourced(spark, sf_dir), SMALL, ["source"])
    return grid.merge_sketches(grid.Sketch(by_source, SMALL)).cells


@query("sketch_grouped_by_source", f"WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)} SELECT source, cell, count(*)::BIGINT AS n FROM hits JOIN documents ON doc_id = id GROUP BY source, cell")
def sketch_grouped_by_source(spark, sf_dir):
    return grid.build_grouped(_sourced(spark, sf_dir), SMALL, ["source"])


_CLOSE_DOCS = "close AS (SELECT DISTINCT qid FROM sims WHERE inter * 10 >= uni * 9)"


@query("sketch_subtract_query", f"""WITH {sql.pairs('doc_shingles')}, {_CLOSE_DOCS}, {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)}
    SELECT cell, count(*)::BIGINT AS n FROM hits WHERE id NOT IN (SELECT qid FROM close) GROUP BY cell""")
def sketch_subtract_query(spark, sf_dir):
    """The sketch with all close queries taken out again."""
    docs = _docs(spark, sf_dir)
    return grid.remove_items(grid.build_sketch(docs, SMALL, engine="arrow"), _close(docs)).cells


@query("sketch_rollup_region", f"""WITH {sql.sketch('basket_customer', 2, 10, 2, 1, 100)},
    g AS (SELECT r_name, n_name, cell FROM hits JOIN customer ON c_custkey = id JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey)
    SELECT r_name, n_name, cell, count(*)::BIGINT AS n, (CASE WHEN grouping(r_name) = 1 THEN 3 WHEN grouping(n_name) = 1 THEN 1 ELSE 0 END) * 2 AS level
    FROM g GROUP BY GROUPING SETS ((r_name, n_name, cell), (r_name, cell), (cell))""")
def sketch_rollup_region(spark, sf_dir):
    items = views.items(spark, sf_dir, "basket_customer")
    t = lambda n: views.table(spark, sf_dir, n)
    places = t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("c_custkey").alias("id"), "r_name", "n_name")
    return grid.build_grouped(items.join(places, "id"), SMALL, ["r_name", "n_name"], how="rollup")


_UNPACK = "SELECT cell // 2000 AS row, (cell // 200) % 10 AS col, (cell // 100) % 2 AS rep, cell % 100 AS bucket, n FROM sketch"


@query("sketch_sparse_layout", f"WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)} SELECT row, col, rep, count(*)::BIGINT AS nonzero, string_agg(bucket || ':' || n, ',' ORDER BY bucket) AS counts FROM ({_UNPACK}) GROUP BY row, col, rep")
def sketch_sparse_layout(spark, sf_dir):
    table = layout.to_sparse(grid.build_sketch(_docs(spark, sf_dir), SMALL, engine="arrow"))
    entries = F.transform(F.sort_array(F.map_entries("counts")), lambda e: F.concat_ws(":", e["key"], e["value"]))
    return table.select("row", "col", "rep", F.size("counts").cast("long").alias("nonzero"), F.array_join(entries, ",").alias("counts"))


@query("sketch_dense_layout", f"""WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)}, u AS ({_UNPACK}), full_ AS (SELECT i AS row, j AS col, o AS rep, b AS bucket FROM range(2) a(i), range(10) c(j), range(2) d(o), range(100) e(b))
    SELECT f.row, f.col, f.rep, string_agg(CAST(coalesce(n, 0) AS VARCHAR), ',' ORDER BY f.bucket) AS counts FROM full_ f LEFT JOIN u ON u.row = f.row AND u.col = f.col AND u.rep = f.rep AND u.bucket = f.bucket GROUP BY f.row, f.col, f.rep""")
def sketch_dense_layout(spark, sf_dir):
    table = layout.to_dense(grid.build_sketch(_docs(spark, sf_dir), SMALL, engine="arrow"))
    return table.select("row", "col", "rep", F.array_join(F.transform("counts", lambda c: c.cast("string")), ",").alias("counts"))


@query("counter_profile", f"WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)} SELECT max(n) AS max_count, count(*)::BIGINT AS nonzero, 1 - count(*) / 4000.0::DOUBLE AS zero_fraction, CASE WHEN max(n) < 128 THEN 8 WHEN max(n) < 32768 THEN 16 ELSE 32 END::INTEGER AS width_bits FROM sketch")
def counter_profile(spark, sf_dir):
    return layout.counter_profile(grid.build_sketch(_docs(spark, sf_dir), SMALL, engine="arrow"))


@query("sketch_signed_matrix", f"WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)} SELECT cell, sum(sign)::BIGINT AS n FROM hits GROUP BY cell HAVING sum(sign) <> 0")
def sketch_signed_matrix(spark, sf_dir):
    return grid.build_sketch(_docs(spark, sf_dir), SketchParams(2, 10, 2, measurement="signed")).cells


@query("sketch_bernoulli_matrix", f"""WITH items AS MATERIALIZED ({sql.items('doc_shingles')}), {sql.constants(2, 4, 1, 1)},
    coins AS (SELECT i AS row, j AS col, {sql.mult("'ba:42:' || i || ':' || j")} AS ca, {sql.off("'bb:42:' || i || ':' || j")} AS cb FROM range(2) a(i), range(4) b(j)),
    {sql.touched('items', 2, 4, 1, 1, 100, placed="placed AS (SELECT id, row, col, 1 AS sign FROM (SELECT DISTINCT id FROM items), coins WHERE ((id % " + str(sql.P) + ") * ca + cb) % " + str(sql.P) + " % 2 = 1)")}
    SELECT cell, count(*)::BIGINT AS n FROM hits GROUP BY cell""")
def sketch_bernoulli_matrix(spark, sf_dir):
    return grid.build_sketch(_docs(spark, sf_dir), SketchParams(2, 4, 1, measurement="bernoulli")).cells


# readings and decoding -------------------------------------------------------------------

_READ = f"WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)}, {_UNSEEN}, {sql.asked('unseen', 10, 2, 100)}, {sql.readings()}"


def _readings(spark, sf_dir, p=SMALL):
    sketch = grid.build_sketch(_docs(spark, sf_dir), p, engine="arrow")
    return sketch, decode.read_counters(sketch, decode.query_cells(_unseen(spark, sf_dir), p))


@query("query_cells_docs", f"WITH {_UNSEEN}, {sql.constants(2, 10, 2, 1)}, {sql.asked('unseen', 10, 2, 100)} SELECT qid, row, col, rep, cell FROM asked")
def query_cells_docs(spark, sf_dir):
    return decode.query_cells(_unseen(spark, sf_dir), SMALL)


for _key, _groups in (("mean", 1), ("mom", 2)):
    QUERIES[f"measurements_{_key}"] = lambda spark, sf_dir, g=_groups: decode.estimate_measurements(_readings(spark, sf_dir)[1], groups=g)
    ORACLES[f"measurements_{_key}"] = f"{_READ}, {sql.measured(_groups)} SELECT qid, row, col, y FROM y"


@query("measurements_median", f"WITH {sql.sketch('doc_shingles', 2, 10, 3, 1, 100)}, {_UNSEEN}, {sql.asked('unseen', 10, 3, 100)}, {sql.readings()}, {sql.measured(3)} SELECT qid, row, col, y FROM y")
def measurements_median(spark, sf_dir):
    return decode.estimate_measurements(_readings(spark, sf_dir, SketchParams(2, 10, 3))[1], groups=3)


@query("measurements_debiased", f"""{_READ}, loads AS (SELECT row, col, rep, sum(n) AS load FROM ({_UNPACK}) GROUP BY row, col, rep)
    SELECT r.qid, r.row, r.col, round(avg((r.n - coalesce(l.load, 0) * 0.01::DOUBLE) / 0.99::DOUBLE), 6) AS y FROM reads r LEFT JOIN loads l ON l.row = r.row AND l.col = r.col AND l.rep = r.rep GROUP BY r.qid, r.row, r.col""")
def measurements_debiased(spark, sf_dir):
    sketch, readings = _readings(spark, sf_dir)
    return decode.estimate_measurements(decode.debiased(readings, sketch)).select("qid", "row", "col", fixed("y", 6).alias("y"))


_SCORES = f"{_READ}, {sql.measured(2)}, {sql.decoded(10)}"


@query("decode_min_docs", f"{_SCORES} SELECT qid, id, score FROM scores")
def decode_min_docs(spark, sf_dir):
    y = decode.estimate_measurements(_readings(spark, sf_dir)[1], groups=2)
    return decode.recover_scores(y, _doc_ids(spark, sf_dir), SMALL)


@query("top_neighbors_docs", f"{_SCORES} {sql.top(V)}")
def top_neighbors_docs(spark, sf_dir):
    """The flagship: documents nearest to each benchmark passage, from the sketch alone."""
    return decode.top_neighbors(grid.build_sketch(_docs(spark, sf_dir), SMALL, engine="arrow"), _unseen(spark, sf_dir), _doc_ids(spark, sf_dir), V, groups=2)


@query("top_neighbors_pruned", f"{_SCORES} {sql.top(V)}")
def top_neighbors_pruned(spark, sf_dir):
    return decode.top_neighbors(grid.build_sketch(_docs(spark, sf_dir), SMALL, engine="arrow"), _unseen(spark, sf_dir), _doc_ids(spark, sf_dir), V, groups=2, decode="threshold")


@query("top_neighbors_arrow", f"{_SCORES} {sql.top(V)}")
def top_neighbors_arrow(spark, sf_dir):
    ys = decode.measure_arrow(grid.build_sketch(_docs(spark, sf_dir), SMALL, engine="arrow"), _unseen(spark, sf_dir), groups=2)
    return decode.top_arrow(ys, _doc_ids(spark, sf_dir), SMALL, V)


_BASKET_READ = f"""WITH {sql.pairs('basket_twins')}, {_CLOSE_DOCS}, {sql.sketch('basket_twins', 2, 12, 3, 1, 100)},
    own AS MATERIALIZED (SELECT * FROM items WHERE id IN (SELECT qid FROM close)), {sql.asked('own', 12, 3, 100)}, {sql.readings(True, 12)}, {sql.measured(3)}, {sql.decoded(12)}"""


@query("top_neighbors_baskets", f"{_BASKET_READ} {sql.top(V, where='id <> qid')}")
def top_neighbors_baskets(spark, sf_dir):
    items = _baskets(spark, sf_dir)
    ys = decode.measure_arrow(grid.build_sketch(items, TWINS, engine="arrow"), _close(items), groups=3, hold_out="decrement_one")
    return decode.top_arrow(ys, views.ids(spark, sf_dir, "basket_twins"), TWINS, V, exclude_own=True)


@query("top_neighbors_baskets_sql", ORACLES["top_neighbors_baskets"])
def top_neighbors_baskets_sql(spark, sf_dir):
    """The same with built-in expressions only."""
    items = _baskets(spark, sf_dir)
    return decode.top_neighbors(grid.build_sketch(items, TWINS), _close(items), views.ids(spark, sf_dir, "basket_twins"), V, groups=3, hold_out="decrement_one")


@query("neighbors_above_baskets", f"{_BASKET_READ} SELECT qid, id, score FROM scores WHERE id <> qid AND score >= 2")
def neighbors_above_baskets(spark, sf_dir):
    items = _baskets(spark, sf_dir)
    sketch = grid.build_sketch(items, TWINS, engine="arrow")
    y = decode.estimate_measurements(decode.own_removed(decode.read_counters(sketch, decode.query_cells(_close(items), TWINS)), TWINS), groups=3)
    return decode.neighbors_above(decode.recover_scores(y, items.select("id"), TWINS), 2).where("id != qid")


@query("reranked_baskets", f"""{_BASKET_READ}, tops AS MATERIALIZED ({sql.top(V, where='id <> qid')}),
    met AS (SELECT t.qid, t.id, coalesce(s.inter, 0)::BIGINT AS inter, (a.n + b.n - coalesce(s.inter, 0))::BIGINT AS uni FROM tops t JOIN sizes a ON a.id = t.qid JOIN sizes b ON b.id = t.id LEFT JOIN sims s ON s.qid = t.qid AND s.id = t.id)
    SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY inter / uni DESC, id)::BIGINT AS rank, id, inter, uni FROM met""")
def reranked_baskets(spark, sf_dir):
    from .operators.exact import rerank

    items = _baskets(spark, sf_dir)
    top = QUERIES["top_neighbors_baskets"](spark, sf_dir)
    return rerank(top, items, _close(items))


# Count-Min sketches ----------------------------------------------------------------------

_CMS = cms.cms_params(4, 50)
_CMS_SQL = f"""WITH {sql.constants(4, 50, 1, 1)}, w AS (SELECT l_partkey AS id, sum(CAST(l_quantity AS BIGINT))::BIGINT AS w FROM lineitem GROUP BY l_partkey),
    placed AS (SELECT id, w, row, {sql.column('a', 'b', 50)} AS col FROM w, rowpar), cms AS (SELECT row, col, sum(w)::BIGINT AS n FROM placed GROUP BY row, col),
    point AS (SELECT p.id AS l_partkey, min(c.n) AS estimate FROM placed p JOIN cms c ON c.row = p.row AND c.col = p.col GROUP BY p.id)"""


def _demand(spark, sf_dir):
    return views.table(spark, sf_dir, "lineitem").select("l_partkey", F.col("l_quantity").cast("long").alias("quantity"))


@query("cms_parts", f"{_CMS_SQL} SELECT row, col, n FROM cms")
def cms_parts(spark, sf_dir):
    return cms.cms_build(_demand(spark, sf_dir), "l_partkey", "quantity", _CMS)


@query("cms_point_parts", f"{_CMS_SQL} SELECT l_partkey, estimate FROM point")
def cms_point_parts(spark, sf_dir):
    return cms.cms_point(cms_parts(spark, sf_dir), _demand(spark, sf_dir), "l_partkey", _CMS)


@query("cms_heavy_hitters", f"{_CMS_SQL} SELECT l_partkey, estimate FROM point WHERE estimate >= 0.01 * (SELECT sum(n) FROM cms WHERE row = 0)")
def cms_heavy_hitters(spark, sf_dir):
    return cms.cms_heavy_hitters(cms_parts(spark, sf_dir), _demand(spark, sf_dir), "l_partkey", 0.01, _CMS)


@query("cms_bound_check", f"""{_CMS_SQL} SELECT count(*)::BIGINT AS keys, (count(*) FILTER (WHERE estimate < w))::BIGINT AS below,
    (count(*) FILTER (WHERE estimate > w + 0.05437 * (SELECT sum(w) FROM w)))::BIGINT AS above FROM point JOIN w ON w.id = l_partkey""")
def cms_bound_check(spark, sf_dir):
    true = _demand(spark, sf_dir).groupBy("l_partkey").agg(F.sum("quantity").alias("w"))
    total = true.agg(F.sum("w").alias("total"))
    met = cms_point_parts(spark, sf_dir).join(true, "l_partkey").crossJoin(F.broadcast(total))  # one row
    return met.agg(F.count(F.lit(1)).alias("keys"), F.count_if(F.col("estimate") < F.col("w")).alias("below"), F.count_if(F.col("estimate") > F.col("w") + F.lit(0.05437) * F.col("total")).alias("above"))


@query("exact_cell_decode", f"""WITH {sql.pairs('basket_twins')}, {sql.constants(3, 60, 1, 1)}, s AS (SELECT qid, id, inter / uni AS s FROM sims),
    placed AS (SELECT id, row, {sql.column("a", "b", 60)} AS col FROM sizes, rowpar), y AS (SELECT qid, row, col, sum(s) AS y FROM s JOIN placed USING (id) GROUP BY qid, row, col)
    SELECT qid, id, round(min(y), 6) AS score FROM placed JOIN y ON placed.row = y.row AND placed.col = y.col WHERE qid IN (SELECT DISTINCT qid FROM sims WHERE inter * 10 >= uni * 9) GROUP BY qid, id HAVING count(*) = 3""")
def exact_cell_decode(spark, sf_dir):
    items = views.sets(spark, sf_dir, "basket_twins")
    return cms.scanned_cell_scores(items, _close(items), 1, SketchParams(3, 60, 1)).select("qid", "id", fixed("score", 6).alias("score"))


# applications ----------------------------------------------------------------------------


@query("density_anomalies", f"""WITH {sql.sketch('doc_shingles', 1, 1, 5, 1, 100)}, {sql.asked('items', 1, 5, 100)}, {sql.readings()}, {sql.measured(5)} SELECT qid, y AS est FROM y ORDER BY y, qid LIMIT 50""")
def density_anomalies(spark, sf_dir):
    docs = _docs(spark, sf_dir)
    return cache.density_anomalies(cache.kde_sketch(docs, KDE), docs, 50, groups=5)


_WIDE = SketchParams(1, 1, 5, buckets=1000)


@query("cache_hits", f"""WITH {sql.sketch('page_tokens', 1, 1, 5, 1, 1000)}, drops AS (SELECT id, element, (29 * 1000003 + 11 + id * 48271) % {sql.P} AS h FROM items),
    probes AS MATERIALIZED (SELECT id, element FROM drops WHERE ((h * 1000003 + element * 48271 + 11) % {sql.P}) % 100 >= 10),
    {sql.asked('probes', 1, 5, 1000)}, {sql.readings()}, {sql.measured(5)} SELECT qid, y AS est, y >= 1 AS hit FROM y""")
def cache_hits(spark, sf_dir):
    pages = views.items(spark, sf_dir, "page_tokens")
    probes = views.to_sets(views.perturbed(pages.select("id", F.explode("elements").alias("element"))))
    return cache.cache_hits(cache.kde_sketch(pages, _WIDE), probes, 1.0, groups=5)


@query("contamination_probe", f"""WITH {sql.sketch('doc_shingles', 1, 1, 5, 1, 1000)}, {_UNSEEN}, {sql.asked('unseen', 1, 5, 1000)}, {sql.readings()}, {sql.measured(5)} SELECT qid, y AS est, y >= 3 AS hit FROM y""")
def contamination_probe(spark, sf_dir):
    return cache.cache_hits(cache.kde_sketch(_docs(spark, sf_dir), _WIDE), _unseen(spark, sf_dir), 3.0, groups=5)


@query("communication_bytes", f"WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)} SELECT source, (count(DISTINCT cell) * 6)::BIGINT AS bytes FROM hits JOIN documents ON doc_id = id GROUP BY source")
def communication_bytes(spark, sf_dir):
    return measures.communication_bytes(grid.build_grouped(_sourced(spark, sf_dir), SMALL, ["source"]), ["source"])
