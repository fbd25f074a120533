"""Queries over views, exact answers and baselines."""

from __future__ import annotations

from functools import partial

from pyspark.sql import functions as F

from .functions import hashing
from .functions.params import PRIME, SketchParams
from .operators import baselines, exact, measures
from .operators.measures import fixed
from .oracles import blocks as sql
from .plans import workloads
from .sources import views
from .sources.store import drop_stored, settle

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = sql.stable(oracle)
        return f

    return add


for _name in views.VIEWS:
    QUERIES[f"view_{_name}"] = partial(views.pairs, name=_name)
    ORACLES[f"view_{_name}"] = sql.view(_name)


@query("dataset_stats", " UNION ALL ".join(
    f"""SELECT * FROM (WITH {sql.pairs(v)} SELECT '{v}' AS view, (SELECT count(*) FROM sizes) AS nodes, (SELECT count(*) FROM v) AS nonzeros,
    round((SELECT count(*) FROM v) / (SELECT count(*) FROM sizes), 6) AS mean_edges,
    round(coalesce((SELECT sum(inter / uni) FROM sims WHERE id < qid), 0) / ((SELECT count(*) FROM sizes) * ((SELECT count(*) FROM sizes) - 1) / 2), 9) AS mean_similarity)"""
    for v in views.VIEWS))
def dataset_stats(spark, sf_dir):
    rows = None
    for name in views.VIEWS:
        items = views.sets(spark, sf_dir, name)
        one = measures.dataset_stats(items).select(F.lit(name).alias("view"), "nodes", "nonzeros", fixed("mean_edges", 6).alias("mean_edges"), fixed("mean_similarity", 9).alias("mean_similarity"))
        if name in views.PAIR_VIEWS:
            drop_stored(items)  # the sums are written
        del items
        settle(spark)  # before the next view's tables are made
        rows = one if rows is None else rows.unionByName(one)
    return rows


_ESTIMATED = " UNION ALL ".join(f"""SELECT * FROM (WITH items AS MATERIALIZED ({sql.items(v)}), {sql.constants(1, 1, 32, 1)},
    codes AS (SELECT id, rep, min((alpha * element + beta) % {sql.P}) AS code FROM items, par GROUP BY id, rep), counts AS (SELECT rep, code, count(*) AS n FROM codes GROUP BY rep, code),
    reps AS (SELECT rep, sum(n)::BIGINT AS nodes, sum(n * n)::BIGINT AS sq FROM counts GROUP BY rep) SELECT '{v}' AS view, max(nodes) AS nodes, round(avg((sq - nodes) / (nodes * (nodes - 1))), 9) AS mean_similarity FROM reps)"""
    for v in views.VIEWS)


@query("mean_similarity_estimates", _ESTIMATED)
def mean_similarity_estimates(spark, sf_dir):
    """The same mean in linear time: two items share a MinHash code with probability J,
    so the sum of squared code counts tells the sum of similarities."""
    rows = None
    for name in views.VIEWS:
        one = measures.mean_similarity_estimate(views.items(spark, sf_dir, name)).select(F.lit(name).alias("view"), "nodes", fixed("mean_similarity", 9).alias("mean_similarity"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


def _truth(name: str):
    return f"WITH {sql.pairs(name)} SELECT qid, id, inter, uni FROM sims WHERE inter * 10 >= uni * 8"


@query("truth_basket_pairs", _truth("basket_twins"))
def truth_basket_pairs(spark, sf_dir):
    return exact.close_pairs(views.sets(spark, sf_dir, "basket_twins"), 8, 10)


@query("truth_doc_pairs", _truth("doc_shingles"))
def truth_doc_pairs(spark, sf_dir):
    return exact.close_pairs(views.sets(spark, sf_dir, "doc_shingles"), 8, 10)


def _exact_top(name: str):
    return f"""WITH {sql.pairs(name)}, q AS (SELECT DISTINCT qid FROM sims WHERE inter * 10 >= uni * 9)
    SELECT qid, rank, id, inter, uni FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY inter / uni DESC, id)::BIGINT AS rank
    FROM sims WHERE qid IN (SELECT qid FROM q)) WHERE rank <= 20"""


def _exact_top_query(spark, sf_dir, name):
    items = views.sets(spark, sf_dir, name)
    queries, _ = workloads.close_queries(items, 9, 10)
    return exact.top_similar(items, queries, 20)


for _key, _view in (("exact_top_baskets", "basket_twins"), ("exact_top_docs", "doc_shingles")):
    QUERIES[_key] = partial(_exact_top_query, name=_view)
    ORACLES[_key] = _exact_top(_view)


@query("exact_top_embeddings", """WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(round(CAST(x AS DOUBLE) * 1000000) AS BIGINT)) AS v FROM embeddings),
    s AS (SELECT a.vec_id AS qid, b.vec_id AS id, CAST(list_sum(list_transform(list_zip(a.v, b.v), lambda z: z[1] * z[2])) AS BIGINT) AS score FROM e a JOIN e b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0)
    SELECT qid, rank, id, score FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id)::BIGINT AS rank FROM s) WHERE rank <= 20""")
def exact_top_embeddings(spark, sf_dir):
    """The nearest of the vectors whose id is divisible by 50, among all vectors."""
    rounded = views.rounded_vectors(spark, sf_dir)
    return exact.top_products(rounded, rounded.where("id % 50 = 0"), 20)


@query("exact_kernel_sum", f"WITH {sql.pairs('basket_twins')} SELECT qid, round(sum(pow(inter / uni, 2)), 6) AS s FROM sims GROUP BY qid")
def exact_kernel_sum(spark, sf_dir):
    items = views.sets(spark, sf_dir, "basket_twins")
    return exact.kernel_sums(items, items, 2).select("qid", fixed("s", 6).alias("s"))


_P3 = SketchParams(3, 60, 1)


@query("column_hash_ids", f"WITH {sql.constants(3, 60, 1, 1)} SELECT id, row, {sql.column('a', 'b', 60)} AS col FROM (SELECT DISTINCT id FROM ({sql.view('basket_twins')})), rowpar")
def column_hash_ids(spark, sf_dir):
    ids = views.pairs(spark, sf_dir, "basket_twins").select("id").distinct()
    return ids.select("id", F.explode(F.array(*[F.struct(F.lit(i).cast("long").alias("row"), hashing.column_hash(F.col("id"), i, _P3).alias("col")) for i in range(3)])).alias("c")).select("id", "c.row", "c.col")


def _projection_sql(m: int) -> str:
    return f"""pm AS (SELECT j, {sql.mult("'pa:42:' || j")} AS a, {sql.off("'pb:42:' || j")} AS b FROM range({m}) t(j)),
    ps AS (SELECT id, j, sum(CASE ((element * a + b) % {PRIME}) % 6 WHEN 0 THEN 1 WHEN 1 THEN -1 ELSE 0 END)::BIGINT AS s FROM items, pm GROUP BY id, j)"""


@query("projection_vectors", f"WITH items AS MATERIALIZED ({sql.items('basket_twins')}), {_projection_sql(8)} SELECT id, string_agg(CAST(s AS VARCHAR), ',' ORDER BY j) AS sums FROM ps GROUP BY id")
def projection_vectors(spark, sf_dir):
    sums = baselines.projection_sums(views.items(spark, sf_dir, "basket_twins"), 8)
    return sums.select("id", F.array_join(F.transform("sums", lambda x: x.cast("string")), ",").alias("sums"))


@query("projection_top_baskets", f"""WITH {sql.pairs('basket_twins')}, items AS MATERIALIZED ({sql.items('basket_twins')}), {_projection_sql(12)},
    q AS (SELECT DISTINCT qid FROM sims WHERE inter * 10 >= uni * 9),
    far AS (SELECT a.id AS qid, b.id, -sum((a.s - b.s) * (a.s - b.s))::BIGINT AS score FROM ps a JOIN ps b ON a.j = b.j AND a.id <> b.id WHERE a.id IN (SELECT qid FROM q) GROUP BY a.id, b.id)
    {sql.top(20, 'far')}""")
def projection_top_baskets(spark, sf_dir):
    items = views.items(spark, sf_dir, "basket_twins")
    queries, _ = workloads.close_queries(items, 9, 10)
    vectors = baselines.projection_sums(items, 12).select("id", F.col("sums").alias("vec"))
    top = baselines.projection_top(vectors, vectors.join(queries.select("id"), "id", "left_semi"), 20)
    return top.withColumn("score", F.round("score").cast("long"))


def _sample_sql(name: str, share: float) -> str:
    rank = f"(id % {PRIME} * {sql.mult(chr(39) + 'ra:42' + chr(39))} + {sql.off(chr(39) + 'rb:42' + chr(39))}) % {PRIME}"
    return f"""chosen AS (SELECT id FROM (SELECT DISTINCT id FROM v) ORDER BY {rank}, id LIMIT (SELECT CAST(round({share} * count(DISTINCT id)) AS BIGINT) FROM v))"""


@query("sample_items", f"WITH v AS MATERIALIZED ({sql.view('basket_twins')}), {_sample_sql('basket_twins', 0.3)} SELECT id FROM chosen")
def sample_items(spark, sf_dir):
    items = views.sets(spark, sf_dir, "basket_twins")
    return baselines.sample_items(items, int(items.count() * 0.3 + 0.5)).select("id")


@query("sample_top_baskets", f"""WITH {sql.pairs('basket_twins')}, {_sample_sql('basket_twins', 0.3)}, q AS (SELECT DISTINCT qid FROM sims WHERE inter * 10 >= uni * 9)
    SELECT qid, rank, id, round(inter / uni, 9) AS score FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY inter / uni DESC, id)::BIGINT AS rank
    FROM sims WHERE qid IN (SELECT qid FROM q) AND id IN (SELECT id FROM chosen)) WHERE rank <= 20""")
def sample_top_baskets(spark, sf_dir):
    items = views.sets(spark, sf_dir, "basket_twins")
    queries, _ = workloads.close_queries(items, 9, 10)
    sample = baselines.sample_items(items, int(items.count() * 0.3 + 0.5))
    return baselines.sample_top(sample, queries, 20).withColumn("score", fixed("score", 9))


@query("bloom_membership", f"""WITH f AS (SELECT j, {sql.mult("'fa:42:' || j")} AS a, {sql.off("'fb:42:' || j")} AS b FROM range(3) t(j)),
    bits AS (SELECT DISTINCT (({sql.code('url')} * a + b) % {PRIME}) % 16384 AS position FROM pages, f),
    p AS (SELECT DISTINCT {sql.code('url')} AS key, 1 AS cached FROM pages UNION SELECT DISTINCT {sql.code("url || '/x'")}, 0 FROM pages)
    SELECT key, count(*) FILTER (WHERE (key * a + b) % {PRIME} % 16384 NOT IN (SELECT position FROM bits)) = 0 AS hit FROM p, f GROUP BY key""")
def bloom_membership(spark, sf_dir):
    pages = views.table(spark, sf_dir, "pages").where("url is not null")
    keys = pages.select(hashing.code(F.col("url")).alias("key"))
    probes = keys.union(pages.select(hashing.code(F.concat("url", F.lit("/x"))).alias("key"))).distinct()
    return baselines.bloom_test(baselines.bloom_build(keys, "key", 16384, 3), probes, "key", 16384, 3)


@query("library_minhash_top")
def library_minhash_top(spark, sf_dir):
    items = views.items(spark, sf_dir, "basket_twins")
    queries, _ = workloads.close_queries(items, 9, 10)
    return baselines.library_top(items, queries, 20)


@query("product_quantized_embeddings")
def product_quantized_embeddings(spark, sf_dir):
    return baselines.product_quantize(views.vectors(spark, sf_dir))


@query("approx_distinct_elements")
def approx_distinct_elements(spark, sf_dir):
    rows = None
    for name in views.VIEWS:
        one = views.pairs(spark, sf_dir, name).agg(F.lit(name).alias("view"), F.approx_count_distinct("id", 0.02).alias("items"), F.approx_count_distinct("element", 0.02).alias("elements"))
        rows = one if rows is None else rows.unionByName(one)
    return rows
