"""Queries over the other hash families, index hashes, layouts, recoveries and the
relational operators around them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import Window

from .functions import hashing, sqlfuncs, theory
from .functions.params import PRIME, SketchParams
from .operators import baselines, cms, decode, grid, layout, measures
from .operators.measures import fixed
from .oracles import blocks as sql
from .plans import workloads
from .sources import store, views

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

SMALL = SketchParams(2, 10, 2)


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = sql.stable(oracle)
        return f

    return add


def _docs(spark, sf_dir):
    return views.items(spark, sf_dir, "doc_shingles")


# hash families ---------------------------------------------------------------------------


@query("onebit_codes_docs", f"""WITH items AS ({sql.items('doc_shingles')}), {sql.constants(1, 1, 8, 1)}
    SELECT id, rep, min((alpha * element + beta) % {sql.P}) % 2 AS bit FROM items, par GROUP BY id, rep""")
def onebit_codes_docs(spark, sf_dir):
    p = SketchParams(1, 1, 8, family="onebit_minhash", buckets=None)
    return grid.touched(_docs(spark, sf_dir), p, keep=["id"]).select("id", F.floor(F.col("cell") / 2).cast("long").alias("rep"), (F.col("cell") % 2).alias("bit"))


_STEP = 300_000


@query("grid_codes_embeddings", f"""WITH {sql.constants(1, 1, 4, 1)}, e AS (SELECT vec_id AS id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS c FROM embeddings),
    s AS (SELECT id, rep, any_value(beta) AS beta, any_value(gamma) AS gamma, sum(CASE WHEN ((alpha * c + beta) % {sql.P}) % 2 = 0 THEN 1 ELSE -1 END * CAST(round(CAST(x AS DOUBLE) * 1000000) AS BIGINT))::BIGINT AS t FROM e, par GROUP BY id, rep)
    SELECT id, rep, ((((floor((t + beta % {_STEP})::DOUBLE / {_STEP})::BIGINT % {sql.P}) + {sql.P}) % {sql.P}) * gamma % {sql.P} % 100)::BIGINT AS bucket FROM s""")
def grid_codes_embeddings(spark, sf_dir):
    """Cells of a shifted grid along projected directions: close vectors share them."""
    p = SketchParams(1, 1, 4, family="euclidean_grid", buckets=100, width=_STEP / 1_000_000)
    return grid.touched(views.vectors(spark, sf_dir), p, keep=["id"]).select("id", F.floor(F.col("cell") / 100).cast("long").alias("rep"), (F.col("cell") % 100).alias("bucket"))


@query("bit_sample_baskets", f"""WITH items AS (SELECT id, element FROM ({sql.view('basket_twins')})), {sql.constants(1, 1, 16, 1)}
    SELECT id, rep, max((element = alpha % 65536)::INTEGER)::BIGINT AS bit FROM items, par GROUP BY id, rep""")
def bit_sample_baskets(spark, sf_dir):
    """Single coordinates of the sets as long bit vectors, one for each repetition."""
    p = SketchParams(1, 1, 16, family="bit_sample", buckets=None)
    return grid.touched(views.sets(spark, sf_dir, "basket_twins"), p, keep=["id"]).select("id", F.floor(F.col("cell") / 2).cast("long").alias("rep"), (F.col("cell") % 2).alias("bit"))


_MURMUR = SketchParams(3, 60, 1, mixer="murmur3")


@query("murmur_columns_ids", f"WITH items AS MATERIALIZED ({sql.items('basket_twins')}), {sql.murmur('items', 3, 60)} SELECT id, row, col::BIGINT AS col FROM placed")
def murmur_columns_ids(spark, sf_dir):
    ids = views.ids(spark, sf_dir, "basket_twins")
    return ids.select("id", F.explode(F.array(*[F.struct(F.lit(i).cast("long").alias("row"), hashing.column_hash(F.col("id"), i, _MURMUR).alias("col")) for i in range(3)])).alias("c")).select("id", "c.row", "c.col")


_MURMUR_SKETCH = f"WITH items AS MATERIALIZED ({sql.items('doc_shingles')}), {sql.constants(2, 10, 2, 1)}, {sql.touched('items', 2, 10, 2, 1, 100, placed=sql.murmur('items', 2, 10))} SELECT cell::BIGINT AS cell, count(*)::BIGINT AS n FROM hits GROUP BY cell"

for _engine in ("arrow", "sql"):
    QUERIES[f"sketch_build_murmur_{_engine}"] = lambda spark, sf_dir, e=_engine: grid.build_sketch(_docs(spark, sf_dir), SketchParams(2, 10, 2, mixer="murmur3"), engine=e).cells
    ORACLES[f"sketch_build_murmur_{_engine}"] = _MURMUR_SKETCH


_SHARE = SketchParams(2, 10, 2, sharing="row")


@query("sketch_shared_hashes", f"WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100, sharing='row')} SELECT cell, n FROM sketch")
def sketch_shared_hashes(spark, sf_dir):
    """One hash a row and repetition for all columns."""
    return grid.build_sketch(_docs(spark, sf_dir), _SHARE, engine="arrow").cells


@query("collision_rate_docs", f"""WITH items AS MATERIALIZED ({sql.items('doc_shingles')}), {sql.pairs('doc_shingles')}, {sql.constants(1, 1, 64, 1)}, near AS (SELECT qid, id, inter / uni AS s FROM sims WHERE qid < id AND inter * 10 >= uni * 8),
    codes AS (SELECT i.id, rep, min((alpha * element + beta) % {sql.P}) AS code FROM items i, par WHERE i.id IN (SELECT qid FROM near UNION SELECT id FROM near) GROUP BY i.id, rep)
    SELECT n.qid, n.id, round(any_value(s), 6) AS similarity, round(avg((a.code = b.code)::INTEGER), 6) AS rate FROM near n JOIN codes a ON a.id = n.qid JOIN codes b ON b.id = n.id AND b.rep = a.rep GROUP BY n.qid, n.id""")
def collision_rate_docs(spark, sf_dir):
    """How often close pairs share a MinHash code, beside their similarity."""
    from .functions.lsh import minhash_code

    docs = _docs(spark, sf_dir)
    queries, pairs = workloads.close_queries(docs, 8, 10)
    c = hashing.constants(SketchParams(1, 1, 64))
    each = F.array(*[minhash_code(F.col("elements"), F.lit(int(c["alpha"][0, 0, o, 0])).cast("long"), F.lit(int(c["beta"][0, 0, o, 0])).cast("long")) for o in range(64)])
    codes = store.stored(queries.select("id", each.alias("codes")), "codes")
    met = pairs.where("qid < id").join(codes.select(F.col("id").alias("qid"), F.col("codes").alias("a")), "qid").join(codes.select("id", F.col("codes").alias("b")), "id")
    agree = F.aggregate(F.zip_with("a", "b", lambda x, y: (x == y).cast("double")), F.lit(0.0), lambda s, x: s + x) / 64
    return met.select("qid", "id", fixed(F.col("inter") / F.col("uni")).alias("similarity"), fixed(agree).alias("rate"))


# layouts ---------------------------------------------------------------------------------


@query("sketch_saved_loaded", f"WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)} SELECT cell, n FROM sketch")
def sketch_saved_loaded(spark, sf_dir):
    """A sketch through its stored form and back."""
    path = store.new_folder(spark, "saved-sketch")
    layout.save_sketch(grid.build_sketch(_docs(spark, sf_dir), SMALL, engine="arrow"), path)
    return layout.load_sketch(spark, path).cells


@query("sketch_packed_bytes", f"""WITH {sql.sketch('doc_shingles', 2, 10, 2, 1, 100)}, full_ AS (SELECT i AS cell FROM range(4000) t(i))
    SELECT f.cell // 2000 AS row, (f.cell // 200) % 10 AS col, (f.cell // 100) % 2 AS rep, string_agg(printf('%02x%02x', coalesce(n, 0) % 256, coalesce(n, 0) // 256), '' ORDER BY f.cell) AS data
    FROM full_ f LEFT JOIN sketch s ON s.cell = f.cell GROUP BY ALL""")
def sketch_packed_bytes(spark, sf_dir):
    packed = layout.pack_bytes(grid.build_sketch(_docs(spark, sf_dir), SMALL, engine="arrow"))
    return packed.select("row", "col", "rep", F.lower(F.hex("data")).alias("data"))


@query("uncompressed_sizes", " UNION ALL ".join(f"""SELECT * FROM (WITH v AS MATERIALIZED ({sql.view(v)}), s AS (SELECT count(*) AS nnz, count(DISTINCT id) AS n, max(element) AS most FROM v)
    SELECT '{v}' AS view, (nnz * 4 + (n + 1) * 4)::BIGINT AS csr_bytes, (nnz * 8)::BIGINT AS coo_bytes, (nnz * CASE WHEN most < 256 THEN 1 WHEN most < 65536 THEN 2 WHEN most < 4294967296 THEN 4 ELSE 8 END)::BIGINT AS smallest_bytes FROM s)""" for v in views.VIEWS))
def uncompressed_sizes(spark, sf_dir):
    """The data by three rules; ratios in the sweeps are to the first."""
    out = None
    for name in views.VIEWS:
        sets = views.sets(spark, sf_dir, name)
        one = measures.uncompressed_bytes(sets).select(F.lit(name).alias("view"), F.col("bytes").alias("csr_bytes"))
        one = one.crossJoin(measures.uncompressed_bytes(sets, "coo").withColumnRenamed("bytes", "coo_bytes")).crossJoin(measures.smallest_bytes(sets).withColumnRenamed("bytes", "smallest_bytes"))  # one row each
        out = one if out is None else out.unionByName(one)
    return out


# decoding --------------------------------------------------------------------------------

_SIGNED = SketchParams(3, 10, 2, measurement="signed")


@query("decode_median_signed", f"""WITH items AS MATERIALIZED ({sql.items('doc_shingles')}), {sql.constants(3, 10, 2, 1)}, {sql.touched('items', 3, 10, 2, 1, 100)}, sketch AS (SELECT cell, sum(sign)::BIGINT AS n FROM hits GROUP BY cell),
    unseen AS MATERIALIZED ({sql.items('benchmark_shingles')}), {sql.asked('unseen', 10, 2, 100)}, {sql.readings()}, {sql.measured(1)},
    cols AS (SELECT id, row, {sql.column('a', 'b', 10)} AS col, CASE WHEN ((id % {sql.P}) * sa + sb) % {sql.P} % 2 = 0 THEN 1 ELSE -1 END AS sign FROM (SELECT DISTINCT id FROM items), rowpar)
    SELECT y.qid, c.id, median(c.sign * y.y) AS score FROM cols c JOIN y ON y.row = c.row AND y.col = c.col GROUP BY y.qid, c.id""")
def decode_median_signed(spark, sf_dir):
    """Signed cells: the median of an id's signed measurements."""
    sketch = grid.build_sketch(_docs(spark, sf_dir), _SIGNED)
    readings = decode.read_counters(sketch, decode.query_cells(views.items(spark, sf_dir, "benchmark_shingles"), _SIGNED))
    return decode.recover_scores(decode.estimate_measurements(readings), views.ids(spark, sf_dir, "doc_shingles"), _SIGNED)


@query("ids_by_column", f"WITH {sql.constants(3, 60, 1, 1)} SELECT row, {sql.column('a', 'b', 60)} AS col, id FROM (SELECT DISTINCT o_custkey AS id FROM orders WHERE o_custkey IS NOT NULL), rowpar")
def ids_by_column(spark, sf_dir):
    """The customers of each column, by a lateral call that inverts the row's hash."""
    sqlfuncs.register(spark)
    p = SketchParams(3, 60, 1)
    ids = views.table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("id")).where("id is not null").distinct()
    ids.createOrReplaceTempView("grid_ids")
    most = ids.agg(F.coalesce(F.max("id") + 1, F.lit(0))).first()[0]
    rows = spark.createDataFrame([(i, *hashing.row_constants(p, i)) for i in range(3)], "row long, a long, b long")
    rows.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(59).cast("long"))).alias("col")).createOrReplaceTempView("grid_columns")
    return spark.sql("SELECT g.row, g.col, x.id FROM grid_columns g, LATERAL ids_in_column(g.a, g.b, 60L, g.col, " + f"{most}L) x LEFT SEMI JOIN grid_ids i ON i.id = x.id")


@query("measurements_arrow_aggregate", f"WITH {sql.sketch('doc_shingles', 2, 10, 3, 1, 100)}, unseen AS MATERIALIZED ({sql.items('benchmark_shingles')}), {sql.asked('unseen', 10, 3, 100)}, {sql.readings()}, {sql.measured(3)} SELECT qid, row, col, y FROM y")
def measurements_arrow_aggregate(spark, sf_dir):
    """The median of the repetitions by an aggregate function over Arrow batches."""
    p = SketchParams(2, 10, 3)

    def middle(n: pd.Series) -> float:
        return float(np.median(n))

    median = F.pandas_udf(middle, "double")
    readings = decode.read_counters(grid.build_sketch(_docs(spark, sf_dir), p, engine="arrow"), decode.query_cells(views.items(spark, sf_dir, "benchmark_shingles"), p))
    return readings.groupBy("qid", "row", "col").agg(median("n").alias("y"))


# Count-Min sizing and sparse recovery ----------------------------------------------------

_CMS_ASKED = [(e, d) for e in (0.1, 0.01, 0.001) for d in (0.1, 0.01)]
_CMS_KEYS = ("l_orderkey", "l_partkey", "l_suppkey")


@query("cms_sizes", f"""WITH k AS ({' UNION ALL '.join(f"SELECT '{k}' AS key, count(DISTINCT {k})::BIGINT AS n FROM lineitem" for k in _CMS_KEYS)})
    SELECT key, n, eps, delta, ceil(ln(n / delta) - 1e-9::DOUBLE)::BIGINT AS rows, ceil(exp(1) / eps - 1e-9::DOUBLE)::BIGINT AS cols
    FROM k, (VALUES {', '.join(f'({e}::DOUBLE, {d}::DOUBLE)' for e, d in _CMS_ASKED)}) t(eps, delta) WHERE n > 0""")
def cms_sizes(spark, sf_dir):
    """Rows and columns of a Count-Min sketch over the lines, by each of their keys."""
    lines = views.table(spark, sf_dir, "lineitem")
    sizes = [(k, lines.select(k).distinct().where(F.col(k).isNotNull()).count()) for k in _CMS_KEYS]
    return spark.createDataFrame([(k, n, e, d, *cms.cms_size(n, e, d)) for k, n in sizes if n for e, d in _CMS_ASKED], "key string, n long, eps double, delta double, rows long, cols long")


@query("sparse_recovery", """WITH w AS (SELECT l_partkey, sum(CAST(l_quantity AS BIGINT))::BIGINT AS w, row_number() OVER (ORDER BY sum(CAST(l_quantity AS BIGINT)) DESC, l_partkey) AS r FROM lineitem GROUP BY l_partkey)
    SELECT l_partkey, w::DOUBLE AS recovered FROM w WHERE r <= 8""")
def sparse_recovery(spark, sf_dir):
    """The parts of greatest demand as a sparse vector, recovered from a few random
    measurements of it: about v log(N / v) of them give it back exactly."""
    demand = views.table(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(F.sum(F.col("l_quantity").cast("long")).alias("w"))
    top = demand.orderBy(F.desc("w"), "l_partkey").limit(8).collect()  # eight rows
    n, v = 400, 8
    keys = sorted(r.l_partkey for r in top)
    places = {k: (i * 37 + 5) % n for i, k in enumerate(keys)}
    x = np.zeros(n)
    for r in top:
        x[places[r.l_partkey]] = r.w
    phi = np.where(np.random.default_rng(42).random((int(np.ceil(4 * v * np.log(n / v))), n)) < 0.5, -1.0, 1.0)
    found = cms.recover_sparse(phi @ x, phi, v)
    return spark.createDataFrame([(int(k), float(np.floor(found[places[k]] * 1e6 + 0.5) / 1e6)) for k in keys], "l_partkey long, recovered double")


# baselines -------------------------------------------------------------------------------

_RANK = f"(id % {sql.P} * {sql.mult(chr(39) + 'ra:42' + chr(39))} + {sql.off(chr(39) + 'rb:42' + chr(39))}) % {sql.P}"


@query("reservoir_items", f"WITH v AS MATERIALIZED ({sql.view('basket_twins')}) SELECT id FROM (SELECT DISTINCT id FROM v) ORDER BY {_RANK}, id LIMIT 100")
def reservoir_items(spark, sf_dir):
    return baselines.reservoir(views.sets(spark, sf_dir, "basket_twins"), 100).select("id")


@query("sample_top_euclidean", f"""WITH {sql.pairs('basket_twins')}, chosen AS (SELECT id FROM (SELECT DISTINCT id FROM v) ORDER BY {_RANK}, id LIMIT (SELECT CAST(floor(0.3 * count(DISTINCT id) + 0.5) AS BIGINT) FROM v)),
    q AS (SELECT DISTINCT qid FROM sims WHERE inter * 10 >= uni * 9),
    far AS (SELECT q.qid, c.id, (2 * coalesce(s.inter, 0) - a.n - b.n)::DOUBLE AS score FROM q JOIN sizes a ON a.id = q.qid JOIN chosen c ON c.id <> q.qid JOIN sizes b ON b.id = c.id LEFT JOIN sims s ON s.qid = q.qid AND s.id = c.id)
    {sql.top(20, 'far')}""")
def sample_top_euclidean(spark, sf_dir):
    """Euclidean search over all sampled items, those that share nothing as well."""
    items = views.sets(spark, sf_dir, "basket_twins")
    queries, _ = workloads.close_queries(items, 9, 10)
    return baselines.sample_top(baselines.sample_items(items, int(items.count() * 0.3 + 0.5)), queries, 20, "euclidean")


@query("library_vectors_top")
def library_vectors_top(spark, sf_dir):
    vectors = views.vectors(spark, sf_dir)
    return baselines.library_vectors_top(vectors, vectors.where("id % 50 = 0"), 20, most_distance=1.5)


@query("close_item_links", f"WITH {sql.pairs('doc_shingles')} SELECT qid AS id, count(*)::BIGINT AS links FROM sims WHERE inter * 10 >= uni * 8 GROUP BY qid")
def close_item_links(spark, sf_dir):
    """How many others each document is close to: linear in the documents."""
    from .operators import exact

    return exact.close_items(views.sets(spark, sf_dir, "doc_shingles"), 8, 10)


# calculators -----------------------------------------------------------------------------

_ORDERS = "(SELECT count(DISTINCT l_orderkey) FROM lineitem)"


def _orders(spark, sf_dir) -> int:
    """The number of items of ``basket_order``."""
    return views.table(spark, sf_dir, "lineitem").where("l_orderkey is not null").select("l_orderkey").distinct().count()


_ARRAYS = [(r, k, b) for r in (2, 100, 1000) for k in (1, 2, 4) for b in (0, 100, 1000)]


@query("array_bits", f"""SELECT code_range, hashes, buckets, round((CASE WHEN buckets = 0 THEN pow(code_range, hashes) ELSE buckets END) * log2({_ORDERS}), 3) AS bits
    FROM (VALUES {', '.join(f"({r}::BIGINT, {k}::BIGINT, {b}::BIGINT)" for r, k, b in _ARRAYS)}) t(code_range, hashes, buckets)""")
def array_bits(spark, sf_dir):
    """Bits of a collision array for the orders with lines; 0 buckets: without a re-hash."""
    n = _orders(spark, sf_dir)
    rows = [(r, k, b, theory.array_bits(r, k, n, b or None)) for r, k, b in _ARRAYS]
    return spark.createDataFrame(rows, "code_range long, hashes long, buckets long, bits double").withColumn("bits", fixed("bits", 3))


_BUDGETS = [(e, s) for e in (0.1, 0.5) for s in (0.25, 0.5, 0.75)]
_NORMED = ("basket_customer", "user_events")
_NORMS = " UNION ALL ".join(f"""SELECT * FROM (WITH items AS MATERIALIZED ({sql.items(v)}), {sql.constants(1, 1, 1, 1)}, codes AS (SELECT id, min((alpha * element + beta) % {sql.P}) AS code FROM items, par GROUP BY id),
    counts AS (SELECT count(*) AS n FROM codes GROUP BY code) SELECT '{v}' AS view, sum(n * n)::BIGINT / sum(n)::BIGINT AS norm1 FROM counts)""" for v in _NORMED)


@query("error_budgets", f"""SELECT view, eps, share, round(norm1, 9) AS norm1, round(eps * share / norm1, 9) AS cells, round(eps * (1 - share), 9) AS counters FROM ({_NORMS}), (VALUES {', '.join(f'({e}::DOUBLE, {s}::DOUBLE)' for e, s in _BUDGETS)}) t(eps, share)""")
def error_budgets(spark, sf_dir):
    """How total errors split, where a view's items collide with as many (themselves
    included) as the squared counts of a MinHash code tell."""
    rows = []
    for name in _NORMED:
        coded = grid.touched(views.items(spark, sf_dir, name), SketchParams(1, 1, 1, buckets=PRIME), engine="arrow")
        counts = coded.groupBy("cell").agg(F.sum("w").alias("n"))
        size = counts.agg(F.sum(F.col("n") * F.col("n")).alias("sq"), F.sum("n").alias("n")).first()
        if size.n:
            rows += [(name, e, s, size.sq / size.n, *theory.error_budget(e, s, size.sq / size.n)) for e, s in _BUDGETS]
    made = spark.createDataFrame(rows, "view string, eps double, share double, norm1 double, cells double, counters double")
    return made.select("view", "eps", "share", *[fixed(c, 9).alias(c) for c in ("norm1", "cells", "counters")])


_COSTED = [SketchParams(3, 60, 4), SketchParams(2, 100, 2, hashes=2), SketchParams(3, 60, 4, sharing="row"), SketchParams(3, 60, 4, sharing="rep")]


@query("cost_counters", f"""WITH v AS MATERIALIZED ({sql.view('basket_twins')}), s AS (SELECT count(DISTINCT id) AS n, count(*) / count(DISTINCT id) AS mean FROM v),
    p(rows, cols, reps, hashes, sharing, asked) AS (VALUES {', '.join(f"({p.rows}, {p.cols}, {p.reps}, {p.hashes}, '{p.sharing}', {dict(cell=p.arrays, row=p.rows * p.reps, rep=p.reps)[p.sharing]})" for p in _COSTED)})
    SELECT rows::BIGINT AS rows, cols::BIGINT AS cols, reps::BIGINT AS reps, hashes::BIGINT AS hashes, sharing, round(n * rows * reps * hashes * mean, 3) AS build_hashes, round(n * rows * reps, 3) AS build_updates,
      round(100 * asked * hashes * mean, 3) AS query_hashes, round(100 * rows * cols * reps, 3) AS query_reads, round(100 * n * rows, 3) AS decoded FROM p, s""")
def cost_counters(spark, sf_dir):
    """Work of building over the baskets and of 100 queries, by phase."""
    size = views.sets(spark, sf_dir, "basket_twins").agg(F.count(F.lit(1)).alias("n"), F.avg(F.size("elements")).alias("mean")).first()
    rows = []
    for p in _COSTED:
        c = theory.cost_counters(p, size.n, 100, size["mean"])
        rows.append((p.rows, p.cols, p.reps, p.hashes, p.sharing, *[float(c[k]) for k in ("build_hashes", "build_updates", "query_hashes", "query_reads", "decoded")]))
    names = ["build_hashes", "build_updates", "query_hashes", "query_reads", "decoded"]
    made = spark.createDataFrame(rows, "rows long, cols long, reps long, hashes long, sharing string, " + ", ".join(f"{c} double" for c in names))
    return made.select("rows", "cols", "reps", "hashes", "sharing", *[fixed(c, 3).alias(c) for c in names])


@query("suggested_params", f"""SELECT rows, cols, reps, hashes, buckets, bytes, round({_ORDERS} / cols, 6) AS load FROM (
    SELECT r AS rows, c AS cols, o AS reps, k AS hashes, b AS buckets, r * c * o * b * 2 AS bytes FROM (SELECT unnest([2, 3, 4, 5]::BIGINT[]) AS r), (SELECT unnest([100, 200, 500, 1000]::BIGINT[]) AS c), (SELECT unnest([2, 4, 8]::BIGINT[]) AS o),
      (SELECT unnest([1, 2]::BIGINT[]) AS k), (SELECT unnest([100, 300, 1000]::BIGINT[]) AS b)) WHERE bytes <= 6000000""")
def suggested_params(spark, sf_dir):
    """The grids of the usual ranges within six million bytes, for the orders with lines."""
    found = theory.suggest_params(0.9, 0.5, 4.0, _orders(spark, sf_dir), 6_000_000)
    rows = [tuple(int(x[k]) for k in ("rows", "cols", "reps", "hashes", "buckets", "bytes")) + (float(x["load"]),) for x in found]
    return spark.createDataFrame(rows, "rows long, cols long, reps long, hashes long, buckets long, bytes long, load double").withColumn("load", fixed("load"))


# relational operators around the method --------------------------------------------------


@query("size_distribution", f"""WITH v AS MATERIALIZED ({sql.view('basket_twins')}), s AS (SELECT id, count(*) AS n FROM v GROUP BY id)
    SELECT id, round(percent_rank() OVER (ORDER BY n), 9) AS below, round(cume_dist() OVER (ORDER BY n), 9) AS upto, ntile(10) OVER (ORDER BY n, id)::INTEGER AS tenth FROM s WHERE id % 5 = 0""")
def size_distribution(spark, sf_dir):
    """Where each customer stands by the size of its set, among those of one fifth (a
    fixed share by id, so that one window is no more than that)."""
    sizes = views.sets(spark, sf_dir, "basket_twins").where("id % 5 = 0").select("id", F.size("elements").alias("n"))
    by_size = Window.orderBy("n")
    return sizes.select("id", fixed(F.percent_rank().over(by_size), 9).alias("below"), fixed(F.cume_dist().over(by_size), 9).alias("upto"), F.ntile(10).over(Window.orderBy("n", "id")).alias("tenth"))


@query("size_quantiles", " UNION ALL ".join(f"SELECT '{v}' AS view, {q}::DOUBLE AS q, quantile_disc(n, {q})::BIGINT AS size FROM (SELECT id, count(*) AS n FROM ({sql.view(v)}) GROUP BY id)" for v in ("basket_twins", "doc_shingles") for q in (0.25, 0.5, 0.75, 0.95)))
def size_quantiles(spark, sf_dir):
    """Quantiles of set sizes by the mergeable summary, fine enough to be exact here."""
    out, asked = None, [0.25, 0.5, 0.75, 0.95]
    for name in ("basket_twins", "doc_shingles"):
        sizes = views.sets(spark, sf_dir, name).agg(F.percentile_approx(F.size("elements"), asked, 1_000_000).alias("x"))
        one = sizes.select(F.lit(name).alias("view"), F.explode(F.arrays_zip(F.array(*[F.lit(q) for q in asked]).alias("q"), F.col("x").alias("size"))).alias("z")).select("view", "z.q", F.col("z.size").cast("long").alias("size"))
        out = one if out is None else out.unionByName(one)
    return out


@query("shared_elements", f"""WITH a AS (SELECT DISTINCT element FROM ({sql.view('doc_shingles')})), b AS (SELECT element FROM ({sql.view('benchmark_shingles')}))
    SELECT 'both' AS part, count(*)::BIGINT AS elements FROM (SELECT element FROM a INTERSECT SELECT element FROM b) UNION ALL SELECT 'unseen', count(*)::BIGINT FROM (SELECT element FROM b EXCEPT ALL SELECT element FROM a)""")
def shared_elements(spark, sf_dir):
    """Benchmark shingles that documents have, and those left when one of each such is taken off."""
    a = views.pairs(spark, sf_dir, "doc_shingles").select("element").distinct()
    b = views.pairs(spark, sf_dir, "benchmark_shingles").select("element")
    count = lambda df, name: df.agg(F.lit(name).alias("part"), F.count(F.lit(1)).alias("elements"))
    return count(a.intersect(b), "both").unionByName(count(b.exceptAll(a), "unseen"))


@query("event_properties", "SELECT event_type, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*)::BIGINT AS n FROM events GROUP BY ALL")
def event_properties(spark, sf_dir):
    events = views.table(spark, sf_dir, "events")
    return events.select("event_type", F.from_json("props", "k long")["k"].alias("k")).groupBy("event_type", "k").agg(F.count(F.lit(1)).alias("n"))


@query("page_hosts", "SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*)::BIGINT AS pages FROM pages WHERE url IS NOT NULL GROUP BY host")
def page_hosts(spark, sf_dir):
    return views.table(spark, sf_dir, "pages").where("url is not null").groupBy(F.try_parse_url("url", F.lit("HOST")).alias("host")).agg(F.count(F.lit(1)).alias("pages"))
