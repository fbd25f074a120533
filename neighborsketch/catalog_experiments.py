"""Queries over query difficulty, accuracy measures, experiments and time."""

from __future__ import annotations

import shutil
import tempfile

from pyspark.sql import functions as F

from .functions import theory
from .functions.params import SketchParams
from .operators import baselines, cache, cms, decode, exact, grid, layout, measures, stability
from .operators.measures import fixed
from .oracles import blocks as sql
from .plans import planner, workloads
from .sources import views
from .streaming import stream

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

DOCS_P = SketchParams(3, 30, 4)
TWINS_P = SketchParams(3, 60, 4)
MEASURED_V = 1


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = sql.stable(oracle)
        return f

    return add


def _union(parts: list[str]) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)


# query difficulty ------------------------------------------------------------------------


def _kernel(spark, sf_dir, name="basket_twins"):
    items = views.sets(spark, sf_dir, name)
    queries, _ = workloads.close_queries(items, 8, 10)
    return stability.kernel(exact.overlaps(items, queries)), items.count()


_STATS = f"""WITH {sql.pairs('basket_twins')}, close AS (SELECT DISTINCT qid FROM sims WHERE inter * 10 >= uni * 8),
    k AS (SELECT qid, id, inter / uni AS p, row_number() OVER (PARTITION BY qid ORDER BY inter / uni DESC, id) AS rank FROM sims WHERE qid IN (SELECT qid FROM close)),
    raw AS (SELECT qid, max(p) FILTER (WHERE rank = 1) AS p_v, max(p) FILTER (WHERE rank = 2) AS p_next, sum(sqrt(p)) FILTER (WHERE rank > 1) AS root_tail, sum(p) AS norm1, sum(sqrt(p)) AS norm_tilde FROM k GROUP BY qid),
    stats AS (SELECT qid, p_v, p_next, coalesce(p_next, 0) / p_v AS gap, root_tail / sqrt(p_next) AS tail, norm1, norm_tilde,
      CASE WHEN p_v IS NULL THEN 'few_neighbors' WHEN p_next IS NULL THEN 'empty_tail' WHEN coalesce(p_next, 0) / p_v >= 1 THEN 'unstable_tie' ELSE 'ok' END AS status FROM raw),
    hashed AS (SELECT *, CASE WHEN status = 'empty_tail' THEN 1 WHEN status <> 'ok' THEN NULL WHEN tail <= 1 THEN 1 ELSE greatest(1, ceil(2 * ln(tail) / ln(1 / gap) - 1e-9)) END::INTEGER AS hashes FROM stats)"""
_N = "(SELECT count(*) FROM sizes)"


@query("stability_stats", f"{_STATS} SELECT qid, round(p_v, 6) AS p_v, round(p_next, 6) AS p_next, round(gap, 6) AS gap, round(tail, 6) AS tail, round(norm1, 6) AS norm1, round(norm_tilde, 6) AS norm_tilde, status, {_N} AS n_items FROM stats")
def stability_stats(spark, sf_dir):
    kernel, n = _kernel(spark, sf_dir)
    stats = stability.stability_stats(kernel, MEASURED_V, n)
    return stats.select("qid", *[fixed(c, 6).alias(c) for c in ("p_v", "p_next", "gap", "tail", "norm1", "norm_tilde")], "status", "n_items")


@query("choose_hashes", f"{_STATS} SELECT qid, hashes FROM hashed")
def choose_hashes(spark, sf_dir):
    kernel, n = _kernel(spark, sf_dir)
    return stability.with_hashes(stability.stability_stats(kernel, MEASURED_V, n)).select("qid", "hashes")


@query("sparsity_check", f"""{_STATS}, o AS (SELECT k.qid, hashes, rank, pow(p, hashes) AS s FROM k JOIN hashed USING (qid) WHERE hashes IS NOT NULL),
    c AS (SELECT qid, hashes, max(s) FILTER (WHERE rank = 1) AS top_p, coalesce(sum(s) FILTER (WHERE rank > 1), 0) AS tail_sum, sum(s) AS norm1, sum(sqrt(s)) AS norm_tilde FROM o GROUP BY qid, hashes)
    SELECT qid, hashes, round(top_p, 6) AS top_p, round(tail_sum, 6) AS tail_sum, top_p >= tail_sum - 1e-9 AS tail_below, norm1 <= 2 + 1e-9 AS norm1_bounded, norm_tilde <= 2 + 1e-9 AS tilde_bounded FROM c""")
def sparsity_check(spark, sf_dir):
    kernel, n = _kernel(spark, sf_dir)
    hashed = stability.with_hashes(stability.stability_stats(kernel, MEASURED_V, n))
    found = stability.check_sparsity(kernel, hashed, MEASURED_V)
    return found.select("qid", "hashes", fixed("top_p", 6).alias("top_p"), fixed("tail_sum", 6).alias("tail_sum"), "tail_below", "norm1_bounded", "tilde_bounded")


@query("kernel_norms", f"{_STATS} SELECT qid, round(sum(pow(p, 2)), 6) AS norm1, round(sum(p), 6) AS norm_tilde FROM k GROUP BY qid")
def kernel_norms(spark, sf_dir):
    return stability.kernel_norms(_kernel(spark, sf_dir)[0], 2).select("qid", fixed("norm1", 6).alias("norm1"), fixed("norm_tilde", 6).alias("norm_tilde"))


@query("variance_bound", f"{_STATS} SELECT qid, round(pow(sum(sqrt(p)), 2), 5) AS bound FROM k GROUP BY qid")
def variance_bound(spark, sf_dir):
    return stability.variance_bound(_kernel(spark, sf_dir)[0], 1).select("qid", fixed("bound", 5).alias("bound"))


@query("repetitions_needed", f"{_STATS} SELECT qid, round(180 * pow(sum(p), 2) / 0.25::DOUBLE * ln(180 / 0.01::DOUBLE), 3) AS repetitions FROM k GROUP BY qid")
def repetitions_needed(spark, sf_dir):
    norms = stability.kernel_norms(_kernel(spark, sf_dir)[0], 2)
    unit = theory.repetitions_needed(180, 1.0, 0.5, 0.01)
    return norms.select("qid", fixed(F.lit(unit) * F.col("norm_tilde") * F.col("norm_tilde"), 3).alias("repetitions"))


@query("arrays_needed", f"""{_STATS}, t AS (SELECT k.qid, g.h AS hashes, sum(pow(p, h)) AS norm1, sum(sqrt(pow(p, h))) AS norm_tilde,
      coalesce(max(pow(p, h)) FILTER (WHERE rank = 1), 0) - coalesce(max(pow(p, h)) FILTER (WHERE rank = 2), 0) AS eps FROM k, range(1, 5) g(h) GROUP BY k.qid, g.h),
    u AS (SELECT *, ln({_N} / 0.01::DOUBLE) AS deep FROM t)
    SELECT qid, hashes::INTEGER AS hashes, round(norm1, 6) AS norm1, round(norm_tilde, 6) AS norm_tilde, round(eps, 6) AS eps,
      CASE WHEN eps > 0 THEN round(ln(norm_tilde * norm_tilde * norm1 / pow(eps, 3) * ln(greatest(norm1 / (eps * 0.01::DOUBLE) * deep, exp(1))) * deep), 6) END AS log_arrays FROM u""")
def arrays_needed(spark, sf_dir):
    kernel, n = _kernel(spark, sf_dir)
    found = stability.hashes_tradeoff(kernel, MEASURED_V, 4, n)
    return found.select("qid", "hashes", fixed("norm1", 6).alias("norm1"), fixed("norm_tilde", 6).alias("norm_tilde"), fixed("eps", 6).alias("eps"), fixed(F.log("arrays"), 6).alias("log_arrays"))


_EXP = f"{_STATS}, e AS (SELECT qid, CASE WHEN gap > 0 AND gap < 1 THEN (6 * abs(ln(p_v)) + 2 * ln(2)) / ln(1 / gap) END AS b FROM stats)"


@query("memory_exponent", f"{_EXP} SELECT qid, round(b, 6) AS b, coalesce(b < 1, false) AS sublinear FROM e")
def memory_exponent(spark, sf_dir):
    kernel, n = _kernel(spark, sf_dir)
    return stability.with_exponent(stability.stability_stats(kernel, MEASURED_V, n), 2).select("qid", fixed("b", 6).alias("b"), "sublinear")


@query("coverage_by_exponent", f"{_EXP} SELECT c AS committed, (count(*) FILTER (WHERE b <= c))::BIGINT AS guaranteed, count(*)::BIGINT AS queries, round((count(*) FILTER (WHERE b <= c)) / count(*), 6) AS covered FROM e, (SELECT unnest([0.5, 0.75, 1.0, 1.5, 2.0]::DOUBLE[]) AS c) GROUP BY c")
def coverage_by_exponent(spark, sf_dir):
    kernel, n = _kernel(spark, sf_dir)
    found = stability.coverage(stability.with_exponent(stability.stability_stats(kernel, MEASURED_V, n), 2), [0.5, 0.75, 1.0, 1.5, 2.0])
    return found.withColumn("covered", fixed("covered", 6))


@query("unstable_queries", f"""WITH {sql.pairs('user_events')}, k AS (SELECT qid, 1 - inter / uni AS d FROM sims), c AS (SELECT qid, min(d) AS d0, count(*) AS sharing FROM k GROUP BY qid),
    m AS (SELECT qid, (1.5::DOUBLE * d0 + 1e-9) AS reach, sharing, (SELECT count(*) FROM k WHERE k.qid = c.qid AND d <= 1.5::DOUBLE * c.d0 + 1e-9) AS near FROM c)
    SELECT qid, round((near + CASE WHEN reach >= 1 THEN {_N} - 1 - sharing ELSE 0 END) / ({_N} - 1), 6) AS near, (near + CASE WHEN reach >= 1 THEN {_N} - 1 - sharing ELSE 0 END) / ({_N} - 1) > 0.5 AS unstable FROM m""")
def unstable_queries(spark, sf_dir):
    items = views.sets(spark, sf_dir, "user_events")
    return stability.is_unstable(stability.kernel(exact.overlaps(items, items)), items.count(), 0.5).withColumn("near", fixed("near", 6))


def _stats_sql(view: str, where: str) -> str:
    """CTE stats of the queries of a view."""
    return _STATS.replace(sql.pairs("basket_twins"), sql.pairs(view)).replace("WHERE inter * 10 >= uni * 8), k AS", f"WHERE {where}), k AS").replace("inter * 10 >= uni * 8", where)


@query("geometry_classes", _union([f"""{_stats_sql(v, 'true')} SELECT '{v}' AS view, CASE WHEN tail IS NULL OR tail / {_N} < 0.01::DOUBLE THEN 'sparse' WHEN tail / {_N} >= 0.5::DOUBLE THEN 'equidistant' ELSE 'between' END AS geometry, count(*)::BIGINT AS queries
    FROM stats GROUP BY ALL""" for v in ("basket_twins", "user_events")]))
def geometry_classes(spark, sf_dir):
    out = None
    for name in ("basket_twins", "user_events"):
        items = views.sets(spark, sf_dir, name)
        found = stability.geometry_class(stability.scanned_stats(items, items, MEASURED_V, items.count()))
        one = found.groupBy(F.lit(name).alias("view"), "geometry").agg(F.count(F.lit(1)).alias("queries"))
        out = one if out is None else out.unionByName(one)
    return out


# accuracy and size -----------------------------------------------------------------------


def _tops_sql(view: str, p: SketchParams, *, protocol: str = "decrement_one", v: int = 20) -> str:
    """CTEs up to tops, below sims and close."""
    d, w, o, k, r = p.rows, p.cols, p.reps, p.hashes, p.slots
    out = "id NOT IN (SELECT qid FROM close)" if protocol == "holdout_all" else "true"
    own = f"SELECT * FROM ({sql.items(view)}) WHERE id IN (SELECT qid FROM close)"
    return f"""{sql.sketch(view, d, w, o, k, r, where=out, sharing=p.sharing)},
    own AS MATERIALIZED ({own}), {sql.asked('own', w, o, r)}, {sql.readings(protocol == 'decrement_one', w)}, {sql.measured(1)}, {sql.decoded(w)},
    tops AS MATERIALIZED ({sql.top(v, where='id <> qid')})"""


def _close_sql(view: str, num: int = 8) -> str:
    return f"{sql.pairs(view)}, close AS (SELECT DISTINCT qid FROM sims WHERE inter * 10 >= uni * {num})"


def _sketch_sql(view: str, p: SketchParams) -> str:
    return f"WITH {_close_sql(view)}, {_tops_sql(view, p)}"


def _both(sql_head: str) -> str:
    """Recall at both thresholds from the same heads."""
    parts = [f"SELECT {num / den}::DOUBLE AS threshold, queries, round(recall, 6) AS recall FROM ({sql.recall(20, num, den)})" for num, den in workloads.THRESHOLDS]
    return sql.stable(f"{sql_head} {parts[0]} UNION ALL {parts[1]}")


def _recalls(top, truth):
    return measures.recall_at_each(top, truth, workloads.THRESHOLDS).withColumn("recall", fixed("recall", 6))


def _recall_query(view: str, p: SketchParams):
    def run(spark, sf_dir):
        items = views.items(spark, sf_dir, view)
        queries, truth = workloads.close_queries(items, 8, 10)
        return _recalls(workloads.sketch_top(items, queries, p), truth)

    return run


for _name, _view, _p in (("docs", "doc_shingles", DOCS_P), ("baskets", "basket_twins", TWINS_P), ("suppliers", "part_suppliers", TWINS_P), ("orders", "basket_order", TWINS_P)):
    QUERIES[f"recall_sketch_{_name}"] = _recall_query(_view, _p)
    ORACLES[f"recall_sketch_{_name}"] = _both(_sketch_sql(_view, _p))


_PROJECTED = f"""WITH {sql.pairs('basket_twins')}, items AS MATERIALIZED ({sql.items('basket_twins')}), close AS (SELECT DISTINCT qid FROM sims WHERE inter * 10 >= uni * 8),
    pm AS (SELECT j, {sql.mult("'pa:42:' || j")} AS a, {sql.off("'pb:42:' || j")} AS b FROM range(12) t(j)),
    ps AS (SELECT id, j, sum(CASE ((element * a + b) % {sql.P}) % 6 WHEN 0 THEN 1 WHEN 1 THEN -1 ELSE 0 END) AS s FROM items, pm GROUP BY id, j),
    far AS (SELECT a.id AS qid, b.id, -sum((a.s - b.s) * (a.s - b.s)) AS score FROM ps a JOIN ps b ON a.j = b.j AND a.id <> b.id WHERE a.id IN (SELECT qid FROM close) GROUP BY a.id, b.id),
    tops AS MATERIALIZED ({sql.top(20, 'far')})"""


@query("recall_projection", _both(_PROJECTED))
def recall_projection(spark, sf_dir):
    items = views.items(spark, sf_dir, "basket_twins")
    queries, truth = workloads.close_queries(items, 8, 10)
    vectors = baselines.projection_sums(items, 12).select("id", F.col("sums").alias("vec"))
    return _recalls(baselines.projection_top(vectors, vectors.join(queries.select("id"), "id", "left_semi"), 20), truth)


_RANK = f"(id % {sql.P} * {sql.mult(chr(39) + 'ra:42' + chr(39))} + {sql.off(chr(39) + 'rb:42' + chr(39))}) % {sql.P}"
_SAMPLED = f"""WITH {sql.pairs('basket_twins')}, chosen AS (SELECT id FROM sizes ORDER BY {_RANK}, id LIMIT (SELECT CAST(round(0.3 * count(*)) AS BIGINT) FROM sizes)),
    tops AS MATERIALIZED (SELECT qid, rank, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY inter / uni DESC, id) AS rank FROM sims WHERE id IN (SELECT id FROM chosen)) WHERE rank <= 20)"""


@query("recall_sampling", _both(_SAMPLED))
def recall_sampling(spark, sf_dir):
    items = views.sets(spark, sf_dir, "basket_twins")
    queries, truth = workloads.close_queries(items, 8, 10)
    sample = baselines.sample_items(items, int(items.count() * 0.3 + 0.5))
    return _recalls(baselines.sample_top(sample, queries, 20), truth)


_PROTOCOLS = ("decrement_one", "holdout_all", "exclude_at_decode")


@query("recall_protocols", _union([f"SELECT '{x}' AS protocol, * FROM ({_both('WITH ' + _close_sql('basket_twins') + ', ' + _tops_sql('basket_twins', TWINS_P, protocol=x))})" for x in _PROTOCOLS]))
def recall_protocols(spark, sf_dir):
    """The three ways of keeping a query out of its own answer."""
    items = views.items(spark, sf_dir, "basket_twins")
    queries, truth = workloads.close_queries(items, 8, 10)
    out = None
    for protocol in _PROTOCOLS:
        one = _recalls(workloads.sketch_top(items, queries, TWINS_P, protocol=protocol), truth).select(F.lit(protocol).alias("protocol"), "*")
        out = one if out is None else out.unionByName(one)
    return out


_SHARED = [SketchParams(3, 30, 4, sharing=x) for x in ("cell", "row", "rep")]


@query("recall_by_sharing", _union([f"SELECT '{p.sharing}' AS sharing, * FROM ({_both(_sketch_sql('doc_shingles', p))})" for p in _SHARED]))
def recall_by_sharing(spark, sf_dir):
    """Independent hashes per cell against hashes shared by a row or by all."""
    items = views.items(spark, sf_dir, "doc_shingles")
    queries, truth = workloads.close_queries(items, 8, 10)
    out = None
    for p in _SHARED:
        one = _recalls(workloads.sketch_top(items, queries, p), truth).select(F.lit(p.sharing).alias("sharing"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query("recall_by_band", f"""{_sketch_sql('doc_shingles', DOCS_P)} SELECT least(floor(inter * 10 / uni), 9)::INTEGER AS band, count(*)::BIGINT AS pairs, round(count(t.id) / count(*), 6) AS recall
    FROM sims s LEFT JOIN tops t ON t.qid = s.qid AND t.id = s.id WHERE s.qid IN (SELECT qid FROM close) GROUP BY band""")
def recall_by_band(spark, sf_dir):
    items = views.items(spark, sf_dir, "doc_shingles")
    queries, _ = workloads.close_queries(items, 8, 10)
    return measures.recall_by_band(workloads.sketch_top(items, queries, DOCS_P), exact.overlaps(items, queries)).withColumn("recall", fixed("recall", 6))


@query("all_found_rate", f"""{_sketch_sql('basket_twins', TWINS_P)}, best AS (SELECT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY inter / uni DESC, id) AS r FROM sims WHERE qid IN (SELECT qid FROM close)) WHERE r <= 1)
    SELECT count(*)::BIGINT AS queries, round(avg(CASE WHEN n = hits THEN 1 ELSE 0 END), 6) AS all_found, round(sum(hits) / sum(n), 6) AS each_found
    FROM (SELECT b.qid, count(*) AS n, count(t.id) AS hits FROM best b LEFT JOIN (SELECT * FROM tops WHERE rank <= 1) t ON t.qid = b.qid AND t.id = b.id GROUP BY b.qid)""")
def all_found_rate(spark, sf_dir):
    items = views.items(spark, sf_dir, "basket_twins")
    queries, _ = workloads.close_queries(items, 8, 10)
    found = measures.all_found_rate(workloads.sketch_top(items, queries, TWINS_P), exact.top_similar(items, queries, 1), 1)
    return found.select("queries", fixed("all_found", 6).alias("all_found"), fixed("each_found", 6).alias("each_found"))


@query("size_accounting", f"""WITH {sql.sketch('doc_shingles', 3, 30, 4, 1, 100)}, s AS (SELECT count(*) AS nnz, count(DISTINCT id) AS n FROM items)
    SELECT nnz * 4 + (n + 1) * 4 AS csr_bytes, nnz * 8 AS coo_bytes, (SELECT count(*) FROM sketch) * 6 + 12 AS sparse_bytes, 72000::BIGINT AS dense_bytes, n * 400 AS projection_bytes FROM s""")
def size_accounting(spark, sf_dir):
    items = views.items(spark, sf_dir, "doc_shingles")
    sketch = grid.build_sketch(items, DOCS_P, engine="arrow")
    parts = [measures.uncompressed_bytes(items).withColumnRenamed("bytes", "csr_bytes"), measures.uncompressed_bytes(items, "coo").withColumnRenamed("bytes", "coo_bytes"),
             layout.sketch_bytes(sketch, "sparse").withColumnRenamed("bytes", "sparse_bytes"), layout.sketch_bytes(sketch, "dense").withColumnRenamed("bytes", "dense_bytes"),
             items.agg((F.count(F.lit(1)) * 400).alias("projection_bytes"))]
    out = parts[0]
    for p in parts[1:]:
        out = out.crossJoin(p)  # one row each
    return out


_COUNTED = [(view, cols, buckets) for view in ("doc_shingles", "basket_twins", "part_suppliers") for cols, buckets in ((30, 100), (100, 100), (100, 1000), (300, 100))]


@query("counter_study", _union([f"""WITH {sql.sketch(v, 3, c, 2, 1, b)} SELECT '{v}' AS view, {c}::INTEGER AS cols, {b}::INTEGER AS buckets, max(n) AS max_count, count(*)::BIGINT AS nonzero,
    round(1 - count(*) / {3 * c * 2 * b}.0::DOUBLE, 9) AS zero_fraction, CASE WHEN max(n) < 128 THEN 8 WHEN max(n) < 32768 THEN 16 ELSE 32 END::INTEGER AS width_bits FROM sketch""" for v, c, b in _COUNTED]))
def counter_study(spark, sf_dir):
    """Largest counters and shares of zeros over sizes of the grid."""
    out = None
    for view, cols, buckets in _COUNTED:
        profile = layout.counter_profile(grid.build_sketch(views.items(spark, sf_dir, view), SketchParams(3, cols, 2, buckets=buckets), engine="arrow"))
        one = profile.select(F.lit(view).alias("view"), F.lit(cols).alias("cols"), F.lit(buckets).alias("buckets"), "max_count", "nonzero", fixed("zero_fraction", 9).alias("zero_fraction"), "width_bits")
        out = one if out is None else out.unionByName(one)
    return out


_SEEDS = (1, 2, 3, 4, 5, 6, 7, 8)


@query("estimator_error_seeds", f"""WITH {sql.pairs('doc_shingles', 'v')}, b AS MATERIALIZED ({sql.view('benchmark_shingles')}), nb AS (SELECT id, count(*) AS n FROM b GROUP BY id),
    e AS (SELECT b.id AS qid, v.id, count(*) AS inter FROM b JOIN v ON b.element = v.element GROUP BY b.id, v.id),
    ex AS (SELECT qid, sum(inter / (nb.n + s.n - inter)) AS s FROM e JOIN nb ON nb.id = qid JOIN sizes s ON s.id = e.id GROUP BY qid),
    c AS (SELECT h AS seed, {sql.mult("'alpha:' || h || ':0:0:0:0'")} AS alpha, {sql.off("'beta:' || h || ':0:0:0:0'")} AS beta, {sql.mult("'gamma:' || h || ':0:0:0:0'")} AS gamma FROM range(1, 9) t(h)),
    ci AS (SELECT v.id, seed, (min((alpha * element + beta) % {sql.P}) * any_value(gamma)) % {sql.P} % 1000 AS bucket FROM v, c GROUP BY v.id, seed),
    cb AS (SELECT b.id AS qid, seed, (min((alpha * element + beta) % {sql.P}) * any_value(gamma)) % {sql.P} % 1000 AS bucket FROM b, c GROUP BY b.id, seed),
    est AS (SELECT cb.qid, cb.seed, count(ci.id) AS est FROM cb LEFT JOIN ci ON ci.seed = cb.seed AND ci.bucket = cb.bucket GROUP BY cb.qid, cb.seed)
    SELECT est.qid, round(avg(est - coalesce(s, 0)), 6) AS bias, round(var_pop(est), 6) AS variance, round(avg((est - coalesce(s, 0)) * (est - coalesce(s, 0))), 6) AS mse FROM est LEFT JOIN ex ON ex.qid = est.qid GROUP BY est.qid""")
def estimator_error_seeds(spark, sf_dir):
    docs, asked = views.items(spark, sf_dir, "doc_shingles"), views.items(spark, sf_dir, "benchmark_shingles")
    estimates = None
    for seed in _SEEDS:
        p = SketchParams(1, 1, 1, buckets=1000, seed=seed)
        one = cache.kde_estimate(cache.kde_sketch(docs, p, engine="arrow"), asked).withColumn("seed", F.lit(seed))
        estimates = one if estimates is None else estimates.unionByName(one)
    found = measures.estimator_error(estimates, exact.exact_kde(exact.overlaps(docs, asked), 1))
    return found.select("qid", *[fixed(c, 6).alias(c) for c in ("bias", "variance", "mse")])


_RECOVERED = f"""WITH {_close_sql('basket_twins', 9)}, {sql.sketch('basket_twins', 3, 60, 4, 1, 100)}, own AS MATERIALIZED (SELECT * FROM items WHERE id IN (SELECT qid FROM close)),
    {sql.asked('own', 60, 4, 100)}, {sql.readings()}, {sql.measured(1)}, {sql.decoded(60)},
    kern AS MATERIALIZED (SELECT qid, id, inter / uni AS s FROM sims WHERE qid IN (SELECT qid FROM close) UNION ALL SELECT qid, qid, 1.0::DOUBLE FROM close),
    ey AS (SELECT k.qid, c.row, c.col, sum(s) AS y FROM kern k JOIN cols c ON c.id = k.id GROUP BY k.qid, c.row, c.col),
    es AS (SELECT ey.qid, c.id, min(ey.y) AS score FROM cols c JOIN ey ON ey.row = c.row AND ey.col = c.col GROUP BY ey.qid, c.id HAVING count(*) = 3),
    e AS (SELECT 'exact_cells' AS cells, es.qid, es.score - coalesce(k.s, 0) AS e FROM es LEFT JOIN kern k ON k.qid = es.qid AND k.id = es.id
          UNION ALL SELECT 'sketch', s.qid, s.score - coalesce(k.s, 0) FROM scores s LEFT JOIN kern k ON k.qid = s.qid AND k.id = s.id)
    SELECT cells, count(*)::BIGINT AS pairs, round(max(abs(e)), 6) AS worst, round(avg((abs(e) <= 0.25::DOUBLE)::INTEGER), 6) AS within, round(avg((e < -1e-9::DOUBLE)::INTEGER), 6) AS below FROM e GROUP BY cells"""


@query("recovery_error", _RECOVERED)
def recovery_error(spark, sf_dir):
    """Exact cells never read below the kernel; estimated ones may."""
    items = views.items(spark, sf_dir, "basket_twins")
    queries, _ = workloads.close_queries(items, 9, 10)
    kernel = exact.exact_kernel(exact.overlaps(items, queries), 1)
    ideal = measures.recovery_error(cms.exact_cell_scores(kernel, items.select("id"), TWINS_P), kernel, 0.5).select(F.lit("exact_cells").alias("cells"), "*")
    sketch = grid.build_sketch(items, TWINS_P, engine="arrow")
    y = decode.estimate_measurements(decode.read_counters(sketch, decode.query_cells(queries, TWINS_P)))
    both = ideal.unionByName(measures.recovery_error(decode.recover_scores(y, items.select("id"), TWINS_P), kernel, 0.5).select(F.lit("sketch").alias("cells"), "*"))
    return both.select("cells", "pairs", *[fixed(c).alias(c) for c in ("worst", "within", "below")])


_ROC = f"""WITH {sql.sketch('page_tokens', 1, 1, 5, 1, 1000)}, drops AS (SELECT id, element, (29 * 1000003 + 11 + id * 48271) % {sql.P} AS h FROM items),
    probes AS MATERIALIZED (SELECT id, element, 1 AS should FROM drops WHERE ((h * 1000003 + element * 48271 + 11) % {sql.P}) % 100 >= 10
      UNION ALL SELECT id + (1::BIGINT << 40), element, 0 FROM ({sql.items('benchmark_shingles')})), {sql.asked('probes', 1, 5, 1000)}, {sql.readings()}, {sql.measured(5)},
    m AS (SELECT y.y, p.should FROM y JOIN (SELECT DISTINCT id, should FROM probes) p ON p.id = y.qid)
    SELECT tau, round(avg(CASE WHEN should = 1 THEN (y >= tau)::INTEGER END), 6) AS hit_rate, round(avg(CASE WHEN should = 0 THEN (y >= tau)::INTEGER END), 6) AS false_rate
    FROM m, (SELECT unnest([0.5, 1, 2, 3]::DOUBLE[]) AS tau) GROUP BY tau"""


@query("cache_roc", _ROC)
def cache_roc(spark, sf_dir):
    pages = views.items(spark, sf_dir, "page_tokens")
    probes = views.to_sets(views.perturbed(pages.select("id", F.explode_outer("elements").alias("element"))))
    strangers = views.items(spark, sf_dir, "benchmark_shingles").withColumn("id", F.col("id") + (1 << 40))
    p = SketchParams(1, 1, 5, buckets=1000)
    estimates = cache.kde_estimate(cache.kde_sketch(pages, p, engine="arrow"), probes.unionByName(strangers), groups=5)
    return cache.roc(estimates, probes.select(F.col("id").alias("qid")), [0.5, 1, 2, 3]).select("tau", fixed("hit_rate").alias("hit_rate"), fixed("false_rate").alias("false_rate"))


@query("mutual_neighbors", f"WITH {_close_sql('basket_twins')}, {_tops_sql('basket_twins', TWINS_P, v=5)} SELECT a.qid AS a, a.id AS b FROM tops a JOIN tops b ON a.qid = b.id AND a.id = b.qid WHERE a.qid < a.id")
def mutual_neighbors(spark, sf_dir):
    items = views.items(spark, sf_dir, "basket_twins")
    queries, _ = workloads.close_queries(items, 8, 10)
    return workloads.mutual_pairs(workloads.sketch_top(items, queries, TWINS_P, 5))


@query("planned_neighbors", f"WITH {_close_sql('part_suppliers', 9)}, {_tops_sql('part_suppliers', TWINS_P)} SELECT qid, rank, id, score FROM tops")
def planned_neighbors(spark, sf_dir):
    items = views.items(spark, sf_dir, "part_suppliers")
    queries, _ = workloads.close_queries(items, 9, 10)
    return planner.report_neighbors(items, queries, TWINS_P, 20, hold_out="decrement_one")


def _projected_sql(p: SketchParams, where: str) -> str:
    """CTEs up to tops for embeddings under signed projections (no re-hash), for the
    queries that ``where`` names."""
    d, w, o, k = p.rows, p.cols, p.reps, p.hashes
    code = "SUM(CASE WHEN ((alpha * c + beta) % {P}) % 2 = 0 THEN x ELSE -x END) >= 0".format(P=sql.P)
    bits = f"sum(bit * (1 << ({k - 1} - k)))::BIGINT"
    return f"""{sql.constants(d, w, o, k)}, items AS MATERIALIZED (SELECT vec_id AS id, unnest(embedding) AS raw, generate_subscripts(embedding, 1) AS c FROM embeddings),
    coords AS MATERIALIZED (SELECT id, c, CAST(round(CAST(raw AS DOUBLE) * 1000000) AS BIGINT) AS x FROM items), placed AS (SELECT id, row, {sql.column('a', 'b', w)} AS col FROM (SELECT DISTINCT id FROM items), rowpar),
    hits AS (SELECT id, row, col, rep, (((row * {w} + col) * {o} + rep) * {1 << k} + {bits})::BIGINT AS cell FROM (
      SELECT s.id, p.row, p.col, q.rep, q.k, ({code})::INTEGER AS bit FROM coords s JOIN placed p ON p.id = s.id JOIN par q ON q.row = p.row AND q.col = p.col GROUP BY ALL) GROUP BY id, row, col, rep),
    sketch AS (SELECT cell, count(*)::BIGINT AS n FROM hits GROUP BY cell),
    asked AS (SELECT id AS qid, row, col, rep, (((row * {w} + col) * {o} + rep) * {1 << k} + {bits})::BIGINT AS cell FROM (
      SELECT s.id, q.row, q.col, q.rep, q.k, ({code})::INTEGER AS bit FROM coords s, par q WHERE {where} GROUP BY ALL) GROUP BY id, row, col, rep),
    {sql.readings(True, w)}, {sql.measured(1)}, {sql.decoded(w)}, tops AS MATERIALIZED ({sql.top(20, where='id <> qid')})"""


_HASHED_P = SketchParams(2, 8, 4, hashes=4, family="signed_projection", buckets=None)


@query("embedding_hash_arrow", f"WITH {_projected_sql(_HASHED_P, 'false')} SELECT cell, n FROM sketch")
def embedding_hash_arrow(spark, sf_dir):
    return grid.build_sketch(views.vectors(spark, sf_dir), _HASHED_P, engine="arrow").cells


_VECTORS_P = SketchParams(3, 40, 6, hashes=6, family="signed_projection", buckets=None)


@query("embedding_neighbors", f"""WITH {_projected_sql(_VECTORS_P, 's.id % 50 = 0')},
    dots AS (SELECT a.id AS qid, b.id, sum(a.x * b.x)::BIGINT AS score FROM coords a JOIN coords b ON a.c = b.c AND a.id <> b.id WHERE a.id % 50 = 0 GROUP BY a.id, b.id),
    best AS (SELECT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, id) AS r FROM dots) WHERE r = 1)
    SELECT count(*)::BIGINT AS queries, round(avg((t.id IS NOT NULL)::INTEGER), 6) AS all_found, round(count(t.id) / count(*), 6) AS each_found FROM best b LEFT JOIN tops t ON t.qid = b.qid AND t.id = b.id""")
def embedding_neighbors(spark, sf_dir):
    """Another family: hard queries all (every vector whose id is divisible by 50), so the
    measure is how few of the true neighbours are found."""
    vectors = views.vectors(spark, sf_dir)
    asked = vectors.where("id % 50 = 0")
    sketch = grid.build_sketch(vectors, _VECTORS_P, engine="arrow")
    ys = decode.measure_arrow(sketch, asked, hold_out="decrement_one")
    top = decode.top_arrow(ys, vectors.select("id"), _VECTORS_P, 20, exclude_own=True)
    rounded = views.rounded_vectors(spark, sf_dir)
    found = measures.all_found_rate(top, decode.best(exact.dot_products(rounded, rounded.where("id % 50 = 0")), 1), 20)
    return found.select("queries", fixed("all_found").alias("all_found"), fixed("each_found").alias("each_found"))


# time ------------------------------------------------------------------------------------

_EVENT_ITEMS = f"SELECT event_id AS id, {sql.code(chr(39) + 'u:' + chr(39) + ' || user_id')} AS element, ts FROM events"
_EVENT_P = SketchParams(2, 10, 2)


def _event_items(events):
    from .functions.hashing import code

    return events.select(F.col("event_id").alias("id"), "ts", F.array(code(F.concat(F.lit("u:"), F.col("user_id").cast("string")))).alias("elements"))


_EVENT_CELLS = f"items AS MATERIALIZED ({_EVENT_ITEMS}), {sql.constants(2, 10, 2, 1)}, {sql.touched('items', 2, 10, 2, 1, 100)}"


@query("stream_sketch_equals_batch", f"WITH {_EVENT_CELLS} SELECT cell, count(*)::BIGINT AS n FROM hits GROUP BY cell")
def stream_sketch_equals_batch(spark, sf_dir):
    """The sketch of the event stream, kept in memory by a running query."""
    # as a pattern, the path may be one file or a folder of part files
    source = stream.file_stream(spark, f"{sf_dir}/events.parque[t]", stream.EVENTS)
    running = stream.running_sketch(_event_items(source), _EVENT_P)
    at = spark.conf.get("spark.checkpoint.dir", None)
    folder = tempfile.mkdtemp(prefix="stream-") if at is None else f"{at}/stream-{id(running)}"
    name = f"running_{id(running)}"
    q = running.writeStream.outputMode("complete").format("memory").queryName(name).option("checkpointLocation", folder).trigger(availableNow=True).start()
    try:
        q.awaitTermination()
    finally:
        q.stop()
        if at is None:
            shutil.rmtree(folder, ignore_errors=True)
    return spark.table(name)


@query("interval_window_sketch", f"""WITH {_EVENT_CELLS}, days AS (SELECT CAST(date_trunc('day', i.ts) AS DATE) AS day, cell FROM hits h JOIN items i ON i.id = h.id),
    span AS (SELECT min(CAST(date_trunc('day', ts) AS DATE)) AS d0, max(CAST(date_trunc('day', ts) AS DATE)) AS d1 FROM events),
    iv AS (SELECT g AS interval_id, d0 + CAST(3 * g AS INTEGER) AS first, d0 + CAST(3 * g + 6 AS INTEGER) AS last FROM (SELECT d0, unnest(range(0, (d1 - d0) // 3 + 1)) AS g FROM span))
    SELECT interval_id, cell, count(*)::BIGINT AS n FROM days JOIN iv ON day BETWEEN first AND last GROUP BY interval_id, cell""")
def interval_window_sketch(spark, sf_dir):
    items = _event_items(views.table(spark, sf_dir, "events")).withColumn("day", F.to_date("ts"))
    daily = grid.build_grouped(items, _EVENT_P, ["day"])
    # weeks that begin every three days, from the first day of the events to the last
    span = views.table(spark, sf_dir, "events").agg(F.to_date(F.min("ts")).alias("d0"), F.to_date(F.max("ts")).alias("d1"))
    steps = span.select("d0", F.explode(F.sequence(F.lit(0), F.floor(F.datediff("d1", "d0") / 3).cast("int"))).alias("g"))
    intervals = steps.select(F.col("g").cast("long").alias("interval_id"), F.date_add("d0", 3 * F.col("g")).alias("first"), F.date_add("d0", 3 * F.col("g") + 6).alias("last"))
    return stream.interval_sketch(daily, intervals)


@query("asof_snapshot_query", """WITH s AS (SELECT DISTINCT date_trunc('day', ts) AS taken FROM events WHERE event_type = (SELECT min(event_type) FROM events))
    SELECT event_id, CAST((SELECT max(taken) FROM s WHERE taken <= ts) AS VARCHAR)[1:10] AS snapshot FROM events""")
def asof_snapshot_query(spark, sf_dir):
    events = stream.with_event_time(views.table(spark, sf_dir, "events"))
    kind = events.agg(F.min("event_type").alias("first_type"))
    snapshots = events.join(F.broadcast(kind), F.col("event_type") == F.col("first_type")).select(F.date_trunc("day", "ts").alias("taken")).distinct()  # one row
    return stream.as_of(events.select("event_id", F.col("ts").alias("at")), snapshots).select("event_id", F.date_format("snapshot", "yyyy-MM-dd").alias("snapshot"))


@query("session_sets", """WITH o AS (SELECT user_id, ts, event_type, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS opens FROM events),
    g AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS visit FROM o)
    SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS types FROM g GROUP BY user_id, visit""")
def session_sets(spark, sf_dir):
    events = stream.with_event_time(views.table(spark, sf_dir, "events"))
    found = stream.session_sets(events, key="user_id", element="event_type", time_col="ts", gap="12 hours")
    return found.select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), F.array_join("elements", ",").alias("types"))
