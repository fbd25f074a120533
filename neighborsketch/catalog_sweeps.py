"""Queries over sweeps of all methods, difficulty bands and growth."""

from __future__ import annotations

from pyspark.sql import functions as F

from .catalog_experiments import _EXP, _N, _STATS, MEASURED_V, TWINS_P, _close_sql, _kernel, _stats_sql, _tops_sql, _union
from .functions import theory
from .functions.params import SketchParams
from .operators import cache, decode, exact, grid, layout, measures, stability
from .operators.measures import fixed
from .oracles import blocks as sql
from .plans import workloads
from .sources import store, views

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = sql.stable(oracle)
        return f

    return add


# sweeps ----------------------------------------------------------------------------------

SMALL_GRID = [SketchParams(d, w, r, hashes=k, buckets=b) for d, w, r, k, b in ((2, 50, 2, 1, 100), (3, 60, 4, 1, 100), (3, 60, 4, 2, 100), (4, 100, 4, 1, 100), (2, 100, 2, 1, 1000), (3, 200, 4, 1, 1000))]
SMALL_M, SMALL_F = (5, 20, 50), (0.1, 0.5, 0.9)
#: The published ranges, one parameter at a time from a base point: rows 2-5, columns
#: 100-1000, repetitions 2-8, buckets 100-1000, one and two hashes; projections 5-500.
BASE = SketchParams(3, 200, 4, buckets=1000)
RANGES = {"rows": (2, 3, 4, 5), "cols": (100, 200, 500, 1000), "reps": (2, 4, 8), "buckets": (100, 300, 1000), "hashes": (1, 2)}
PUBLISHED_M, PUBLISHED_F = (5, 10, 20, 50, 100, 200, 500), (0.1, 0.3, 0.5, 0.7, 0.9)


def published_grid() -> list[SketchParams]:
    made = [SketchParams(**(BASE.as_dict() | {name: value})) for name, values in RANGES.items() for value in values]
    return list(dict.fromkeys(made))


_RANK = f"(id % {sql.P} * {sql.mult(chr(39) + 'ra:42' + chr(39))} + {sql.off(chr(39) + 'rb:42' + chr(39))}) % {sql.P}"


def _recalled(tops: str = "tops") -> str:
    return " UNION ALL ".join(f"SELECT '{num / den:.1f}' AS threshold, queries, round(recall, 9) AS recall FROM ({sql.recall(20, num, den, tops)})" for num, den in workloads.THRESHOLDS)


def points_sql(view: str, grid_: list[SketchParams], projections: tuple[int, ...], fractions: tuple[float, ...]) -> str:
    """CTEs up to points: method, setting, bytes, ratio, threshold, queries, recall."""
    ctes, parts = [], []
    for i, p in enumerate(grid_):
        ctes.append(f"""s{i} AS MATERIALIZED (SELECT * FROM (WITH {_tops_sql(view, p)}, size_ AS (SELECT count(*) AS nz FROM sketch)
            SELECT {2 * p.counters}::BIGINT AS dense, (nz * 6 + {4 * p.rows})::BIGINT AS sparse, r.* FROM size_, ({_recalled()}) r))""")
        parts += [f"SELECT 'sketch_{kind}' AS method, '{workloads.setting_of(p)}' AS setting, {kind} AS bytes, threshold, queries, recall FROM s{i}" for kind in ("dense", "sparse")]
    if projections:
        sums = ", ".join(f"-sum((a.s - b.s) * (a.s - b.s)) FILTER (WHERE a.j < {m}) AS far{m}" for m in projections)
        ctes.append(f"""pitems AS MATERIALIZED ({sql.items(view)}), pm AS (SELECT j, {sql.mult("'pa:42:' || j")} AS a, {sql.off("'pb:42:' || j")} AS b FROM range({max(projections)}) t(j)),
            ps AS MATERIALIZED (SELECT id, j, sum(CASE ((element * a + b) % {sql.P}) % 6 WHEN 0 THEN 1 WHEN 1 THEN -1 ELSE 0 END) AS s FROM pitems, pm GROUP BY id, j),
            far AS MATERIALIZED (SELECT a.id AS qid, b.id, {sums} FROM ps a JOIN ps b ON a.j = b.j AND a.id <> b.id WHERE a.id IN (SELECT qid FROM close) GROUP BY a.id, b.id)""")
        for m in projections:
            ctes.append(f"ptops{m} AS MATERIALIZED ({sql.top(20, 'far', f'far{m}')})")
            parts.append(f"SELECT 'projections' AS method, 'm={m}' AS setting, (4 * {m} * n)::BIGINT AS bytes, threshold, queries, recall FROM base, ({_recalled(f'ptops{m}')})")
    for i, f in enumerate(fractions):
        ctes.append(f"""chosen{i} AS MATERIALIZED (SELECT id, n FROM sizes ORDER BY {_RANK}, id LIMIT (SELECT greatest(1, CAST(floor({f}::DOUBLE * count(*) + 0.5::DOUBLE) AS BIGINT)) FROM sizes)),
            far_{i} AS (SELECT q.qid, c.id, 2 * coalesce(s.inter, 0) - a.n - c.n AS score FROM close q JOIN sizes a ON a.id = q.qid JOIN chosen{i} c ON c.id <> q.qid LEFT JOIN sims s ON s.qid = q.qid AND s.id = c.id),
            ctops{i} AS MATERIALIZED ({sql.top(20, f'far_{i}')}), cbytes{i} AS (SELECT (sum(n) * 4 + (count(*) + 1) * 4)::BIGINT AS bytes FROM chosen{i})""")
        parts.append(f"SELECT 'sampling' AS method, 'fraction={f}' AS setting, bytes, threshold, queries, recall FROM cbytes{i}, ({_recalled(f'ctops{i}')})")
    return f"""{_close_sql(view)}, base AS MATERIALIZED (SELECT count(DISTINCT id) AS n, (count(*) * 4 + (count(DISTINCT id) + 1) * 4)::BIGINT AS full_bytes FROM v), {', '.join(ctes)},
    points AS MATERIALIZED (SELECT method, setting, bytes, round(bytes / full_bytes, 9) AS ratio, threshold, queries, recall FROM base, ({' UNION ALL '.join(parts)}))"""


def _points(spark, sf_dir, view, grid_, projections, fractions):
    return workloads.sweep(views.items(spark, sf_dir, view), grid=grid_, projections=projections, fractions=fractions).withColumn("ratio", fixed("ratio", 9))


_KNOWN: dict[tuple[str, str, str], list] = {}


def _small(spark, sf_dir, view="basket_twins"):
    """The points of the small grid, a few dozen rows, found once a session and folder."""
    key = (spark.sparkContext.applicationId, sf_dir, view)
    if key not in _KNOWN:
        _KNOWN[key] = _points(spark, sf_dir, view, SMALL_GRID, SMALL_M, SMALL_F).collect()
    return spark.createDataFrame(_KNOWN[key], workloads.POINT)


_SMALL_SQL = {view: f"WITH {points_sql(view, SMALL_GRID, SMALL_M, SMALL_F)}" for view in ("basket_twins", "doc_shingles")}
_LEAST = "SELECT method, threshold, min(CASE WHEN recall >= 0.8::DOUBLE THEN bytes END) AS bytes FROM points GROUP BY method, threshold"


@query("sweep_published", f"WITH {points_sql('basket_twins', published_grid(), PUBLISHED_M, PUBLISHED_F)} SELECT * FROM points")
def sweep_published(spark, sf_dir):
    return _points(spark, sf_dir, "basket_twins", published_grid(), PUBLISHED_M, PUBLISHED_F)


@query("pareto_points", f"""{_SMALL_SQL['basket_twins']} SELECT method, setting, bytes, ratio, threshold, queries, recall FROM (
    SELECT *, max(recall) OVER (PARTITION BY method, threshold ORDER BY bytes, recall DESC, setting ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS best FROM points) WHERE best IS NULL OR recall > best""")
def pareto_points(spark, sf_dir):
    return workloads.frontier(_small(spark, sf_dir))


@query("bytes_at_recall", f"{_SMALL_SQL['basket_twins']} {_LEAST}")
def bytes_at_recall(spark, sf_dir):
    return workloads.headline(_small(spark, sf_dir))


@query("bytes_at_recall_docs", f"{_SMALL_SQL['doc_shingles']} {_LEAST}")
def bytes_at_recall_docs(spark, sf_dir):
    return workloads.headline(_small(spark, sf_dir, "doc_shingles"))


@query("advantage_factors", f"""{_SMALL_SQL['basket_twins']}, least_ AS ({_LEAST})
    SELECT b.method AS against, b.threshold, round(b.bytes / a.bytes, 6) AS factor FROM least_ a JOIN least_ b ON a.threshold = b.threshold WHERE a.method = 'sketch_sparse' AND b.method <> 'sketch_sparse'""")
def advantage_factors(spark, sf_dir):
    """Bytes that each other method needs for the target recall, by those of the sparse sketch."""
    return measures.advantages(_small(spark, sf_dir), 0.8, "sketch_sparse").withColumn("factor", fixed("factor"))


# difficulty ------------------------------------------------------------------------------

_FOUND = f"""{_EXP}, {_tops_sql('basket_twins', TWINS_P)}, near AS (SELECT s.qid, s.gap, e.b, (t.id IS NOT NULL)::INTEGER AS hit FROM stats s JOIN e ON e.qid = s.qid JOIN k ON k.qid = s.qid AND k.rank = 1 LEFT JOIN tops t ON t.qid = k.qid AND t.id = k.id)"""


@query("recall_by_gap", f"{_FOUND} SELECT least(floor(gap * 10), 9)::INTEGER AS band, count(*)::BIGINT AS queries, round(avg(hit), 6) AS recall FROM near GROUP BY band")
def recall_by_gap(spark, sf_dir):
    """How often the nearest neighbour is reported, by tenths of the gap to the next."""
    return _found_by(spark, sf_dir, F.least(F.floor(F.col("gap") * 10), F.lit(9)).cast("int"))


@query("recall_by_exponent", f"{_FOUND} SELECT least(floor(b), 9)::INTEGER AS band, count(*)::BIGINT AS queries, round(avg(hit), 6) AS recall FROM near GROUP BY band")
def recall_by_exponent(spark, sf_dir):
    """The same by the memory exponent (null: the query has no finite one)."""
    return _found_by(spark, sf_dir, F.least(F.floor("b"), F.lit(9)).cast("int"))


def _found_by(spark, sf_dir, band):
    items = views.items(spark, sf_dir, "basket_twins")
    queries, _ = workloads.close_queries(items, 8, 10)
    shared = exact.overlaps(items, queries)
    stats = stability.with_exponent(stability.stability_stats(stability.kernel(shared), MEASURED_V, 0), 2)
    nearest = exact.exact_top(shared, 1).select("qid", "id")
    found = workloads.sketch_top(items, queries, TWINS_P).select("qid", "id", F.lit(1).alias("hit"))
    met = stats.join(nearest, "qid").join(found, ["qid", "id"], "left")
    return met.groupBy(band.alias("band")).agg(F.count(F.lit(1)).alias("queries"), fixed(F.avg(F.coalesce("hit", F.lit(0))), 6).alias("recall"))


_DOC_STATS = _stats_sql("doc_shingles", "inter * 10 >= uni * 8")
_STATS_COLUMNS = ("p_v", "p_next", "gap", "tail", "norm1", "norm_tilde")


@query("stability_docs", f"{_DOC_STATS} SELECT qid, {', '.join(f'round({c}, 6) AS {c}' for c in _STATS_COLUMNS)}, status, coalesce(hashes, 0) AS hashes, {_N} AS n_items FROM hashed")
def stability_docs(spark, sf_dir):
    items = store.stored(views.sets(spark, sf_dir, "doc_shingles"), "doc-sets")
    queries, _ = workloads.close_queries(items, 8, 10)
    stats = stability.with_hashes(stability.scanned_stats(items, queries, MEASURED_V, items.count()))
    return stats.select("qid", *[fixed(c).alias(c) for c in _STATS_COLUMNS], "status", F.coalesce("hashes", F.lit(0)).alias("hashes"), "n_items")


@query("stability_embeddings", """WITH coords AS MATERIALIZED (SELECT vec_id AS id, generate_subscripts(embedding, 1) AS c, CAST(round(CAST(unnest(embedding) AS DOUBLE) * 1000000) AS BIGINT) AS x FROM embeddings),
    norms AS (SELECT id, sqrt(sum(x * x)::DOUBLE) AS l FROM coords GROUP BY id),
    dots AS (SELECT a.id AS qid, b.id, sum(a.x * b.x)::DOUBLE AS d FROM coords a JOIN coords b ON a.c = b.c AND a.id <> b.id WHERE a.id % 50 = 0 GROUP BY a.id, b.id),
    k AS (SELECT qid, d.id, 1 - acos(greatest(-1::DOUBLE, least(1::DOUBLE, d / (m.l * n.l)))) / pi() AS p, row_number() OVER (PARTITION BY qid ORDER BY d / (m.l * n.l) DESC, d.id) AS rank FROM dots d JOIN norms m ON m.id = qid JOIN norms n ON n.id = d.id)
    SELECT qid, round(max(p) FILTER (WHERE rank = 1), 6) AS p_v, round(max(p) FILTER (WHERE rank = 2), 6) AS p_next, round(sum(sqrt(p)), 6) AS norm_tilde FROM k GROUP BY qid""")
def stability_embeddings(spark, sf_dir):
    """Signed projections on the vectors: every pair collides about as often as not, so
    the kernel is flat. Queries are the vectors whose id is divisible by 50."""
    rounded = views.rounded_vectors(spark, sf_dir)
    length = F.sqrt(F.aggregate("elements", F.lit(0).cast("long"), lambda s, x: s + x * x).cast("double"))
    norms = rounded.select("id", length.alias("l"))
    dot = F.aggregate(F.zip_with("q", "elements", lambda a, b: a * b), F.lit(0).cast("long"), lambda s, x: s + x)
    met = exact.meet_blocks(rounded, rounded.where("id % 50 = 0")).where("id != qid").select("qid", "id", dot.cast("double").alias("d"))
    cosine = F.greatest(F.lit(-1.0), F.least(F.lit(1.0), F.col("d") / (F.col("m") * F.col("l"))))
    kernel = met.join(norms, "id").join(norms.select(F.col("id").alias("qid"), F.col("l").alias("m")), "qid").select("qid", "id", (1 - F.acos(cosine) / F.pi()).alias("p"))
    stats = stability.stability_stats(kernel, MEASURED_V, 0)
    return stats.select("qid", *[fixed(c).alias(c) for c in ("p_v", "p_next", "norm_tilde")])


@query("sketch_bits", f"{_EXP} SELECT qid, round(b * ln({_N}) + 3 * ln(ln({_N})), 6) AS log_bits, round((b + 1) * ln({_N}) + 3 * ln(ln({_N})), 6) AS log_time FROM e WHERE b IS NOT NULL")
def sketch_bits(spark, sf_dir):
    """Natural logarithms of the promised bits and steps of each query."""
    kernel, n = _kernel(spark, sf_dir)
    stats = stability.with_exponent(stability.stability_stats(kernel, MEASURED_V, n), 2).where("b is not null")
    log_n = F.log(F.col("n_items").cast("double"))
    return stats.select("qid", fixed(F.col("b") * log_n + 3 * F.log(log_n)).alias("log_bits"), fixed((F.col("b") + 1) * log_n + 3 * F.log(log_n)).alias("log_time"))


@query("direct_bits", f"""{_STATS}, u AS (SELECT qid, norm1, norm_tilde, ln({_N} / 0.01::DOUBLE) AS deep FROM stats)
    SELECT qid, round(ln(norm_tilde * norm_tilde * norm1 / 0.125::DOUBLE * ln(greatest(norm1 / (0.5::DOUBLE * 0.01::DOUBLE) * deep, exp(1))) * deep * 100 * log2({_N})), 6) AS log_bits FROM u""")
def direct_bits(spark, sf_dir):
    """The bits that bounded norms promise (error 0.5, 100 buckets), as logarithms."""
    kernel, n = _kernel(spark, sf_dir)
    stats = stability.stability_stats(kernel, MEASURED_V, n)
    arrays = theory.arrays_needed_column(F.col("norm1"), F.col("norm_tilde"), F.lit(0.5), 0.01, F.col("n_items").cast("double"))
    return stats.select("qid", fixed(F.log(arrays * theory.array_bits(100, 1, n, 100))).alias("log_bits"))


# growth, caches, speed -------------------------------------------------------------------

_PARTS = (1, 2, 4, 8)


@query("sketch_growth", _union([f"""WITH {sql.sketch('doc_shingles', 2, w, 2, 1, 1000, where=f'{_RANK} % 8 < {t}')}, s AS (SELECT count(DISTINCT id) AS n, count(*) AS nnz FROM items)
    SELECT '{kind}' AS grid, {t}::INTEGER AS eighths, n AS items, (nnz * 4 + (n + 1) * 4)::BIGINT AS data_bytes, ((SELECT count(*) FROM sketch) * 6 + 8)::BIGINT AS sparse_bytes, {2 * 2 * w * 2 * 1000}::BIGINT AS dense_bytes FROM s"""
    for kind, t, w in [("fixed", t, 100) for t in _PARTS] + [("load", t, 25 * t) for t in _PARTS]]))
def sketch_growth(spark, sf_dir):
    """Bytes of data and sketch over growing shares of the documents: with a fixed grid,
    whose counters only fill up, and at a constant load of its columns."""
    from .operators.baselines import sample_rank

    docs, out = views.items(spark, sf_dir, "doc_shingles"), None
    for kind, t, w in [("fixed", t, 100) for t in _PARTS] + [("load", t, 25 * t) for t in _PARTS]:
        own = docs.where(sample_rank(F.col("id"), 42) % 8 < t)
        sketch = grid.build_sketch(own, SketchParams(2, w, 2, buckets=1000), engine="arrow")
        one = own.agg(F.lit(kind).alias("grid"), F.lit(t).alias("eighths"), F.count(F.lit(1)).alias("items"))
        for bytes_, name in ((measures.uncompressed_bytes(own), "data_bytes"), (layout.sketch_bytes(sketch, "sparse"), "sparse_bytes"), (layout.sketch_bytes(sketch, "dense"), "dense_bytes")):
            one = one.crossJoin(bytes_.withColumnRenamed("bytes", name))  # one row each
        out = one if out is None else out.unionByName(one)
    return out


@query("cache_hits_turns", f"""WITH {sql.sketch('turn_shingles', 1, 1, 5, 1, 1000)}, {sql.asked('items', 1, 5, 1000)}, {sql.readings()}, {sql.measured(5)} SELECT qid, y AS est, y >= 2 AS hit FROM y""")
def cache_hits_turns(spark, sf_dir):
    """Whether a conversation has a turn that others come close to (its own counts one)."""
    turns = views.items(spark, sf_dir, "turn_shingles")
    return cache.cache_hits(cache.kde_sketch(turns, SketchParams(1, 1, 5, buckets=1000), engine="arrow"), turns, 2.0, groups=5)


@query("throughput")
def throughput(spark, sf_dir):
    """Vectors a second of building and of query hashing with reading, as measured now."""
    docs = views.items(spark, sf_dir, "doc_shingles").cache()
    n, p = docs.count(), SketchParams(3, 60, 4, buckets=1000)
    sketch = grid.build_sketch(docs, p, engine="arrow")
    built = measures.timed(sketch.cells)
    asked = measures.timed(decode.measure_arrow(sketch, docs))
    docs.unpersist()
    return spark.createDataFrame([("build", n, built, n / built), ("query", n, asked, n / asked)], "phase string, vectors long, seconds double, per_second double")
