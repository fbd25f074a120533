r"""Secret scans with corpus-wide ownership frequency, in built-in expressions.

Base kinds, leftmost and non-overlapping per kind, failing matches dropped after
matching (so that they still consume their text): ``assign``, ``access`` and
``hex`` as the fixed patterns below say. Candidate kinds add what has the shape of
a credential without standing in an assignment: known key prefixes, private key
blocks, signed tokens, and long mixed strings of high entropy.

Spans come from two built-in passes: the text between matches (``split``) and the
matches (``regexp_extract_all``) alternate, so their running lengths are the
offsets. Texts without any hint of a kind skip its passes.

Ownership: the candidates' hashes are counted over the corpus by distinct
repositories and distinct owners. A value that at least ``EXAMPLE_OWNERS`` owners
have is a widely copied example, and so is one in at least ``EXAMPLE_REPOS``
repositories, whosever they are: a key that is live is seldom pasted that widely. The
other values belong to few and are live-looking. Base spans stay whatever their
status; candidate spans join ``spans`` only if they are live-looking. Without finer
columns a document's source stands for its owner and the document for its repository.
A value that very many documents hold meets its counts by a broadcast of the most
frequent ones, at most ``BROADCAST_VALUES``.

Edge cases: null texts count as empty; null owners count as one owner, null
repositories as none; repeated rows get equal results; overlapping spans of different kinds all stay; an empty
table gives an empty result; texts are scanned whole; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import join_hot, stored, table, whole

EXAMPLE_OWNERS, EXAMPLE_REPOS = 3, 20
BROADCAST_VALUES = 100_000
BLOCK = 64  # matches of a text whose offsets add up at a time
LEAST_ENTROPY = 3.5

# The base patterns (Java and RE2 read them alike), the least length
# of what counts, and a literal hint that every match contains in lower case.
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
BASE = (("assign", ASSIGN, 1, 6), ("access", ACCESS, 0, 20), ("hex", HEX, 0, 24))
# Candidate kinds: name and pattern. The word boundaries keep them whole.
CANDIDATES = (
    ("prefixed", r"\b(?:gh[pousr]_[A-Za-z0-9]{30,}|sk_(?:live|test)_[A-Za-z0-9]{16,}|xox[abprs]-[A-Za-z0-9-]{10,}|AIza[A-Za-z0-9_-]{35}|glpat-[A-Za-z0-9_-]{20,})"),
    ("signed", r"\beyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}"),
    ("block", r"-----BEGIN [A-Z ]*PRIVATE KEY-----[A-Za-z0-9+/=\s]+-----END [A-Z ]*PRIVATE KEY-----"),
    ("mixed", r"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/_=-]*[0-9])(?=[^A-Z\s]*[A-Z])(?=[^a-z\s]*[a-z])[A-Za-z0-9+/_=-]{24,}"),
)
# Hints: a text without one has no match of the kind (a plain scan, no pattern with groups).
HINTS = {
    "assign": r"(?i)password|passwd|secret|token|api_?key", "access": r"AKIA[A-Z0-9]{16}", "hex": r"[0-9a-f]{24}",
    "prefixed": r"gh[pousr]_|sk_live_|sk_test_|xox[abprs]-|AIza|glpat-", "signed": r"eyJ", "block": r"PRIVATE KEY-----", "mixed": r"[A-Za-z0-9+/_=-]{24}",
}
_SPAN = "array<struct<start:int,rank:int,kind:string,end:int,value:string>>"


def _spans(text: Column, kind: str, pattern: str, group: int, least: int, rank: int) -> Column:
    """Spans of a kind, in code points."""
    gaps, found = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    values = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else found
    parts = F.zip_with(F.transform(F.slice(gaps, 1, F.size(found)), F.length), F.zip_with(found, values, lambda m, v: F.struct(F.length(m).alias("n"), v.alias("v"))), lambda g, m: F.struct(g.alias("gap"), m["n"].alias("n"), m["v"].alias("v")))
    state = F.struct(F.lit(0).alias("at"), F.array().cast(_SPAN).alias("spans"))
    n_blocks = lambda ps: F.ceil(F.size(ps) / BLOCK).cast("int")

    def step(acc: Column, p: Column) -> Column:
        start = acc["at"] + p["gap"]
        span = F.struct(start.alias("start"), F.lit(rank).alias("rank"), F.lit(kind).alias("kind"), (start + p["n"]).alias("end"), p["v"].alias("value"))
        return F.struct((start + p["n"]).alias("at"), F.when(F.length(p["v"]) >= least, F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"]).alias("spans"))

    def shifted(bs: Column) -> Column:
        """The blocks' spans, moved by what the blocks before them cover."""
        ahead = F.aggregate(bs, F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("starts")), lambda acc, b: F.struct((acc["at"] + b["at"]).alias("at"), F.concat(acc["starts"], F.array(acc["at"])).alias("starts")))["starts"]
        moved = lambda s, by: F.struct((s["start"] + by).alias("start"), s["rank"].alias("rank"), s["kind"].alias("kind"), (s["end"] + by).alias("end"), s["value"].alias("value"))
        return F.flatten(F.zip_with(bs, ahead, lambda b, by: F.transform(b["spans"], lambda s: moved(s, by))))

    blocks = lambda ps: F.transform(F.sequence(F.lit(0), n_blocks(ps) - 1), lambda b: F.aggregate(F.slice(ps, b * BLOCK + 1, BLOCK), state, step))
    # arrays of one element name what is used more than once
    spans = F.flatten(F.transform(F.array(parts), lambda ps: F.when(F.size(ps) > 0, F.flatten(F.transform(F.array(blocks(ps)), shifted))).otherwise(F.array().cast(_SPAN))))
    return F.when(text.rlike(HINTS[kind]), spans).otherwise(F.array().cast(_SPAN))


def entropy(value: Column) -> Column:
    """Bits a character, from the characters' shares."""
    chars = F.split(value, "")
    n = F.length(value).cast("double")
    return -F.aggregate(
        F.transform(F.array_distinct(chars), lambda c: F.size(F.filter(chars, lambda x: x == c)) / n), F.lit(0.0), lambda a, p: a + p * F.log2(p))


def scan(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", repo_col: str = "doc_id", owner_col: str = "source") -> DataFrame:
    """One row per document: its base spans and its candidate spans."""
    text = whole(text_col)
    base = [_spans(F.col("text"), k, p, g, n, i) for i, (k, p, g, n) in enumerate(BASE)]
    more = [_spans(F.col("text"), k, p, 0, 1, len(BASE) + i) for i, (k, p) in enumerate(CANDIDATES)]
    return docs.select(
        F.col(id_col).alias("doc_id"), F.col(repo_col).cast("string").alias("repo"), F.coalesce(F.col(owner_col).cast("string"), F.lit("")).alias("owner"), text.alias("text"),
    ).select(
        "doc_id", "repo", "owner", F.xxhash64("text").alias("row_key"), F.sort_array(F.concat(*base)).alias("base"), F.sort_array(F.concat(*more)).alias("more"))


def ownership(found: DataFrame) -> DataFrame:
    """Each candidate value's hash with its numbers of repositories and owners."""
    values = found.select("repo", "owner", F.explode(F.concat("base", "more")).alias("s")).select(F.xxhash64(F.col("s.value")).alias("value_hash"), "repo", "owner")
    return (
        values.groupBy("value_hash", "owner", "repo").agg(F.lit(1).alias("one"))
        .groupBy("value_hash", "owner").agg(F.count("repo").alias("repos"))
        .groupBy("value_hash").agg(F.sum("repos").alias("n_repos"), F.count(F.lit(1)).alias("n_owners"))
    )


def report(docs: DataFrame, **columns: str) -> DataFrame:
    """``doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_live, n_examples,
    most_owners, most_repos`` (of the document's values)."""
    found = stored(scan(docs, **columns), "secret-spans")
    listed = found.where("size(base) + size(more) > 0")
    each = listed.select("doc_id", "row_key", F.explode(F.concat("base", "more")).alias("s")).select("doc_id", "row_key", "s", F.xxhash64(F.col("s.value")).alias("value_hash"))
    status = join_hot(each, stored(ownership(listed), "secret-owners"), "value_hash", "n_repos", BROADCAST_VALUES)
    live = (F.col("n_owners") < EXAMPLE_OWNERS) & (F.col("n_repos") < EXAMPLE_REPOS)
    added = live & (F.col("s.rank") >= len(BASE)) & ((F.col("s.kind") != "mixed") | (entropy(F.col("s.value")) >= LEAST_ENTROPY))
    at = F.struct("s.start", "s.rank", "s.kind", "s.end")
    marks = status.groupBy("doc_id", "row_key").agg(
        F.collect_set(F.when(added, at)).alias("added"), F.collect_set(F.when(live, at)).alias("live"), F.collect_set(F.when(~live, at)).alias("examples"),
        F.max("n_owners").alias("most_owners"), F.max("n_repos").alias("most_repos"))
    marks = marks.withColumnsRenamed({"doc_id": "mark_id", "row_key": "mark_key"})
    both = found.join(marks, F.col("doc_id").eqNullSafe(F.col("mark_id")) & (F.col("row_key") == F.col("mark_key")), "left")
    line = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    plain = F.transform("base", lambda s: F.struct(s["start"].alias("start"), s["rank"].alias("rank"), s["kind"].alias("kind"), s["end"].alias("end")))
    count = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    size = lambda c: F.coalesce(F.size(c), F.lit(0)).cast("long")
    return both.select(
        "doc_id", count("assign"), count("access"), count("hex"), F.sha2(line(plain), 256).alias("base_sha256"),
        line(F.when(F.size("added") > 0, F.sort_array(F.concat(plain, "added"))).otherwise(plain)).alias("spans"), size("live").alias("n_live"), size("examples").alias("n_examples"),
        *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("most_owners", "most_repos")],
    )


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return report(table(spark, sf_dir, "documents"))
