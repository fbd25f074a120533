r"""N-gram Jaccard join with signature trees.

A text's set holds its distinct runs of ``k`` words (64-bit hashes; words are runs
of other than ``[\x20\x09-\x0D]``, with A-Z in lower case; a shorter text is one
run). Two texts link when their Jaccard similarity is at least ``num / den``; the
result is each text's connected component. No link between different sets is lost:

1. *Classes.* Equal sets are one class, found by a 128-bit set hash in salted
   steps; the class's smallest id stands for it from here on.
2. *Neighbourhoods.* Linked sets of at most ``U`` shingles differ in at most ``d =
   floor((1 - t) / (1 + t) 2 U)`` of them. So if shingles are dealt by hash into ``m >
   d`` parts, linked sets agree exactly in ``m - d`` parts at least, and a hash of
   part, content and size class is a key that they have in common. Sizes are cut
   into classes of ratio ``1 / t``; a text makes keys for its own class and the next,
   so texts of neighbouring classes meet. Shingles that repeat within chunks of the
   corpus (common phrases and passages) are left out of the parts, which can only
   take differences away, and parts with few shingles make no key. A text whose
   number of such small parts would reach ``m - d`` makes the keys of all its parts,
   with all its shingles, as well; two such texts meet there. Texts with a common
   key are tied to the smallest id among them, first within a chunk and then
   globally: one row per chunk and key at most, however hot the key. The connected
   parts of these ties are the neighbourhoods.
3. *Signature trees.* A neighbourhood is dealt into chunks of about ``CHUNK``
   texts. Each chunk gets a tree whose nodes hold the OR (and the AND) of their
   texts' shingle bitmaps and the range of their sizes; a dual traversal drops a
   pair of nodes when the largest overlap that bitmaps and sizes allow is too
   small, or when all their texts are already connected; pairs of leaves that
   are left are compared exactly.
4. *Large neighbourhoods.* One text of each component found goes on to the next
   round of chunks until one chunk is left. Where several components remain, all
   texts outside the largest are traversed against all texts of the neighbourhood,
   chunk by chunk, so every pair is compared or known to be connected. A group of
   near copies costs a few rounds of linear size. The copies of texts that these
   pairs of chunks need grow with the square of the neighbourhood, so they go out in
   rounds of at most ``ROUND_SHARE`` of all texts' shingles, one after the other.

Edge cases: null, empty and blank texts have empty sets and link with nothing;
null ids link with nothing and have a null component; ids should be unique: rows
that repeat an id are one node, linked by the texts of either; equal similarity
to the threshold links; an empty table gives an empty result; texts are read
whole; other columns, whatever their names, are not read by :func:`components`
and come back untouched from :func:`keep_one`.
"""

from __future__ import annotations

import math
from bisect import bisect_right
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from .byte_bpe import _rows
from ..sources.store import settle
from .common import drop_stored, free_name, row_salt, stored, table

WORDS, NUM, DEN = 3, 9, 10
CHUNK = 512
BITS = 1024
LEAF, FANOUT = 32, 4
MATRIX_ENTRIES = 16_000_000
SALTS = 32
LOCAL_REPEATS, REPEATS, COMMON_SHINGLES = 3, 8, 200_000
CHUNK_SHINGLES = 1_500_000
BROADCAST_IDS = 200_000
ROUND_SHARE, ROUND_LEAST = 0.75, 20_000_000

_MASK = (1 << 64) - 1
_A, _B, _C = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _A
    x = (x ^ (x >> np.uint64(27))) * _B
    return x ^ (x >> np.uint64(31))


def _byte_table() -> tuple[np.ndarray, np.ndarray]:
    """A random word for each byte, A-Z as a-z; and which bytes part words."""
    low = np.arange(256)
    low[65:91] += 32
    parts = np.zeros(256, bool)
    parts[[0x20, *range(0x09, 0x0E)]] = True
    return mix((low.astype(np.uint64) + np.uint64(1)) * _C), parts


_BYTE, _PARTS = _byte_table()
_POWERS = np.ones(1, np.uint64)


def _powers(n: int) -> np.ndarray:
    global _POWERS
    if len(_POWERS) < n:
        size = max(n, 2 * len(_POWERS), 256)
        _POWERS = np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(size - 1, 0xD1342543DE82EF95, np.uint64)]))
    return _POWERS


def word_hashes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """All words' hashes, and each text's number of words."""
    raw = [t.encode("utf-8", "surrogatepass") + b" " for t in texts]
    data = np.frombuffer(b"".join(raw), np.uint8)
    part = _PARTS[data]
    starts = np.flatnonzero(~part & np.concatenate([[True], part[:-1]]))
    ends = np.cumsum([len(r) for r in raw])
    counts = np.diff(np.searchsorted(starts, np.concatenate([[0], ends])))
    if not len(starts):
        return np.zeros(0, np.uint64), counts
    inside = np.flatnonzero(~part)
    lengths = np.add.reduceat((~part).astype(np.int64), starts)
    within = inside - np.repeat(starts, lengths)
    weighted = _BYTE[data[inside]] * _powers(int(lengths.max()) + 1)[within]
    first = np.cumsum(lengths) - lengths
    return mix(np.add.reduceat(weighted, first) + lengths.astype(np.uint64)), counts


def shingle_sets(texts: list[str], k: int) -> list[np.ndarray]:
    """Each text's set as a sorted array of distinct hashes."""
    words, counts = word_hashes(texts)
    chain = words.copy()
    for j in range(1, k):
        chain = mix(words[: max(0, len(words) - j)] + _C * chain[1:]) if len(words) > j else np.zeros(0, np.uint64)
    out, at = [], 0
    for n in counts.tolist():
        if n == 0:
            out.append(np.zeros(0, np.uint64))
        elif n >= k:
            out.append(np.unique(chain[at : at + n - k + 1]))
        else:
            value = words[at + n - 1 : at + n]
            for j in range(n - 2, -1, -1):
                value = mix(words[at + j : at + j + 1] + _C * value)
            out.append(mix(value + np.uint64(n)))
        at += n
    return out


def set_hash(own: np.ndarray) -> tuple[int, int]:
    if not len(own):
        return 0, 0
    a, b = np.add.reduce(mix(own + _A)), np.bitwise_xor.reduce(mix(own + _B))
    return int(a.astype(np.int64)), int(b.astype(np.int64))


class Parts:
    """How sets are dealt into parts, by size class."""

    def __init__(self, num: int, den: int):
        self.num, self.den = num, den
        self.bounds = [1]
        self.known: dict[int, tuple[int, int, int]] = {}

    def size_class(self, n: int) -> int:
        """Sets that link are in the same class or in neighbouring ones."""
        while self.bounds[-1] <= n:
            self.bounds.append(self.bounds[-1] * self.den // self.num + 1)
        return bisect_right(self.bounds, n) - 1

    def deal(self, tag: int) -> tuple[int, int, int]:
        """For sets of the classes tag - 1 and tag: the most differences d, the number
        of parts m, and the least number of shingles of a part that makes a key."""
        if tag not in self.known:
            while len(self.bounds) < tag + 2:
                self.bounds.append(self.bounds[-1] * self.den // self.num + 1)
            largest, smallest = self.bounds[tag + 1] - 1, self.bounds[max(0, tag - 1)]
            d = (self.den - self.num) * 2 * largest // (self.den + self.num)
            self.known[tag] = self._parts(d, smallest)
        return self.known[tag]

    @staticmethod
    def _parts(d: int, smallest: int) -> tuple[int, int, int]:
        for least in (3, 2, 1):
            m = d + 2
            while m <= smallest:
                mean = smallest / m
                small = m * sum(math.exp(-mean) * mean**i / math.factorial(i) for i in range(least))
                if small + 2 * math.sqrt(small) + 1 <= m - d - 1:
                    return d, m, least
                m += 1 + m // 50
        return d, d + 1, 1

    def keys(self, own: np.ndarray, common: np.ndarray) -> list[np.ndarray]:
        """The keys of a set. common: which of its shingles are common ones."""
        out = []
        i = self.size_class(len(own))
        rare = own[~common] if common.any() else own
        for tag in (i, i + 1):
            d, m, least = self.deal(tag)
            if d == 0:
                continue  # only equal sets link, and these are one class
            size, sums = _part_sums(rare, m)
            big = np.flatnonzero(size >= least)
            base = np.uint64(2 * tag * int(_B) & _MASK)
            out.append(mix(sums[big] + (big.astype(np.uint64) + np.uint64(1)) * _C + base))
            if m - len(big) >= m - d:
                size, sums = _part_sums(own, m)
                out.append(mix(sums + np.arange(1, m + 1, dtype=np.uint64) * _C + base + _B))
        return out


def _part_sums(own: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """Each part's number of shingles and a hash of its content."""
    part = (mix(own + _C) % np.uint64(m)).astype(np.int64)
    value = mix(own ^ _C)
    low = np.bincount(part, (value & np.uint64(0xFFFFFFFF)).astype(np.float64), m)  # exact: below 2**53
    high = np.bincount(part, (value >> np.uint64(32)).astype(np.float64), m)
    return np.bincount(part, minlength=m), mix(low.astype(np.uint64)) + _A * high.astype(np.uint64)


def links(a: np.ndarray, b: np.ndarray, num: int, den: int) -> bool:
    if num * max(len(a), len(b)) > den * min(len(a), len(b)):
        return False
    inter = len(a) + len(b) - len(np.union1d(a, b))
    return den * inter >= num * (len(a) + len(b) - inter)


class SignatureTree:
    """Texts in an order that keeps like ones together. A leaf is a range of LEAF
    texts and an inner node one of FANOUT nodes; each has the OR and the AND of its
    texts' bitmaps and the range of their sizes."""

    def __init__(self, sets: list[np.ndarray]):
        self.n = len(sets)
        bits = np.zeros((self.n, BITS), bool)
        for i, s in enumerate(sets):
            bits[i, (s % np.uint64(BITS)).astype(np.int64)] = True
        sizes = np.array([len(s) for s in sets])
        level = (np.packbits(bits, 1), np.packbits(bits, 1), sizes, sizes)
        self.levels = []
        width = LEAF
        while True:
            union, common, low, high = level
            at = np.arange(0, len(union), width)
            level = (np.bitwise_or.reduceat(union, at, 0), np.bitwise_and.reduceat(common, at, 0), np.minimum.reduceat(low, at), np.maximum.reduceat(high, at))
            self.levels.append(level)
            width = FANOUT
            if len(at) == 1:
                break

    def texts(self, level: int, node: int) -> slice:
        width = LEAF * FANOUT**level
        return slice(node * width, min(self.n, (node + 1) * width))

    def children(self, level: int, node: int) -> range:
        return range(node * FANOUT, min(len(self.levels[level - 1][0]), (node + 1) * FANOUT))


def may_link(x: SignatureTree, lx: int, i: int, y: SignatureTree, ly: int, j: int, num: int, den: int) -> bool:
    """Whether the largest possible overlap of two nodes' texts is large enough."""
    ux, cx, lowx, highx = (a[i] for a in x.levels[lx])
    uy, cy, lowy, highy = (a[j] for a in y.levels[ly])
    if num * lowx > den * highy or num * lowy > den * highx:
        return False
    outside_x = int(np.bitwise_count(cx & ~uy).sum())  # of any text in x, shingles that no text in y has
    outside_y = int(np.bitwise_count(cy & ~ux).sum())
    most = min(highx - outside_x, highy - outside_y)
    return (num + den) * most >= num * (lowx + lowy)


def tree_order(sets: list[np.ndarray]) -> list[int]:
    """Like texts side by side: by their smallest hashes."""
    return sorted(range(len(sets)), key=lambda i: (sets[i][:3].tolist(), len(sets[i])))


class Overlaps:
    """Exact overlaps of ranges of texts: products of the incidence matrix over the
    shingles that several texts have, or pair by pair where that were too large."""

    def __init__(self, sets: list[np.ndarray], num: int, den: int):
        self.sets, self.num, self.den = sets, num, den
        self.sizes = np.array([len(s) for s in sets])
        owner = np.repeat(np.arange(len(sets)), self.sizes)
        _, place, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        shared = counts >= 2
        column = np.cumsum(shared) - 1
        width = int(shared.sum())
        self.matrix = None
        if width * len(sets) <= MATRIX_ENTRIES:
            keep = shared[place]
            self.matrix = np.zeros((len(sets), width), np.float32)
            self.matrix[owner[keep], column[place[keep]]] = 1

    def linked(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """(len(a), len(b)): which texts link."""
        if self.matrix is None:
            return np.array([[links(self.sets[i], self.sets[j], self.num, self.den) for j in b] for i in a])
        inter = np.rint(self.matrix[a] @ self.matrix[b].T).astype(np.int64)
        union = self.sizes[a][:, None] + self.sizes[b][None, :] - inter
        return self.den * inter >= self.num * union


def traverse(left: list[int], right: list[int] | None, sets: list[np.ndarray], label: np.ndarray, num: int, den: int) -> None:
    """Gives all texts that links connect one label, for the links of left with
    itself or with right."""
    exact = Overlaps(sets, num, den)
    left = np.array(left)[tree_order([sets[a] for a in left])]
    x = y = SignatureTree([sets[a] for a in left])
    if right is None:
        right = left
    else:
        right = np.array(right)[tree_order([sets[a] for a in right])]
        y = SignatureTree([sets[a] for a in right])
    stack = [(len(x.levels) - 1, 0, len(y.levels) - 1, 0)]
    while stack:
        lx, i, ly, j = stack.pop()
        a, b = left[x.texts(lx, i)], right[y.texts(ly, j)]
        first = label[a[0]]
        if (label[a] == first).all() and (label[b] == first).all():
            continue
        same = x is y and lx == ly and i == j
        if not same and not may_link(x, lx, i, y, ly, j, num, den):
            continue
        if lx == 0 and ly == 0:
            found = exact.linked(a, b)
            while len(at := np.argwhere(found & (label[a][:, None] != label[b][None, :]))):
                one, two = sorted((label[a[at[0, 0]]], label[b[at[0, 1]]]))
                label[label == two] = one
        elif lx >= ly:
            for c in x.children(lx, i):
                if lx == ly:
                    stack += [(lx - 1, c, ly - 1, d) for d in y.children(ly, j) if not same or d >= c]
                else:
                    stack.append((lx - 1, c, ly, j))
        else:
            stack += [(lx, i, ly - 1, d) for d in y.children(ly, j)]


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


_SURVEY = "kind int, doc_id long, n long, s1 long, s2 long"


def _survey(texts: DataFrame, k: int) -> DataFrame:
    """kind 0: a text's id, set size and set hash. kind 1: a shingle (s1) that n
    sets of a chunk have."""
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["kind", "doc_id", "n", "s1", "s2"]
        held: list[np.ndarray] = []
        known: set[tuple[int, int]] = set()

        def flush() -> Iterator[pa.RecordBatch]:
            if held:
                values, counts = np.unique(np.concatenate(held), return_counts=True)
                often = counts >= LOCAL_REPEATS
                v, c = values[often].view(np.int64), counts[often]
                if len(v):
                    zero = np.zeros(len(v), np.int64)
                    yield pa.record_batch([pa.array(zero.astype(np.int32) + 1), pa.array(zero), pa.array(c), pa.array(v), pa.array(zero)], names)
            held.clear()
            known.clear()

        size = 0
        for ids, texts in _rows(batches):
            sets = shingle_sets(texts, k)
            marks = [set_hash(s) for s in sets]
            for s, m in zip(sets, marks):
                if m not in known:
                    known.add(m)
                    held.append(s)
                    size += len(s)
            yield pa.record_batch([
                pa.array(np.zeros(len(sets), np.int32)), ids, pa.array([len(s) for s in sets], pa.int64()),
                pa.array([m[0] for m in marks], pa.int64()), pa.array([m[1] for m in marks], pa.int64()),
            ], names)
            if size >= CHUNK_SHINGLES:
                yield from flush()
                size = 0
        yield from flush()

    return texts.mapInArrow(run, _SURVEY)


def _key_rows(texts: DataFrame, k: int, num: int, den: int, common) -> DataFrame:
    """``key, doc_id``: for every chunk, one row per key with the smallest id that
    has it, and two rows per tie to that id."""
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        values, deal = common.value, Parts(num, den)
        keys: list[np.ndarray] = []
        ids_of: list[np.ndarray] = []
        known: set[tuple[int, int]] = set()

        def flush() -> Iterator[pa.RecordBatch]:
            if keys:
                key, own = np.concatenate(keys), np.concatenate(ids_of)
                order = np.lexsort((own, key))
                key, own = key[order], own[order]
                first = np.concatenate([[True], key[1:] != key[:-1]])
                hub = own[first][np.cumsum(first) - 1]
                ties = np.unique(np.stack([hub[~first], own[~first]], 1), axis=0)
                ties = ties[ties[:, 0] != ties[:, 1]]
                tie_key = mix(mix(ties[:, 0].astype(np.uint64) + _A) + _C * ties[:, 1].astype(np.uint64))
                all_keys = np.concatenate([key[first], tie_key, tie_key]).view(np.int64)
                all_ids = np.concatenate([own[first], ties[:, 0], ties[:, 1]])
                for at in range(0, len(all_keys), 100_000):
                    yield pa.record_batch([pa.array(all_keys[at : at + 100_000]), pa.array(all_ids[at : at + 100_000])], ["key", "doc_id"])
            keys.clear()
            ids_of.clear()
            known.clear()

        size = 0
        for ids, group in _rows(batches):
            for i, s in zip(ids.to_pylist(), shingle_sets(group, k)):
                if i is None or not len(s) or (m := set_hash(s)) in known:
                    continue
                known.add(m)
                often = values[np.minimum(np.searchsorted(values, s), len(values) - 1)] == s if len(values) else np.zeros(len(s), bool)
                for made in deal.keys(s, often):
                    keys.append(made)
                    ids_of.append(np.full(len(made), i, np.int64))
                    size += len(made)
            if size >= CHUNK_SHINGLES:
                yield from flush()
                size = 0
        yield from flush()

    return texts.mapInArrow(run, "key long, doc_id long")


def connected(edges: DataFrame) -> DataFrame:
    """``doc_id, label`` of all nodes of the edges (a, b): the smallest id that is
    reachable. In each round every node hooks to its smallest smaller neighbour, the
    hooks are followed to their roots by doubling, and the edges shrink to those
    between different roots; each step is one written table."""
    ordered = edges.where("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    left = stored(ordered, "edges")
    nodes = stored(left.select(F.col("a").alias("doc_id")).union(left.select("b")).distinct().select("doc_id", F.col("doc_id").alias("label")), "labels")
    while not left.isEmpty():
        roots = stored(left.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("root")), "hooks")
        while True:
            above = roots.select(F.col("node").alias("root"), F.col("root").alias("above"))
            jumped = stored(roots.join(above, "root", "left").select("node", F.coalesce("above", "root").alias("root"), F.col("above").isNotNull().alias("moved")), "hooks")
            roots = jumped.select("node", "root")
            if jumped.where("moved").isEmpty():
                break
        to = lambda df, c: df.join(roots.withColumnRenamed("node", c), c, "left").withColumn(c, F.coalesce("root", c)).drop("root")
        nodes = stored(to(nodes, "label").select("doc_id", "label"), "labels")
        met = to(to(left, "b"), "a")
        left = stored(met.where("a != b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    return nodes


def _linked(texts: DataFrame, tasks: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """``a, b``: ties between texts of different labels that a task found connected.
    tasks: doc_id, task, side, label. Side 0 meets side 1, or itself where a task
    has no side 1; texts of one label count as connected."""
    wanted = tasks.select(F.col("doc_id").alias("wanted")).distinct()
    if wanted.count() <= BROADCAST_IDS:
        wanted = F.broadcast(wanted)
    needed = texts.join(wanted, F.col("doc_id") == F.col("wanted"), "left_semi")
    # never broadcast: a text has a row for each of its tasks, which Spark's estimate, made before the rows multiply, leaves out
    rows = needed.join(tasks.hint("merge"), "doc_id").select("task", "side", "doc_id", "label", "text")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def solve(part: list[tuple]) -> pa.RecordBatch:
            part = sorted(part, key=lambda r: r[1])
            ids, place = [r[1] for r in part], {}
            before = np.array([place.setdefault(r[2], i) for i, r in enumerate(part)])
            label = before.copy()
            sides = [[i for i, r in enumerate(part) if r[0] == s] for s in (0, 1)]
            traverse(sides[0], sides[1] or None, [r[3] for r in part], label, num, den)
            # one tie for each former label, by the smallest id that it has here
            least: dict[int, int] = {}
            pairs = []
            for i in np.flatnonzero(before == np.arange(len(part))).tolist():
                first = least.setdefault(int(label[i]), ids[i])
                if first != ids[i]:
                    pairs.append((first, ids[i]))
            return pa.record_batch([pa.array([p[0] for p in pairs], pa.int64()), pa.array([p[1] for p in pairs], pa.int64())], ["a", "b"])

        task, part = None, []
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                cut = batch.slice(at, 200)
                sets = shingle_sets([t or "" for t in cut.column(4).to_pylist()], k)
                for key, side, i, label, own in zip(cut.column(0).to_pylist(), cut.column(1).to_pylist(), cut.column(2).to_pylist(), cut.column(3).to_pylist(), sets):
                    if key != task:
                        if len(part) > 1:
                            yield solve(part)
                        task, part = key, []
                    part.append((side, i, label, own))
        if len(part) > 1:
            yield solve(part)

    return rows.repartition("task").sortWithinPartitions("task").mapInArrow(run, "a long, b long")


def _pieces(size: Column) -> Column:
    return F.greatest(F.lit(1), F.ceil(size / CHUNK)).cast("int")


def _few(df: DataFrame) -> DataFrame:
    """A written table, broadcast if it has at most ``BROADCAST_IDS`` rows."""
    return F.broadcast(df) if df.count() <= BROADCAST_IDS else df


def _sizes(rows: DataFrame, least: int) -> DataFrame:
    """``hood, size`` of the neighbourhoods with more than ``least`` texts."""
    return _few(stored(rows.groupBy("hood").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") > least), "hood-sizes"))


def _piece(seed: int) -> Column:
    return F.pmod(F.xxhash64("doc_id", F.lit(seed)), F.col("pieces")).cast("int")


def _components(texts: DataFrame, sets: DataFrame, ties: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """``doc_id, label`` of the texts that stand in some tie. sets: doc_id, n."""
    hoods = stored(connected(ties).select("doc_id", F.col("label").alias("hood")), "hoods")
    members = stored(hoods.join(_sizes(hoods, CHUNK), "hood", "left").select("doc_id", "hood", _pieces(F.coalesce("size", F.lit(1))).alias("pieces")), "members")
    found, heads, turn = None, members, 0
    while True:
        tasks = heads.select("doc_id", F.struct("hood", _piece(turn).alias("piece")).alias("t")).select("doc_id", F.xxhash64("t", F.lit(turn)).alias("task"), F.lit(0).alias("side"), F.col("doc_id").alias("label"))
        new = _linked(texts, tasks, k, num, den)
        found = stored(new if found is None else found.unionByName(new), "links")
        if heads.where("pieces > 1").isEmpty():
            break
        labels = connected(found)
        # one text for each component so far of the neighbourhoods that had several chunks
        rest = stored(heads.where("pieces > 1").join(labels, "doc_id", "left").where("label is null or label = doc_id").select("doc_id", "hood"), "heads")
        before = heads.where("pieces > 1").count()
        heads = stored(rest.join(_sizes(rest, 1), "hood").select("doc_id", "hood", _pieces(F.col("size")).alias("pieces")), "members")
        after = heads.count()
        if after == 0 or after > 0.9 * before:
            break
        turn += 1
    large = members.where("pieces > 1")
    if large.isEmpty():
        return connected(found)
    labels = connected(found)
    state = stored(large.join(labels, "doc_id", "left").select("doc_id", "hood", "pieces", F.coalesce("label", "doc_id").alias("label")), "hood-labels")
    counts = state.groupBy("hood", "label").agg(F.count(F.lit(1)).alias("n"))
    main = counts.groupBy("hood").agg(F.max(F.struct("n", "label")).alias("top"), F.count(F.lit(1)).alias("labels"), F.sum("n").alias("all")).where("labels > 1").select("hood", F.col("top.label").alias("main"), _pieces(F.col("all") - F.col("top.n")).alias("outer"))
    open_state = stored(state.join(_few(stored(main, "main-labels")), "hood"), "open-hoods")
    if open_state.isEmpty():
        return labels
    drawn = lambda o, p: F.pmod(F.xxhash64("hood", o, p, F.lit(96)), F.lit(rounds)).cast("int")
    copies = F.when(F.col("label") != F.col("main"), F.col("pieces")).otherwise(0) + F.col("outer")
    shipped = open_state.join(sets.select("doc_id", "n").groupBy("doc_id").agg(F.max("n").alias("n")), "doc_id").agg(F.sum(copies * F.col("n")).alias("n")).first().n or 0
    held = sets.agg(F.sum("n").alias("n")).first().n or 0
    rounds = max(1, math.ceil(shipped / max(ROUND_LEAST, ROUND_SHARE * held)))
    needed = texts
    if rounds > 1:
        ids = open_state.select(F.col("doc_id").alias("wanted")).distinct()
        needed = stored(texts.join(_few(stored(ids, "open-ids")), F.col("doc_id") == F.col("wanted"), "left_semi"), "open-texts")
    for turn in range(rounds):
        outside = open_state.where("label != main").withColumn("o", F.pmod(F.xxhash64("doc_id", F.lit(97)), F.col("outer")).cast("int")).withColumn("p", F.explode(F.sequence(F.lit(0), F.col("pieces") - 1))).withColumn("side", F.lit(0))
        inside = open_state.withColumn("p", _piece(98)).withColumn("o", F.explode(F.sequence(F.lit(0), F.col("outer") - 1))).withColumn("side", F.lit(1))
        both = outside.unionByName(inside).where(drawn(F.col("o"), F.col("p")) == turn)
        tasks = both.select("doc_id", F.xxhash64("hood", "o", "p", F.lit(99)).alias("task"), "side", "label")
        found = stored(found.unionByName(_linked(needed, tasks, k, num, den)), "links")
        if rounds > 1:
            settle(texts.sparkSession)  # this round's copies go before the next are made
    if rounds > 1:
        drop_stored(texts.sparkSession, needed)
    return connected(found)


def components(docs: DataFrame, *, k: int = WORDS, num: int = NUM, den: int = DEN, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_shingles, component_id``, one row per input row."""
    spark = docs.sparkSession
    texts = _texts(docs, id_col, text_col)
    survey = stored(_survey(texts, k), "shingle-survey")
    sets = survey.where("kind = 0").select("doc_id", "n", "s1", "s2")
    often = stored(survey.where("kind = 1").groupBy("s1").agg(F.sum("n").alias("n")).where(F.col("n") >= REPEATS), "common-shingles")
    steps = {r.step: r.k for r in often.groupBy(F.floor(F.log2("n")).cast("int").alias("step")).agg(F.count(F.lit(1)).alias("k")).collect()}  # at most 64 rows
    least, held = 64, 0
    for step in sorted(steps, reverse=True):
        if held + steps[step] > COMMON_SHINGLES:
            break
        least, held = step, held + steps[step]
    got = often.where(F.floor(F.log2("n")) >= least).select("s1").toArrow()  # at most COMMON_SHINGLES rows
    common = spark.sparkContext.broadcast(np.sort(np.array(got.column("s1").to_pylist(), np.int64).view(np.uint64)))
    salted = sets.where("n > 0 and doc_id is not null").withColumn("salt", row_salt("doc_id", SALTS))
    same = Window.partitionBy("s1", "s2", "n")
    classes = salted.groupBy("s1", "s2", "n", "salt").agg(F.min("doc_id").alias("m")).repartition("s1", "s2", "n").withColumn("head", F.min("m").over(same)).drop("m")
    heads = stored(salted.join(classes, ["s1", "s2", "n", "salt"]).select("doc_id", "head"), "set-classes")
    rows = _key_rows(texts, k, num, den, common)
    hub = F.min("doc_id").over(Window.partitionBy("key"))
    near = rows.withColumn("hub", hub).where("doc_id != hub").select(F.col("hub").alias("x"), F.col("doc_id").alias("y")).distinct()
    ties = near.join(heads.select(F.col("doc_id").alias("x"), F.col("head").alias("a")), "x").join(heads.select(F.col("doc_id").alias("y"), F.col("head").alias("b")), "y").select("a", "b").where("a != b")
    ties = stored(ties.distinct(), "ties")
    labels = _components(texts, sets, ties, k, num, den)
    named = stored(heads.join(labels.withColumnRenamed("doc_id", "head"), "head", "left").select("doc_id", F.coalesce("label", "head").alias("own")).distinct(), "set-names")
    # the texts of one id tie their components, unlike though they may be
    several = named.groupBy("doc_id").agg(F.min("own").alias("a"), F.max("own").alias("b")).where("a != b").select("doc_id", "a")
    whole_ids = connected(named.join(several, "doc_id").select("a", F.col("own").alias("b"))).withColumnRenamed("doc_id", "own")
    named = named.join(whole_ids, "own", "left").groupBy(F.col("doc_id").alias("__id")).agg(F.min(F.coalesce("label", "own")).alias("own"))
    return sets.join(named, F.col("doc_id") == F.col("__id"), "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("own", "doc_id").alias("component_id"))


def keep_one(docs: DataFrame, *, k: int = 5, num: int = 4, den: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows whose id is the smallest of their component, with all columns."""
    name = free_name(docs, "kept_id")
    keep = components(docs, k=k, num=num, den=den, id_col=id_col, text_col=text_col).where("doc_id <=> component_id").select(F.col("doc_id").alias(name)).distinct()
    return docs.join(keep, F.col(id_col).cast("long").eqNullSafe(F.col(name)), "left_semi")


def op8_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return components(table(spark, sf_dir, "documents"))
