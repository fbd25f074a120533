"""Byte-level BPE encoding and decoding.

Pre-tokenisation runs over arrays of code point classes, without a regex. A text
is the input of a small automaton whose symbols are the classes, widened by one
code point of lookahead; each symbol is a function from state to state. Most of
these are constant, so the associative scan that composes neighbouring functions
needs very few doublings until every prefix's function is constant: the state
before each code point then tells by a table whether a pre-token starts there.
The slices between the starts go through a bounded cache of merged pairs.

Encoding keeps the byte offset at which each token ends in its text; decoding puts
the tokens' bytes, from one blob, at these offsets, a whole batch with array
operations, and refuses offsets that don't fit the ids.

Edge cases: null counts as empty, and an empty text has no ids; texts of any
length are encoded whole, in groups of rows whose size is bounded unless a
single text is larger; repeated rows and null ids give a row each; an empty
table gives an empty result; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import unicodedata
from collections.abc import Iterable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

CACHE_PIECES = 1_000_000
GROUP_CHARS = 500_000

# White space of the pattern's \s, and its contractions.
SPACES = [*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
ONE_LETTER = "stmd"
TWO_LETTERS = ["re", "ve", "ll"]

# Symbols. BLANK_LAST and SPACE_LAST stand before something that isn't white space.
LETTER, NUMBER, OTHER, SPACE, BLANK_LAST, SPACE_LAST, QUOTE, SHORT, LONG = range(9)
# States: what the code points so far end with. QUOTED: an apostrophe that opens
# a pre-token; HALF: that and the first of two letters; DONE: a whole contraction.
BEGIN, IN_LETTERS, IN_NUMBERS, IN_OTHERS, IN_SPACES, AT_BLANK, AT_SPACE, QUOTED, HALF, DONE = range(10)


def _automaton() -> tuple[np.ndarray, np.ndarray]:
    """next[symbol, state] and starts[symbol, state] (a pre-token starts here)."""
    states = range(10)
    to, starts = np.zeros((9, 10), np.uint8), np.zeros((9, 10), bool)
    spaces = {IN_SPACES, AT_BLANK, AT_SPACE}
    for s in states:
        for symbol, own in ((LETTER, IN_LETTERS), (NUMBER, IN_NUMBERS), (OTHER, IN_OTHERS)):
            to[symbol, s] = own
            same = {own} | ({QUOTED} if symbol == OTHER else set())
            starts[symbol, s] = s not in same | {AT_BLANK}
        to[LETTER, HALF], starts[LETTER, HALF] = DONE, False
        opens = s not in (IN_OTHERS, QUOTED, AT_BLANK)
        to[QUOTE, s], starts[QUOTE, s] = (QUOTED if opens else IN_OTHERS), opens
        for symbol, then in ((SHORT, DONE), (LONG, HALF)):
            to[symbol, s], starts[symbol, s] = to[LETTER, s], starts[LETTER, s]
            if s == QUOTED:
                to[symbol, s], starts[symbol, s] = then, False
        for symbol, own in ((SPACE, IN_SPACES), (BLANK_LAST, AT_BLANK), (SPACE_LAST, AT_SPACE)):
            to[symbol, s] = own
            starts[symbol, s] = s not in spaces or symbol != SPACE
    return to, starts


NEXT, STARTS = _automaton()
_CONSTANT = (NEXT == NEXT[:, :1]).all(axis=1)


@cache
def _classes() -> np.ndarray:
    """A symbol for each code point, before lookahead."""
    out = np.full(0x110000, OTHER, np.uint8)
    for c in range(0x110000):
        kind = unicodedata.category(chr(c))[0]
        if kind == "L":
            out[c] = LETTER
        elif kind == "N":
            out[c] = NUMBER
    out[SPACES] = SPACE
    out[ord("'")] = QUOTE
    out[[ord(c) for c in ONE_LETTER]] = SHORT
    return out


def scan(symbols: np.ndarray, firsts: np.ndarray) -> np.ndarray:
    """The state before each symbol. firsts: where texts begin. Composes each
    symbol's function with those before it, twice as far each time, until the
    composed functions are constant."""
    n = len(symbols)
    state = NEXT[symbols, 0]
    known = _CONSTANT[symbols]
    state[firsts] = NEXT[symbols[firsts], BEGIN]
    known[firsts] = True
    open_at = np.flatnonzero(~known)
    slot = np.zeros(n, np.int32)
    slot[open_at] = np.arange(len(open_at))
    functions, before = NEXT[symbols[open_at]], open_at - 1
    while len(open_at):
        ready = known[before]
        rows = np.flatnonzero(ready)
        state[open_at[rows]] = functions[rows, state[before[rows]]]
        wait = np.flatnonzero(~ready)
        earlier = slot[before[wait]]
        composed = np.take_along_axis(functions[wait], functions[earlier].astype(np.intp), 1)
        further = before[earlier]
        known[open_at[rows]] = True
        constant = (composed == composed[:, :1]).all(axis=1)
        at = open_at[wait]
        state[at[constant]] = composed[constant, 0]
        known[at[constant]] = True
        open_at, functions, before = at[~constant], composed[~constant], further[~constant]
        slot[open_at] = np.arange(len(open_at))
    out = np.empty(n, np.uint8)
    out[1:] = state[:-1]
    out[firsts] = BEGIN
    return out


def token_starts(text: str, firsts: np.ndarray) -> np.ndarray:
    """Offsets at which pre-tokens start. text: texts one after the other;
    firsts: where each non-empty one begins."""
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    symbols = _classes()[points]
    last = np.zeros(len(points), bool)
    last[firsts[1:] - 1] = True
    last[-1:] = True
    after = np.full(len(points), SPACE, np.uint8)
    after[:-1] = symbols[1:]
    after[last] = SPACE
    is_space = symbols == SPACE
    closing = is_space & (after != SPACE)
    follows = np.zeros(len(points), np.uint32)
    follows[:-1] = points[1:]
    follows[last] = 0
    for first, second in TWO_LETTERS:
        symbols[(points == ord(first)) & (follows == ord(second))] = LONG
    symbols[closing] = SPACE_LAST
    symbols[closing & (points == 0x20)] = BLANK_LAST
    return np.flatnonzero(STARTS[symbols, scan(symbols, firsts)])


class PairMerger(dict):
    """Pre-token to its ids as little-endian 32-bit bytes; merges what is new."""

    def __init__(self, ranks: dict[bytes, int], most: int = CACHE_PIECES):
        super().__init__()
        self.ranks, self.most = ranks, most

    def ids(self, piece: bytes) -> list[int]:
        ranks = self.ranks
        if piece in ranks:
            return [ranks[piece]]
        if len(piece) > 200:
            return self._long(piece)
        parts = [piece[i : i + 1] for i in range(len(piece))]
        get, none = ranks.get, 1 << 32
        pairs = [get(a + b, none) for a, b in zip(parts, parts[1:])]
        while pairs and (best := min(pairs)) != none:
            i = pairs.index(best)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del pairs[i]
            if i:
                pairs[i - 1] = get(parts[i - 1] + parts[i], none)
            if i < len(pairs):
                pairs[i] = get(parts[i] + parts[i + 1], none)
        return [ranks[p] for p in parts]

    def _long(self, piece: bytes) -> list[int]:
        """The same by a heap of pairs, for pieces where rescanning is quadratic."""
        import heapq

        n, ranks = len(piece), self.ranks
        end, before = list(range(1, n + 1)), list(range(-1, n - 1))
        alive = bytearray(b"\1" * n)
        heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(piece[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, stop = heapq.heappop(heap)
            j = end[i] if alive[i] else n
            if not alive[i] or j >= n or end[j] != stop:
                continue
            alive[j] = 0
            end[i] = stop
            if stop < n:
                before[stop] = i
                if (r := ranks.get(piece[i : end[stop]])) is not None:
                    heapq.heappush(heap, (r, i, end[stop]))
            if (p := before[i]) >= 0 and (r := ranks.get(piece[p:stop])) is not None:
                heapq.heappush(heap, (r, p, stop))
        return [ranks[piece[i : end[i]]] for i in range(n) if alive[i]]

    def __missing__(self, piece: str) -> bytes:
        if len(self) >= self.most:
            self.clear()
        out = np.array(self.ids(piece.encode("utf-8", "surrogatepass")), "<u4").tobytes()
        if len(piece) <= 64:
            self[piece] = out
        return out


class Codec:
    """Encodes and decodes lists of texts."""

    def __init__(self, ranks: dict[bytes, int]):
        self.merger = PairMerger(ranks)
        size = max(ranks.values(), default=-1) + 1
        tokens = [b""] * size
        for token, i in ranks.items():
            tokens[i] = token
        self.blob = np.frombuffer(b"".join(tokens), np.uint8)
        self.length = np.array([len(t) for t in tokens], np.int64)
        self.offset = np.cumsum(self.length) - self.length

    def encode(self, texts: list[str]) -> list[bytes]:
        """Each text's ids as little-endian 32-bit bytes."""
        ends = np.cumsum([len(t) for t in texts], dtype=np.int64)
        begins = ends - [len(t) for t in texts]
        joined = "".join(texts)
        if not joined:
            return [b""] * len(texts)
        starts = token_starts(joined, begins[begins < ends])
        bounds = starts.tolist() + [len(joined)]
        get = self.merger.__getitem__
        merged = [get(joined[a:b]) for a, b in zip(bounds, bounds[1:])]
        first = np.searchsorted(starts, begins).tolist() + [len(starts)]
        return [b"".join(merged[a:b]) for a, b in zip(first, first[1:])]

    def ends(self, encoded: list[bytes]) -> list[np.ndarray]:
        """The byte offset in its text at which each token ends."""
        return [np.cumsum(self.length[np.frombuffer(e, "<u4")]) for e in encoded]

    def decode(self, encoded: list[bytes], ends: list[np.ndarray] | None = None) -> list[bytes]:
        """The texts' bytes from ids and the tokens' offsets."""
        ends = self.ends(encoded) if ends is None else ends
        ids = np.frombuffer(b"".join(encoded), "<u4").astype(np.int64)
        total = np.cumsum([0, *[int(e[-1]) if len(e) else 0 for e in ends]])
        stops = np.concatenate([np.zeros(0, np.int64), *[e + t for e, t in zip(ends, total)]])
        size = self.length[ids]
        if len(stops) != len(ids) or (np.diff(stops, prepend=0) != size).any():
            raise ValueError("the offsets don't fit the ids")
        source = np.arange(total[-1], dtype=np.int64) + np.repeat(self.offset[ids] - (stops - size), size)
        data = self.blob[source].tobytes()
        return [data[a:b] for a, b in zip(total.tolist(), total[1:].tolist())]


def parse_ranks(raw: bytes) -> dict[bytes, int]:
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, raw.splitlines())}


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as file:
        return parse_ranks(file.read())


def groups(texts: list[str], most: int = GROUP_CHARS) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about ``most`` characters, one row at least."""
    begin, used = 0, 0
    for i, t in enumerate(texts):
        if used and used + len(t) > most:
            yield begin, i
            begin, used = i, 0
        used += len(t)
    if begin < len(texts):
        yield begin, len(texts)


_CODECS: dict[str, Codec] = {}


def _codec(digest: str, shipped) -> Codec:
    """One codec per worker process, so that its cache outlives a task; known by the
    digest of its vocabulary."""
    if digest not in _CODECS:
        _CODECS.clear()
        _CODECS[digest] = Codec(shipped.value)
    return _CODECS[digest]


def _rows(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple[pa.Array, list[str]]]:
    for batch in batches:
        for at in range(0, batch.num_rows, 1000):
            part = batch.slice(at, 1000)
            texts = [t or "" for t in part.column(1).to_pylist()]
            for a, b in groups(texts):
                yield part.column(0).slice(a, b - a), texts[a:b]


def _ranks(spark: SparkSession, path: str) -> tuple:
    with open(path, "rb") as file:
        raw = file.read()
    return hashlib.sha256(raw).hexdigest(), spark.sparkContext.broadcast(parse_ranks(raw))  # the vocabulary: a fixed size


def encode(docs: DataFrame, path: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, ids, ends``: ids in the order of the text, and the byte offset at which
    each token ends."""
    digest, shipped = _ranks(docs.sparkSession, path)

    def run(batches):
        codec = _codec(digest, shipped)
        for ids, texts in _rows(batches):
            found = codec.encode(texts)
            yield pa.record_batch([ids, pa.array([np.frombuffer(e, "<i4") for e in found], pa.list_(pa.int32())), pa.array(codec.ends(found), pa.list_(pa.int64()))], ["doc_id", "ids", "ends"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, ids array<int>, ends array<long>")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """``doc_id, text`` from ``doc_id, ids, ends``; bytes that aren't UTF-8 become U+FFFD."""
    digest, shipped = _ranks(encoded.sparkSession, path)

    def run(batches):
        codec = _codec(digest, shipped)
        for batch in batches:
            raw = [np.array(i or [], "<u4").tobytes() for i in batch.column(1).to_pylist()]
            ends = [np.array(e or [], np.int64) for e in batch.column(2).to_pylist()]
            yield pa.record_batch([batch.column(0), pa.array([b.decode("utf-8", "replace") for b in codec.decode(raw, ends)], pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids", "ends").mapInArrow(run, "doc_id long, text string")


def digest(docs: DataFrame, path: str, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256``: encodes, then decodes
    the ids by the retained offsets, in one pass."""
    name, shipped = _ranks(docs.sparkSession, path)

    def run(batches):
        codec = _codec(name, shipped)
        for ids, texts in _rows(batches):
            encoded = codec.encode(texts)
            decoded = codec.decode(encoded, codec.ends(encoded))
            yield pa.record_batch([
                ids, pa.array([len(e) // 4 for e in encoded], pa.int64()),
                pa.array([hashlib.sha256(e).hexdigest() for e in encoded], pa.string()),
                pa.array([hashlib.sha256(d).hexdigest() for d in decoded], pa.string()),
            ], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def vocabulary() -> str:
    """The default vocabulary file, from the installed package of public ones."""
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.tiktoken"))


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(table(spark, sf_dir, "documents"), vocabulary())
