"""SQL fragments: views, hash constants, sketches, readings and decoding."""

from __future__ import annotations

P = 2147483647


def code(x: str) -> str:
    return f"(('0x' || substr(md5(CAST({x} AS VARCHAR)), 1, 8))::BIGINT % {P})"


def mult(text: str) -> str:
    return f"(1 + ('0x' || substr(md5({text}), 1, 8))::BIGINT % {P - 1})"


def off(text: str) -> str:
    return f"(('0x' || substr(md5({text}), 1, 8))::BIGINT % {P})"


def _shingled(table: str, row_id: str, text: str) -> str:
    return f"""
      SELECT DISTINCT id, {code('g')} AS element FROM (
        SELECT id, unnest(CASE WHEN len(w) = 0 THEN CAST([] AS VARCHAR[]) WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
               ELSE list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) END) AS g
        FROM (SELECT {row_id} AS id, regexp_extract_all(coalesce({text}, ''), '[^\\s]+') AS w FROM {table}))"""


_CUSTOMER = "SELECT DISTINCT o_custkey AS id, l_partkey AS element FROM lineitem JOIN orders ON l_orderkey = o_orderkey"


def _twins(base: str) -> str:
    return f"""
      WITH b AS ({base}), h AS (SELECT id, element, (17 * 1000003 + 11 + id * 48271) % {P} AS h FROM b)
      SELECT id, element FROM b UNION ALL
      SELECT id + (SELECT max(id) FROM b) + 1, element FROM h WHERE h % 5 = 0 AND ((h * 1000003 + element * 48271 + 11) % {P}) % 100 >= 5"""


VIEWS = {
    "basket_customer": _CUSTOMER,
    "basket_twins": _twins(_CUSTOMER),
    "basket_order": "SELECT DISTINCT l_orderkey AS id, l_partkey AS element FROM lineitem",
    "part_suppliers": _twins("SELECT DISTINCT l_partkey AS id, l_suppkey AS element FROM lineitem"),
    "user_events": f"SELECT DISTINCT user_id AS id, {code('''event_type || ':' || CAST(hour(ts) AS VARCHAR)''')} AS element FROM events",
    "doc_shingles": _shingled("documents", "doc_id", "text"),
    "page_tokens": _shingled("pages", "page_id", r"regexp_replace(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g')"),
    "turn_shingles": _shingled("conversations", "(conv_id * 1048576 + turn)", "text"),
    "benchmark_shingles": _shingled("benchmark", "item_id", "text"),
}
RAW = ("basket_customer", "basket_twins", "basket_order", "part_suppliers")


def view(name: str) -> str:
    return VIEWS[name]


def items(name: str) -> str:
    """The long form with elements as codes."""
    return f"SELECT id, {code('element')} AS element FROM ({VIEWS[name]})" if name in RAW else VIEWS[name]


def fixed(x: str, digits: int = 6) -> str:
    """Rounded by steps that every engine takes alike: rounding functions differ where a
    value lies just between two results."""
    return f"(floor(CAST({x} AS DOUBLE) * 1e{digits}::DOUBLE + 0.5::DOUBLE) / 1e{digits}::DOUBLE)"


def stable(query: str) -> str:
    """A query whose two-argument ``round`` calls are written out as ``fixed``."""
    out, at = [], 0
    while (begin := query.find("round(", at)) >= 0:
        depth, comma, end = 0, -1, begin + 6
        while depth or query[end] != ")":
            depth += (query[end] in "([") - (query[end] in ")]")
            if query[end] == "," and not depth:
                comma = end
            end += 1
        if comma < 0:
            out.append(query[at : begin + 6])
            at = begin + 6
        else:
            out.append(query[at:begin] + fixed(stable(query[begin + 6 : comma]), int(query[comma + 1 : end])))
            at = end + 1
    return "".join(out) + query[at:]


def constants(d: int, w: int, reps: int, k: int, seed: int = 42, sharing: str = "cell") -> str:
    """CTEs par(row, col, rep, k, alpha, beta, gamma) and rowpar(row, a, b, sa, sb)."""
    own = {"cell": "i || ':' || j", "row": "i || ':0'", "rep": "'0:0'"}[sharing]
    tail = f"'{seed}:' || {own} || ':' || o || ':' || h"
    alpha, beta, gamma = (f"'{n}:' || {tail}" for n in ("alpha", "beta", "gamma"))
    one = lambda n: f"'{n}:{seed}:' || i"
    return f"""
    par AS (SELECT i AS row, j AS col, o AS rep, h AS k, {mult(alpha)} AS alpha, {off(beta)} AS beta, {mult(gamma)} AS gamma
            FROM range({d}) a(i), range({w}) b(j), range({reps}) c(o), range({k}) e(h)),
    rowpar AS (SELECT i AS row, {mult(one('a'))} AS a, {off(one('b'))} AS b, {mult(one('sa'))} AS sa, {off(one('sb'))} AS sb FROM range({d}) t(i))"""


def column(a: str, b: str, w: int, row_id: str = "id") -> str:
    return f"(((({row_id} % {P}) * {a} + {b}) % {P}) % {w})"


def murmur(source: str, d: int, w: int, seed: int = 42) -> str:
    """CTE ``placed`` by the 32-bit Murmur hash (third version) of id and row."""
    mod = 1 << 32
    steps = ["id & 4294967295 AS lo", "(id >> 32) & 4294967295 AS hi"]
    times = lambda x, c: f"(CAST({x} AS HUGEINT) * {c} % {mod})::BIGINT"
    turned = lambda x, n: f"((({x} << {n}) & 4294967295) | ({x} >> {32 - n}))"

    def mixed(h: str, word: str, name: str) -> str:
        steps.extend([f"{times(word, 0xCC9E2D51)} AS {name}_k", f"{times(turned(f'{name}_k', 15), 0x1B873593)} AS {name}_m", f"xor({h}, {name}_m) AS {name}_x", f"({turned(f'{name}_x', 13)} * 5 + {0xE6546B64}) % {mod} AS {name}"])
        return name

    def finished(h: str, length: int, name: str) -> str:
        steps.extend([f"xor({h}, {length}) AS {name}_a", f"xor({name}_a, {name}_a >> 16) AS {name}_b", f"{times(f'{name}_b', 0x85EBCA6B)} AS {name}_c", f"xor({name}_c, {name}_c >> 13) AS {name}_d", f"{times(f'{name}_d', 0xC2B2AE35)} AS {name}_e", f"xor({name}_e, {name}_e >> 16) AS {name}"])
        return name

    first = finished(mixed(mixed("42::BIGINT", "lo", "h1"), "hi", "h2"), 8, "h3")
    last = finished(mixed(first, "word", "h4"), 4, "h5")
    return f"""
    mm AS (SELECT id, row, {', '.join(steps)} FROM (SELECT id, row, ({seed * 1009} + row)::BIGINT AS word FROM (SELECT DISTINCT id FROM {source}), range({d}) t(row))),
    placed AS (SELECT id, row, ((CASE WHEN {last} >= 2147483648 THEN {last} - {mod} ELSE {last} END % {w}) + {w}) % {w} AS col, 1 AS sign FROM mm)"""


def touched(source: str, d: int, w: int, reps: int, k: int, r: int, name: str = "hits", placed: str | None = None) -> str:
    """CTEs up to ``hits``: id, row, col, rep, cell and sign. source: a CTE (id, element);
    placed: a CTE of that name in place of the universal hash."""
    placed = placed or f"""
    placed AS (SELECT id, row, {column('a', 'b', w)} AS col, CASE WHEN ((id % {P}) * sa + sb) % {P} % 2 = 0 THEN 1 ELSE -1 END AS sign
               FROM (SELECT DISTINCT id FROM {source}), rowpar)"""
    return f"""{placed},
    codes AS (SELECT s.id, p.row, p.col, q.rep, q.k, any_value(p.sign) AS sign, min((q.alpha * s.element + q.beta) % {P}) AS code, any_value(q.gamma) AS gamma
              FROM {source} s JOIN placed p ON s.id = p.id JOIN par q ON q.row = p.row AND q.col = p.col GROUP BY s.id, p.row, p.col, q.rep, q.k),
    {name} AS (SELECT id, row, col, rep, any_value(sign) AS sign,
               (((row * {w} + col) * {reps} + rep) * {r} + (sum((code * gamma) % {P}) % {P}) % {r})::BIGINT AS cell
               FROM codes GROUP BY id, row, col, rep)"""


def sketch(name: str, d: int, w: int, reps: int, k: int, r: int, seed: int = 42, where: str = "true", sharing: str = "cell") -> str:
    """CTEs up to ``sketch``: cell, n."""
    return f"""items AS MATERIALIZED (SELECT * FROM ({items(name)}) WHERE {where}), {constants(d, w, reps, k, seed, sharing)}, {touched('items', d, w, reps, k, r)},
    sketch AS (SELECT cell, count(*)::BIGINT AS n FROM hits GROUP BY cell)"""


def asked(queries: str, w: int, reps: int, r: int) -> str:
    """CTEs up to ``asked``: qid, row, col, rep, cell. queries: a CTE (id, element)."""
    return f"""
    qcodes AS (SELECT s.id AS qid, q.row, q.col, q.rep, q.k, min((q.alpha * s.element + q.beta) % {P}) AS code, any_value(q.gamma) AS gamma
               FROM {queries} s, par q GROUP BY s.id, q.row, q.col, q.rep, q.k),
    asked AS (SELECT qid, row, col, rep, (((row * {w} + col) * {reps} + rep) * {r} + (sum((code * gamma) % {P}) % {P}) % {r})::BIGINT AS cell
              FROM qcodes GROUP BY qid, row, col, rep)"""


def readings(decrement: bool = False, w: int = 1) -> str:
    """CTE ``reads``: qid, row, col, rep, n."""
    own = f" - CASE WHEN {column('rp.a', 'rp.b', w, 'q.qid')} = q.col THEN 1 ELSE 0 END" if decrement else ""
    return f"""
    reads AS (SELECT q.qid, q.row, q.col, q.rep, coalesce(s.n, 0){own} AS n FROM asked q LEFT JOIN sketch s ON q.cell = s.cell JOIN rowpar rp ON rp.row = q.row)"""


def measured(groups: int) -> str:
    """CTE ``y``: qid, row, col, y."""
    return f"""
    means AS (SELECT qid, row, col, rep % {groups} AS g, avg(n) AS m FROM reads GROUP BY qid, row, col, rep % {groups}),
    y AS (SELECT qid, row, col, median(m) AS y FROM means GROUP BY qid, row, col)"""


def decoded(w: int, ids: str = "items") -> str:
    """CTE ``scores``: qid, id, score."""
    return f"""
    cols AS (SELECT id, row, {column('a', 'b', w)} AS col FROM (SELECT DISTINCT id FROM {ids}), rowpar),
    scores AS (SELECT y.qid, c.id, min(y.y) AS score FROM cols c JOIN y ON y.row = c.row AND y.col = c.col GROUP BY y.qid, c.id)"""


def top(v: int, source: str = "scores", score: str = "score", where: str = "true") -> str:
    return f"SELECT qid, rank, id, {score} FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY {score} DESC, id)::BIGINT AS rank FROM {source} WHERE {where}) WHERE rank <= {v}"


def pairs(name: str, alias: str = "v") -> str:
    """CTEs ``v`` (id, element), ``sizes`` and ``sims`` (qid, id, inter, uni), of different items."""
    return f"""{alias} AS MATERIALIZED ({VIEWS[name]}), sizes AS (SELECT id, count(*) AS n FROM {alias} GROUP BY id),
    shared AS (SELECT a.id AS qid, b.id AS id, count(*) AS inter FROM {alias} a JOIN {alias} b ON a.element = b.element AND a.id <> b.id GROUP BY a.id, b.id),
    sims AS (SELECT qid, s.id, inter, (x.n + y.n - inter)::BIGINT AS uni FROM shared s JOIN sizes x ON x.id = qid JOIN sizes y ON y.id = s.id)"""


def recall(v: int, num: int, den: int, top_cte: str = "tops", denom: str = "true_n") -> str:
    """One row of queries and recall, from CTEs sims and tops (qid, rank, id)."""
    return f"""
    SELECT count(*)::BIGINT AS queries, avg(hits / {denom}) AS recall FROM (
      SELECT s.qid, count(*) AS true_n, count(t.id) AS hits FROM sims s LEFT JOIN (SELECT qid, id FROM {top_cte} WHERE rank <= {v}) t ON t.qid = s.qid AND t.id = s.id
      WHERE s.inter * {den} >= s.uni * {num} GROUP BY s.qid)"""
