import random
import re

import numpy as np

from neighborsketch.llm import ngram_join as nj


def word_set(text, k):
    ws = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not ws:
        return frozenset()
    return frozenset(tuple(ws[i : i + k]) for i in range(len(ws) - k + 1)) if len(ws) >= k else frozenset([tuple(ws)])


def brute(rows, k, num, den):
    sets = [word_set(t, k) for _, t in rows]
    label = [i for i, _ in rows]
    changed = True
    pairs = [(x, y) for x in range(len(rows)) for y in range(x) if sets[x] and sets[y] and den * len(sets[x] & sets[y]) >= num * len(sets[x] | sets[y])]
    while changed:
        changed = False
        for x, y in pairs:
            m = min(label[x], label[y])
            if label[x] != m or label[y] != m:
                label[x] = label[y] = m
                changed = True
    return sorted((i, len(s), c) for (i, _), s, c in zip(rows, sets, label))


def corpus(seed, n=260):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefé") for _ in range(3))
    passage = [word() for _ in range(25)]
    rows = [(900, None), (901, ""), (902, " \t\n"), (903, "One"), (904, "one"), (905, "one two"), (906, "ONE\ttwo"), (907, "one two three"), (908, "a " * 4000)]
    bases = [[word() for _ in range(rng.choice([4, 12, 40, 90, 150]))] + (passage if rng.random() < 0.4 else []) for _ in range(30)]
    for i in range(n):
        ws = list(rng.choice(bases[:1] if i % 3 == 0 else bases))
        for _ in range(rng.choice([0, 1, 1, 2, 4, 8])):
            ws[rng.randrange(len(ws))] = word()
        rows.append((i, rng.choice([" ", "\n", " \t"]).join(w.upper() if rng.random() < 0.2 else w for w in ws)))
    rng.shuffle(rows)
    return rows


def test_components_against_brute_force(spark):
    for seed, k, num, den in ((1, 3, 9, 10), (2, 5, 4, 5)):
        rows = corpus(seed)
        docs = spark.createDataFrame([(a, b, 1) for a, b in rows], "doc_id long, text string, n_shingles int").repartition(5)
        assert sorted(map(tuple, nj.components(docs, k=k, num=num, den=den).collect())) == brute(rows, k, num, den)
        kept = nj.keep_one(docs, k=k, num=num, den=den)
        assert sorted(r.doc_id for r in kept.collect()) == sorted(i for i, _, c in brute(rows, k, num, den) if i == c)


def test_large_neighbourhoods_in_small_chunks(spark, monkeypatch):
    monkeypatch.setattr(nj, "CHUNK", 6)
    monkeypatch.setattr(nj, "BROADCAST_IDS", 0)
    rows = corpus(3, 150)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted(map(tuple, nj.components(docs, k=3, num=4, den=5).collect())) == brute(rows, 3, 4, 5)


def test_nulls_repeats_and_empty(spark):
    text = "a b c d e f g h i j k l m n o p q r s t u v w x y z"
    docs = spark.createDataFrame([(None, text), (5, text), (5, text), (7, text + " Z"), (9, None)], "doc_id long, text string")
    got = sorted(map(repr, map(tuple, nj.components(docs).collect())))
    assert got == sorted(map(repr, [(None, 24, None), (5, 24, 5), (5, 24, 5), (7, 25, 5), (9, 0, 9)]))
    assert nj.components(docs.limit(0)).count() == 0


def test_texts_of_one_id_tie_their_components(spark):
    x, y, z = (" ".join(c + str(i) for i in range(30)) for c in "xyz")
    rows = [(3, x), (4, y), (5, x), (5, y), (6, y + " w"), (7, z), (8, z), (8, y + " v"), (9, "alone")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r.doc_id, r.component_id) for r in nj.components(docs).collect()}
    assert got == {(3, 3), (4, 3), (5, 3), (6, 3), (7, 3), (8, 3), (9, 9)}
    assert sorted(r.doc_id for r in nj.keep_one(docs).collect()) == [3, 9]


def test_traversal_finds_all_pairs(monkeypatch):
    monkeypatch.setattr(nj, "LEAF", 4)
    rng = np.random.default_rng(0)
    base = rng.integers(0, 2**63, 60, dtype=np.uint64)
    sets = [np.unique(np.concatenate([base[rng.permutation(60)[: rng.integers(50, 61)]], rng.integers(0, 2**63, rng.integers(0, 6), dtype=np.uint64)])) for _ in range(80)]
    sets[7] = sets[3]
    want = list(range(80))
    for i in range(80):
        for j in range(i):
            if nj.links(sets[i], sets[j], 9, 10) and want[i] != want[j]:
                low, high = sorted((want[i], want[j]))
                want = [low if w == high else w for w in want]
    for entries in (nj.MATRIX_ENTRIES, 0):
        monkeypatch.setattr(nj, "MATRIX_ENTRIES", entries)
        for halves in (False, True):
            got = np.arange(80)
            if halves:
                for left, right in ((list(range(40)), list(range(40, 80))), (list(range(40)), None), (list(range(40, 80)), None)):
                    nj.traverse(left, right, sets, got, 9, 10)
            else:
                nj.traverse(list(range(80)), None, sets, got, 9, 10)
            assert got.tolist() == want


def broadcast_rows(df):
    """The rows of each table that an executed plan broadcast."""
    out, left = [], [df._jdf.queryExecution().executedPlan()]
    while left:
        plan = left.pop()
        kind = plan.getClass().getSimpleName()
        if kind == "BroadcastExchangeExec":
            out.append(plan.metrics().apply("numOutputRows").value())
        if kind == "AdaptiveSparkPlanExec":
            left.append(plan.executedPlan())
        elif kind.endswith("QueryStageExec"):
            left.append(plan.plan())
        else:
            left += [plan.children().apply(i) for i in range(plan.children().size())]
    return out


def test_ids_of_many_tasks_are_broadcast_once(spark):
    """A large neighbourhood's text stands in a task for each chunk; what the driver
    holds to find the texts is an id each, not a row for each task."""
    words = [f"w{i}" for i in range(40)]
    texts = spark.createDataFrame([(i, " ".join([*words, f"v{i}"])) for i in range(20)], "doc_id long, text string")
    ids = spark.range(20).withColumnRenamed("id", "doc_id")
    tasks = ids.selectExpr("doc_id", "explode(sequence(0L, 49L)) as task", "cast(doc_id % 2 as int) as side", "doc_id as label")
    found = nj._linked(texts, tasks, 3, 9, 10)
    rows = found.collect()
    assert {i for r in rows for i in (r.a, r.b)} == set(range(20))
    assert broadcast_rows(found) == [20]


def test_copies_of_a_large_neighbourhood_go_out_in_rounds(spark, monkeypatch):
    """The texts that the pairs of chunks of an unlinked neighbourhood need are shipped a
    bounded share at a time, however often each is needed."""
    monkeypatch.setattr(nj, "CHUNK", 6)
    monkeypatch.setattr(nj, "ROUND_LEAST", 0, raising=False)
    monkeypatch.setattr(nj, "ROUND_SHARE", 2, raising=False)
    rng = random.Random(9)
    base = [f"w{i}" for i in range(60)]
    rows = [(i, " ".join(f"x{i}.{j}" if j in out else w for j, w in enumerate(base))) for i in range(90) for out in [set(rng.sample(range(60), 4))]]
    rows += [(100 + i, rows[i][1] + " y") for i in range(0, 90, 9)]
    shipped, linked = [], nj._linked

    def counted(texts, tasks, *args):
        shipped.append(tasks.count())
        return linked(texts, tasks, *args)

    monkeypatch.setattr(nj, "_linked", counted)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted(map(tuple, nj.components(docs, k=3, num=4, den=5).collect())) == brute(rows, 3, 4, 5)
    assert sum(shipped) > 10 * len(rows)  # one neighbourhood, all pairs of chunks
    assert max(shipped) < 4 * len(rows)
