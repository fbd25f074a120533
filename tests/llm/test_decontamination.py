import random
import re
from collections import Counter

from neighborsketch.llm import decontamination as dc


def tokens(text):
    return [w for w in re.split(r"[\W_]+", (text or "").lower()) if w]


def bag(ws, k):
    return Counter(tuple(ws[i : i + k]) for i in range(len(ws) - k + 1))


def brute(docs, items):
    out = []
    for d, t in docs:
        ws, hit = tokens(t), []
        for i, it in items:
            own = tokens(it)
            if i is None or not own:
                continue
            k, n = min(5, len(own)), len(own)
            b = bag(own, k)
            for s in range(max(1, len(ws) - n + 1)):
                a = bag(ws[s : s + n], k)
                if a and 5 * sum((a & b).values()) >= 4 * sum((a | b).values()):
                    hit.append(i)
                    break
        out.append((d, sorted(set(hit))))
    return sorted(map(repr, out))


def test_against_brute_force(spark):
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(4))
    items = [(i, " ".join(word() for _ in range(n))) for i, n in enumerate([3, 5, 9, 15, 20, 33, 57, 80])] + [(90, "to be or to be or to be or to be"), (91, ""), (92, None), (None, "xx yy zz xx yy"), (93, "  ... ")]
    docs = [(1000, None), (1001, ""), (1002, "!!!"), (1003, "to be or to be or to be"), (1004, "to be or " * 200)]
    for j in range(160):
        i, it = items[rng.randrange(8)]
        ws = it.split()
        for _ in range(rng.choice([0, 0, 1, 1, 2])):
            at = rng.randrange(len(ws) + 1)
            act = rng.randrange(3)
            if act == 0:
                ws.insert(at, word())
            elif act == 1:
                ws[at : at + 1] = []
            else:
                ws[at : at + 1] = [word()]
        lead, tail = [word() for _ in range(rng.randrange(40))], [word() for _ in range(rng.randrange(40))]
        docs.append((j, rng.choice([", ", " ", "\n"]).join([w.upper() if rng.random() < 0.1 else w for w in lead + ws + tail])))
    docs.append(docs[10])
    got = dc.report(spark.createDataFrame([(a, b, 0) for a, b in docs], "doc_id long, text string, item_id int"), spark.createDataFrame(items, "item_id long, text string"))
    have = sorted(repr((r.doc_id, r.item_ids)) for r in got.collect())
    want = brute(docs, items)
    missed = [w for w in want if w not in have]
    assert have == want, (missed[:3], [h for h in have if h not in want][:3])
    clean = dc.drop_contaminated(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    assert clean.count() == sum(w.endswith("[])") for w in want)


def test_reordered_passages_against_brute_force(spark):
    rng = random.Random(11)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(4))
    items = [(i, " ".join(word() for _ in range(n))) for i, n in enumerate([60, 60, 100, 100, 40, 80])]
    docs = []
    for j in range(90):
        ws = items[j % 6][1].split()
        part = rng.randrange(1, len(ws) // 2)
        ws = [ws[-part:] + ws[:-part], ws[part:] + ws[:part], ws[: len(ws) // 3] + ws[-part:] + ws[len(ws) // 3 : -part]][j // 6 % 3]
        docs.append((j, " ".join([word() for _ in range(rng.choice([0, 1, 30, 70]))] + ws + [word() for _ in range(rng.choice([0, 1, 30, 70]))])))
    for j, (n, moved) in enumerate(((60, 10), (100, 30))):
        ws = items[2 * j][1].split()[:n]
        docs.append((1000 + j, " ".join([word() for _ in range(50)] + ws[-moved:] + ws[:-moved] + [word() for _ in range(50)])))
    docs.append((2000, " ".join(t for _, t in docs)))
    got = dc.report(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    want = brute(docs, items)
    assert sorted(repr((r.doc_id, r.item_ids)) for r in got.collect()) == want
    assert sum(not w.endswith("[])") for w in want) > 20


def test_fillers_of_one_word_reach_verification(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    items, docs = [], []
    for i, (n, filler) in enumerate([(404, 44)] * 6 + [(204, 22)] * 4):
        ws = [word() for _ in range(n)]
        items.append((i, " ".join(ws)))
        docs.append((i, " ".join(ws[:-filler] + ["0"] * filler)))
    got = dc.report(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    assert sorted((r.doc_id, r.item_ids) for r in got.collect()) == [(i, [i]) for i in range(10)]


def test_empty(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    docs = spark.createDataFrame([(1, "a b c d e f")], "doc_id long, text string")
    items = spark.createDataFrame([], "item_id long, text string")
    assert dc.report(none, items.unionByName(spark.createDataFrame([(1, "a b c d e f")], "item_id long, text string"))).count() == 0
    assert [tuple(r)[:3] for r in dc.report(docs, items).collect()] == [(1, False, 0)]


def test_shuffled_lookup(spark, monkeypatch):
    monkeypatch.setattr(dc, "BROADCAST_ROWS", 0)
    docs = spark.createDataFrame([(1, "x a b c d e f g y"), (2, "a b c")], "doc_id long, text string")
    items = spark.createDataFrame([(5, "A b c; d e f g")], "item_id long, text string")
    assert sorted((r.doc_id, r.item_ids) for r in dc.report(docs, items).collect()) == [(1, [5]), (2, [])]
