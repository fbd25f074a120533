"""Edge cases and brute force for the operators without a test file of their own."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from neighborsketch.llm import chat_format, exact_dedup, language_id, quality, sharding

WS = " \t\n\x0b\x0c\r"


def strip(text):
    return (text or "").translate({ord(c): None for c in WS})


TEXTS = [(1, "a b"), (2, "ab"), (3, "a  b "), (4, None), (5, ""), (6, " \n\t"), (7, "x" * 200_000), (8, "é é"), (9, "éé"), (10, "a b"), (None, "a b"), (1, "a b")]


def test_exact_dedup_against_brute_force(spark):
    docs = spark.createDataFrame([(i, t, 5) for i, t in TEXTS], "doc_id long, text string, kept int").repartition(3)
    groups = defaultdict(list)
    for i, t in TEXTS:
        groups[strip(t)].append((len(t or ""), i))
    got = exact_dedup.report(docs).collect()
    assert len(got) == len(TEXTS)
    stays = Counter()
    for r in got:
        text = next(t for i, t in TEXTS if i == r.doc_id)
        own = groups[strip(text)]
        best = min(own, key=lambda x: (-x[0], x[1] is None, x[1] or 0))
        assert (r.keep_id, r.group_size) == (best[1], len(own))
        assert r.text_sha256 == hashlib.sha256(strip(text).encode()).hexdigest()
        stays[r.text_sha256] += r.kept
    assert set(stays.values()) == {1} and len(stays) == len(groups)
    kept = exact_dedup.drop_copies(docs)
    assert kept.columns == docs.columns and kept.count() == len(groups)
    assert exact_dedup.report(docs.limit(0)).count() == 0


def test_equal_digests_are_told_apart_by_text(spark, monkeypatch):
    from pyspark.sql import functions as F

    keyed = exact_dedup._keyed
    monkeypatch.setattr(exact_dedup, "_keyed", lambda *a: keyed(*a).withColumn("digest", F.unhex(F.lit("00"))))
    docs = spark.createDataFrame([(1, "a"), (2, "b"), (3, "a "), (4, "c"), (5, "b")], "doc_id long, text string")
    assert sorted((r.doc_id, r.keep_id, r.group_size) for r in exact_dedup.report(docs).collect()) == [(1, 3, 2), (2, 2, 2), (3, 3, 2), (4, 4, 1), (5, 2, 2)]


ROLES = ["user", "assistant", "assistant", "system", None, "odd\nrole<|im_end|>&nl;", ""]


def test_chat_round_trip(spark):
    rng = random.Random(2)
    bits = ["<|im_start|>", "<|im_end|>\n", "<|im_next|>", "&amp;", "&lt;|", "<", "|", "\n", "é", "ok", "&nl;", "\U0001f600", ""]
    rows = [(c, t, rng.choice(ROLES), rng.choice([None, "".join(rng.choice(bits) for _ in range(rng.randrange(12)))])) for c in range(40) for t in range(rng.randrange(1, 9))]
    rows += [(900, 0, "user", "a"), (900, 0, "user", "a"), (None, 1, "assistant", "n"), (901, None, "assistant", "z" * 50_000)]
    turns = spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, formatted int").repartition(4)
    want = defaultdict(list)
    for c, t, role, text in rows:
        want[c].append(((t is not None, t or 0), role or "", text or ""))
    formatted = chat_format.render(turns)
    got = {r.conv_id: r for r in chat_format.digest(formatted).collect()}
    assert set(got) == set(want)
    for c, own in want.items():
        own.sort()
        lines = "".join(f"{role}\n{text}\n" for _, role, text in own)
        loss = "".join(text for _, role, text in own if role == "assistant")
        assert (got[c].n_turns, got[c].turns_sha256) == (len(own), hashlib.sha256(lines.encode()).hexdigest())
        assert (got[c].loss_chars, got[c].loss_sha256) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    blocks = {r.conv_id: r.formatted for r in formatted.collect()}
    for c, own in want.items():
        runs = sum(i == 0 or own[i][1] != own[i - 1][1] for i in range(len(own)))
        assert blocks[c].count("<|im_start|>") == runs == blocks[c].count("<|im_end|>")
    assert chat_format.digest(chat_format.render(turns.limit(0))).count() == 0


def test_sharding_is_minimax(spark):
    rng = random.Random(4)
    rows = [(i, rng.choice(["hot"] * 3 + [f"t{rng.randrange(60)}" * rng.randrange(1, 9)])) for i in range(900)] + [(None, None), (5, ""), (5, "hot")]
    docs = spark.createDataFrame([(*r, 0) for r in rows], "doc_id long, text string, shard int").repartition(5)
    got = sharding.assign(docs).collect()
    assert len(got) == len(rows)
    shards, texts = defaultdict(list), {}
    sizes = Counter()
    for t in (t or "" for _, t in rows):
        sizes[hashlib.md5(t.encode()).hexdigest()] += len(t.encode()) + 8
        texts[zlib.crc32(t.encode())] = hashlib.md5(t.encode()).hexdigest()
    groups = defaultdict(set)
    for r in got:
        shards[r.shard].append(r)
        groups[texts[r.text_crc32]].add(r.shard)
        assert r.law == "bytes" and r.grown_shard is None
    assert all(len(s) == 1 for s in groups.values())
    assert all(sorted(r.slot for r in own) == list(range(len(own))) for own in shards.values())
    capacity, _ = sharding.minimax_cuts([sizes[k] for k in sorted(sizes)], 24)
    assert max(sum(r.size for r in own) for own in shards.values()) == capacity
    assert sharding.assign(docs.limit(0)).count() == 0


@pytest.mark.parametrize("resolution", [1, 3])
def test_sharding_is_minimax_with_many_groups_a_cell(spark, resolution):
    rng = random.Random(resolution)
    rows = [(i, f"t{i} " + "x" * rng.randrange(60)) for i in range(900)]
    got = sharding.assign(spark.createDataFrame(rows, "doc_id long, text string"), resolution=resolution).collect()
    sizes = {hashlib.md5(t.encode()).hexdigest(): len(t.encode()) + 8 for _, t in rows}
    capacity, _ = sharding.minimax_cuts([sizes[k] for k in sorted(sizes)], 24)
    used, slots = Counter(), defaultdict(list)
    for r in got:
        used[r.shard] += r.size
        slots[r.shard].append(r.slot)
    assert max(used.values()) == capacity and len(used) <= 24
    assert all(sorted(own) == list(range(len(own))) for own in slots.values())


def test_minimax_against_all_partitions():
    from itertools import combinations

    rng = random.Random(1)
    for _ in range(60):
        sizes = [rng.randrange(1, 30) for _ in range(rng.randrange(1, 9))]
        k = rng.randrange(1, 5)
        best = min(max(sum(sizes[a:b]) for a, b in zip((0, *cut), (*cut, len(sizes)))) for n in range(min(k, len(sizes))) for cut in combinations(range(1, len(sizes)), n))
        capacity, cuts = sharding.minimax_cuts(sizes, k)
        assert capacity == best and len(cuts) <= k
        assert max(sum(sizes[a:b]) for a, b in zip(cuts, (*cuts[1:], len(sizes)))) == best
    even = sharding.minimax_cuts([10] * 1000, 24)[1]
    assert {b - a for a, b in zip(even, (*even[1:], 1000))} == {41, 42}


def test_forest_is_the_trees_one_by_one():
    rng = np.random.default_rng(3)
    x = rng.normal(size=(3000, len(quality.FEATURES))).astype(np.float32)
    y = ((x[:, 0] > 0.3) ^ (x[:, 4] > 0)).astype(float)
    forest = quality.fit(x[:2000], y[:2000])
    assert ((forest.score(x[2000:]) >= 0.5) == y[2000:]).mean() > 0.95

    def walk(t, row):
        node, inner = 0, forest.feature.shape[1]
        while node < inner:
            node = 2 * node + 1 + (row[forest.feature[t, node]] > forest.threshold[t, node])
        return forest.leaf[t, node - inner]

    slow = [forest.base + sum(walk(t, r) for t in range(len(forest.leaf))) for r in x[:20]]
    assert np.allclose(slow, forest.raw(x[:20]))
    assert quality.fit(x[:0], y[:0]).score(x[:2]).tolist() == [0.5, 0.5]


def test_quality_edges(spark):
    rng = random.Random(0)
    good = lambda: " ".join("".join(rng.choice("aeinrst") for _ in range(rng.randrange(2, 9))) for _ in range(60)) + "."
    bad = lambda: "BUY!! " * 60
    rows = [(i, good() if i % 3 else bad()) for i in range(300)] + [(1000, None), (1001, ""), (1002, " \n"), (None, "abc"), (3, bad()), (1003, "x" * 300_000)]
    docs = spark.createDataFrame([(*r, "e", 1.5) for r in rows], "doc_id long, text string, lang string, score double")
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(300)] + [(None, 1), (7, None), (7, 1)], "doc_id long, quality int")
    forest = quality.train(docs, labels)
    got = quality.score(docs, forest).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in got)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got if r.doc_id is not None)
    right = [r.predicted == (r.doc_id % 3 > 0) for r in got if r.doc_id is not None and r.doc_id < 300 and r.held_out]
    assert np.mean(right) > 0.95
    kept = quality.keep(docs, forest)
    assert kept.columns == docs.columns and kept.count() == sum(r.predicted for r in got)
    assert quality.score(docs.limit(0), forest).count() == 0 and quality.train(docs, labels.limit(0)).score(np.zeros((1, len(quality.FEATURES)))).tolist() == [0.5]


def test_language_edges(spark):
    rng = random.Random(1)
    words = {"en": "the of and that with from".split(), "de": "und der nicht die schön für".split(), "fr": "été le que les être où".split()}
    rows = [(i, " ".join(rng.choice(words[lang]) for _ in range(20)), lang) for i in range(240) for lang in [list(words)[i % 3]]]
    rows += [(900, None, "en"), (901, "", "de"), (902, "12 !?", None), (None, "the and of", "en"), (903, "the " * 30_000, None), (5, rows[5][1], rows[5][2])]
    docs = spark.createDataFrame([(*r, 0) for r in rows], "doc_id long, text string, lang string, score int")
    model = language_id.train(docs)
    got = language_id.identify(docs, model).collect()
    assert len(got) == len(rows)
    for r in got:
        if r.doc_id in (900, 901, 902):
            assert (r.lang_pred, r.score) == ("und", 0.0)
        elif r.doc_id is not None and r.doc_id < 240:
            assert r.lang_pred == list(words)[r.doc_id % 3]
            assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1)
        assert 0 <= r.score <= 1
    assert {r.lang_pred for r in language_id.identify(docs, language_id.train(docs.where("lang is null"))).collect()} == {"und"}
    assert language_id.identify(docs.limit(0), model).count() == 0


@pytest.mark.parametrize("k", [2, 3, 5, 9, 40])
def test_codewords_differ(k):
    code = language_id.codewords(k)
    apart = min((a != b).sum() for i, a in enumerate(code) for b in code[:i])
    assert len(code) == k and apart >= (1 if k < 4 else 4 if k < 6 else 8)
    assert all(abs(c) < k for c in code.sum(0))


def test_held_out_accuracy_on_the_tables(spark):
    from pathlib import Path

    from neighborsketch.llm.common import table

    sf = "/root/testdata/sf0.01"
    if not Path(sf).exists():
        pytest.skip("no test tables here")
    docs = table(spark, sf, "documents")
    lang = language_id.op7_language_id(spark, sf).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").selectExpr("avg(cast(lang_pred = lang as int))").first()[0]
    good = quality.op4_quality(spark, sf).join(table(spark, sf, "labels"), "doc_id").where("held_out").selectExpr("avg(cast(predicted = quality as int))").first()[0]
    assert lang > 0.95 and good > 0.95


def test_pipeline_against_brute_force(spark):
    from pathlib import Path

    import corpus_pipeline
    from neighborsketch.llm import byte_bpe
    from neighborsketch.llm.common import table

    sf = "/root/testdata/sf0.001"
    if not Path(sf).exists():
        pytest.skip("no test tables here")
    docs = table(spark, sf, "documents")
    forest = quality.train(docs, table(spark, sf, "labels"))
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    scores = forest.score(quality.statistics([t for _, t in rows]))
    rows = [r for r, s in zip(rows, scores) if s >= quality.KEEP_AT]
    best = {}
    for i, t in sorted(rows, key=lambda r: (-len(r[1]), r[0])):
        best.setdefault(strip(t), (i, t))
    rows = sorted(best.values())

    def bag(text):
        ws = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text))
        return {tuple(ws[i : i + 5]) for i in range(len(ws) - 4)} if len(ws) >= 5 else {tuple(ws)} - {()}

    sets = {i: bag(t) for i, t in rows}
    label = {i: i for i in sets}
    pairs = [(a, b) for a in sets for b in sets if a < b and sets[a] and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b])]
    for _ in range(len(pairs)):
        for a, b in pairs:
            label[a] = label[b] = min(label[a], label[b])
    rows = [r for r in rows if label[r[0]] == r[0]]
    items = [tokens(r.text) for r in table(spark, sf, "benchmark").collect()]

    def leaked(text):
        ws = tokens(text)
        for own in items:
            want = Counter(tuple(own[i : i + 5]) for i in range(len(own) - 4))
            for s in range(max(1, len(ws) - len(own) + 1)):
                part = ws[s : s + len(own)]
                have = Counter(tuple(part[i : i + 5]) for i in range(len(part) - 4))
                if have and 5 * sum((have & want).values()) >= 4 * sum((have | want).values()):
                    return True
        return False

    rows = [r for r in rows if not leaked(r[1])]
    codec = byte_bpe.Codec(byte_bpe.load_ranks(byte_bpe.vocabulary()))
    want = sorted((i, len(e) // 4, hashlib.sha256(e).hexdigest(), hashlib.sha256(t.encode()).hexdigest()) for (i, t), e in zip(rows, codec.encode([t for _, t in rows])))
    assert sorted(map(tuple, corpus_pipeline.run(spark, sf).collect())) == want


def tokens(text):
    return [w for w in re.split(r"[\W_]+", (text or "").lower()) if w]


def test_pipeline_stages_on_nulls_repeats_long_texts_and_clashing_names(spark):
    import corpus_pipeline
    from neighborsketch.llm.common import stored

    good = " ".join(f"Word{i % 40} of the text goes on, number {i}." for i in range(60))
    rows = [(1, good), (1, good), (2, good + " "), (3, None), (4, ""), (None, "some other text of a row without id"), (5, "long " * 50_000), (6, None)]
    docs = spark.createDataFrame([(i, t, "en", "s", 0, 7, 8) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, hit_id int, __keep int")
    sf = "/root/testdata/sf0.001"
    for given in (docs, docs.limit(0)):
        at = given
        for name, stage in corpus_pipeline.STAGES[1:]:
            at = stored(stage(spark, at, sf), f"edge-{name}")
            if name != "encode":
                assert at.columns == docs.columns
        ids = sorted((r.doc_id for r in at.collect()), key=lambda i: (i is None, i))
        assert ids == ([2, 3, 5, None] if given is docs else [])
    forest = quality.train(docs, spark.createDataFrame([], "doc_id long, quality int"))
    assert quality.keep(docs, forest).count() == len(rows) and quality.keep(docs.limit(0), forest).count() == 0
