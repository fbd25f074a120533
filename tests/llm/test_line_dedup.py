from collections import Counter

import numpy as np

from neighborsketch.llm import line_dedup as ld

WS = " \t\n\x0b\x0c\r"
SHOUT = {ord(c): c.lower() for c in ld.UPPER}
ROWS = [(i, f"Common LINE\n own {i}\n\n \t\nTwice\nTwice\nÉte") for i in range(6)] + [(7, None), (8, ""), (9, "common line "), (None, "x\ncommon line"), (3, "Common LINE\n own 3\n\n \t\nTwice\nTwice\nÉte"), (11, "a\n" * 3000 + "common line")]


def brute(rows, threshold):
    keys = [[line.strip(WS).translate(SHOUT) for line in (t or "").split("\n")] for _, t in rows]
    seen = Counter(k for own in keys for k in set(own))
    out = []
    for (i, t), own in zip(rows, keys):
        lines = (t or "").split("\n")
        stays = [x for x, k in zip(lines, own) if not k or seen[k] < threshold]
        out.append((i, len(lines), len(lines) - len(stays), "\n".join(stays)))
    return sorted(map(repr, out))


def frame(spark, rows):
    return spark.createDataFrame([(a, b, 0) for a, b in rows], "doc_id long, text string, n_lines int")


def result(docs, index):
    return sorted(repr(tuple(r)) for r in ld.clean(docs, index).collect())


def test_against_brute_force(spark):
    docs = frame(spark, ROWS)
    for threshold in (2, 6, 9):
        assert result(docs, ld.LineIndex.build(docs, threshold=threshold)) == brute(ROWS, threshold)


def test_paths_beyond_the_size_bounds(spark, monkeypatch):
    monkeypatch.setattr(ld, "FILTER_BYTES", 0)
    monkeypatch.setattr(ld, "BROADCAST_KEYS", 0)
    docs = frame(spark, ROWS)
    assert result(docs, ld.LineIndex.build(docs, threshold=6)) == brute(ROWS, 6)


def test_insertions_and_deletions_are_reversible(spark):
    first, second = frame(spark, ROWS[:5]), frame(spark, ROWS[5:])
    both = frame(spark, ROWS)
    grown = ld.LineIndex.build(first, threshold=6).insert(second)
    assert result(both, grown) == brute(ROWS, 6)
    back = grown.delete(second)
    assert sorted(map(repr, back.counts.collect())) == sorted(map(repr, ld.LineIndex.build(first, threshold=6).counts.collect()))
    assert result(first, back) == brute(ROWS[:5], 6)
    assert back.maybe_common(back.counts).count() == 0


def test_empty(spark):
    docs = frame(spark, [])
    assert ld.clean(docs, ld.LineIndex.build(docs)).count() == 0


def test_cuckoo_filter():
    rng = np.random.default_rng(1)
    keys = rng.integers(0, 256, (5000, 16), dtype=np.uint8)
    f = ld._filled(keys)
    assert f.contains(keys).all()
    assert f.contains(rng.integers(0, 256, (20000, 16), dtype=np.uint8)).mean() < 0.01
    f.delete(keys[:2500])
    assert f.contains(keys[2500:]).all() and f.contains(keys[:2500]).mean() < 0.01
    assert (ld.CuckooFilter.from_bytes(f.to_bytes()).table == f.table).all()
