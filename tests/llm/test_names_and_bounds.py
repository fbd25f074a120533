"""Clashing names, repeated ids, grown indexes and paths beyond the size bounds."""

import random

import numpy as np
import pytest

from neighborsketch.llm import byte_bpe, common, decontamination, exact_dedup, language_id, line_dedup, ngram_join, quality, secret_scan, sharding

CLASHES = ["__keep", "__id", "__key", "__sha", "kept_id", "kept_digest", "kept_mark", "hit_id", "hit_key", "row_key", "digest", "salt", "again", "text_sha256"]


def clashing(spark, rows):
    schema = "doc_id long, text string, " + ", ".join(f"{c} int" for c in CLASHES)
    return spark.createDataFrame([(i, t, *range(len(CLASHES))) for i, t in rows], schema)


def test_filters_leave_clashing_columns_untouched(spark):
    docs = clashing(spark, [(1, "a b c d e f"), (2, "a b c d e f "), (3, "x y z u v w"), (4, None)])
    items = spark.createDataFrame([(1, "x y z u v w")], "item_id long, text string")
    for got, want in ((exact_dedup.drop_copies(docs), [2, 3, 4]), (ngram_join.keep_one(docs), [1, 3, 4]), (decontamination.drop_contaminated(docs, items), [1, 2, 4])):
        assert got.columns == docs.columns
        assert sorted(r.doc_id for r in got.collect()) == want
        assert all(list(r)[2:] == list(range(len(CLASHES))) for r in got.collect())


def test_of_rows_that_share_an_id_the_longest_stays(spark):
    rows = [(1, "a b"), (1, "ab"), (1, "a  b"), (2, "a b"), (3, "c"), (3, "c"), (3, " c"), (5, "d"), (5, "d")]
    docs = spark.createDataFrame([(*r, n) for n, r in enumerate(rows)], "doc_id long, text string, other int").repartition(3)
    marks = [(r.doc_id, r.kept) for r in exact_dedup.report(docs).collect()]
    assert sum(k for _, k in marks) == 3 and len(marks) == len(rows)
    assert sorted((r.doc_id, r.text) for r in exact_dedup.drop_copies(docs).collect()) == [(1, "a  b"), (3, " c"), (5, "d")]


def test_salts_change_no_result(spark):
    docs = spark.createDataFrame([(i, "hot" if i % 2 else f"t{i % 7} ") for i in range(60)], "doc_id long, text string")
    results = [sorted(map(tuple, exact_dedup.report(docs, salts=n).collect())) for n in (1, 5, 64)]
    assert results[0] == results[1] == results[2]


def test_prefix_sums_by_levels(spark, monkeypatch):
    monkeypatch.setattr(sharding, "BUCKET_ROWS", 1)
    monkeypatch.setattr(sharding, "TOP_DIGITS", 1)
    docs = spark.createDataFrame([(i, f"t{i} " + "x" * (i % 40)) for i in range(400)], "doc_id long, text string")
    deep = sorted(map(tuple, sharding.assign(docs).collect()), key=repr)
    monkeypatch.undo()
    assert deep == sorted(map(tuple, sharding.assign(docs).collect()), key=repr)


def test_a_second_vocabulary_gets_its_own_codec():
    one, two = {b"a": 0, b"b": 1, b"ab": 2}, {b"a": 0, b"b": 1}

    class Shipped:
        def __init__(self, value):
            self.value = value

    assert byte_bpe._codec("one", Shipped(one)).encode(["ab"]) == [np.array([2], "<u4").tobytes()]
    assert byte_bpe._codec("two", Shipped(two)).encode(["ab"]) == [np.array([0, 1], "<u4").tobytes()]


def test_offsets_place_the_tokens():
    codec = byte_bpe.Codec(byte_bpe.load_ranks(byte_bpe.vocabulary()))
    texts = ["Hello, wörld", "", "two  words 漢字"]
    encoded = codec.encode(texts)
    ends = codec.ends(encoded)
    assert [int(e[-1]) if len(e) else 0 for e in ends] == [len(t.encode()) for t in texts]
    assert [d.decode() for d in codec.decode(encoded, ends)] == texts
    with pytest.raises(ValueError):
        codec.decode(encoded, [ends[0] + 1, *ends[1:]])


def test_repositories_and_owners_tell_examples(spark):
    narrow, wide, many = "Zx9Qw8Er7Ty6Ui5Op4As3Df2Gh", "Kj8Hg7Fd6Sa5Po4Iu3Yt2Re1Wq", "Bn7Mv6Cx5Zl4Kj3Hg2Fd1SaQ0"
    rows = [(i, f"see {wide} here", "hot") for i in range(25)] + [(100 + i, f"own {narrow}", "hot") for i in range(3)] + [(200 + i, f"doc {many}", f"s{i}") for i in range(3)]
    got = {r.doc_id: r for r in secret_scan.report(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert got[0].spans == "" and (got[0].most_owners, got[0].most_repos) == (1, 25)
    assert got[100].spans == "mixed:4:30" and (got[100].most_owners, got[100].most_repos) == (1, 3)
    assert got[200].spans == "" and (got[200].most_owners, got[200].most_repos) == (3, 3)


def test_many_spans_of_one_long_text(spark, monkeypatch):
    text = " ".join(f"token = abcdef{i}" for i in range(3000))
    docs = spark.createDataFrame([(1, text, "s")], "doc_id long, text string, source string")
    got = secret_scan.report(docs).first()
    assert got.n_assign == 3000
    monkeypatch.setattr(secret_scan, "BLOCK", 1 << 20)
    monkeypatch.setattr(secret_scan, "BROADCAST_VALUES", 0)
    assert secret_scan.report(docs).first() == got


def test_hot_keys_are_broadcast_and_the_rest_joined(spark):
    left = spark.createDataFrame([(i, i % 5 if i % 2 else 0) for i in range(50)], "row long, key long")
    right = common.stored(left.groupBy("key").count(), "sizes")
    want = sorted(map(tuple, left.join(right, "key").collect()))
    for most in (0, 1, 3, 100):
        assert sorted(map(tuple, common.join_hot(left, right, "key", "count", most).collect())) == want


def test_filters_probed_by_shard_hold_back_other_lines(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "SHARD_KEYS", 3)
    rows = [(i, "\n".join(f"line {j}" for j in range(i % 12, 24)) + f"\nown {i}") for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    index = line_dedup.LineIndex.build(docs, threshold=20)
    assert index.n_shards > 3
    near = sorted(map(repr, line_dedup.clean(docs, index).collect()))
    monkeypatch.setattr(line_dedup, "FILTER_BYTES", 0)
    assert sorted(map(repr, line_dedup.clean(docs, index).collect())) == near
    lines = index.counts.select("digest", "n_docs")
    common_keys = {bytes(r.digest) for r in index.counts.where("n_docs >= 20").collect()}
    found = {bytes(r.digest) for r in index.maybe_common(lines).collect()}
    assert common_keys <= found and len(found) < lines.count()


def test_an_index_that_grows_gets_more_shards(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "SHARD_KEYS", 2)
    small = spark.createDataFrame([(i, "a\nb") for i in range(3)], "doc_id long, text string")
    large = spark.createDataFrame([(10 + i, "\n".join(f"l{j}" for j in range(30))) for i in range(3)], "doc_id long, text string")
    index = line_dedup.LineIndex.build(small, threshold=3)
    grown = index.insert(large)
    assert index.n_shards == 1 and grown.n_shards == 16
    with pytest.raises(ValueError):
        index.delete(large)


def test_training_keeps_its_bound_where_ids_repeat(spark):
    rng = random.Random(6)
    rows = [(i % 20, " ".join(rng.choice(["the", "of", "und", "der"]) for _ in range(30)), f"l{i % 400}") for i in range(800)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(20)], "doc_id long, quality int")
    seen = []
    fit = quality.fit
    quality.fit = lambda x, y: seen.append(len(y)) or fit(x, y, trees=2)
    try:
        quality.train(docs, labels, rows=10)
    finally:
        quality.fit = fit
    assert seen == [10]
    model = language_id.train(docs, rows=50)
    assert len(model.languages) <= language_id.LANGUAGES


def test_language_decoding_takes_the_codeword_of_least_weighted_loss():
    rng = np.random.default_rng(2)
    words = {"en": "the of and that with".split(), "de": "und der nicht die".split(), "fr": "que les pas une".split()}
    names = [n for n in words for _ in range(40)]
    texts = [" ".join(rng.choice(words[n], 15)) for n in names]
    x, _ = language_id.grams(texts)
    model = language_id.fit(x, names)
    got, scores, _ = model.predict(texts)
    for i in range(0, len(texts), 7):
        margins = [sum(float(a) * float(b) for a, b in zip(x[i], model.weights[:, j])) + model.bias[j] for j in range(model.code.shape[1])]
        losses = [sum(t * np.log1p(np.exp(-m * c)) for t, m, c in zip(model.trust, margins, word)) for word in model.code]
        share = [np.exp(min(losses) - v) for v in losses]
        assert got[i] == model.languages[int(np.argmin(losses))]
        assert abs(scores[i] - max(share) / sum(share)) < 1e-4
    assert np.mean([a == b for a, b in zip(got, names)]) > 0.95


def test_statistics_by_hand():
    text = "One two, two!\nA 1 | B"
    own = dict(zip(quality.FEATURES, quality.statistics([text])[0].tolist()))
    words = text.split()
    want = {
        "log_chars": np.log1p(len(text)), "log_words": np.log1p(len(words)), "log_lines": np.log1p(2), "digits": 1 / len(text), "bars": 1 / len(text), "bangs": 1 / len(text), "commas": 1 / len(text),
        "letters": sum(c.isalpha() for c in text) / len(text), "uppers": sum(c.isupper() for c in text) / sum(c.isalpha() for c in text), "spaces": sum(c.isspace() for c in text) / len(text),
        "word_length": sum(map(len, words)) / len(words), "longest_word": np.log1p(4), "words_a_line": np.log1p(len(words) / 2), "distinct_words": len(set(words)) / len(words), "distinct_lines": 1.0,
        "top_word": 1 / len(words), "ends_with_stop": 0.0, "non_ascii": 0.0, "short_words": 4 / len(words), "odd_ends": 3 / len(words), "distinct_pairs": (len(set(zip(words, words[1:]))) + 1) / len(words),
    }
    for name, value in want.items():
        assert abs(own[name] - value) < 1e-5, name


def test_shared_folder_is_needed_on_a_cluster(spark, monkeypatch):
    class Conf:
        def get(self, *_):
            return None

    class Context:
        master = "spark://elsewhere:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        conf, sparkContext = Conf(), Context()

    with pytest.raises(ValueError):
        common.shared_dir(Session())
