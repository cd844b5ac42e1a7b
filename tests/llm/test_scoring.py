"""Context-tree weighting against a sequential definition, and the quality classifier."""

import math
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from meshspan.llm import context_tree as tree
from meshspan.llm import quality

SF = "/root/testdata/sf0.001"


def sequential_log(symbols: list[tuple[bytes, int]], depth: int) -> float:
    """Log weighted probability of (context, byte) events by the recursive definition, per decision."""

    def weighted(events, d):
        a = sum(1 for _, b in events if not b)
        b = len(events) - a
        block = math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)
        if d == depth or not events:
            return block if events else 0.0
        children: dict = {}
        for context, bit in events:
            children.setdefault(context[-1 - d], []).append((context, bit))
        below = sum(weighted(own, d + 1) for own in children.values())
        return np.logaddexp(math.log(0.5) + block, math.log(0.5) + below)

    nodes: dict = {}
    for context, byte in symbols:
        for bit in range(8):
            nodes.setdefault((bit, byte >> (8 - bit)), []).append((context, (byte >> (7 - bit)) & 1))
    return sum(weighted(events, 0) for events in nodes.values())


def events_of(streams, depth):
    out = []
    for s in streams:
        padded = b"\n" * depth + s
        out += [(padded[i : i + depth], padded[i + depth]) for i in range(len(s))]
    return out


def test_tree_equals_recursive_definition():
    streams = [b"ab ab a \n", b"ba ba \n", b"\n", b"abba \n"]
    for depth in (3, 4):
        keys, counts = tree._merged_keys(streams, depth)
        grown = tree.grown(keys, counts, depth, 0)
        total = sum(level[4][0] for level in grown[0][:1]) + sum(float(grown[0][bit][4].sum()) for bit in range(1, 8))
        assert abs(total - sequential_log(events_of(streams, depth), depth)) < 1e-9


def test_prediction_is_the_ratio_of_weighted_probabilities():
    """For contexts that training has seen to the full depth, a prediction is P(data, next) / P(data)."""
    streams, depth = [b"abab abab \n" * 1, b"abab \n"], 3
    keys, counts = tree._merged_keys(streams, depth)
    grown = tree.grown(keys, counts, depth, 0)
    base = events_of(streams, depth)
    for context, byte in [(b"\n\n\n", ord("a")), (b"bab", ord(" ")), (b"aba", ord("b"))]:
        key = int.from_bytes(context[::-1] + bytes([byte]), "big")
        log10 = tree.priced(np.array([key], np.uint64), depth, grown)[0]
        ratio = sequential_log([*base, (context, byte)], depth) - sequential_log(base, depth)
        assert abs(log10 * math.log(10) - ratio) < 1e-9


@settings(max_examples=10, deadline=None)
@given(st.lists(st.text("ab ", max_size=20), min_size=1, max_size=5), st.binary(min_size=3, max_size=3))
def test_probabilities_sum_to_one(texts, context):
    streams = [tree.stream_of(tree.token_bytes(t)) for t in texts]
    keys, counts = tree._merged_keys(streams, 3)
    grown = tree.grown(keys, counts, 3, 0)
    every = np.array([int.from_bytes(context[::-1] + bytes([b]), "big") for b in range(256)], np.uint64)
    assert abs((10.0 ** tree.priced(every, 3, grown)).sum() - 1) < 1e-9


def test_keys_and_lists_round_trip():
    s = np.frombuffer(b"\n\n\nabcd", np.uint8)
    assert tree.n_grams(s, 3).tolist() == [int.from_bytes((s[i - 3 : i][::-1].tobytes() + s[i : i + 1].tobytes()), "big") for i in range(3, 7)]
    for depth in (3, 4, 5, 6):
        long = np.random.default_rng(depth).integers(0, 256, 40).astype(np.uint8)
        assert tree.n_grams(long, depth).tolist() == [int.from_bytes(long[i - depth : i][::-1].tobytes() + long[i : i + 1].tobytes(), "big") for i in range(depth, 40)]
    keys = np.array([3, 9, 2**47], np.uint64)
    assert (tree._undelta(tree._delta(keys)) == keys).all() and (tree._unints(tree._ints(np.array([0, 5, 7]))) == [0, 5, 7]).all()
    assert len(tree._undelta(tree._delta(keys[:0]))) == 0


def test_log_gamma():
    x = np.array([0.5, 1, 2.5, 10, 99.5, 1e6])
    assert np.allclose(tree.log_gamma(x), [math.lgamma(v) for v in x], rtol=1e-12, atol=1e-12)


def brute_scores(texts, ids, depth):
    """Counts and the recursive tree, directly."""
    tokens = [(t or "").encode().lower().split() for t in texts]
    held = [zlib.crc32(str(i).encode()) % 10 == 0 for i in ids]
    counts: dict = {}
    for words, h in zip(tokens, held, strict=True):
        if not h:
            for w in [*words, b"\n"]:
                counts[w] = counts.get(w, 0) + 1
    n, v = sum(counts.values()), len(counts)
    streams = [tree.stream_of(w) for w in tokens]
    keys, number = tree._merged_keys([s for s, h in zip(streams, held, strict=True) if not h], depth)
    grown = tree.grown(keys, number, depth, 0)
    out = []
    for i, words, h, s in zip(ids, tokens, held, streams, strict=True):
        base = sum(math.log10((counts.get(w, 0) + 0.1) / (n + 0.1 * (v + 1))) for w in [*words, b"\n"])
        known = sum(1 for w in [*words, b"\n"] if counts.get(w))
        own = np.concatenate(list(tree._block_keys([s], depth)))
        out.append((i, h, len(words) + 1, known, n, base, float(tree.priced(own, depth, grown).sum())))
    return out


def test_scores_equal_brute_force(spark, docs):
    texts = ["The cat", None, "", "the cat sat", "The cat", " \t\n", "été À b", "a b \x00c"] + [f"word{i} the cat {i % 3}" for i in range(40)]
    frame = docs(texts)
    got = {r["doc_id"]: r for r in tree.score_documents(frame, depth=4).collect()}
    assert len(got) == len(texts)
    for i, held, n_tokens, known, train, base, score in brute_scores(texts, range(len(texts)), 4):
        r = got[i]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held, n_tokens, known, train)
        assert abs(r["base_score"] - base) < 1e-9 and abs(r["score"] - score) < 1e-4 * abs(score)
    repeated = tree.score_documents(frame.union(frame)).count()
    assert repeated == 2 * len(texts) and tree.score_documents(frame.limit(0)).count() == 0


def test_held_out_documents_beat_word_frequencies(spark):
    rows = tree.score_documents(spark.read.parquet(SF.replace("0.001", "0.01") + "/documents.parquet")).where("held_out").toPandas()
    assert rows.score.sum() > rows.base_score.sum()


def test_null_ids_train(spark, docs):
    rows = tree.score_documents(docs(["a b", "c"], ids=[None, 3])).collect()
    assert {r["doc_id"] for r in rows} == {None, 3} and all(not r["held_out"] for r in rows if r["doc_id"] is None)


# ---------------------------------------------------------------- quality


def test_features_are_word_and_character_grams():
    s = quality.Settings()
    ids, owner = quality.features([b"ab", "é".encode()], s)
    assert (owner == 0).sum() == 1 + 2 + 1 and (owner == 1).sum() == 1 + 1  # <ab> has two 3-grams and one 4-gram
    again, _ = quality.features([b"ab"], s)
    assert set(again) == set(ids[owner == 0])
    weights = quality.bag("ab ab cd", s)[1]
    assert abs(weights.sum() - 1) < 1e-6 and len(quality.bag(None, s)[0]) == 0


def test_held_out_accuracy(spark):
    folder = SF.replace("0.001", "0.01")
    d, labels = spark.read.parquet(folder + "/documents.parquet"), spark.read.parquet(folder + "/labels.parquet")
    model = quality.fit(d, labels)
    rows = quality.scored(d, model).join(labels, "doc_id").where("held_out").toPandas()
    assert (rows.predicted == rows.quality).mean() > 0.95
    kept = quality.kept(d, labels)
    assert kept.columns == d.columns and 0 < kept.count() < d.count()


def test_labels_of_the_held_out_fold_are_not_read(spark, docs):
    texts = [f"good prose number {i}" if i % 2 else f"### junk {i} @@@" for i in range(60)]
    labels = spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, quality int")
    wrong = spark.createDataFrame([(i, (i % 2) ^ (zlib.crc32(str(i).encode()) % 3 == 1)) for i in range(60)], "doc_id long, quality int")
    frame = docs(texts)
    small = quality.Settings(least_steps=2000)
    a, b = (quality.scored(frame, quality.fit(frame, x, small)).orderBy("doc_id").toPandas() for x in (labels, wrong))
    assert (a.score == b.score).all() and (a.predicted == [i % 2 for i in range(60)]).mean() > 0.9


def test_quality_edges(spark, docs):
    frame = docs([None, "", "a", "a"], ids=[None, 1, 2, 2])
    nothing = spark.createDataFrame([(2, None), (None, 1)], "doc_id long, quality int")
    rows = quality.scored(frame, quality.fit(frame, nothing)).collect()
    assert len(rows) == 4 and all(r["score"] == 0.5 and r["predicted"] == 1 for r in rows)
    assert quality.scored(frame.limit(0), quality.fit(frame, nothing)).count() == 0


def test_an_id_that_repeats_teaches_once(spark, docs):
    labels = spark.createDataFrame([(i, i % 2) for i in range(30)] * 2, "doc_id long, quality int")
    texts = [f"good prose number {i}" if i % 2 else f"### junk {i} @@@" for i in range(30)]
    small = quality.Settings(least_steps=500)
    once, often = docs(texts), docs(texts + [texts[3]] * 500, ids=[*range(30), *[3] * 500])
    a, b = (quality.scored(once, quality.fit(frame, labels, small)).orderBy("doc_id").toPandas() for frame in (once, often))
    assert (a.score == b.score).all()


def test_quality_of_very_long_texts(spark, docs):
    texts = ["good prose " * 400_000, "x" * 3_000_000, "### @@@ " * 3]
    labels = spark.createDataFrame([(0, 1), (2, 0)], "doc_id long, quality int")
    frame = docs(texts)
    rows = quality.scored(frame, quality.fit(frame, labels, quality.Settings(least_steps=200))).collect()
    assert len(rows) == 3 and all(0 <= r["score"] <= 1 for r in rows)


def brute_probability(text, model):
    """Score of a text from the scores of its features, word by word."""
    words = quality.words_of(text)
    total = 0.0
    for w in words:
        ids, _ = quality.features([w], model.settings)
        total += model.scores[ids].mean()
    return 1 / (1 + np.exp(-(total / max(1, len(words)) + model.bias)))


def test_quality_scores_equal_brute_force(spark):
    d, labels = spark.read.parquet(SF + "/documents.parquet"), spark.read.parquet(SF + "/labels.parquet")
    model = quality.fit(d, labels, quality.Settings(least_steps=500))
    texts = {r["doc_id"]: r["text"] for r in d.collect()}
    for r in quality.scored(d, model).collect():
        assert abs(r["score"] - brute_probability(texts[r["doc_id"]], model)) < 1e-9


def test_training_sample_stays_off_the_driver(spark, monkeypatch):
    """The sample is read and learned from in one task: no table of texts or features comes to the driver."""
    from pyspark.sql import DataFrame

    docs = spark.createDataFrame([(i, f"word{i} good text") for i in range(50)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(50)], "doc_id long, quality int")
    monkeypatch.setattr(DataFrame, "toArrow", lambda self: pytest.fail("a table came to the driver"))
    model = quality.fit(docs, labels, quality.Settings(least_steps=500))
    assert len(model.scores) == model.settings.buckets and model.scores.any()
