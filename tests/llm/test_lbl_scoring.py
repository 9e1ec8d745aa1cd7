import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitextspark.llm import lbl_scoring as lbl


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def plain_base(rows):
    held = lambda i: zlib.crc32(str(i).encode()) % 5 == 1
    counts = Counter(w for i, t, *_ in rows if i is not None and not held(i) for w in [*words(t), None])
    n, v = sum(counts.values()), len(counts)
    out = {}
    for i, t, *_ in rows:
        ws = [*words(t), None]
        out[i] = (i is not None and held(i), len(ws), sum(counts[w] > 0 for w in ws), n, sum(math.log10((counts[w] + 0.5) / (n + 0.5 * (v + 1))) for w in ws))
    return out


@pytest.mark.parametrize("hot", [8, 120_000])
def test_base_equals_brute_force(spark, hot, monkeypatch):
    monkeypatch.setattr(lbl, "HOT_WORDS", hot)
    rng = random.Random(3)
    rows = [(i, " ".join(rng.choices(["The", "the", "Élan", "a", "b"] + [f"r{k}" for k in range(300)], weights=[40, 40, 9, 9, 9] + [0.2] * 300, k=rng.randrange(60))), "x") for i in range(120)]
    rows += [(500, None, "x"), (501, "", None), (None, "the zz", ""), (502, "new " * 20_000, ""), (7, rows[7][1], "x")]
    got = lbl.score(spark.createDataFrame(rows, "doc_id long, text string, score string")).collect()
    want = plain_base(rows)
    assert len(got) == len(rows)
    for r in got:
        w = want[r["doc_id"]]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == w[:4] and abs(r["base_score"] - w[4]) < 1e-6 * max(1, abs(w[4]))
        assert r["score"] < 0


def test_probabilities_sum_to_one():
    rng = np.random.default_rng(1)
    unigram = rng.random(30)
    texts = [rng.integers(0, 30, size=40) for _ in range(20)]
    model = lbl.train(texts, unigram, rounds=1)
    before = rng.integers(0, 31, size=(25, lbl.CONTEXT))
    s = model.hidden(before) @ model.target.T + model.bias
    assert np.allclose(np.exp(s - model.log_partition(before)[:, None]).sum(axis=1), 1, atol=1e-4)


def test_training_finds_order():
    # a cycle: the token before sets the next one
    texts = [(np.arange(60) + s) % 12 for s in range(40)]
    model = lbl.train(texts, np.ones(12), rounds=40)
    before = np.stack([np.arange(12), (np.arange(12) - 1) % 12], axis=1)
    s = model.hidden(before) @ model.target.T + model.bias
    assert (s.argmax(axis=1) == (np.arange(12) + 1) % 12).all()


def test_better_than_base_on_held_out(spark):
    got = lbl.score(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).filter("held_out").agg(F.sum("score").alias("s"), F.sum("base_score").alias("b"), F.sum("n_tokens").alias("n")).first()
    assert got["s"] > got["b"]


def test_empty_and_untrained(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert lbl.score(df).count() == 0
    only = spark.createDataFrame([(None, "a b")], "doc_id long, text string")
    assert [tuple(r) for r in lbl.score(only).collect()] == [(None, False, 3, 0, 0, 0.0, 0.0)]


def test_both_factors_sum_to_one(monkeypatch):
    monkeypatch.setattr(lbl, "SHORT", 8)
    monkeypatch.setattr(lbl, "MEMBERS", 5)
    rng = np.random.default_rng(2)
    model = lbl.train([rng.integers(0, 30, size=40) for _ in range(20)], rng.random(30), rounds=1)
    for before in rng.integers(0, 31, size=(6, lbl.CONTEXT)):
        assert abs(np.exp(model.log_probability(np.arange(30), np.tile(before, (30, 1)))).sum() - 1) < 1e-4


def test_every_training_document_is_learned_from(spark, monkeypatch):
    # each document has a pair of words of its own, far beyond 1,200 documents; all of them must have been drawn
    monkeypatch.setattr(lbl, "LEAST_COUNT", 5)
    rows = [(i, f"a{i} b{i} " * 6) for i in range(1500)]
    seen = []
    monkeypatch.setattr(lbl, "fit", lambda *a, f=lbl.fit: seen.append((a[3], f(*a))) or seen[-1][1])
    lbl.score(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    number, model = seen[0]
    trained = [i for i, _ in rows if zlib.crc32(str(i).encode()) % 5 != 1]
    assert len(trained) < len(number) // 2 + 1 and len(model.word) == len(number) == 2 * len(trained) + 1
    fresh = lbl.Learner(np.ones(len(number) + 1)).model()
    moved = np.abs(model.word - fresh.word).max(axis=1) > 1e-6
    assert all(moved[number[f"{c}{i}".encode()]] for i in trained for c in "ab" if number[f"{c}{i}".encode()] >= lbl.SHORT)


def test_a_full_bucket_at_the_border_is_shared_by_hash(spark):
    """Thousand tokens with one count and room for a hundred: some are taken, the model isn't dropped, and what is more frequent stays."""
    rows = [(f"w{i}".encode(), 130) for i in range(1000)]
    found = lbl.most_frequent(spark.createDataFrame(rows, "token binary, c long"), 100)
    assert 50 < len(found) <= 100 and found == sorted(found, key=lambda x: (-x[1], x[0]))
    found = lbl.most_frequent(spark.createDataFrame([(b"often", 9000), *rows], "token binary, c long"), 100)
    assert found[0] == (b"often", 9000) and 50 < len(found) <= 100
    assert len(lbl.most_frequent(spark.createDataFrame(rows, "token binary, c long"), 1000)) == 1000


def test_each_distinct_context_is_summed_once_and_far_scores_hold(monkeypatch):
    """Repeated contexts cost one sum; words whose exponentials leave the floats' reach have their right probabilities; and a pickled model scores alike."""
    import pickle

    monkeypatch.setattr(lbl, "HELD", 12)
    rng = np.random.default_rng(4)
    model = lbl.Learner(rng.random(901)).model()
    model.word *= 400
    model.__post_init__()
    before, y = np.tile(rng.integers(0, 902, size=(70, lbl.CONTEXT)), (9, 1)), rng.integers(0, 901, size=630)
    asked = []
    monkeypatch.setattr(lbl.LogBilinear, "log_partition", lambda self, b, f=lbl.LogBilinear.log_partition: asked.append(len(b)) or f(self, b))
    got = model.log_probability(y, before)
    assert sum(asked) == len(np.unique(before, axis=0)) == 70
    h = model.hidden(before).astype(np.float64)
    log_sum = lambda s: np.logaddexp.reduce(s, axis=1)
    s = h @ model.target.T + model.bias
    cls = lbl.class_of(y, model.edges)
    want = s[np.arange(len(y)), cls] - log_sum(s)
    for i in np.flatnonzero((y >= lbl.SHORT) & (y < 900)):
        lo, hi = model.edges[cls[i]], model.edges[cls[i] + 1]
        s = h[i : i + 1] @ model.word[lo:hi].T.astype(np.float64) + model.word_bias[lo:hi]
        want[i] += s[0, y[i] - lo] - log_sum(s)[0]
    assert np.abs(h @ model.word.T).max() > 90 and np.allclose(got, want, rtol=1e-4, atol=2e-3)
    assert np.array_equal(pickle.loads(pickle.dumps(model)).log_probability(y, before), got)


def test_sums_by_runs_of_any_length():
    rng = np.random.default_rng(5)
    for few in (0, 3, 48):
        lbl_few, lbl.FEW_RUNS = lbl.FEW_RUNS, few
        rows = np.sort(np.concatenate([rng.integers(0, 40, 300), np.full(200, 7), [99]]))
        x, order = rng.random((len(rows), 5)).astype(np.float32), rng.permutation(len(rows))
        starts = np.flatnonzero(np.concatenate([[True], rows[1:] != rows[:-1]]))
        found = lbl._sums(x, order, starts, np.diff(np.append(starts, len(rows))))
        lbl.FEW_RUNS = lbl_few
        assert np.allclose(found, np.add.reduceat(x[order], starts, axis=0), rtol=1e-4)
