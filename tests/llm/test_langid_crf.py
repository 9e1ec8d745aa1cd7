import itertools
import random

import numpy as np
from pyspark.sql import functions as F

from bitextspark.llm import langid_crf as langid


def test_forward_backward_equals_enumeration():
    rng = np.random.default_rng(2)
    n, lengths = 3, np.array([5, 1, 4])
    scores, a, start = rng.normal(size=(3, 5, n)), rng.normal(size=(n, n)), rng.normal(size=n)
    got, pairs, starts = langid.forward_backward(scores, lengths, a, start)
    want, want_pairs = np.zeros_like(got), np.zeros((n, n))
    for b, t in enumerate(lengths):
        paths = list(itertools.product(range(n), repeat=int(t)))
        p = np.exp([start[y[0]] + sum(scores[b, i, y[i]] for i in range(t)) + sum(a[y[i], y[i + 1]] for i in range(t - 1)) for y in paths])
        for y, w in zip(paths, p / p.sum(), strict=True):
            for i in range(t):
                want[b, i, y[i]] += w
            for i in range(t - 1):
                want_pairs[y[i], y[i + 1]] += w
    assert np.allclose(got, want) and np.allclose(pairs, want_pairs) and np.allclose(starts, want[:, 0].sum(axis=0))


def test_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    got = langid.predict(docs).filter("held_out").join(docs.select("doc_id", "lang", F.size(F.split("text", r"\s+")).alias("n")), "doc_id").filter("n >= 20")
    r = got.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int")).alias("a"), F.count("*").alias("n"), F.min("score").alias("lo"), F.max("score").alias("hi")).first()
    assert r["n"] > 1500 and r["a"] > 0.99 and r["lo"] >= 0 and r["hi"] <= 1


def test_code_switched_words_get_their_own_labels(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labeller = langid.Labeller(langid.learn(docs))
    texts = {r["lang"]: r["text"].split()[:60] for r in docs.filter("crc32(string(doc_id)) % 5 = 0 and length(text) > 600").collect()}
    mixed = " ".join(texts["en"][:40] + texts["de"][:40] + texts["fr"][:40]).encode()
    (_, marginals, _), = labeller.words([mixed])
    best = [labeller.model.labels[i] for i in marginals.argmax(axis=1)]
    assert np.mean([x == y for x, y in zip(best, ["en"] * 40 + ["de"] * 40 + ["fr"] * 40, strict=True)]) > 0.9


def test_odd_rows(spark):
    rng = random.Random(1)
    rows = [(i, " ".join(rng.choices(["the", "and", "of"] if i % 2 else ["der", "und", "von"], k=30)), "en" if i % 2 else "de", "z") for i in range(80)]
    rows += [(100, None, "en", None), (101, "", "en", ""), (102, "123 !! ***", "de", ""), (None, "the and of", "en", ""), (103, "der und", None, ""), (103, "der und", None, ""), (104, "the " * 60_000, None, ""), (105, "\x02 \x03 a", "en", "")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, score string")
    got = langid.predict(df)
    assert got.columns == ["doc_id", "held_out", "lang_pred", "score"] and got.count() == len(rows)
    by = {r["doc_id"]: r for r in got.collect()}
    assert [by[i]["lang_pred"] for i in (100, 101, 102, None, 103, 104)] == ["und", "und", "und", "en", "de", "en"]
    kept = langid.keep(df)
    assert kept.columns == df.columns and kept.filter("doc_id in (100, 101, 102)").isEmpty() and kept.filter("doc_id = 104").count() == 1
    nothing = langid.predict(df.limit(0))
    assert nothing.count() == 0
    unlabelled = langid.predict(df.withColumn("lang", F.lit(None).cast("string")))
    assert {r["lang_pred"] for r in unlabelled.collect()} == {"und"}


def test_every_label_can_be_learned(spark):
    # 300 labels with words of their own
    rows = [(i, " ".join(f"{chr(97 + k % 26)}{chr(97 + k // 26)}q{chr(97 + j)}" for j in range(12)), f"l{k:03d}") for i, k in enumerate(list(range(300)) * 8)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.learn(df)
    assert len(model.labels) == 300 and model.weights.size <= langid.MOST_WEIGHTS
    found = langid.Labeller(model).documents([t.encode() for _, t, _ in rows[:300]])
    assert sum(p == lang for (p, _), (_, _, lang) in zip(found, rows, strict=False)) > 200


def test_long_words_are_learned_whole(spark):
    long = "z" * 80
    rows = [(i, f"{long}{'aa' if i % 2 else 'bb'} " * 20, "x" if i % 2 else "y") for i in range(40)]
    runs = langid.sample(spark.createDataFrame(rows, "doc_id long, text string, lang string"), "doc_id", "text", "lang")
    assert {w for _, words in runs for w in words} == {f"{long}aa", f"{long}bb"}
