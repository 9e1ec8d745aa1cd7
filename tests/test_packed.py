import numpy as np
import pytest
from pyspark.sql import functions as F

from bitextspark.operators import ngram, packed, selection
from bitextspark.plans import q_models

SF = "/root/testdata/sf0.001"
#: Texts that hold the marks' spelling, a word thrice, and none at all.
TEXTS = ["a b a b a", "<s> a </s> b", "</s>", "b <s> <s> a </s> </s>", "a", "", "x y z a b a"]


def _rows(spark, texts=TEXTS):
    return spark.createDataFrame([(f"i{i}", t.split(), "uv"[i % 2]) for i, t in enumerate(texts)], "id string, toks array<string>, lm_id string")


@pytest.mark.parametrize("n", [2, 3])
def test_packed_scores_equal_the_tables(spark, monkeypatch, n):
    monkeypatch.setattr(packed, "BUCKET", 7)  # many buckets
    df = _rows(spark)
    _, got = packed.scores(packed.sliced(df, "id", "toks"), n)
    want = {r["id"]: r["score"] for r in ngram.scores(df, "id", "toks", ngram.fit_counts(df, "toks", n), n).collect()}
    assert {r["id"]: r["scores"][0] for r in got.collect()} == pytest.approx(want)


def test_packed_scores_by_label_equal_the_tables(spark):
    df = _rows(spark)
    labels, got = packed.scores(packed.sliced(df, "id", "toks", "lm_id"), 2)
    got = {(r["id"], m): s for r in got.collect() for m, s in zip(labels, r["scores"])}
    want = {(r["id"], r["lm_id"]): r["score"] for r in selection.genre_scores(df.drop("lm_id"), "id", "toks", ngram.fit_counts(df, "toks", 2, ("lm_id",)), 2).collect()}
    assert got == pytest.approx(want)


@pytest.mark.parametrize("form, sides", [("difference", ("src", "tgt")), ("literal", ("src", "tgt")), ("difference", ("tgt",))])
def test_packed_cross_entropy_equals_the_tables(spark, form, sides):
    pool, models = q_models._ce_parts(spark, SF)
    want = {r["pair_id"]: r["ce"] for r in selection.bilingual_ce(pool, models, form=form, sides=sides).collect()}
    assert {r["pair_id"]: r["ce"] for r in q_models._ce(spark, SF, form, sides).collect()} == pytest.approx(want)


def test_keys_come_back():
    rng = np.random.default_rng(3)
    k, c = np.sort(rng.integers(0, 2**64, 5000, np.uint64)), rng.integers(0, 2**16, 5000, np.uint16)
    back = packed._unpack_keys(packed._pack_keys(k, c))
    assert (back[0] == k).all() and (back[1] == c).all()
    x = rng.integers(0, 2**32, 999, np.uint32)
    assert (packed._unpack(packed._pack(x), np.uint32) == x).all()


@pytest.mark.parametrize("name", ["lm_token_trigram_score", "genre_confusion", "genre_top_sentences", "bilingual_ce_scores"])
def test_no_ngram_is_a_row(spark, name):
    """F2, F4, F8, F9: neither joins nor n-grams as rows in what is run last, which took the disk."""
    plan = q_models.QUERIES[name](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "CoGroup" in plan


@pytest.mark.parametrize("name", ["select_bilingual_ce", "select_literal_ce", "select_monolingual_ce", "select_similar"])
def test_selections_use_packed_counts(spark, monkeypatch, name):
    """F11 to F14: no table of an n-gram a row is fitted."""
    monkeypatch.setattr(ngram, "fit_counts", lambda *a, **b: pytest.fail("counted by rows"))
    assert q_models.QUERIES[name](spark, SF).agg(F.count("*")).first()[0] > 0
