import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from bitextspark.functions import nn, noise
from bitextspark.operators import bleu, classify, ensemble, filters, lexical, ngram, rerank, selection, subword
from bitextspark.operators.translate import Ensemble, ModelSpec, TranslationModel, search


def pairs_of(spark, rows):
    return filters.with_pair_id(spark.createDataFrame(rows, "src string, tgt string"))


def test_limits_at_their_ends(spark):
    w = lambda n: " ".join(["w"] * n)
    v = w(120).replace("w", "v")
    rows = [(w(120), v), (w(121), v), ("a" * 40 + " b c", "x y z"), ("a" * 41 + " b c", "x y z"), ("a", "b c d"), ("a", "b c d e"), ("a b c", "d"), ("a b c d", "e"), ("<b>x</b> y", "a b"), ("Same Text", "same  text")]
    got = filters.FilterCascade.bilingual().annotate(pairs_of(spark, rows)).select("src", "tgt", "reasons").collect()
    want = [[], ["max_words"], [], ["long_word"], [], ["length_ratio"], [], ["length_ratio"], ["markup"], ["copy"]]
    assert [r["reasons"] for r in got] == want


def test_cascade_is_idempotent_and_splits_its_input(spark):
    cascade = filters.FilterCascade.bilingual()
    df = pairs_of(spark, [("a b", "c d"), ("a", "b c d e f"), ("<i>", "x"), (None, "x"), ("x", None)])
    kept = cascade.apply(df)
    assert cascade.apply(kept).count() == kept.count()
    report = {r["reason"]: r["n_rows"] for r in cascade.report(df).collect()}
    assert report["kept"] == kept.count()


def test_duplicates_by_mode(spark):
    df = pairs_of(spark, [("a", "x"), ("a", "x"), ("A ", "x"), ("a", "y"), ("b", "x"), ("c", "c")])
    n = lambda mode: filters.duplicates(df, mode).filter("duplicate").count()
    assert (n("pair"), n("source"), n("target"), n("copy")) == (2, 3, 3, 1)
    assert filters.one_of_each(df).count() == 4 == filters.one_of_each(df.repartition(7)).count()


def test_noise_ends_and_rate(spark):
    toks = [f"t{i}" for i in range(4000)]
    df = spark.createDataFrame([("k", toks), ("e", [])], "id string, toks array<string>")
    t, k = F.col("toks"), F.col("id")
    r = df.select(noise.noise_delete(t, k, 0.0).alias("a"), noise.noise_delete(t, k, 1.0).alias("b"), noise.noise_blank(t, k, 1.0).alias("c"), noise.noise_swap(t, k, 0.05).alias("d"), noise.noise_swap(t, k, style="local").alias("e"), noise.noise_delete(t, k).alias("f"), noise.add_noise(t, k).alias("g")).collect()
    assert r[0]["a"] == toks and r[0]["b"] == [] and set(r[0]["c"]) == {"<blank>"}
    assert sorted(r[0]["d"]) == sorted(toks) == sorted(r[0]["e"]) and r[0]["d"] != toks
    assert max(abs(i - int(x[1:])) for i, x in enumerate(r[0]["e"])) <= 3
    assert abs(4000 - len(r[0]["f"]) - 200) < 4 * math.sqrt(4000 * 0.05 * 0.95)
    assert all(r[1][c] == [] for c in "abcdefg")
    again = df.repartition(3).select("id", noise.add_noise(t, k).alias("g")).filter("id = 'k'").first()["g"]
    assert again == r[0]["g"]


@pytest.mark.parametrize("smoothing", ["addk", "kn"])
def test_probabilities_sum_to_one_over_seen_and_unseen(spark, smoothing):
    df = spark.createDataFrame([(["a", "b", "a"],), (["b", "a"],), (["a", "c"],)], "toks array<string>")
    counts = ngram.fit_counts(df, "toks", 2)
    probs = ngram.probabilities(counts, 2, smoothing)
    total = {r["ctx"]: r["s"] for r in probs.groupBy("ctx").agg(F.sum("p").alias("s")).collect()}
    seen = {r["ctx"]: r["c"] for r in counts.filter("n = 2").groupBy("ctx").agg(F.sum("cnt").alias("c"), F.count("*").alias("k")).collect()}
    kinds = {r["ctx"]: r["k"] for r in counts.filter("n = 2").groupBy("ctx").agg(F.count("*").alias("k")).collect()}
    for ctx, s in total.items():
        if smoothing == "addk":
            assert abs(s + (4 - kinds[ctx]) * 0.1 / (seen[ctx] + 0.1 * 4) - 1) < 1e-9
        else:
            low = {r["tok"]: r["k"] for r in counts.filter("n = 2").groupBy("tok").agg(F.count("*").alias("k")).collect()}
            have = {r["tok"] for r in counts.filter((F.col("n") == 2) & (F.col("ctx") == ctx)).collect()}
            missing = sum(v for k, v in low.items() if k not in have) / sum(low.values())
            assert abs(s + 0.75 * kinds[ctx] / seen[ctx] * missing - 1) < 1e-9


def test_counts_merge(spark):
    df = spark.createDataFrame([(["a", "b"],), (["b"],)], "toks array<string>")
    whole = sorted(map(tuple, ngram.fit_counts(df, "toks", 2).collect()))
    parts = ngram.merge_counts(ngram.fit_counts(df.limit(1), "toks", 2), ngram.fit_counts(df.subtract(df.limit(1)), "toks", 2))
    assert sorted(map(tuple, parts.collect())) == whole


def test_ce_difference_is_zero_for_equal_models_and_flips(spark):
    df = spark.createDataFrame([("1", ["a", "b"], ["x", "y"]), ("2", ["b"], ["y"])], "pair_id string, src_toks array<string>, tgt_toks array<string>")
    one, two = df.filter("pair_id = '1'"), df.filter("pair_id = '2'")
    fit = lambda d: {"src": ngram.fit_counts(d, "src_toks", 2), "tgt": ngram.fit_counts(d, "tgt_toks", 3)}
    models = lambda i, o: {"in_src": fit(i)["src"], "out_src": fit(o)["src"], "in_tgt": fit(i)["tgt"], "out_tgt": fit(o)["tgt"]}
    ce = lambda i, o: {r["pair_id"]: r["ce"] for r in selection.bilingual_ce(df, models(i, o)).collect()}
    assert all(abs(v) < 1e-12 for v in ce(df, df).values())
    a, b = ce(one, two), ce(two, one)
    assert a["1"] < 0 < a["2"] and all(abs(a[k] + b[k]) < 1e-9 for k in a)


@pytest.mark.parametrize("k", [0, 1, 37, 500, 999, 1000, 5000])
def test_threshold_refine_equals_a_full_sort(spark, k):
    rng = random.Random(k)
    rows = [(f"{i:04d}", float(rng.randrange(40))) for i in range(1000)]
    df = spark.createDataFrame(rows, "pair_id string, s double").repartition(6)
    for lowest in (True, False):
        want = {i for i, _ in sorted(rows, key=lambda r: (r[1] if lowest else -r[1], r[0]))[:k]}
        assert {r["pair_id"] for r in selection.threshold_refine(df, "s", k, "pair_id", lowest).collect()} == want


def test_em_on_a_toy_corpus(spark):
    df = spark.createDataFrame([("1", ["das", "haus"], ["the", "house"]), ("2", ["das", "buch"], ["the", "book"]), ("3", ["ein", "buch"], ["a", "book"])], "pair_id string, src_toks array<string>, tgt_toks array<string>")
    values = [lexical.log_likelihood(df, lexical.fit_alignment(df, n)) for n in (1, 2, 4, 8)]
    assert values == sorted(values)
    lex = {(r["f"], r["e"]): r["p"] for r in lexical.fit_alignment(df, 12).collect()}
    assert lex["haus", "house"] > 0.5 and lex["das", "the"] > 0.5
    sums = {}
    for (f, _), p in lex.items():
        sums[f] = sums.get(f, 0) + p
    assert all(abs(s - 1) < 1e-9 for s in sums.values())


def test_bleu_worked_cases(spark):
    rows = [("same", "the cat sat on the mat", "the cat sat on the mat"), ("apart", "x y z w", "the cat sat on"), ("case", "The cat sat on the mat", "the cat sat on the mat"), ("short", "the cat sat on", "the cat sat on the mat"), ("none", "", "a b"), ("null", None, "a b")]
    df = spark.createDataFrame(rows, "id string, h string, r string")
    b = {r["id"]: r["bleu"] for r in bleu.corpus_bleu(df, "id", "h", "r", ("id",)).collect()}
    assert b["same"] == 100 and b["none"] == 0 == b["null"] and b["case"] < 100 and abs(b["short"] - 100 * math.exp(-0.5)) < 1e-4
    assert abs(b["apart"] - 100 * math.exp(sum(math.log(1 / (2**k * t)) for k, t in ((1, 4), (2, 3), (3, 2), (4, 1))) / 4)) < 1e-4
    assert abs(bleu.corpus_bleu(df.filter("id = 'case'"), "id", "h", "r", lowercase=True).first()["bleu"] - 100) < 1e-9


def test_combination_by_hand(spark):
    steps = spark.createDataFrame([("a", "s", 0, 0, "x", math.log(0.6)), ("a", "s", 0, 0, "y", math.log(0.4)), ("b", "s", 0, 0, "x", math.log(0.2)), ("b", "s", 0, 0, "z", math.log(0.8))], "model_id string, sent_id string, hyp_id int, step int, tok string, logp double")
    got = lambda how: {r["tok"]: r["p"] for r in ensemble.combine(steps, how).collect()}
    assert got("max") == pytest.approx({"x": 0.6 / 1.8, "y": 0.4 / 1.8, "z": 0.8 / 1.8})
    assert got("avg") == pytest.approx({"x": 0.4, "y": 0.2, "z": 0.4})
    raw = {"x": math.sqrt(0.12), "y": math.sqrt(0.4e-9), "z": math.sqrt(0.8e-9)}
    assert got("logavg") == pytest.approx({k: v / sum(raw.values()) for k, v in raw.items()})
    probs = spark.createDataFrame([("s", "a", 1.0), ("s", "b", 0.0)], "sent_id string, domain string, prob double")
    weighted = {r["tok"]: r["p"] for r in ensemble.combine_weighted(steps.withColumnRenamed("model_id", "domain"), probs).collect()}
    assert weighted == pytest.approx({"x": 0.6, "y": 0.4, "z": 0.0})


def test_greedy_takes_the_pair_that_beats_the_best_singles():
    value = {("a",): 5, ("b",): 4, ("c",): 1, ("d",): 1, ("c", "d"): 9, ("a", "c", "d"): 10}
    score = lambda s: value.get(s, max(value[(m,)] for m in s))
    evaluate = lambda subsets: {s: score(s) for s in subsets}
    trace = ensemble.greedy_ensemble(list("abcd"), evaluate)
    assert trace.rows[0][0] == 1 and trace.chosen == ("a", "c", "d") and trace.best == 10 and trace.evaluations == 6 + 2 + 1
    assert ensemble.exhaustive_ensemble(list("abcd"), evaluate).evaluations == 15
    assert ensemble.topn_ensemble(list("abcd"), evaluate).best <= trace.best
    with pytest.raises(ValueError):
        ensemble.exhaustive_ensemble(list("abcdefghijkl"), evaluate)


def toy(arch="base"):
    lex = {"f1": [("a", 0.7), ("b", 0.3)], "f2": [("c", 0.6), ("d", 0.4)]}
    prior = {(0, 0): 0.8, (0, 1): 0.1, (0, -1): 0.1, (1, 0): 0.8, (1, 1): 0.1, (1, -1): 0.1}
    return TranslationModel(ModelSpec(arch=arch), lex, prior, {"<s>": {"a": 0.5}}, {"a": 0.3, "b": 0.2, "c": 0.3, "d": 0.2}, 0.3, arch)


def test_decoding_invariants():
    m = toy()
    d = m.next_dist([], ["f1", "f2"])
    assert abs(sum(d.values()) - 1) < 1e-9
    assert search(m.next_dist, ["f1", "f2"], "beam", beam=1)[0] == search(m.next_dist, ["f1", "f2"], "greedy")[0]
    assert search(m.next_dist, ["f1", "f2"], "topk", k=1)[0][0] == search(m.next_dist, ["f1", "f2"], "greedy")[0][0]
    drawn = [search(m.next_dist, ["f1"], "sample", key=str(i))[0][0][0] for i in range(2000)]
    p = m.next_dist([], ["f1"])
    assert all(abs(drawn.count(t) / 2000 - q) < 0.05 for t, q in p.items())
    assert search(m.next_dist, [], "beam") == [([], 0.0)]
    for how in ("max", "avg", "logavg"):
        assert Ensemble([m, m], how).next_dist([], ["f1", "f2"]) == pytest.approx(d)
    assert Ensemble([m, toy("revsrc")]).next_dist([], ["f1", "f2"], [1.0, 0.0])["a"] == pytest.approx(d["a"])


def test_kernels():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(6, 8))
    zero = np.zeros((5, 8))
    assert np.allclose(nn.relative_attention(x, x, x, zero, zero, 2), nn.attention(x, x, x))
    y = x.copy()
    y[4:] += 1
    assert np.allclose(nn.attention(x, x, x, nn.causal(6))[:4], nn.attention(y, y, y, nn.causal(6))[:4])
    order = rng.permutation(6)
    assert np.allclose(nn.attention(x[order], x[order], x[order]), nn.attention(x, x, x)[order])
    assert np.allclose(nn.sinusoid(4, 6)[3, :2], [math.sin(3), math.cos(3)])
    for arch in ("base", "relpos", "revsrc"):
        assert nn.Stack(ModelSpec(arch=arch, layers=1, heads=2, hidden=8, inner=16, clip=2))(x, x).shape == (6, 8)
    p = {"w": np.ones(2)}
    adam = nn.Adam(lr=0.1)
    for _ in range(200):
        adam.step(p, {"w": 2 * p["w"]})
    assert np.abs(p["w"]).max() < 0.05


def test_mira_finds_the_separating_weight(spark):
    good, bad = [float(x) for x in (4, 3, 2, 1, 4, 3, 2, 1, 4, 4)], [float(x) for x in (1, 0, 0, 0, 4, 3, 2, 1, 4, 4)]
    rows = [(s, r, [float(r == best), 1.0], good if r == best else bad) for s, best in (("s1", 2), ("s2", 1)) for r in (1, 2, 3)]
    df = spark.createDataFrame(rows, "sent_id string, hyp_rank int, feats array<double>, stats array<double>")
    w = rerank.kbmira(df, epochs=5)
    assert {r["sent_id"]: r["hyp_rank"] for r in rerank.rerank(df, w).collect()} == {"s1": 2, "s2": 1}


def test_bpe_rounds_and_reading_back(spark):
    types = spark.createDataFrame([("low", 5), ("lower", 2), ("newest", 6), ("widest", 3)], "word string, cnt long")
    merges = subword.learn_bpe(types, 8)
    assert merges[:2] == [("e", "s"), ("es", "t")]
    assert subword.learn_bpe(types, 8, local_types=0) == merges
    df = spark.createDataFrame([("1", "newest low widest"), ("2", ""), ("3", None)], "id string, text string")
    out = {r["id"]: r["t"] for r in subword.apply_bpe(df, merges, "id").select("id", subword.decode_pieces("pieces").alias("t")).collect()}
    assert out == {"1": "newest low widest"}


def test_checkpoints_and_lloyd(spark):
    ckpt = spark.createDataFrame([("m", s, "p", 0, float(s)) for s in range(1, 13)] + [("n", 1, "p", 0, 7.0)], "model_id string, step int, param string, idx int, value double")
    assert {r["model_id"]: r["value"] for r in ensemble.average_checkpoints(ckpt).collect()} == {"m": 7.5, "n": 7.0}
    points = spark.createDataFrame([(0, [0.0, 0.0]), (1, [0.0, 2.0]), (2, [10.0, 0.0]), (3, [10.0, 2.0])], "vec_id int, x array<double>")
    centres = spark.createDataFrame([(0, [1.0, 1.0]), (1, [9.0, 1.0]), (2, [99.0, 99.0])], "cluster int, x array<double>")
    _, moved = ensemble.lloyd_step(points, centres)
    assert {r["cluster"]: (r["x"], r["n"]) for r in moved.collect()} == {0: ([0.0, 1.0], 2), 1: ([10.0, 1.0], 2), 2: ([99.0, 99.0], 0)}


def test_auc_with_ties(spark):
    df = spark.createDataFrame([(1, 0.9), (0, 0.9), (1, 0.5), (0, 0.1)], "y int, s double")
    assert classify.binary_metrics(df, "y", "s").first()["auc"] == 0.625
