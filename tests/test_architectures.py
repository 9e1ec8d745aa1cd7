from bitextspark.operators import translate
from bitextspark.plans import q_training, training

EVERY = {"base", "relpos", "wide", "revsrc"}


def test_workloads_have_all_architectures(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(training, "ladder", lambda pairs, archs=training.ladder.__defaults__[0]: seen.append(set(archs)) or [("a", "s", 1, "d", 0.0)])
    q_training.ladder(spark, "/root/testdata/sf0.001")
    assert seen == [EVERY] and set(training.alternate_distill.__defaults__[0]) == EVERY
    taught = []

    def stop(teacher, *_, **__):
        taught.append({m.model_id for m in teacher.members})
        raise StopIteration

    monkeypatch.setattr(q_training, "distill", stop)
    monkeypatch.setattr(q_training, "train_many", lambda pairs, jobs, **_: [type("M", (), {"model_id": j.model_id})() for j in jobs])
    try:
        q_training.distill_pairs(spark, "/root/testdata/sf0.001")
    except StopIteration:
        pass
    assert taught == [EVERY - {"base"}]


def test_distillation_goes_on_while_it_gains(spark, monkeypatch):
    # means rise for five rounds, then stay
    values = iter([0, 1, 2, 3, 4, 5, 5])
    pairs = spark.createDataFrame([("1", ["a"], ["b"])], "pair_id string, src_toks array<string>, tgt_toks array<string>")
    made = pairs.selectExpr("*", "'base' AS student")
    teachers = []
    monkeypatch.setattr(training, "distilled", lambda students, *_: teachers.append(set(students)) or made)
    monkeypatch.setattr(training, "train_many", lambda pairs, jobs, **_: [j.model_id for j in jobs])

    def scores(models, devs):
        v = next(values)
        return {(m, d): v for m in models for d in devs}

    monkeypatch.setattr(training, "score_many", scores)
    _, history = training.alternate_distill(pairs, pairs, pairs)
    assert max(r[0] for r in history.rows) == 6 and teachers == [EVERY] * 6


def test_models_of_one_training_equal_models_of_their_own(spark):
    rows = [(str(i), [f"f{(i + k) % 7}" for k in range(5)], [f"e{(i + k) % 7}" for k in range(5)]) for i in range(60)]
    pairs = spark.createDataFrame(rows, "pair_id string, src_toks array<string>, tgt_toks array<string>")
    one = [translate.train(pairs, translate.SPECS[a], a) for a in ("base", "revsrc")]
    both = translate.train_many(pairs, [translate.Training(a, translate.SPECS[a]) for a in ("base", "revsrc")])
    for a, b in zip(one, both, strict=True):
        assert a.unigram == b.unigram and a.ends == b.ends
        assert {f: [e for e, _ in es[:1]] for f, es in a.lex.items() if f} == {f: [e for e, _ in es[:1]] for f, es in b.lex.items() if f}
    assert all(m.lex[f"f{i}"][0][0] == f"e{i}" for m in both for i in range(7))
    assert all(translate.score_many({m.model_id: m for m in both}, {"d": pairs})[m.model_id, "d"] > 90 for m in both)
    part = translate.train_many(pairs.withColumn("w", translate.F.col("pair_id") < "3"), [translate.Training("all"), translate.Training("part", where=translate.F.col("w"))])
    assert sum(len(x) for x in part[1].lm.values()) <= sum(len(x) for x in part[0].lm.values())


def test_an_end_mark_lets_lengths_differ():
    lex = {"f": [("a", 1.0)], "g": [("b", 1.0)]}
    ends = {d: (0.0 if d < -1 else 0.4 if d == -1 else 0.5 if d == 0 else 0.9) for d in range(-8, 9)}
    m = translate.TranslationModel(translate.ModelSpec(), lex, {(-1, 0): 1.0, (-1, -1): 0.2}, {}, {"a": 0.3, "b": 0.3, "</s>": 0.4}, 0.3, "m", ends)
    lengths = [len(translate.search(m.next_dist, ["f", "g"], beam=8, alpha=alpha)[0][0]) for alpha in (0.0, 1.4, 6.0)]
    assert lengths == sorted(lengths) and lengths[0] < lengths[-1]


def test_tuning_moves_a_model_to_its_domain(spark):
    general = [(str(i), ["x", f"f{i % 5}"], ["the", f"e{i % 5}"]) for i in range(50)]
    own = [(f"d{i}", ["x", f"f{i % 5}"], ["der", f"e{i % 5}"]) for i in range(50)]
    frame = lambda rows: spark.createDataFrame(rows, "pair_id string, src_toks array<string>, tgt_toks array<string>")
    m = translate.train(frame(general))
    assert m.lex["x"][0][0] == "the" and translate.fine_tune(m, frame(own), 0.8).lex["x"][0][0] == "der"
    assert translate.averaged([m, m]).lex["x"][0][0] == "the"
