import random

import numpy as np
import pyarrow as pa
import pytest

from bitextspark.operators import batched, bleu, translate


@pytest.fixture(scope="module")
def models(spark):
    rng = random.Random(5)
    rows = []
    for i in range(400):
        n = rng.randrange(2, 9)
        k = [min(int(rng.paretovariate(0.8)), 25) for _ in range(n)]
        tgt = [f"e{x}{rng.choice('aab')}" for x in k if rng.random() > 0.1]
        rows.append((str(i), [f"f{x % 9}" for x in k], tgt))
    pairs = spark.createDataFrame(rows, "pair_id string, src_toks array<string>, tgt_toks array<string>").repartition(3)
    found = translate.train_many(pairs, [translate.Training(a, translate.SPECS[a], lm_weight=w) for a, w in (("base", 0.3), ("relpos", 1.0), ("revsrc", 0.3))])
    return pairs, found


SOURCES = [[], ["f1"], ["f1", "f2", "f3", "f4"], ["new", "f1"], ["new", "new"], ["f8"] * 7, [f"f{i % 9}" for i in range(20)]]


def systems(found):
    return [*found, *(translate.Ensemble(found, how) for how in ("max", "avg", "logavg"))]


@pytest.mark.parametrize("how", [{"mode": "greedy"}, {"mode": "topk", "k": 3}, {"mode": "sample"}, {"mode": "beam", "beam": 1}, {"mode": "beam", "beam": 4}, {"mode": "beam", "beam": 10, "alpha": 0.0}, {"mode": "beam", "beam": 3, "alpha": 3.0, "nbest": 5}])
def test_batches_decode_as_sentence_by_sentence(models, how):
    sources = SOURCES + [r["src_toks"] for r in models[0].limit(60).collect()]
    for system in systems(models[1]):
        s = batched.Searcher(system)
        ids = [f"id{i}" for i in range(len(sources))]
        sent, toks, length, score = s.search(*s.numbered(pa.array(sources, pa.list_(pa.string()))), ids, **how)
        ends = np.cumsum(length)
        words = s.names.known.take(pa.array(toks)).to_pylist()
        got = {}
        for x, hi, n, v in zip(sent.tolist(), ends.tolist(), length.tolist(), score.tolist(), strict=True):
            got.setdefault(x, []).append((words[hi - n : hi], v))
        for x, source in enumerate(sources):
            want = translate.search(system.next_dist, source, key=ids[x], **how)
            assert [h for h, _ in got[x]] == [h for h, _ in want]
            assert np.allclose([v for _, v in got[x]], [v for _, v in want], rtol=1e-9, atol=1e-12)


def test_training_makes_no_dict_of_entries(models):
    for m in models[1]:
        assert batched.members_of(m) and isinstance(m.lex, batched.Table) and isinstance(m.lm, batched.Table)
        assert dict(m.lex) and dict(m.lex) == m.lex.plain() and dict(m.lm) == {k: dict(v) for k, v in m.lm.plain().items()}
        assert all(abs(sum(r.values()) - 1) < 1e-9 for r in m.lm.values())


def test_counts_of_rows():
    rng = random.Random(3)
    some = lambda: [[rng.choice("abc") for _ in range(rng.randrange(0, 9))] for _ in range(200)]
    hyp, ref = some(), some()
    kind = pa.list_(pa.string())
    got = batched.row_matches(pa.array(hyp, kind), pa.array(ref, kind))
    assert got.tolist() == [bleu.row_statistics(h, r) for h, r in zip(hyp, ref, strict=True)]
    assert batched.row_matches(pa.array([], kind), pa.array([], kind)).shape == (0, len(bleu.SUMS))


def test_the_gate_judges_as_row_by_row(spark):
    rng = random.Random(9)
    rows = [(str(i), " ".join(rng.choice("abcd") for _ in range(rng.randrange(0, 8))), " ".join(rng.choice("abcd") for _ in range(rng.randrange(0, 8)))) for i in range(300)] + [("x", None, "a b")]
    df = spark.createDataFrame(rows, "id string, h string, r string")
    scores = {r["id"]: round(r["bleu"], 9) for r in bleu.sentence_bleu(df, "id", "h", "r", "split").collect()}
    assert {r["id"] for r in bleu.gate_by_bleu(df, "id", "h", "r", 28.0, "split").collect()} == {i for i, v in scores.items() if v >= 28}
    values = bleu._smoothed(np.array([bleu.row_statistics((h or "").split(), r.split()) for _, h, r in rows]))
    assert [round(float(v), 9) for v in values] == [scores[i] for i, _, _ in rows]
