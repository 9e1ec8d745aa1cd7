from pyspark.sql import functions as F

from bitextspark.plans import q_training, training


def test_the_model_learns_from_pairs_of_noised_lengths(spark, monkeypatch):
    seen = []

    class Stop(Exception):
        pass

    def train(pairs, *_, **__):
        seen.append(pairs)
        raise Stop

    monkeypatch.setattr(q_training, "train", train)
    try:
        q_training.decode_modes_bleu(spark, "/root/testdata/sf0.001")
    except Stop:
        pass
    n, other = seen[0].agg(F.count("*"), F.sum((F.size("src_toks") != F.size("tgt_toks")).cast("int"))).first()
    first = q_training._parts(spark, "/root/testdata/sf0.001")[0]
    assert n == first.count() and n / 10 < other < n and first.filter(F.size("src_toks") != F.size("tgt_toks")).count() == 0
    words = lambda df: df.agg(F.sum(F.size("tgt_toks"))).first()[0]
    assert 0.92 < words(training.noised_lengths(first)) / words(first) < 0.98
