from pyspark.sql import functions as F

from bitextspark.plans import q_models

SF = "/root/testdata/sf0.001"


def test_out_of_domain_counts_cover_the_pool(spark):
    pool, models = q_models._ce_parts(spark, SF)
    for side in ("src", "tgt"):
        tokens = pool.agg(F.sum(F.size(f"{side}_toks") + 1)).first()[0]
        assert models[f"out_{side}"].filter("n = 1").agg(F.sum("cnt")).first()[0] == tokens


def test_local_merges_equal_plain_rounds():
    import random
    from collections import Counter

    from bitextspark.operators import subword

    rng = random.Random(4)
    types = dict(Counter("".join(rng.choices("abcd", k=rng.randrange(1, 7))) for _ in range(300)))
    held, want = {w: [*w, subword.END_MARK] for w in types}, []
    while True:
        pairs = Counter()
        for w, s in held.items():
            for p in zip(s, s[1:]):
                pairs[p] += types[w]
        if not pairs or max(pairs.values()) < 2:
            break
        best = min(pairs, key=lambda p: (-pairs[p], p))
        want.append(best)
        held = {w: subword.merge_word(s, {best: 0}) for w, s in held.items()}
    assert subword._learn_local(types, 10_000) == want and len(want) > 20
