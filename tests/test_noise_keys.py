from pyspark.sql import functions as F

from bitextspark.functions import noise
from bitextspark.operators import classify
from bitextspark.plans import q_eval


def _plan(df):
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_a_key_is_not_worked_out_for_each_token(spark):
    pairs = spark.createDataFrame([("a b c d", "x")], "t string, s string").select(F.md5(F.concat("s", F.lit("|"), "t")).alias("pair_id"), F.split("t", " ").alias("tgt_toks"), F.split("s", " ").alias("src_toks"))
    for f in (noise.noise_delete, noise.noise_blank, noise.noise_swap, noise.add_noise):
        assert "concat_ws(:, md5(" not in _plan(pairs.select(f(F.col("tgt_toks"), F.col("pair_id")).alias("x")))
    assert "concat_ws(:, md5(" not in _plan(classify.make_negatives(pairs, ("shuffled",)))
    assert "concat_ws(:, md5(" not in _plan(q_eval.hyps(spark, "/root/testdata/sf0.001").select("hyp"))
