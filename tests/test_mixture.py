from pyspark.sql import functions as F

from bitextspark.plans import registry
from bitextspark.sources import bitext

SF = "/root/testdata/sf0.001"


def test_one_pass_gives_the_union_of_the_parts(spark):
    cb = bitext.cipher_bitext(spark, SF)
    want = bitext.mixture_sample({"bitext": cb.filter("split = 'train'"), "bt": cb.filter("split = 'spare'")}, {"bitext": 0.5, "bt": 0.9})
    want = want.groupBy("origin").agg(F.count("*").alias("n"), F.min("pair_id").alias("first_id"))
    got = registry.QUERIES["mixture_sample"](spark, SF)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    plan = got._jdf.queryExecution().optimizedPlan().collectLeaves()
    assert plan.size() == 1
