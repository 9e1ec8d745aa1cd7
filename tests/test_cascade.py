from bitextspark.operators import cascade
from bitextspark.plans import registry

SF = "/root/testdata/sf0.001"


def test_whole_cascade_catches_what_row_rules_miss(spark):
    rows = {(r["truth"], r["reason"]): r["n_rows"] for r in registry.QUERIES["filter_cascade_whole"](spark, SF).collect()}
    of = lambda truth: sum(n for (t, _), n in rows.items() if t == truth)
    assert rows[("wrong_lang", "language")] > 0 and ("wrong_lang", "kept") not in rows
    # one of the two copies goes, the other stays unless a score is low
    assert rows[("duplicate", "duplicate")] * 2 >= of("duplicate") * 0.8
    assert rows[("clean", "kept")] > 0.85 * of("clean")
    plain = registry.QUERIES["filter_quality"](spark, SF).first()
    whole = registry.QUERIES["filter_quality_whole"](spark, SF).first()
    assert whole["recall"] > plain["recall"] and whole["f1"] > plain["f1"]


def test_later_copies_keep_the_least(spark):
    df = spark.createDataFrame([("c", "A b", "x"), ("a", "a  B", "X"), ("b", "a b", "y"), ("d", None, "x")], "row_id string, src string, tgt string")
    got = {r["row_id"]: r["duplicate"] for r in cascade.later_copies(df, "row_id").collect()}
    assert got == {"a": False, "b": False, "c": True, "d": False}
