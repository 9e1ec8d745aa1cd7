"""Queries that train and decode: but for the plans no SQL says them; tests hold them to invariants."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..operators import bleu, ensemble, filters
from ..operators.lexical import fit_alignment
from ..operators.translate import FINE_TUNE, ITERATIVE, MAIN, SPECS, Ensemble, Training, averaged, back_translate, distill, flip, score_many, train, train_many, translate
from ..sources import bitext
from . import training

QUERIES, SQL = {}, {}


def query(name: str, text: str | None = None):
    def register(f):
        QUERIES[name] = f
        if text:
            SQL[name] = text
        return f

    return register


def _parts(spark, d):
    cb = training.keep_table(bitext.cipher_bitext(spark, d, digits=3), "pairs")
    rows = {s: cb.filter(F.col("split") == s) for s in ("train", "dev_a", "dev_b")}
    half = F.pmod(F.xxhash64("pair_id"), F.lit(2))
    return rows["train"].filter(half == 0), rows["train"].filter(half == 1), rows["dev_a"], rows["dev_b"]


def _table(spark, systems, devs, schema, **how):
    """(system, a BLEU for each split) in the order of the systems."""
    found = score_many(systems, devs, **how)
    return spark.createDataFrame([(s, *(found[s, x] for x in devs)) for s in systems], schema)


_PLANS = [(n, p.steps, p.validate_every, p.average_last, p.lr, p.early_stop) for n, p in (("main", MAIN), ("iterative", ITERATIVE), ("fine_tune", FINE_TUNE))]


@query("train_plans", "WITH p(plan, steps, validate_every, average_last, lr, early_stop) AS (VALUES " + ", ".join(f"('{n}', {a}, {b}, {c}, CAST({lr!r} AS DOUBLE), {stop})" for n, a, b, c, lr, stop in _PLANS) + """),
m AS (SELECT plan, l_orderkey AS step, count(*) AS n FROM p JOIN lineitem ON l_orderkey BETWEEN 1 AND steps GROUP BY ALL), v AS (SELECT plan, step, row_number() OVER (PARTITION BY plan ORDER BY step DESC) AS r FROM m JOIN p USING (plan) WHERE step % validate_every = 0),
a AS (SELECT plan, CAST(sum(n) AS BIGINT) AS records FROM m GROUP BY plan), b AS (SELECT plan, count(*) AS validations, min(step) FILTER (r <= average_last) AS averaged_from FROM v JOIN p USING (plan) GROUP BY plan)
SELECT p.*, coalesce(records, 0) AS records, coalesce(validations, 0) AS validations, averaged_from FROM p LEFT JOIN a USING (plan) LEFT JOIN b USING (plan)""")
def train_plans(spark, d):
    """Each plan over the steps that lineitem records (orders stand for steps): how many records it trains on, how often it validates, and from which checkpoint on it averages."""
    plans = spark.createDataFrame(_PLANS, "plan string, steps int, validate_every int, average_last int, lr double, early_stop boolean")
    few = F.broadcast(plans)  # three rows
    met = bitext.table(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("step")).agg(F.count("*").alias("n")).join(few, F.col("step").between(1, F.col("steps")))
    records = met.groupBy("plan").agg(F.sum("n").alias("records"))
    # as many steps at most as the plan validates
    ranked = met.filter(F.col("step") % F.col("validate_every") == 0).withColumn("r", F.row_number().over(Window.partitionBy("plan").orderBy(F.desc("step"))))
    checked = ranked.groupBy("plan").agg(F.count("*").alias("validations"), F.min(F.when(F.col("r") <= F.col("average_last"), F.col("step"))).alias("averaged_from"))
    return plans.join(records, "plan", "left").join(checked, "plan", "left").fillna(0, ["records", "validations"])


@query("architectures_bleu")
def architectures_bleu(spark, d):
    """Every architecture, trained alike, on both development splits."""
    first, _, a, b = _parts(spark, d)
    models = train_many(training.pick(first), [Training(name, spec) for name, spec in SPECS.items()])
    return _table(spark, {m.model_id: m for m in models}, {"a": a, "b": b}, "arch string, dev_a double, dev_b double")


def curves(first, dev, rounds: int = 6, archs=training.ARCHITECTURES):
    """(model, round, BLEU) of every architecture after each round of EM, and the models by (architecture, round)."""
    rows, models = [], {}

    def note(n, found):
        scores = score_many({m.model_id: m for m in found}, {"dev": dev})
        for m in found:
            rows.append((m.model_id, n, scores[m.model_id, "dev"]))
            models[m.model_id, n] = m

    train_many(training.pick(first), [Training(a, SPECS[a]) for a in archs], rounds, note)
    return rows, models


@query("training_curves")
def training_curves(spark, d):
    """Validation after each round of training, by architecture: the best checkpoint, the first round at 99 % of the base model's best, and the mean of the last three checkpoints."""
    first, _, a, b = _parts(spark, d)
    rows, models = curves(first, a)
    evals = spark.createDataFrame(rows, "model_id string, step int, bleu double")
    target = 0.99 * max(v for m, _, v in rows if m == "base")
    last = max(n for _, n, _ in rows)
    mean = score_many({m: averaged([models[m, n] for n in range(last - 2, last + 1)], m) for m in training.ARCHITECTURES}, {"a": a, "b": b})
    means = spark.createDataFrame([(m, mean[m, "a"], mean[m, "b"]) for m in training.ARCHITECTURES], "model_id string, averaged_a double, averaged_b double")
    best = ensemble.best_checkpoint(evals).withColumnsRenamed({"step": "best_step", "bleu": "best_bleu"})
    reach = bleu.steps_to(evals, target).withColumnRenamed("step", "converged_step")
    return evals.join(best, "model_id").join(reach, "model_id").join(means, "model_id")


@query("decode_modes_bleu")
def decode_modes_bleu(spark, d):
    """Decoding modes, beam widths and length penalties of one model trained on noised-length data."""
    first, _, a, _ = _parts(spark, d)
    model = train(training.noised_lengths(first))
    rows = [(f"{mode} {width}".strip(), training.score(model, a, mode, **how)) for mode, width, how in (
        ("greedy", "", {}), ("beam", "4", {"beam": 4}), ("beam", "10", {"beam": 10}), ("beam", "10, penalty 0", {"beam": 10, "alpha": 0.0}), ("beam", "10, penalty 3", {"beam": 10, "alpha": 3.0}),
        ("topk", "10", {"k": 10}), ("topk", "1", {"k": 1}), ("sample", "", {}),
    )]
    return spark.createDataFrame(rows, "mode string, bleu double")


@query("bt_modes_bleu")
def bt_modes_bleu(spark, d):
    """Back-translation by greedy, beam, sampled and noised decoding: BLEU of a student of bitext and synthetic pairs."""
    first, second, a, b = _parts(spark, d)
    base = training.pick(first)
    reverse = train(flip(base), model_id="t2s")
    every, names = base.withColumn("how", F.lit("none")), ["none"]
    for name, mode, noise in (("greedy", "greedy", None), ("beam", "beam", None), ("topk", "topk", None), ("sample", "sample", None), ("beam, noised input", "beam", "input"), ("beam, noised output", "beam", "output")):
        every = every.unionByName(back_translate(reverse, second.select("pair_id", "tgt_toks"), noise, mode, beam=3).withColumn("how", F.lit(name)))
        names.append(name)
    every = training.keep_table(every, "bt")
    made = {r["how"]: r["count"] for r in every.groupBy("how").count().collect()} | {"none": 0}  # a row a mode
    students = train_many(every, [Training(n, SPECS["base"], F.col("how").isin("none", n)) for n in names], made=F.col("how") != "none")
    found = score_many({m.model_id: m for m in students}, {"a": a, "b": b})
    return spark.createDataFrame([(n, found[n, "a"], found[n, "b"], made.get(n, 0)) for n in names], "mode string, dev_a double, dev_b double, n_synthetic long")


@query("joint_training_history")
def joint_training_history(spark, d):
    first, second, a, _ = _parts(spark, d)
    _, _, history = training.joint_train(first, second.select("pair_id", "src_toks"), second.select("pair_id", "tgt_toks"), a)
    return spark.createDataFrame(history.rows, "iteration int, s2t double, t2s double, n_bt long, n_ft long")


@query("distill_history")
def distill_history(spark, d):
    """Alternate distillation with the gate, and without it."""
    first, second, a, _ = _parts(spark, d)
    rows = []
    for gate in (28.0, None):
        _, history = training.alternate_distill(first, second, a, reference="tgt", least_bleu=gate)
        rows += [("gated" if gate else "ungated", *r) for r in history.rows]
    return spark.createDataFrame(rows, "gate string, iteration int, arch string, bleu double, n_distilled long")


@query("distill_pairs")
def distill_pairs(spark, d):
    """Survivors of the gate when the ensemble of all other architectures teaches the base."""
    first, second, _, _ = _parts(spark, d)
    teacher = Ensemble(train_many(training.pick(first), [Training(a, SPECS[a]) for a in ("relpos", "wide", "revsrc")]))
    made = distill(teacher, second, "tgt", 28.0, mode="greedy")
    return made.select("pair_id", F.size("tgt_toks").alias("n"))


@query("translate_dev")
def translate_dev(spark, d):
    first, _, a, _ = _parts(spark, d)
    return translate(train(training.pick(first)), a, beam=10, alpha=1.4).select("pair_id", "hyp", "tgt")


def members(first, n: int = 10):
    """Models of all architectures, each without another portion of the pairs: diverse by architecture and data."""
    portions = bitext.split_portions(first)
    plans = [(training.ARCHITECTURES[i % 4], i % 6) for i in range(n)]
    return train_many(portions, [Training(f"{a}-{i}", SPECS[a], F.col("portion") != p) for i, (a, p) in enumerate(plans)])


@query("ensemble_decode_bleu")
def ensemble_decode_bleu(spark, d):
    """Ten members alone, all together by each combination, and the greedy choice from the pairs of the best eight, with real decoding."""
    first, _, a, b = _parts(spark, d)
    models = members(first)
    systems = {m.model_id: m for m in models} | {how: Ensemble(models, how) for how in ("max", "avg", "logavg")}
    trace = training.greedy_members(models, a)
    systems["greedy: " + "+".join(trace.chosen)] = Ensemble([m for m in models if m.model_id in trace.chosen])
    return _table(spark, systems, {"a": a, "b": b}, "system string, dev_a double, dev_b double")


@query("final_composition_bleu")
def final_composition_bleu(spark, d):
    """The composition of the final system (two base, one relative, two wide, one reversed), each member of its own nine tenths of the pairs; beam 10 and penalty 1.4."""
    first, _, a, b = _parts(spark, d)
    archs = [x for x, n in ensemble.FINAL_COMPOSITION.items() for _ in range(n)]
    second_wide = iter(("wide", "wider"))
    jobs = [Training(f"{x}-{i}", SPECS[next(second_wide) if x == "wide" else x], uniform(F.col("pair_id"), F.lit(i)) < 0.9) for i, x in enumerate(archs)]
    models = train_many(training.pick(first), jobs)
    return _table(spark, {m.model_id: m for m in models} | {"final": Ensemble(models)}, {"a": a, "b": b}, "system string, dev_a double, dev_b double", mode="beam", beam=10, alpha=1.4)


@query("filtered_training_bleu")
def filtered_training_bleu(spark, d):
    """One model of damaged bitext as it is, one of what the cascade keeps, one of what is really clean."""
    _, _, a, b = _parts(spark, d)
    held = training.keep_table(a.select("tgt").unionByName(b.select("tgt")), "held")
    noted = filters.FilterCascade.bilingual().annotate(bitext.corrupted_bitext(spark, d)).join(held, "tgt", "left_anti")
    split = lambda c: F.split(c, " ")
    src = F.transform(split("src"), lambda t: F.when(t.rlike("^c[0-9a-f]{4}$"), F.substring(t, 1, 4)).otherwise(t))  # the splits' codes have three digits
    rows = noted.select("pair_id", src.alias("src_toks"), split("tgt").alias("tgt_toks"), (F.size("reasons") == 0).alias("passes"), (F.col("truth") == "clean").alias("clean"))
    models = train_many(rows, [Training("unfiltered"), Training("filtered", where=F.col("passes")), Training("clean", where=F.col("clean"))])
    return _table(spark, {m.model_id: m for m in models}, {"a": a, "b": b}, "data string, dev_a double, dev_b double")


@query("ladder")
def ladder(spark, d):
    rows = training.ladder(bitext.domain_bitext(spark, d))
    return spark.createDataFrame(rows, "arch string, stage string, stage_no int, split string, bleu double")


@query("portion_search")
def portion_search(spark, d):
    """The training pairs in six portions, a model of each, the three best by development BLEU."""
    first, _, a, _ = _parts(spark, d)
    models = train_many(bitext.split_portions(first), [Training(str(p), SPECS["base"], F.col("portion") == p) for p in range(6)])
    found = score_many({m.model_id: m for m in models}, {"a": a})
    return ensemble.best_portions(spark.createDataFrame([(p, found[str(p), "a"]) for p in range(6)], "portion int, bleu double"))


@query("lexicon_recovery")
def lexicon_recovery(spark, d):
    """How often a code's most probable word really has that code, by the code's frequency."""
    pairs = bitext.cipher_bitext(spark, d).filter("split = 'train'")
    top = fit_alignment(pairs, 3).withColumn("r", F.row_number().over(Window.partitionBy("f").orderBy(F.desc("p"), "e"))).filter("r = 1 AND f <> '<null>'")
    right = F.col("f") == F.concat(F.lit("c"), F.substring(F.md5(F.lower("e")), 1, 4))
    seen = pairs.select(F.explode("src_toks").alias("f")).groupBy("f").agg(F.count("*").alias("n"))
    return top.join(seen, "f").groupBy(F.floor(F.log2("n")).cast("int").alias("log2_n")).agg(F.count("*").alias("codes"), F.round(F.avg(right.cast("double")), 6).alias("right"))
