"""Queries of measures, ensembles, domains, checkpoints, kernels and re-ranking, each with its SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import nn, noise
from ..functions.hashing import uniform
from ..operators import bleu, ensemble, ngram, rerank
from ..operators.lexical import keep_table
from ..sources import bitext
from . import sql
from .q_filters import SENTS, sents
from .q_models import counts_sql

QUERIES, SQL = {}, {}


def query(name: str, text: str | None = None):
    def register(f):
        QUERIES[name] = f
        if text:
            SQL[name] = text
        return f

    return register


# hypotheses: the target with words deleted
def _deleted(key: str, p: str = "0.05") -> str:
    return f"list_filter(list_transform(tgt_toks, lambda t, i: CASE WHEN {sql.u(key, 'i - 1', chr(39) + 'del' + chr(39))} >= {p} THEN t END), lambda t: t IS NOT NULL)"


HYP = f"{sql.cipher()}, hy AS (SELECT pair_id AS id, split, genre, {_deleted('pair_id')} AS h, tgt_toks AS r FROM cb)"


def hyps(spark, d):
    cb = bitext.cipher_bitext(spark, d)
    return cb.select("pair_id", "split", "genre", F.array_join(noise.noise_delete(F.col("tgt_toks"), F.col("pair_id")), " ").alias("hyp"), F.col("tgt").alias("ref"), "src_toks", "tgt_toks")


def bleu_stats(src: str, key: str = "id", extra: str = "") -> str:
    """CTEs st (key, extra, m1.., t1.., hl, rl) from src (key, extra, h, r)."""
    grams = " UNION ALL ".join(f"SELECT {key}, {s} AS s, {n} AS n, array_to_string(x[i:i + {n - 1}], ' ') AS g FROM (SELECT {key}, {c} AS x, unnest(range(1, len({c}) - {n - 2})) AS i FROM {src})" for n in range(1, 5) for s, c in ((0, "h"), (1, "r")))
    sums = ", ".join(f"coalesce(sum(least(hc, rc)) FILTER (n = {n}), 0) AS m{n}" for n in range(1, 5))
    totals = ", ".join(f"greatest(len(h) - {n - 1}, 0) AS t{n}" for n in range(1, 5))
    return f"""gr AS ({grams}), gc AS (SELECT {key}, n, g, count(*) FILTER (s = 0) AS hc, count(*) FILTER (s = 1) AS rc FROM gr GROUP BY ALL), gm AS (SELECT {key}, {sums} FROM gc GROUP BY {key}),
st AS (SELECT {src}.{key}, {extra} coalesce(m1, 0) AS m1, coalesce(m2, 0) AS m2, coalesce(m3, 0) AS m3, coalesce(m4, 0) AS m4, {totals}, len(h) AS hl, len(r) AS rl FROM {src} LEFT JOIN gm USING ({key}))"""


_BP = "CASE WHEN hl > rl THEN 1.0 ELSE exp(1 - rl / hl) END"
_SENT_BLEU = f"CASE WHEN hl = 0 OR m1 = 0 THEN 0.0 ELSE 100 * {_BP} * exp((ln(m1 / t1) + ln((m2 + 1) / (t2 + 1)) + ln((m3 + 1) / (t3 + 1)) + ln((m4 + 1) / (t4 + 1))) / 4) END"
_SUMS = ", ".join(f"CAST(sum({c}) AS BIGINT) AS {c}" for c in ("m1", "m2", "m3", "m4", "t1", "t2", "t3", "t4", "hl", "rl"))


@query("corpus_bleu", f"WITH {HYP}, {bleu_stats('hy', 'id', 'split,')}, s AS (SELECT split, {_SUMS} FROM st GROUP BY split) SELECT split, round(100 * {_BP} * exp((ln(m1 / t1) + ln(m2 / t2) + ln(m3 / t3) + ln(m4 / t4)) / 4), 6) AS bleu, hl AS hyp_len, rl AS ref_len FROM s")
def corpus_bleu(spark, d):
    return bleu.corpus_bleu(hyps(spark, d), "pair_id", "hyp", "ref", ("split",), tokenize="split")


def _13a(text: str) -> str:
    """SQL of bleu.tokens_13a."""
    for name, char in (("&quot;", '"'), ("&lt;", "<"), ("&gt;", ">"), ("&amp;", "&")):
        text = f"replace({text}, '{name}', '{char}')"
    text = rf"' ' || regexp_replace({text}, '\s', ' ', 'g') || ' '"
    for pattern, to in ((r"([{-~\[-` -&(-+:-@/])", r" \1 "), (r"([^0-9])([.,])", r"\1 \2 "), (r"([.,])([^0-9])", r" \1 \2"), (r"([0-9])(-)", r"\1 \2 ")):
        text = f"regexp_replace({text}, '{pattern}', '{to}', 'g')"
    return f"list_filter(string_split(trim(regexp_replace({text}, '\\s+', ' ', 'g')), ' '), lambda x: x <> '')"


_SYSTEMS = {"noised cased": ("hyp", "ref"), "noised uncased": ("lower(hyp)", "lower(ref)"), "lowered cased": ("lower(ref)", "ref"), "lowered uncased": ("lower(ref)", "lower(ref)")}
_TOKENS = " UNION ALL ".join(f"SELECT '{name}:' || id AS id, '{name}' AS system, {_13a(h)} AS h, {_13a(r)} AS r FROM texts" for name, (h, r) in _SYSTEMS.items())


@query("corpus_bleu_13a", f"""WITH {HYP}, texts AS (SELECT id, array_to_string(hy.h, ' ') AS hyp, cb.tgt AS ref FROM hy JOIN cb ON cb.pair_id = hy.id), tk AS ({_TOKENS}),
{bleu_stats('tk', 'id', 'system,')}, s AS (SELECT system, {_SUMS} FROM st GROUP BY system) SELECT system, round(100 * {_BP} * exp((ln(m1 / t1) + ln(m2 / t2) + ln(m3 / t3) + ln(m4 / t4)) / 4), 6) AS bleu, hl AS hyp_len, rl AS ref_len FROM s""")
def corpus_bleu_13a(spark, d):
    """Cased and uncased BLEU of the standard tokens, of the noised targets and of lower-cased ones."""
    rows = hyps(spark, d)
    low = rows.withColumn("hyp", F.lower("ref"))
    out = None
    for name, df, fold in (("noised cased", rows, False), ("noised uncased", rows, True), ("lowered cased", low, False), ("lowered uncased", low, True)):
        part = bleu.corpus_bleu(df, "pair_id", "hyp", "ref", lowercase=fold).withColumn("system", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


@query("sentence_bleu", f"WITH {HYP}, {bleu_stats('hy')} SELECT id AS pair_id, round({_SENT_BLEU}, 6) AS bleu FROM st")
def sentence_bleu(spark, d):
    return bleu.sentence_bleu(hyps(spark, d), "pair_id", "hyp", "ref", tokenize="split").select("pair_id", F.round("bleu", 6).alias("bleu"))


@query("dialogue_bleu", f"WITH d AS (SELECT * FROM (SELECT conv_id, turn, role, text AS src, lead(role) OVER w AS nr, lead(text) OVER w AS tgt FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND nr = 'assistant'), hy AS (SELECT conv_id || ':' || turn AS id, list_filter(string_split(src, ' '), lambda x: x <> '') AS h, list_filter(string_split(tgt, ' '), lambda x: x <> '') AS r FROM d), {bleu_stats('hy')} SELECT id, round({_SENT_BLEU}, 6) AS bleu FROM st")
def dialogue_bleu(spark, d):
    """Questions scored against their answers: a negative control."""
    pairs = bitext.dialogue_pairs(spark, d).withColumn("id", F.concat_ws(":", "conv_id", "turn"))
    return bleu.sentence_bleu(pairs, "id", "src", "tgt", tokenize="split").select("id", F.round("bleu", 6).alias("bleu"))


@query("distill_gate", f"WITH {HYP}, {bleu_stats('hy')} SELECT id AS pair_id FROM st WHERE round({_SENT_BLEU}, 9) >= 28")
def distill_gate(spark, d):
    return bleu.gate_by_bleu(hyps(spark, d), "pair_id", "hyp", "ref", 28.0, "split").select("pair_id")


# lineitem stands for the records of training runs: suppliers for models, line numbers for stages, orders for steps, mean quantities for scores
@query("published_ladder", "WITH e AS (SELECT 'm' || l_suppkey AS testset, l_linenumber AS stage_no, round(avg(l_quantity), 4) AS bleu FROM lineitem GROUP BY ALL) SELECT testset, stage_no, bleu, round(bleu - lag(bleu) OVER w, 6) AS gain, round(bleu - first_value(bleu) OVER w, 6) AS total FROM e WINDOW w AS (PARTITION BY testset ORDER BY stage_no)")
def published_ladder(spark, d):
    e = bitext.table(spark, d, "lineitem").groupBy(F.concat(F.lit("m"), F.col("l_suppkey").cast("string")).alias("testset"), F.col("l_linenumber").alias("stage_no")).agg(F.round(F.avg("l_quantity"), 4).alias("bleu"))
    return bleu.ladder(e)


# next-token distributions: bigram models of three groups of sources, for every word before
_STEP = f"""{SENTS.removeprefix('WITH ')}, w AS (SELECT doc_id || ':' || pos AS id, toks, CAST(substr(source, 4) AS INTEGER) % 3 AS model_id FROM s WHERE lang = 'en'),
{counts_sql('c', 'w', 'id', 'toks', 2, 'model_id')},
step AS (SELECT model_id, ctx AS sent_id, tok, q AS p FROM c2), members AS (SELECT sent_id, count(DISTINCT model_id) AS m FROM step GROUP BY sent_id)"""


def steps(spark, d):
    s = sents(spark, d).withColumn("model_id", F.substring("source", 4, 9).cast("int") % 3)
    counts = ngram.fit_counts(s, "toks", 2, ("model_id",)).filter("n = 2")
    c = ngram.with_totals(keep_table(counts, "counts"), ("model_id",))
    return c.select("model_id", F.col("ctx").alias("sent_id"), F.lit(0).alias("hyp_id"), F.lit(0).alias("step"), "tok", F.log(F.col("cnt") / F.col("ctx_cnt")).alias("logp"))


def _combined(how: str) -> str:
    x = {"max": "max(p)", "avg": "sum(p) / any_value(m)", "logavg": "exp((sum(ln(greatest(p, 1e-9))) + (any_value(m) - count(*)) * ln(1e-9)) / any_value(m))"}[how]
    return f"WITH {_STEP}, x AS (SELECT sent_id, tok, {x} AS x FROM step JOIN members USING (sent_id) GROUP BY ALL) SELECT sent_id, tok, round(x / sum(x) OVER (PARTITION BY sent_id), 7) AS p FROM x"


for _how in ("max", "avg", "logavg"):

    @query(f"ensemble_{_how}", _combined(_how))
    def _one(spark, d, how=_how):
        return ensemble.combine(steps(spark, d), how).select("sent_id", "tok", F.round("p", 7).alias("p"))


_ROUTE = f"route AS (SELECT sent_id, domain, w / sum(w) OVER (PARTITION BY sent_id) AS prob FROM (SELECT sent_id, domain, {sql.u('sent_id', 'domain', chr(39) + 'route' + chr(39))} + 0.1 AS w FROM (SELECT DISTINCT sent_id FROM step), (SELECT unnest([0, 1, 2]) AS domain)))"


def routes(step_rows):
    w = step_rows.select("sent_id").distinct().select("sent_id", F.explode(F.array(*map(F.lit, (0, 1, 2)))).alias("domain"))
    w = w.withColumn("w", uniform(F.col("sent_id"), F.col("domain"), F.lit("route")) + 0.1)
    return w.select("sent_id", "domain", (F.col("w") / F.sum("w").over(Window.partitionBy("sent_id"))).alias("prob"))


@query("ensemble_domain_weighted", f"WITH {_STEP}, {_ROUTE}, x AS (SELECT sent_id, tok, sum(prob * p) AS x FROM step JOIN route ON route.sent_id = step.sent_id AND domain = model_id GROUP BY step.sent_id, tok) SELECT sent_id, tok, round(x / sum(x) OVER (PARTITION BY sent_id), 7) AS p FROM x".replace("x AS (SELECT sent_id", "x AS (SELECT step.sent_id AS sent_id"))
def ensemble_domain_weighted(spark, d):
    s = steps(spark, d).withColumnRenamed("model_id", "domain")
    return ensemble.combine_weighted(s, routes(s)).select("sent_id", "tok", F.round("p", 7).alias("p"))


@query("ensemble_domain_log", f"WITH {_STEP}, {_ROUTE}, x AS (SELECT step.sent_id AS sent_id, tok, exp(sum(prob * ln(greatest(p, 1e-9)))) AS x FROM step JOIN route ON route.sent_id = step.sent_id AND domain = model_id GROUP BY step.sent_id, tok) SELECT sent_id, tok, round(x / sum(x) OVER (PARTITION BY sent_id), 7) AS p FROM x")
def ensemble_domain_log(spark, d):
    s = steps(spark, d).withColumnRenamed("model_id", "domain")
    return ensemble.combine_weighted(s, routes(s), "log").select("sent_id", "tok", F.round("p", 7).alias("p"))


@query("route_hard", f"WITH {_STEP}, {_ROUTE}, best AS (SELECT sent_id, min({{'q': -prob, 'd': domain}}).d AS domain FROM route GROUP BY sent_id) SELECT best.sent_id, domain, count(tok) AS n FROM best JOIN step ON step.sent_id = best.sent_id AND model_id = domain GROUP BY ALL")
def route_hard(spark, d):
    s = steps(spark, d).withColumnRenamed("model_id", "domain")
    return ensemble.route_hard(s, routes(s)).groupBy("sent_id", "domain").agg(F.count("*").alias("n"))


@query("topk_sample", f"""WITH {_STEP}, r AS (SELECT model_id, sent_id, tok, p, row_number() OVER (PARTITION BY model_id, sent_id ORDER BY p DESC, tok) AS r FROM step),
c AS (SELECT model_id, sent_id, tok, r, sum(p) OVER (PARTITION BY model_id, sent_id ORDER BY r ROWS UNBOUNDED PRECEDING) / sum(p) OVER (PARTITION BY model_id, sent_id) AS c FROM r WHERE r <= 5)
SELECT model_id, sent_id, arg_min(tok, r) AS tok FROM c WHERE c > {sql.u('model_id', 'sent_id', "'7'")} GROUP BY ALL""")
def topk_sample(spark, d):
    return ensemble.topk_sample(steps(spark, d), 5, "7", ("model_id", "sent_id")).select("model_id", "sent_id", "tok")


@query("unrestricted_sample", f"""WITH {_STEP}, r AS (SELECT model_id, sent_id, tok, p, row_number() OVER (PARTITION BY model_id, sent_id ORDER BY p DESC, tok) AS r FROM step),
c AS (SELECT model_id, sent_id, tok, r, sum(p) OVER (PARTITION BY model_id, sent_id ORDER BY r ROWS UNBOUNDED PRECEDING) / sum(p) OVER (PARTITION BY model_id, sent_id) AS c FROM r)
SELECT model_id, sent_id, arg_min(tok, r) AS tok FROM c WHERE c > {sql.u('model_id', 'sent_id', "'8'")} GROUP BY ALL""")
def unrestricted_sample(spark, d):
    return ensemble.topk_sample(steps(spark, d), 0, "8", ("model_id", "sent_id")).select("model_id", "sent_id", "tok")


@query("beam_step", f"WITH {_STEP} SELECT sent_id, model_id AS hyp_id, tok, CAST(r AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY sent_id ORDER BY round(ln(p) - model_id, 9) DESC, model_id, tok) AS r FROM step) WHERE r <= 10")
def beam_step(spark, d):
    s = steps(spark, d).select("sent_id", F.col("model_id").alias("hyp_id"), "step", "tok", F.round(F.col("logp") - F.col("model_id"), 9).alias("score"))
    return ensemble.beam_step(s, 10).select("sent_id", "hyp_id", "tok", "rank")


@query("length_penalty", f"{SENTS} SELECT doc_id, pos, round(-len(toks) / pow(len(toks), 1.4), 6) AS power, round(-len(toks) / pow((5 + len(toks)) / 6, 1.4), 6) AS gnmt FROM s")
def length_penalty(spark, d):
    n = F.size("toks").cast("double")
    return sents(spark, d, "true").select("doc_id", "pos", F.round(ensemble.length_norm(-n, n), 6).alias("power"), F.round(ensemble.length_norm(-n, n, form="gnmt"), 6).alias("gnmt"))


#: Models that the searches choose from; the greedy one looks at the pairs of the best eight.
MODELS = 10


def rescored(spark, d):
    """(scores by model, hypothesis and sentence; BLEU statistics): five noised versions of each development target under MODELS language models."""
    cb = bitext.cipher_bitext(spark, d)
    dev = cb.filter("split = 'dev_a'")
    out = None
    for r in range(5):
        h = noise.noise_swap(noise.noise_delete(F.col("tgt_toks"), F.concat_ws("#", "pair_id", F.lit(r)), 0.04 * r), F.concat_ws("#", "pair_id", F.lit(r)), 0.1 * (5 - r))
        part = dev.select(F.col("pair_id").alias("sent_id"), F.lit(r).alias("hyp_id"), h.alias("toks"), "tgt")
        out = part if out is None else out.unionByName(part)
    out = keep_table(out.withColumn("key", F.concat_ws("#", "sent_id", "hyp_id")), "hyps")
    train = cb.filter("split = 'train'").withColumn("lm_id", F.concat(F.lit("m"), F.floor(uniform(F.col("pair_id"), F.lit("lm")) * MODELS).cast("int").cast("string")))
    from ..operators.selection import genre_scores

    scores = genre_scores(out, "key", "toks", ngram.fit_counts(train, "tgt_toks", 2, ("lm_id",)), 2)
    scores = scores.withColumnsRenamed({"lm_id": "model_id", "score": "logp"}).withColumn("sent_id", F.split("key", "#")[0]).withColumn("hyp_id", F.split("key", "#")[1].cast("int"))
    stats = bleu.statistics(out.withColumn("hyp", F.array_join("toks", " ")), "key", "hyp", "tgt", "split").join(out.select("key", "sent_id", "hyp_id"), "key")
    return keep_table(scores.drop("key"), "scores"), keep_table(stats.drop("key"), "stats")


def _searches(spark, d, how="logavg"):
    scores, stats = rescored(spark, d)
    evaluate = ensemble.rescoring(spark, scores, stats, how)
    names = [r["model_id"] for r in scores.select("model_id").distinct().orderBy("model_id").collect()]  # MODELS rows
    single = evaluate([(m,) for m in names])
    return sorted(names, key=lambda m: (-single[(m,)], m)), evaluate


def _trace(spark, found: dict[str, ensemble.SearchTrace]):
    rows = [(name, i, n, "+".join(s), v, t.evaluations, s == t.chosen) for name, t in found.items() for i, (n, s, v) in enumerate(t.rows)]
    return spark.createDataFrame(rows, "search string, evaluation int, round int, subset string, bleu double, evaluations int, chosen boolean")


@query("greedy_ensemble_trace")
def greedy_ensemble_trace(spark, d):
    models, evaluate = _searches(spark, d)
    return _trace(spark, {"greedy": ensemble.greedy_ensemble(models, evaluate)})


@query("ensemble_searches")
def ensemble_searches(spark, d):
    """Greedy, exhaustive and simply enlarged ensembles over the same models."""
    models, evaluate = _searches(spark, d)
    return _trace(spark, {"greedy": ensemble.greedy_ensemble(models, evaluate), "exhaustive": ensemble.exhaustive_ensemble(models, evaluate), "topn": ensemble.topn_ensemble(models, evaluate)})


@query("compare_combiners")
def compare_combiners(spark, d):
    scores, stats = rescored(spark, d)
    names = tuple(sorted(r["model_id"] for r in scores.select("model_id").distinct().collect()))
    rows = [(how, next(iter(ensemble.rescoring(spark, scores, stats, how)([names]).values()))) for how in ("max", "avg", "logavg")]
    return spark.createDataFrame(rows, "how string, bleu double")


_EVALS = "evals AS (SELECT 'm' || l_suppkey AS model_id, (l_orderkey % 40 + 1) * 1000 AS step, round(avg(l_quantity), 4) AS bleu FROM lineitem GROUP BY ALL)"


def evals(spark, d):
    """(model_id, step, bleu): validations of as many models as there are suppliers, at 40 steps."""
    t = bitext.table(spark, d, "lineitem")
    return t.groupBy(F.concat(F.lit("m"), F.col("l_suppkey").cast("string")).alias("model_id"), ((F.col("l_orderkey") % 40 + 1) * 1000).alias("step")).agg(F.round(F.avg("l_quantity"), 4).alias("bleu"))


@query("best_checkpoint", f"WITH {_EVALS} SELECT model_id, min({{'q': -bleu, 's': step}}).s AS step, max(bleu) AS bleu FROM evals GROUP BY model_id")
def best_checkpoint(spark, d):
    return ensemble.best_checkpoint(evals(spark, d))


@query("convergence_steps", f"WITH {_EVALS} SELECT model_id, min(step) FILTER (bleu >= 29) AS step FROM evals GROUP BY model_id")
def convergence_steps(spark, d):
    return bleu.steps_to(evals(spark, d), 29.0)


@query("model_ranking", f"WITH {_EVALS}, b AS (SELECT model_id, max(bleu) AS bleu FROM evals GROUP BY model_id) SELECT model_id, bleu, CAST(row_number() OVER (ORDER BY bleu DESC, model_id) AS INTEGER) AS rank FROM b")
def model_ranking(spark, d):
    return bleu.rank_models(evals(spark, d).groupBy("model_id").agg(F.max("bleu").alias("bleu")))


@query("best_portions", f"WITH {_EVALS} SELECT model_id AS portion, max(bleu) AS bleu FROM evals GROUP BY model_id ORDER BY bleu DESC, portion LIMIT 3")
def best_portions(spark, d):
    return ensemble.best_portions(evals(spark, d).groupBy(F.col("model_id").alias("portion")).agg(F.max("bleu").alias("bleu")), 3)


@query("checkpoint_average", """WITH c AS (SELECT 'm' || l_suppkey % 3 AS model_id, l_orderkey % 40 AS step, 'p' || l_linenumber AS param, l_partkey % 5 AS idx, l_quantity AS value FROM lineitem),
st AS (SELECT model_id, step FROM (SELECT model_id, step, row_number() OVER (PARTITION BY model_id ORDER BY step DESC) AS r FROM (SELECT DISTINCT model_id, step FROM c)) WHERE r <= 10)
SELECT model_id, param, idx, round(avg(value), 6) AS value FROM c JOIN st USING (model_id, step) GROUP BY ALL""")
def checkpoint_average(spark, d):
    t = bitext.table(spark, d, "lineitem")
    ckpt = t.select(F.concat(F.lit("m"), (F.col("l_suppkey") % 3).cast("string")).alias("model_id"), (F.col("l_orderkey") % 40).alias("step"), F.concat(F.lit("p"), F.col("l_linenumber").cast("string")).alias("param"), (F.col("l_partkey") % 5).alias("idx"), F.col("l_quantity").alias("value"))
    return ensemble.average_checkpoints(ckpt).withColumn("value", F.round("value", 6))


ARCHS = ("base", "relpos", "wide", "revsrc")
_RUNS = f"runs AS (SELECT DISTINCT {list(ARCHS)}[l_suppkey % 4 + 1] AS arch, CAST(l_orderkey % 3 AS INTEGER) AS seed, CAST(l_partkey % 3 AS INTEGER) AS portion FROM lineitem)"


def runs(spark, d):
    """(arch, seed, portion) of the models that lineitem's records are of."""
    t = bitext.table(spark, d, "lineitem")
    arch = F.element_at(F.array(*map(F.lit, ARCHS)), (F.col("l_suppkey") % 4 + 1).cast("int"))
    return t.select(arch.alias("arch"), (F.col("l_orderkey") % 3).cast("int").alias("seed"), (F.col("l_partkey") % 3).cast("int").alias("portion")).distinct()


@query("diverse_specs", f"WITH {_RUNS} SELECT arch, seed, portion, arch || '-' || seed || '-' || portion AS model_id FROM (SELECT DISTINCT arch FROM runs), (SELECT DISTINCT seed FROM runs), (SELECT DISTINCT portion FROM runs)")
def diverse_specs(spark, d):
    one = lambda name: runs(spark, d).select(name).distinct()
    return ensemble.diverse_specs(one("arch"), one("seed"), one("portion"))


@query("teacher_members", f"WITH {_RUNS} SELECT s.arch AS student, t.arch, t.seed, t.portion FROM (SELECT DISTINCT arch FROM runs) s, runs t WHERE s.arch <> t.arch")
def teacher_members(spark, d):
    """For each architecture that is there, the models of all others."""
    models, out = runs(spark, d), None
    students = [r["arch"] for r in models.select("arch").distinct().collect()]  # four at most
    for student in students:
        part = ensemble.teacher_members(models, student).select(F.lit(student).alias("student"), "arch", "seed", "portion")
        out = part if out is None else out.unionByName(part)
    return out if out is not None else models.select(F.col("arch").alias("student"), "arch", "seed", "portion")


def _lloyd_sql() -> str:
    return """WITH p AS (SELECT vec_id, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS x FROM embeddings), c AS (SELECT CAST(vec_id AS INTEGER) AS cluster, x FROM p WHERE vec_id IN (0, 1)),
d AS (SELECT p.vec_id, c.cluster, list_sum(list_transform(range(1, 65), lambda i: (p.x[i] - c.x[i]) * (p.x[i] - c.x[i]))) AS d FROM p, c), b AS (SELECT vec_id, min({'d': round(d, 9), 'c': cluster}).c AS cluster FROM d GROUP BY vec_id),
m AS (SELECT cluster, i, avg(x[i]) AS v, count(*) AS n FROM b JOIN p USING (vec_id), (SELECT unnest(range(1, 65)) AS i) GROUP BY ALL)
SELECT cluster, CAST(i - 1 AS INTEGER) AS i, round(v, 6) AS v, n FROM m"""


@query("lloyd_iteration", _lloyd_sql())
def lloyd_iteration(spark, d):
    p = bitext.table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    centres = p.filter("vec_id IN (0, 1)").select(F.col("vec_id").cast("int").alias("cluster"), "x")
    _, moved = ensemble.lloyd_step(p, centres)
    return moved.select("cluster", F.posexplode("x").alias("i", "v"), "n").select("cluster", "i", F.round("v", 6).alias("v"), "n")


@query("cluster_domains")
def cluster_domains(spark, d):
    """Two clusters of hashed sentence vectors, against the language that they should not know of."""
    from pyspark.ml.functions import array_to_vector

    s = ensemble.hashed_vectors(sents(spark, d, "true"), "toks").withColumn("features", array_to_vector("vec"))
    model = ensemble.cluster_domains(s, restarts=2)
    return model.transform(s).groupBy("domain", "lang").agg(F.count("*").alias("n"))


@query("domain_router")
def domain_router(spark, d):
    """Routers over both sides and over the source alone, held-out accuracy for the two styles."""
    pairs = bitext.two_style_bitext(spark, d).withColumn("domain", F.col("style").cast("double"))
    train, test = pairs.filter("split = 'train'"), pairs.filter("split = 'dev_a'")
    out = None
    for name, cols in (("both", ("src_toks", "tgt_toks")), ("source", ("src_toks",))):
        model = ensemble.train_domain_router(train, cols)
        part = model.transform(test).agg(F.round(F.avg((F.col("prediction") == F.col("domain")).cast("double")), 6).alias("accuracy"), F.count("*").alias("n")).withColumn("features", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


@query("style_split", f"{SENTS} SELECT CASE WHEN lang = 'en' THEN 'native' ELSE 'translated' END AS style, count(*) AS n FROM s GROUP BY 1")
def style_split(spark, d):
    return ensemble.style_split(bitext.sentences(spark, d), "lang", "en").groupBy("style").agg(F.count("*").alias("n"))


_NBEST = f"{sql.cipher()}, nb AS (SELECT pair_id, CAST(r AS INTEGER) AS hyp_rank, src_toks, tgt_toks, {_deleted('pair_id || ' + chr(39) + '#' + chr(39) + ' || r', '0.04 * r')} AS h FROM cb, (SELECT unnest(range(1, 6)) AS r) WHERE split <> 'train')"


def nbest(spark, d, where="split <> 'train'"):
    cb = bitext.cipher_bitext(spark, d).filter(where)
    out = None
    for r in range(1, 6):
        h = noise.noise_delete(F.col("tgt_toks"), F.concat_ws("#", "pair_id", F.lit(r)), 0.04 * r)
        part = cb.select(F.col("pair_id").alias("sent_id"), F.lit(r).alias("hyp_rank"), "src_toks", h.alias("hyp_toks"), "tgt", "split", F.lit(-0.1 * (6 - r)).alias("nmt"))
        out = part if out is None else out.unionByName(part)
    return out


@query("rerank_apply", f"WITH {_NBEST}, f AS (SELECT pair_id, hyp_rank, round(-0.1 * (6 - hyp_rank) + 0.5 * (len(h) / len(src_toks)) + 0.01 * (len(h) - len(src_toks)), 9) AS s FROM nb) SELECT pair_id AS sent_id, min({{'q': -s, 'r': hyp_rank}}).r AS hyp_rank FROM f GROUP BY pair_id")
def rerank_apply(spark, d):
    rows = rerank.add_features(nbest(spark, d)).withColumn("feats", F.array(F.round(F.col("feats")[0] + 0.5 * F.col("feats")[1] + 0.01 * F.col("feats")[2], 9)))
    return rerank.rerank(rows, [1.0]).select("sent_id", "hyp_rank")


@query("kbmira_bleu")
def kbmira_bleu(spark, d):
    """First-best, re-ranked, random and oracle BLEU on development and test lists; weights come from the development list."""
    rows = nbest(spark, d, "split IN ('dev_a', 'test')").withColumn("hyp", F.array_join("hyp_toks", " ")).withColumn("key", F.concat_ws("#", "sent_id", "hyp_rank"))
    train = bitext.cipher_bitext(spark, d).filter("split = 'train'")
    rows = rerank.add_features(rows, {"lm": ngram.fit_counts(train, "tgt_toks", 2)})
    stats = bleu.statistics(rows, "key", "hyp", "tgt", "split")
    names = ("m1", "m2", "m3", "m4", "t1", "t2", "t3", "t4", "hyp_len", "ref_len")
    sized = stats.withColumn("bleu", bleu.from_sums("add1")).select("key", "bleu", F.array(*(F.col(c).cast("double") for c in names)).alias("stats"))
    rows = keep_table(rows.join(sized, "key"), "nbest")
    dev = rows.filter("split = 'dev_a'")
    weights = rerank.kbmira(dev.select("sent_id", "hyp_rank", "feats", "stats"))
    systems = {"first": rerank.first_best(rows), "reranked": rerank.rerank(rows, weights), "oracle": rerank.oracle_best(rows), "random": rows.withColumn("u", uniform(F.col("key"), F.lit("r"))).withColumn("k", F.row_number().over(Window.partitionBy("sent_id").orderBy("u"))).filter("k = 1")}
    out = None
    for name, df in systems.items():
        part = bleu.corpus_bleu(df, "sent_id", "hyp", "tgt", ("split",), tokenize="split").withColumn("system", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


@query("sinusoid_positions", """WITH e AS (SELECT vec_id, vec_id % 128 AS p, generate_subscripts(embedding, 1) - 1 AS i, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings)
SELECT vec_id, CAST(p AS INTEGER) AS pos, CAST(i AS INTEGER) AS dim, round(x + CASE WHEN i % 2 = 0 THEN sin(p / pow(10000.0, 2 * (i // 2) / 64)) ELSE cos(p / pow(10000.0, 2 * (i // 2) / 64)) END, 6) AS v FROM e""")
def sinusoid_positions(spark, d):
    """Vectors, in sequences of 128, with their position added to each of their 64 dimensions."""
    e = bitext.table(spark, d, "embeddings").select("vec_id", (F.col("vec_id") % 128).cast("int").alias("pos"), F.posexplode("embedding").alias("dim", "x"))
    return e.select("vec_id", "pos", "dim", F.round(F.col("x").cast("double") + nn.sinusoid_column(F.col("pos"), F.col("dim"), 64), 6).alias("v"))


@query("attention_scores", """WITH e AS (SELECT vec_id // 16 AS seq, vec_id % 16 AS t, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS x FROM embeddings),
s AS (SELECT q.seq, q.t AS q, k.t AS k, exp(list_dot_product(q.x, k.x) / 8) AS s FROM e q JOIN e k ON q.seq = k.seq AND k.t <= q.t)
SELECT seq, q, k, round(s / sum(s) OVER (PARTITION BY seq, q), 6) AS w FROM s""")
def attention_scores(spark, d):
    """Causal attention weights within sequences of 16 vectors."""
    e = bitext.table(spark, d, "embeddings").select(F.floor(F.col("vec_id") / 16).alias("seq"), (F.col("vec_id") % 16).alias("t"), F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    k = e.select("seq", F.col("t").alias("k"), F.col("x").alias("y"))
    dot = F.aggregate(F.zip_with("x", "y", lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    s = e.withColumnRenamed("t", "q").join(k, "seq").filter("k <= q").select("seq", "q", "k", F.exp(dot / 8).alias("s"))
    return s.select("seq", "q", "k", F.round(F.col("s") / F.sum("s").over(Window.partitionBy("seq", "q")), 6).alias("w"))


@query("model_kernels")
def model_kernels(spark, d):
    """All architectures' kernels (small sizes) over sequences of 16 vectors, in Arrow batches: checksum, and whether the output is finite."""
    import numpy as np
    import pandas as pd

    from ..operators.translate import SPECS, ModelSpec

    e = bitext.table(spark, d, "embeddings").select(F.floor(F.col("vec_id") / 16).alias("seq"), F.struct("vec_id", "embedding").alias("v")).groupBy("seq").agg(F.array_sort(F.collect_list("v")).alias("v")).select("seq", F.transform("v", lambda v: v["embedding"]).alias("x"))

    def run(frames):
        stacks = {name: nn.Stack(ModelSpec(arch=s.arch, layers=1, heads=4, hidden=64, inner=s.inner // 64, clip=4), name) for name, s in SPECS.items()}
        for frame in frames:
            rows = []
            for seq, x in zip(frame["seq"], frame["x"], strict=True):
                m = np.stack([np.asarray(v, dtype=float) for v in x])
                for name, stack in stacks.items():
                    y = stack(m, m)
                    rows.append((seq, name, round(float(np.abs(y).mean()), 6), bool(np.isfinite(y).all())))
            yield pd.DataFrame(rows, columns=["seq", "arch", "mean_abs", "finite"])

    return e.mapInPandas(run, "seq long, arch string, mean_abs double, finite boolean")


@query("label_smoothing", f"WITH {_STEP}, g AS (SELECT model_id, sent_id, max(ln(p)) AS gold, avg(ln(p)) AS mean FROM step GROUP BY ALL) SELECT model_id, sent_id, round(-(0.9 * gold + 0.1 * mean), 6) AS loss_base, round(-(0.8 * gold + 0.2 * mean), 6) AS loss_wide FROM g")
def label_smoothing(spark, d):
    g = steps(spark, d).groupBy("model_id", "sent_id").agg(F.max("logp").alias("gold"), F.avg("logp").alias("mean"))
    return g.select("model_id", "sent_id", F.round(nn.smoothed_xent_column(F.col("gold"), F.col("mean"), 0.1), 6).alias("loss_base"), F.round(nn.smoothed_xent_column(F.col("gold"), F.col("mean"), 0.2), 6).alias("loss_wide"))
