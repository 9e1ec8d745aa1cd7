"""Combining step distributions and choosing members; checkpoints; domains."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

STEP = ("sent_id", "hyp_id", "step")
#: Members of the final system by architecture.
FINAL_COMPOSITION = {"base": 2, "relpos": 1, "wide": 2, "revsrc": 1}


def combine(steps: DataFrame, how: str = "logavg", eps: float = 1e-9, keys: tuple[str, ...] = STEP) -> DataFrame:
    """(keys, tok, p): the members' distributions (model_id, keys, tok, logp) as one, normalised over the tokens that any has.

    max, avg, or logavg (geometric mean; a token that a member lacks has eps).
    """
    members = Window.partitionBy(*keys)
    sized = steps.withColumn("__m", F.size(F.collect_set("model_id").over(members)))
    p = F.exp("logp")
    if how == "max":
        x = F.max(p)
    elif how == "avg":
        x = F.sum(p) / F.first("__m")
    elif how == "logavg":
        x = F.exp((F.sum(F.log(F.greatest(p, F.lit(eps)))) + (F.first("__m") - F.count("*")) * F.log(F.lit(eps))) / F.first("__m"))
    else:
        raise ValueError(how)
    out = sized.groupBy(*keys, "tok").agg(x.alias("x"))
    return out.select(*keys, "tok", (F.col("x") / F.sum("x").over(members)).alias("p"))


def combine_weighted(steps: DataFrame, domain_probs: DataFrame, how: str = "linear", eps: float = 1e-9, keys: tuple[str, ...] = STEP) -> DataFrame:
    """Each domain model's probability times the sentence's probability of that domain; steps have domain, domain_probs (sent_id, domain, prob)."""
    met = steps.join(domain_probs, ["sent_id", "domain"])
    over = Window.partitionBy(*keys)
    if how == "linear":
        x = F.sum(F.col("prob") * F.exp("logp"))
    else:
        x = F.exp(F.sum(F.col("prob") * F.log(F.greatest(F.exp("logp"), F.lit(eps)))))
    out = met.groupBy(*keys, "tok").agg(x.alias("x"))
    return out.select(*keys, "tok", (F.col("x") / F.sum("x").over(over)).alias("p"))


def route_hard(steps: DataFrame, domain_probs: DataFrame) -> DataFrame:
    """Only the most probable domain's steps (ties to the smaller domain)."""
    best = domain_probs.groupBy("sent_id").agg(F.min(F.struct((-F.col("prob")).alias("q"), "domain")).alias("x")).select("sent_id", F.col("x.domain").alias("domain"))
    return steps.join(best, ["sent_id", "domain"], "left_semi")


def topk_sample(steps: DataFrame, k: int, seed: str, keys: tuple[str, ...] = STEP) -> DataFrame:
    """(keys, tok): one token a step from its k most likely, by inverse distribution function at a hash; k = 0: from all."""
    from ..functions.hashing import uniform

    order = Window.partitionBy(*keys).orderBy(F.desc("logp"), "tok")
    top = steps.withColumn("__r", F.row_number().over(order))
    top = top.filter(F.col("__r") <= k) if k else top
    upto = F.sum(F.exp("logp")).over(order.rowsBetween(Window.unboundedPreceding, 0))
    total = F.sum(F.exp("logp")).over(Window.partitionBy(*keys))
    top = top.withColumn("__c", upto / total).withColumn("__u", uniform(*(F.col(c) for c in keys), F.lit(seed)))
    # rounding could leave the last share just under one
    return top.filter(F.col("__c") > F.col("__u")).groupBy(*keys).agg(F.min_by("tok", "__r").alias("tok"))


def beam_step(steps: DataFrame, beam: int, keys: tuple[str, ...] = ("sent_id", "step")) -> DataFrame:
    """The beam best continuations (hyp_id, tok) of each sentence by prefix plus step score."""
    order = Window.partitionBy(*keys).orderBy(F.desc("score"), "hyp_id", "tok")
    return steps.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= beam)


def length_norm(logp: Column, length: Column, alpha: float = 1.4, form: str = "power") -> Column:
    return logp / (F.pow(length, F.lit(alpha)) if form == "power" else F.pow((5 + length) / 6, F.lit(alpha)))


@dataclass
class SearchTrace:
    """What a search has looked at: (round, subset, score); chosen is the best subset found and best its score."""

    chosen: tuple[str, ...] = ()
    best: float = float("-inf")
    rows: list[tuple[int, tuple[str, ...], float]] = field(default_factory=list)

    @property
    def evaluations(self) -> int:
        return len(self.rows)


Evaluate = Callable[[list[tuple[str, ...]]], dict[tuple[str, ...], float]]


def _best(scores: dict[tuple[str, ...], float]) -> tuple[str, ...]:
    return min(scores, key=lambda s: (-scores[s], s))


def greedy_ensemble(models: list[str], evaluate: Evaluate, top: int = 8, min_gain: float = 0.0, max_size: int | None = None) -> SearchTrace:
    """Start from the best pair among the top models (best first), then add the model that helps most, as long as the gain is over min_gain.

    evaluate gets all subsets of a round at once and gives their scores, so a round is one job.
    """
    trace = SearchTrace()

    def look(n: int, subsets: list[tuple[str, ...]]) -> tuple[str, ...]:
        scores = evaluate(subsets)
        trace.rows += [(n, s, scores[s]) for s in subsets]
        return _best(scores)

    pairs = [tuple(sorted(p)) for p in combinations(models[:top], 2)]
    if not pairs:
        trace.chosen = tuple(models)
        return trace
    chosen = look(1, pairs)
    trace.chosen, trace.best = chosen, next(v for _, s, v in trace.rows if s == chosen)
    n = 1
    while len(trace.chosen) < (max_size or len(models)):
        n += 1
        more = [tuple(sorted((*trace.chosen, m))) for m in models if m not in trace.chosen]
        if not more:
            break
        found = look(n, more)
        value = next(v for _, s, v in reversed(trace.rows) if s == found)
        if value <= trace.best + min_gain:
            break
        trace.chosen, trace.best = found, value
    return trace


def exhaustive_ensemble(models: list[str], evaluate: Evaluate, max_models: int = 10) -> SearchTrace:
    """All subsets; guarded, as their number doubles with each model."""
    if len(models) > max_models:
        raise ValueError(f"{len(models)} models are {2 ** len(models) - 1} subsets; raise max_models to mean it")
    trace = SearchTrace()
    subsets = [tuple(sorted(c)) for n in range(1, len(models) + 1) for c in combinations(models, n)]
    scores = evaluate(subsets)
    trace.rows = [(len(s), s, scores[s]) for s in subsets]
    trace.chosen = _best(scores)
    trace.best = scores[trace.chosen]
    return trace


def topn_ensemble(models: list[str], evaluate: Evaluate) -> SearchTrace:
    """The n best single models for every n: simply enlarging."""
    trace = SearchTrace()
    subsets = [tuple(sorted(models[:n])) for n in range(1, len(models) + 1)]
    scores = evaluate(subsets)
    trace.rows = [(len(s), s, scores[s]) for s in subsets]
    trace.chosen = _best(scores)
    trace.best = scores[trace.chosen]
    return trace


def rescoring(spark, scores: DataFrame, bleu_stats: DataFrame, how: str = "logavg") -> Evaluate:
    """An evaluator over fixed hypotheses: each subset picks, per sentence, the hypothesis with the best combined model score, and is scored by corpus BLEU.

    scores: (model_id, sent_id, hyp_id, logp); bleu_stats: (sent_id, hyp_id, m1.., t1.., hyp_len, ref_len).
    All subsets of a round are one job; one row a subset comes to the driver.
    """
    from .bleu import from_sums

    def evaluate(subsets: list[tuple[str, ...]]) -> dict[tuple[str, ...], float]:
        rows = [("|".join(s), m, len(s)) for s in subsets for m in s]
        wanted = F.broadcast(spark.createDataFrame(rows, "subset string, model_id string, size int"))  # models only
        x = {"logavg": F.sum("logp") / F.first("size"), "avg": F.log(F.sum(F.exp("logp")) / F.first("size")), "max": F.max("logp")}[how]
        total = scores.join(wanted, "model_id").groupBy("subset", "sent_id", "hyp_id").agg(x.alias("x"))
        best = total.groupBy("subset", "sent_id").agg(F.min(F.struct((-F.col("x")).alias("q"), "hyp_id")).alias("b")).select("subset", "sent_id", F.col("b.hyp_id").alias("hyp_id"))
        sums = best.join(bleu_stats, ["sent_id", "hyp_id"]).groupBy("subset").agg(*(F.sum(c).alias(c) for c in ("m1", "m2", "m3", "m4", "t1", "t2", "t3", "t4", "hyp_len", "ref_len")))
        found = {r["subset"]: r["b"] for r in sums.select("subset", F.round(from_sums(), 9).alias("b")).collect()}
        return {s: found["|".join(s)] for s in subsets}

    return evaluate


def teacher_members(models: DataFrame, student_arch: str) -> DataFrame:
    """The models of every architecture but the student's."""
    return models.filter(F.col("arch") != student_arch)


def diverse_specs(archs: DataFrame, seeds: DataFrame, portions: DataFrame) -> DataFrame:
    """Every architecture with every seed and portion of the data (small frames)."""
    out = archs.join(seeds, F.lit(True)).join(portions, F.lit(True))
    return out.withColumn("model_id", F.concat_ws("-", "arch", "seed", "portion"))


def best_checkpoint(evals: DataFrame) -> DataFrame:
    """(model_id, step, bleu): each model's best validated step, ties to the earlier."""
    best = evals.groupBy("model_id").agg(F.min(F.struct((-F.col("bleu")).alias("q"), "step")).alias("x"))
    return best.select("model_id", "x.step", (-F.col("x.q")).alias("bleu"))


def average_checkpoints(ckpt: DataFrame, last: int = 10) -> DataFrame:
    """(model_id, param, idx, value): mean over each model's last steps. Steps are ranked apart from the parameters, which only meet them."""
    steps = ckpt.select("model_id", "step").distinct()
    recent = steps.withColumn("r", F.row_number().over(Window.partitionBy("model_id").orderBy(F.desc("step")))).filter(F.col("r") <= last).drop("r")
    return ckpt.join(recent, ["model_id", "step"], "left_semi").groupBy("model_id", "param", "idx").agg(F.avg("value").alias("value"))


def best_portions(evals: DataFrame, n: int = 3) -> DataFrame:
    return evals.orderBy(F.desc("bleu"), "portion").limit(n)


def interpolate(general: DataFrame, domain: DataFrame, keys: tuple[str, ...], alpha: float = 0.5, value: str = "p") -> DataFrame:
    """Fine-tuning of a table model: (1 - alpha) general + alpha domain, over the keys of both."""
    g, d = general.select(*keys, F.col(value).alias("__g")), domain.select(*keys, F.col(value).alias("__d"))
    return g.join(d, list(keys), "full_outer").select(*keys, ((1 - alpha) * F.coalesce("__g", F.lit(0.0)) + alpha * F.coalesce("__d", F.lit(0.0))).alias(value))


def lloyd_step(points: DataFrame, centres: DataFrame, id_col: str = "vec_id", vec: str = "x", distance: str = "euclidean") -> tuple[DataFrame, DataFrame]:
    """((id, cluster, distance), (cluster, x, n)): one step of k-means in SQL; centres are few and broadcast. Ties go to the smaller cluster; an empty cluster keeps its centre."""
    unit = lambda c: F.transform(c, lambda v: v / F.sqrt(F.aggregate(c, F.lit(0.0), lambda a, b: a + b * b)))
    p = points.select(id_col, (unit(F.col(vec)) if distance == "cosine" else F.col(vec)).alias("__x"))
    d = F.aggregate(F.zip_with("__x", "__c", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda a, b: a + b)
    met = p.crossJoin(F.broadcast(centres.select("cluster", F.col("x").alias("__c")))).select(id_col, "cluster", d.alias("d"))  # k rows
    best = met.groupBy(id_col).agg(F.min(F.struct("d", "cluster")).alias("b")).select(id_col, F.col("b.cluster").alias("cluster"), F.col("b.d").alias("distance"))
    parts = best.join(p, id_col).select("cluster", F.posexplode("__x").alias("i", "v")).groupBy("cluster", "i").agg(F.avg("v").alias("v"), F.count("*").alias("n"))
    moved = parts.groupBy("cluster").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda s: s["v"]).alias("__m"), F.max("n").alias("n"))
    return best, centres.join(moved, "cluster", "left").select("cluster", F.coalesce("__m", "x").alias("x"), F.coalesce("n", F.lit(0)).alias("n"))


def cluster_domains(vectors: DataFrame, k: int = 2, seed: int = 42, distance: str = "euclidean", restarts: int = 5, features: str = "features"):
    """The MLlib model with the least cost of several seeds, over a column of dense vectors."""
    from pyspark.ml.clustering import KMeans

    best = None
    for i in range(restarts):
        model = KMeans(k=k, seed=seed + i, distanceMeasure=distance, featuresCol=features, predictionCol="domain").fit(vectors)
        if best is None or model.summary.trainingCost < best.summary.trainingCost:
            best = model
    return best


def hashed_vectors(df: DataFrame, tokens: str, dims: int = 64) -> DataFrame:
    """df with vec: words' signed hash buckets, summed and brought to unit length (a stand-in for a sentence encoder). Tokens are hashed in the JVM, summed by Arrow batches."""
    buckets = F.transform(F.col(tokens), lambda t: F.pmod(F.xxhash64(t), F.lit(2 * dims)).cast("int"))

    @F.pandas_udf("array<double>")
    def summed(column: pd.Series) -> pd.Series:
        sizes = column.str.len().fillna(0).astype(int).to_numpy()
        row = np.repeat(np.arange(len(sizes)), sizes)
        at = np.concatenate([np.asarray(x, dtype=np.int64) for x in column if x is not None and len(x)] or [np.zeros(0, dtype=np.int64)])
        # even buckets are positive
        out = np.bincount(row * dims + at // 2, np.where(at % 2 == 0, 1.0, -1.0), minlength=len(sizes) * dims).reshape(-1, dims)
        norm = np.sqrt((out * out).sum(axis=1, keepdims=True))
        return pd.Series(list(np.divide(out, norm, out=np.zeros_like(out), where=norm > 0)))

    return df.withColumn("vec", summed(buckets))


def train_domain_router(df: DataFrame, features: tuple[str, ...] = ("src_toks", "tgt_toks"), label: str = "domain", size: int = 1 << 14):
    """A pipeline that gives each sentence its domain probabilities from hashed tokens; for test time, features=("src_toks",)."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF, VectorAssembler

    parts = [HashingTF(inputCol=f, outputCol=f"__h_{f}", numFeatures=size) for f in features]
    both = VectorAssembler(inputCols=[f"__h_{f}" for f in features], outputCol="__all")
    return Pipeline(stages=[*parts, both, LogisticRegression(featuresCol="__all", labelCol=label, probabilityCol="probability", maxIter=30, regParam=1e-3)]).fit(df)


def partition_by_domain(df: DataFrame, model, path: str) -> None:
    model.transform(df).write.partitionBy("domain").parquet(path)


def style_split(df: DataFrame, origin_lang: str, native: str) -> DataFrame:
    """df with style: native where the target side's language is the origin's, else translated."""
    return df.withColumn("style", F.when(F.col(origin_lang) == native, "native").otherwise("translated"))
