"""Re-ranking of n-best lists: features, k-best batch MIRA, application, bounds."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def feat_length(src: Column, hyp: Column) -> tuple[Column, Column]:
    """Length ratio and difference of token arrays."""
    a, b = F.size(src).cast("double"), F.size(hyp).cast("double")
    return F.coalesce(F.try_divide(b, a), F.lit(0.0)), b - a


def add_features(nbest: DataFrame, lms: dict[str, DataFrame] | None = None, src: str = "src_toks", hyp: str = "hyp_toks", n: int = 2) -> DataFrame:
    """nbest (sent_id, hyp_rank, src, hyp, nmt) with feats, an array of doubles: model score, length ratio, length difference, then one score a language model."""
    from . import ngram

    ratio, difference = feat_length(F.col(src), F.col(hyp))
    out, names = nbest.withColumn("__key", F.concat_ws("#", "sent_id", "hyp_rank")), []
    for name, counts in (lms or {}).items():
        out = out.join(ngram.scores(out.select("__key", hyp), "__key", hyp, counts, n, f"__{name}"), "__key", "left")
        names.append(F.coalesce(f"__{name}", F.lit(-20.0)))
    return out.withColumn("feats", F.array(F.col("nmt"), ratio, difference, *names)).drop("__key", *(f"__{x}" for x in lms or {}))


def _bleu(stats: np.ndarray) -> float:
    m, t, hyp, ref = stats[:4] + np.array([0, 1, 1, 1]), stats[4:8] + np.array([0, 1, 1, 1]), stats[8], stats[9]
    if hyp == 0 or m[0] == 0:
        return 0.0
    return float(math.exp(np.log(m / t).mean()) * min(1.0, math.exp(1 - ref / hyp)))


def mira_epoch(sentences: list[tuple[np.ndarray, np.ndarray]], w: np.ndarray, c: float, decay: float, background: np.ndarray) -> tuple[np.ndarray, np.ndarray, int, np.ndarray]:
    """One pass over (features, BLEU statistics) of sentences: sum of visited weights, last weights, their number, background.

    Hope has the largest model score plus BLEU, fear the largest model score
    less BLEU; a clipped step moves the margin between them to their BLEU gap.
    BLEU is that of the sentence on top of a decaying background.
    """
    total, n = np.zeros_like(w), 0
    for f, s in sentences:
        size = max(1.0, background[8] / max(1.0, background[9]) * s[0, 9] + s[0, 9])
        b = np.array([_bleu(background + x) for x in s]) * size
        model = f @ w
        hope, fear = int(np.argmax(model + b)), int(np.argmax(model - b))
        delta, gap = f[hope] - f[fear], b[hope] - b[fear]
        square = float(delta @ delta)
        if square > 0 and gap - float(w @ delta) > 0:
            w = w + min(c, (gap - float(w @ delta)) / square) * delta
        background = decay * (background + s[int(np.argmax(f @ w))])
        total, n = total + w, n + 1
    return total, w, n, background


def kbmira(nbest: DataFrame, c: float = 0.01, epochs: int = 20, decay: float = 0.999, shards: int = 1) -> np.ndarray:
    """Weights from (sent_id, hyp_rank, feats, stats): the mean of all weights visited.

    With one shard the pass is sequential and exact. With more, each shard
    passes over its own sentences from the common weights, and the shards' last
    weights are averaged between epochs; only weights come to the driver.
    """
    grouped = nbest.groupBy("sent_id").agg(F.array_sort(F.collect_list(F.struct("hyp_rank", "feats", "stats"))).alias("h"))
    held = grouped.withColumn("shard", F.pmod(F.xxhash64(F.lit("shard"), "sent_id"), F.lit(shards)).cast("int")).select("shard", "sent_id", F.transform("h", lambda x: x["feats"]).alias("f"), F.transform("h", lambda x: x["stats"]).alias("s"))
    size = len(nbest.select("feats").first()["feats"])
    scale = np.array(nbest.select(*(F.stddev_pop(F.get("feats", F.lit(i))).alias(f"s{i}") for i in range(size))).first(), dtype=float)
    scale = np.where(scale > 0, scale, 1.0)
    w, total, visited = np.zeros(size), np.zeros(size), 0

    def epoch(start: np.ndarray):
        def run(frame: pd.DataFrame) -> pd.DataFrame:
            frame = frame.sort_values("sent_id")
            sentences = [(np.stack([np.asarray(x, dtype=float) for x in f]) / scale, np.stack([np.asarray(x, dtype=float) for x in s])) for f, s in zip(frame["f"], frame["s"], strict=True)]
            added, last, n, _ = mira_epoch(sentences, start.copy(), c, decay, np.zeros(10))
            return pd.DataFrame({"total": [added.tolist()], "last": [last.tolist()], "n": [n]})

        return run

    for _ in range(epochs):
        made = held.groupBy("shard").applyInPandas(epoch(w), "total array<double>, last array<double>, n long").collect()  # a row a shard
        if not made:
            break
        w = np.mean([r["last"] for r in made], axis=0)
        total, visited = total + np.sum([r["total"] for r in made], axis=0), visited + sum(r["n"] for r in made)
    return total / max(1, visited) / scale


def rerank(nbest: DataFrame, weights, id_col: str = "sent_id") -> DataFrame:
    """The hypothesis with the largest weighted sum of each sentence, ties to the better rank."""
    score = F.aggregate(F.zip_with("feats", F.array(*(F.lit(float(x)) for x in weights)), lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    best = nbest.groupBy(id_col).agg(F.min(F.struct((-score).alias("q"), "hyp_rank")).alias("b")).select(F.col(id_col).alias("__i"), F.col("b.hyp_rank").alias("__r"))
    return nbest.join(best, (nbest[id_col] == F.col("__i")) & (nbest["hyp_rank"] == F.col("__r")), "left_semi")


def first_best(nbest: DataFrame) -> DataFrame:
    return nbest.filter("hyp_rank = 1")


def oracle_best(nbest: DataFrame, bleu: str = "bleu", id_col: str = "sent_id") -> DataFrame:
    """The hypothesis with the best sentence BLEU: what no re-ranker can beat by this measure."""
    best = nbest.groupBy(id_col).agg(F.min(F.struct((-F.col(bleu)).alias("q"), "hyp_rank")).alias("b")).select(F.col(id_col).alias("__i"), F.col("b.hyp_rank").alias("__r"))
    return nbest.join(best, (nbest[id_col] == F.col("__i")) & (nbest["hyp_rank"] == F.col("__r")), "left_semi")
