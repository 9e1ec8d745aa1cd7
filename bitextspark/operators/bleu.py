"""BLEU, cased by default, from additive counts; corpus and sentence level, ladders and rankings."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .batched import row_matches

ORDERS = 4


def tokens_13a(text: Column, lowercase: bool = False) -> Column:
    """The 13a tokens of a text: entities decoded, marks and symbols apart, periods and commas apart unless between digits."""
    t = F.lower(text) if lowercase else text
    for name, char in (("&quot;", '"'), ("&lt;", "<"), ("&gt;", ">"), ("&amp;", "&")):
        t = F.replace(t, F.lit(name), F.lit(char))
    t = F.concat(F.lit(" "), F.regexp_replace(t, r"\s", " "), F.lit(" "))
    t = F.regexp_replace(t, r"([\{-\~\[-\` -\&\(-\+\:-\@\/])", " $1 ")
    t = F.regexp_replace(t, r"([^0-9])([\.,])", "$1 $2 ")
    t = F.regexp_replace(t, r"([\.,])([^0-9])", " $1 $2")
    t = F.regexp_replace(t, r"([0-9])(-)", "$1 $2 ")
    return F.filter(F.split(F.trim(F.regexp_replace(t, r"\s+", " ")), " "), lambda x: x != "")


def split_tokens(text: Column, lowercase: bool = False) -> Column:
    return F.filter(F.split(F.lower(text) if lowercase else text, " "), lambda x: x != "")


#: Names of a row's counts: clipped matches and totals of each order, lengths.
SUMS = (*(f"m{n}" for n in range(1, ORDERS + 1)), *(f"t{n}" for n in range(1, ORDERS + 1)), "hyp_len", "ref_len")


def row_statistics(hyp: list[str], ref: list[str]) -> list[int]:
    """SUMS of one sentence."""
    matches = []
    for n in range(1, ORDERS + 1):
        have, want = (Counter(zip(*(x[i:] for i in range(n)), strict=False)) for x in (hyp, ref))
        matches.append(sum((have & want).values()))
    return [*matches, *(max(0, len(hyp) - n) for n in range(ORDERS)), len(hyp), len(ref)]


def statistics(df: DataFrame, id_col: str, hyp: str, ref: str, tokenize: str = "13a", lowercase: bool = False) -> DataFrame:
    """(id, m1..m4, t1..t4, hyp_len, ref_len): clipped matches, totals and lengths of every row; they add over rows and partitions.

    A row is counted by itself, in Arrow batches: no n-gram is shuffled.
    """
    tok = tokens_13a if tokenize == "13a" else split_tokens
    base = df.select(F.col(id_col).alias("id"), tok(F.coalesce(F.col(hyp), F.lit("")), lowercase).alias("h"), tok(F.coalesce(F.col(ref), F.lit("")), lowercase).alias("r"))

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column("id"), *(pa.array(c) for c in row_matches(batch.column("h"), batch.column("r")).T)], names=["id", *SUMS])

    kind = base.schema["id"].dataType.simpleString()
    return base.mapInArrow(run, f"id {kind}, " + ", ".join(f"{c} long" for c in SUMS)).withColumnRenamed("id", id_col)


def from_sums(smooth: str = "exp") -> Column:
    """BLEU in percent from columns m1..m4, t1..t4, hyp_len, ref_len.

    exp: the k-th order without a match counts 1 / 2 ** k matches; add1: one is
    added to matches and totals from the second order on. An empty hypothesis,
    or one without any total of an order, has 0.
    """
    logs, zeros = F.lit(0.0), F.lit(0)
    for n in range(1, ORDERS + 1):
        m, t = F.col(f"m{n}").cast("double"), F.col(f"t{n}").cast("double")
        if smooth == "add1" and n > 1:
            m, t = m + 1, t + 1
        zeros = zeros + F.when(m == 0, 1).otherwise(0)
        p = F.when(m == 0, F.when(F.lit(smooth == "exp"), F.lit(1.0) / (F.pow(F.lit(2.0), zeros) * t)).otherwise(0.0)).otherwise(m / t) if smooth == "exp" else m / t
        logs = logs + F.when(t > 0, F.log(p))
    penalty = F.when(F.col("hyp_len") > F.col("ref_len"), 1.0).otherwise(F.exp(1 - F.col("ref_len") / F.col("hyp_len")))
    return F.when(F.col("hyp_len") > 0, F.coalesce(100 * penalty * F.exp(logs / ORDERS), F.lit(0.0))).otherwise(0.0)


def sentence_bleu(df: DataFrame, id_col: str, hyp: str, ref: str, tokenize: str = "13a", lowercase: bool = False) -> DataFrame:
    """(id, bleu) of every row, with add-one smoothing."""
    return statistics(df, id_col, hyp, ref, tokenize, lowercase).select(id_col, from_sums("add1").alias("bleu"))


def corpus_bleu(df: DataFrame, id_col: str, hyp: str, ref: str, group: tuple[str, ...] = (), tokenize: str = "13a", lowercase: bool = False, smooth: str = "exp") -> DataFrame:
    """(group, bleu, hyp_len, ref_len): one value a group, from sums over its rows."""
    stats = statistics(df.withColumn("__key", F.struct(F.col(id_col).alias("__id"), *group)), "__key", hyp, ref, tokenize, lowercase)
    sums = stats.groupBy(*(F.col(f"__key.{g}").alias(g) for g in group)).agg(*(F.sum(c).alias(c) for c in SUMS))
    return sums.select(*group, F.round(from_sums(smooth), 6).alias("bleu"), "hyp_len", "ref_len")


def _smoothed(counts: np.ndarray) -> np.ndarray:
    """BLEU of sentences from their SUMS, one added to matches and totals from the second order on."""
    out, some = np.zeros(len(counts)), np.flatnonzero((counts[:, 2 * ORDERS] > 0) & (counts[:, 0] > 0))
    x = counts[some]
    logs = np.log(x[:, 0] / x[:, ORDERS])
    for n in range(1, ORDERS):
        logs = logs + np.log((x[:, n] + 1) / (x[:, ORDERS + n] + 1))
    out[some] = 100 * np.minimum(1.0, np.exp(1 - x[:, -1] / x[:, -2])) * np.exp(logs / ORDERS)
    return out


def gate_by_bleu(df: DataFrame, id_col: str, hyp: str, ref: str, least: float | None = 28.0, tokenize: str = "13a") -> DataFrame:
    """df without the rows whose sentence BLEU is lower than least; None keeps all. Rows are judged one by one, nothing is shuffled."""
    if least is None:
        return df
    tok = tokens_13a if tokenize == "13a" else split_tokens

    columns = df.columns

    def run(batches):
        for batch in batches:
            scores = np.round(_smoothed(row_matches(batch.column("__h"), batch.column("__r"))), 9)
            yield batch.select(columns).filter(pa.array(scores >= least))

    judged = df.select("*", tok(F.coalesce(F.col(hyp), F.lit(""))).alias("__h"), tok(F.coalesce(F.col(ref), F.lit(""))).alias("__r"))
    return judged.mapInArrow(run, df.schema)


def ladder(evals: DataFrame, group: str = "testset", order: str = "stage_no") -> DataFrame:
    """evals with gain over the stage before and total gain."""
    by = Window.partitionBy(group).orderBy(order)
    return evals.withColumns({"gain": F.round(F.col("bleu") - F.lag("bleu").over(by), 6), "total": F.round(F.col("bleu") - F.first("bleu").over(by), 6)})


def rank_models(evals: DataFrame) -> DataFrame:
    return evals.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("bleu"), "model_id")))  # a row for each model


def steps_to(evals: DataFrame, target: float) -> DataFrame:
    """(model_id, step): the first step that reaches the target, null if none does."""
    return evals.groupBy("model_id").agg(F.min(F.when(F.col("bleu") >= target, F.col("step"))).alias("step"))
