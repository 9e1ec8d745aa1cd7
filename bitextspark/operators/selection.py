"""In-domain selection: cross-entropy differences, classifier, exact top k at scale, overlap and contamination."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import ngram
from .lexical import keep_table


def cross_entropy(df: DataFrame, id_col: str, tokens: str, counts: DataFrame, n: int, name: str) -> DataFrame:
    """(id, name): mean -ln P per token under the model of counts."""
    return ngram.scores(df, id_col, tokens, counts, n, "__s").select(id_col, (-F.col("__s")).alias(name))


def bilingual_ce(pairs: DataFrame, models: dict[str, DataFrame], n_src: int = 2, n_tgt: int = 3, form: str = "difference", sides: tuple[str, ...] = ("src", "tgt"), id_col: str = "pair_id") -> DataFrame:
    """(id, ce): per side the in-domain cross entropy less the out-of-domain one, added over sides; small means in-domain.

    models: counts by in_src, out_src, in_tgt, out_tgt. form literal takes, per
    side, the cross entropy between the two models' distributions over the
    sentence's own n-grams instead: sum of -p_in ln p_out.
    """
    out = pairs.select(id_col)
    total = F.lit(0.0)
    for side in sides:
        n = n_src if side == "src" else n_tgt
        if form == "difference":
            a = cross_entropy(pairs, id_col, f"{side}_toks", models[f"in_{side}"], n, f"in_{side}")
            b = cross_entropy(pairs, id_col, f"{side}_toks", models[f"out_{side}"], n, f"out_{side}")
            out = out.join(a, id_col).join(b, id_col)
            total = total + F.col(f"in_{side}") - F.col(f"out_{side}")
        else:
            p = literal_ce(pairs, id_col, f"{side}_toks", models[f"in_{side}"], models[f"out_{side}"], n, f"lit_{side}")
            out = out.join(p, id_col)
            total = total + F.col(f"lit_{side}")
    return out.select(id_col, total.alias("ce"))


def literal_ce(df: DataFrame, id_col: str, tokens: str, inside: DataFrame, outside: DataFrame, n: int, name: str) -> DataFrame:
    grams = ngram.explode_ngrams(df, tokens, n, (id_col,))
    look = lambda c, p: ngram.probabilities(c, n).select("ctx", "tok", F.col("p").alias(p))
    floor = lambda c, p: ngram.floor_probability(c, n).select(F.col("floor").alias(p))
    met = grams.join(look(inside, "pi"), ["ctx", "tok"], "left").join(look(outside, "po"), ["ctx", "tok"], "left").crossJoin(F.broadcast(floor(inside, "fi"))).crossJoin(F.broadcast(floor(outside, "fo")))  # one row each
    return met.groupBy(id_col).agg(F.sum(-F.coalesce("pi", "fi") * F.log(F.coalesce("po", "fo"))).alias(name))


def threshold_refine(df: DataFrame, score: str, k: int, tie: str, lowest: bool = True) -> DataFrame:
    """Exactly the k first rows by (score, tie), without sorting all rows in one task.

    A mergeable sketch gives a score that at least k rows reach (checked by a
    count, and widened where the sketch was short). Only rows within it are
    ranked: all but the last distinct scores are taken whole, and the tie-break
    is needed among the rows at the bound only.
    """
    df = keep_table(df, "scored")  # read several times below
    total = df.count()
    if k >= total:
        return df
    if k <= 0:
        return df.limit(0)
    key = F.col(score) if lowest else -F.col(score)
    share = min(1.0, (k + 1) / total * 1.02 + 0.002)
    while True:
        bound = df.agg(F.percentile_approx(key, F.lit(share), F.lit(10_000)).alias("b")).first()["b"]
        inside = df.filter(key <= bound)
        if share >= 1.0 or inside.count() >= k:
            break
        share = min(1.0, share * 2)
    inside = inside.withColumn("__k", key)
    # the exact k-th score, by counting rows per score among what is left
    by_score = inside.groupBy("__k").agg(F.count("*").alias("n"))
    ranked = by_score.repartitionByRange("__k").sortWithinPartitions("__k").withColumn("__part", F.spark_partition_id())
    before = ranked.groupBy("__part").agg(F.sum("n").alias("n")).collect()  # a number for each partition
    start, at = {}, 0
    for r in sorted(before, key=lambda r: r["__part"]):
        start[r["__part"]] = at
        at += r["n"]
    part = max(p for p, s in start.items() if s < k)
    running = F.sum("n").over(Window.orderBy("__k"))
    last = ranked.filter(F.col("__part") == part).withColumn("r", running + start[part]).filter(F.col("r") >= k).agg(F.min(F.struct("__k", "r", "n")).alias("x")).first()["x"]
    taken = inside.filter(F.col("__k") < last["__k"]).drop("__k")
    need = k - (last["r"] - last["n"])
    return taken.unionByName(inside.filter(F.col("__k") == last["__k"]).orderBy(tie).limit(need).drop("__k"))


def select_lowest(df: DataFrame, score: str, k: int, tie: str = "pair_id") -> DataFrame:
    return threshold_refine(df, score, k, tie, lowest=True)


def select_highest(df: DataFrame, score: str, k: int, tie: str = "pair_id") -> DataFrame:
    return threshold_refine(df, score, k, tie, lowest=False)


def select_similar(df: DataFrame, score: str, in_scores: DataFrame, low: float = 0.05, high: float = 0.95) -> DataFrame:
    """Rows whose score lies within the in-domain rows' quantile band."""
    band = in_scores.agg(F.percentile(score, F.lit(low)).alias("__lo"), F.percentile(score, F.lit(high)).alias("__hi"))
    return df.crossJoin(F.broadcast(band)).filter(F.col(score).between(F.col("__lo"), F.col("__hi"))).drop("__lo", "__hi")


def top_per_group(df: DataFrame, group: str, score: str, k: int, tie: str, highest: bool = True) -> DataFrame:
    """The k best rows of each group by (score, tie), with rank. For k beyond what one task can sort, use threshold_refine per group."""
    order = F.col(score).desc() if highest else F.col(score).asc()
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(group).orderBy(order, F.col(tie)))).filter(F.col("rank") <= k)


def in_domain_union(*selected: tuple[str, DataFrame], id_col: str = "pair_id") -> DataFrame:
    """(id, selectors): every selected pair once, with the sorted names of what has selected it."""
    out = None
    for name, df in selected:
        part = df.select(id_col, F.lit(name).alias("selector"))
        out = part if out is None else out.unionByName(part)
    return out.groupBy(id_col).agg(F.array_sort(F.collect_set("selector")).alias("selectors"))


def selector_overlap(a: DataFrame, b: DataFrame, id_col: str = "pair_id") -> DataFrame:
    """Rows in both, in one and the Jaccard index of two selections."""
    both = a.select(id_col, F.lit(1).alias("a")).distinct().join(b.select(id_col, F.lit(1).alias("b")).distinct(), id_col, "full_outer")
    n = lambda c: F.coalesce(F.sum(c.cast("long")), F.lit(0))
    x, y = F.col("a").isNotNull(), F.col("b").isNotNull()
    return both.agg(n(x & y).alias("n_both"), n(x & ~y).alias("n_first"), n(~x & y).alias("n_second")).withColumn("jaccard", F.round(F.try_divide(F.col("n_both"), F.col("n_both") + F.col("n_first") + F.col("n_second")), 6))


def contamination(corpus: DataFrame, held: DataFrame, text: str = "text") -> DataFrame:
    """corpus rows whose text (by digest) occurs in held."""
    key = lambda c: F.md5(F.lower(c))
    return corpus.join(held.select(key(F.col(text)).alias("__h")).distinct(), key(corpus[text]) == F.col("__h"), "left_semi")


def genre_scores(df: DataFrame, id_col: str, tokens: str, counts: DataFrame, n: int, lm: str = "lm_id") -> DataFrame:
    """(id, lm, score) under all models in one pass: the n-grams are exploded once and met by (model, n-gram)."""
    weights = ngram.FIXED[n]
    models = counts.filter("n = 1").groupBy(lm).agg(F.count("*").alias("v"))
    out = ngram.explode_ngrams(df, tokens, n, (id_col,)).crossJoin(F.broadcast(models))  # one row a model
    c = ngram.with_totals(counts, (lm,)).withColumn("q", F.col("cnt") / F.col("ctx_cnt"))
    p = F.lit(weights[-1]) / F.col("v")
    for order in range(n, 0, -1):
        low = c.filter(F.col("n") == order).select(F.col(lm).alias("__m"), F.col("ctx").alias("__c"), F.col("tok").alias("__t"), F.col("q").alias(f"q{order}"))
        tail = F.lit("") if order == 1 else F.array_join(F.slice(F.split("ctx", " "), F.lit(n - order + 1), F.lit(order - 1)), " ")
        out = out.withColumn("__k", tail).join(low, (F.col(lm) == F.col("__m")) & (F.col("__k") == F.col("__c")) & (F.col("tok") == F.col("__t")), "left").drop("__m", "__c", "__t", "__k")
        p = p + weights[n - order] * F.coalesce(F.col(f"q{order}"), F.lit(0.0))
    return out.groupBy(id_col, lm).agg(F.avg(F.log(p)).alias("score"))


def hash_order(df: DataFrame, k: int, seed: str, id_col: str = "pair_id") -> DataFrame:
    """Random k rows, the same on every cluster: a baseline for selectors."""
    return threshold_refine(df.withColumn("__u", F.md5(F.concat(F.lit(seed), F.col(id_col)))).withColumn("__u", F.conv(F.substring("__u", 1, 12), 16, 10).cast("double")), "__u", k, id_col).drop("__u")


def sample_negatives(pool: DataFrame, share: float, seed: str, id_col: str = "pair_id") -> DataFrame:
    from ..functions.hashing import uniform

    return pool.filter(uniform(F.col(id_col), F.lit(seed)) < share)


def column_or(name: str, other: Column) -> Column:
    return F.coalesce(F.col(name), other)
