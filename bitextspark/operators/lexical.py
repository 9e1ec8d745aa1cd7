"""Word alignment by EM over a lexical table, its scores and links."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

NULL = "<null>"


def keep_table(df: DataFrame, tag: str) -> DataFrame:
    """Write to the shared checkpoint folder and read back; without such a folder (tests), a reliable checkpoint in a folder of our own."""
    spark = df.sparkSession
    base = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if not base:
        import tempfile

        base = spark.sparkContext.getCheckpointDir() or tempfile.mkdtemp(prefix="bitextspark-")
    path = f"{base.rstrip('/')}/kept-{uuid.uuid4().hex}/{tag}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def products(pairs: DataFrame, src: str = "src_toks", tgt: str = "tgt_toks", id_col: str = "pair_id", prior: str = "uniform", tension: float = 4.0, null_p: float = 0.08) -> DataFrame:
    """(id, j, e, f, w): every target token with every source token and the empty word, and the prior's weight (a pair's tokens only)."""
    e = pairs.select(id_col, F.size(src).alias("n"), F.size(tgt).alias("m"), F.col(src).alias("fs"), F.posexplode(tgt).alias("j", "e"))
    out = e.select(id_col, "j", "e", "n", "m", F.posexplode(F.concat(F.array(F.lit(NULL)), "fs")).alias("i", "f"))
    if prior == "uniform":
        return out.select(id_col, "j", "e", "f", F.lit(1.0).alias("w"))
    w = F.exp(-tension * F.abs(F.col("i") / F.col("n") - (F.col("j") + 1) / F.col("m")))
    total = Window.partitionBy(id_col, "j")
    out = out.withColumn("w", F.when(F.col("i") > 0, w).otherwise(0.0))
    return out.select(id_col, "j", "e", "f", F.when(F.col("i") == 0, F.lit(null_p)).otherwise((1 - null_p) * F.col("w") / F.sum("w").over(total)).alias("w"))


def em_round(prod: DataFrame, lex: DataFrame | None, id_col: str = "pair_id") -> DataFrame:
    """(f, e, p) after one round; lex None stands for a uniform table."""
    t = prod.withColumn("x", F.col("w")) if lex is None else prod.join(lex, ["f", "e"]).withColumn("x", F.col("w") * F.col("p"))
    post = t.withColumn("c", F.col("x") / F.sum("x").over(Window.partitionBy(id_col, "j")))
    counts = post.groupBy("f", "e").agg(F.sum("c").alias("c"))
    return counts.select("f", "e", (F.col("c") / F.sum("c").over(Window.partitionBy("f"))).alias("p"))


def fit_alignment(pairs: DataFrame, iters: int = 5, prior: str = "uniform", null_p: float = 0.08, tension: float = 4.0, id_col: str = "pair_id", prune: float = 0.0) -> DataFrame:
    """(f, e, p): a lexical table by iters rounds of EM, over buckets of target tokens (aligned.Alignment).

    With prune (entries below it go after each round, the rest is normalised
    again) products of tokens are written as rows; fit it on a hash sample then.
    """
    if not prune:
        from .aligned import Alignment

        return Alignment(pairs, iters, prior, null_p, tension, id_col).table()
    prod = keep_table(products(pairs, id_col=id_col, prior=prior, tension=tension, null_p=null_p), "products")
    lex = None
    for i in range(iters):
        lex = em_round(prod, lex, id_col)
        if prune:
            lex = lex.filter(F.col("p") >= prune).select("f", "e", (F.col("p") / F.sum("p").over(Window.partitionBy("f"))).alias("p"))
        lex = keep_table(lex, f"lex-{i}")
    return lex


def alignment_score(pairs: DataFrame, lex: DataFrame, id_col: str = "pair_id", floor: float = 1e-9, prior: str = "uniform") -> DataFrame:
    """(id, score): mean over target tokens of ln of the mean lexical probability (or the prior's mean)."""
    prod = products(pairs, id_col=id_col, prior=prior)
    per = prod.join(lex, ["f", "e"], "left").groupBy(id_col, "j").agg((F.sum(F.col("w") * F.coalesce("p", F.lit(0.0))) / F.sum("w")).alias("q"))
    return per.groupBy(id_col).agg(F.avg(F.log(F.greatest("q", F.lit(floor)))).alias("score"))


def symmetric_score(pairs: DataFrame, forward: DataFrame, backward: DataFrame, id_col: str = "pair_id") -> DataFrame:
    """Mean of both directions' scores; backward is a table fitted with the sides exchanged."""
    flipped = pairs.select(id_col, F.col("tgt_toks").alias("src_toks"), F.col("src_toks").alias("tgt_toks"))
    a = alignment_score(pairs, forward, id_col).withColumnRenamed("score", "a")
    return a.join(alignment_score(flipped, backward, id_col), id_col).select(id_col, ((F.col("a") + F.col("score")) / 2).alias("score"))


def viterbi_links(pairs: DataFrame, lex: DataFrame, id_col: str = "pair_id") -> DataFrame:
    """(id, j, e, f, p): the most probable source token of each target token, ties to the smaller token."""
    met = products(pairs, id_col=id_col).join(lex, ["f", "e"])
    best = met.groupBy(id_col, "j", "e").agg(F.min(F.struct(F.round(-F.col("p"), 9).alias("q"), "f")).alias("x"))
    return best.select(id_col, "j", "e", "x.f", (-F.col("x.q")).alias("p"))


def log_likelihood(pairs: DataFrame, lex: DataFrame, id_col: str = "pair_id") -> float:
    per = products(pairs, id_col=id_col).join(lex, ["f", "e"], "left").groupBy(id_col, "j").agg(F.avg(F.coalesce("p", F.lit(0.0))).alias("q"))
    return per.agg(F.sum(F.log(F.greatest("q", F.lit(1e-12)))).alias("x")).first()["x"]
