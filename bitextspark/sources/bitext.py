"""Sentence pairs derived from the given tables: cipher bitext, its corrupted and two-style forms, dialogue pairs, page texts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import pair_id, uniform
from ..functions.text import segment, words

SPLITS = (("train", 0.80), ("dev_a", 0.85), ("dev_b", 0.90), ("test", 0.95), ("spare", 1.0))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sentences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, lang, source, pos, text) of documents."""
    return segment(table(spark, sf_dir, "documents"))


def codes(tokens: Column, digits: int) -> Column:
    return F.transform(tokens, lambda t: F.concat(F.lit("c"), F.substring(F.md5(F.lower(t)), 1, digits)))


def swapped(coded: Column) -> Column:
    """Neighbours 2j and 2j + 1 change places where a hash of both says so (one in four): local reordering that can be learned."""

    def at(_: Column, i: Column) -> Column:
        j = F.floor(i / 2) * 2
        other = F.when(i % 2 == 0, i + 1).otherwise(i - 1)
        swap = (other < F.size(coded)) & (F.substring(F.md5(F.concat(F.get(coded, j.cast("int")), F.get(coded, (j + 1).cast("int")))), 1, 1) < "4")
        return F.get(coded, F.when(swap, other).otherwise(i).cast("int"))

    return F.transform(coded, at)


def split_of(tgt: Column) -> Column:
    u, out = uniform(tgt, "split"), F.lit(SPLITS[-1][0])
    for name, below in reversed(SPLITS[:-1]):
        out = F.when(u < below, F.lit(name)).otherwise(out)
    return out


def cipher_bitext(spark: SparkSession, sf_dir: str, digits: int = 4, longest: int = 120) -> DataFrame:
    """(pair_id, src, tgt, src_toks, tgt_toks, genre, split): English sentences and their cipher, one row per distinct sentence.

    A token's code is the head of its MD5, so equal words have one code and,
    with few digits, several words share one. split depends on the sentence
    alone, so equal sentences never lie in two splits.
    """
    return cipher_pairs(sentences(spark, sf_dir).filter("lang = 'en'").select("text", F.col("source").alias("genre")), digits, longest)


def cipher_pairs(sents: DataFrame, digits: int = 4, longest: int = 120) -> DataFrame:
    """The cipher of any sentences (text, genre)."""
    en = sents.groupBy("text").agg(F.min("genre").alias("genre"))
    en = en.withColumn("tgt_toks", words(F.col("text"))).filter(F.size("tgt_toks").between(3, longest))
    out = en.withColumn("coded", codes(F.col("tgt_toks"), digits)).withColumn("src_toks", swapped(F.col("coded")))
    out = out.select(F.array_join("src_toks", " ").alias("src"), F.col("text").alias("tgt"), "src_toks", "tgt_toks", "genre", split_of(F.col("text")).alias("split"))
    return out.select(pair_id(F.col("src"), F.col("tgt")).alias("pair_id"), "*")


def two_style_bitext(spark: SparkSession, sf_dir: str, digits: int = 4) -> DataFrame:
    """Cipher bitext with column style: in style 1 frequent target words have another form and a source cue word stands in front."""
    pairs = cipher_bitext(spark, sf_dir, digits).withColumn("style", (uniform(F.col("genre"), F.col("tgt"), F.lit("style")) < 0.5).cast("int"))
    styled = F.transform("tgt_toks", lambda t: F.when((F.length(t) <= 3) & (F.col("style") == 1), F.concat(t, F.lit("~"))).otherwise(t))
    cue = F.when(F.col("style") == 1, F.array(F.lit("cue1"))).otherwise(F.array(F.lit("cue0")))
    out = pairs.withColumn("tgt_toks", styled).withColumn("src_toks", F.concat(cue, "src_toks"))
    return out.withColumn("tgt", F.array_join("tgt_toks", " ")).withColumn("src", F.array_join("src_toks", " ")).withColumn("pair_id", pair_id(F.col("src"), F.col("tgt")))


def domain_bitext(spark: SparkSession, sf_dir: str, digits: int = 3, inside: float = 0.15, inside_mono: float = 0.5) -> DataFrame:
    """Cipher bitext of a general and an in-domain register, with columns style (0, 1; 2 for general) and part (bitext, mono; null outside the training split).

    General pairs write short target words in a form of their own. In-domain
    pairs come in the two styles of two_style_bitext, each with its cue word
    in the source. Training bitext is mostly general, monolingual text (the
    other half of the training split) less so; the other splits are in-domain.
    """
    base = cipher_bitext(spark, sf_dir, digits)
    u = lambda what: uniform(F.col("genre"), F.col("tgt"), F.lit(what))
    part = F.when(F.col("split") == "train", F.when(u("part") < 0.5, "bitext").otherwise("mono"))
    share = F.when(part == "bitext", inside).when(part == "mono", inside_mono).otherwise(1.0)
    style = F.when(u("domain") < share, (u("style") < 0.5).cast("int")).otherwise(2)
    out = base.withColumn("part", part).withColumn("style", style)
    form = F.element_at(F.array(F.lit(""), F.lit("~"), F.lit("^")), F.col("style") + 1)
    styled = F.transform("tgt_toks", lambda t: F.when(F.length(t) <= 3, F.concat(t, form)).otherwise(t))
    cue = F.when(F.col("style") == 2, F.array().cast("array<string>")).otherwise(F.array(F.concat(F.lit("cue"), F.col("style").cast("string"))))
    out = out.withColumn("tgt_toks", styled).withColumn("src_toks", F.concat(cue, "src_toks"))
    return out.withColumn("tgt", F.array_join("tgt_toks", " ")).withColumn("src", F.array_join("src_toks", " ")).withColumn("pair_id", pair_id(F.col("src"), F.col("tgt")))


def corrupted_bitext(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pair_id, src, tgt, truth): cipher bitext of which about a quarter is damaged, each kind at three in a hundred."""
    pairs = cipher_bitext(spark, sf_dir).select("src", "tgt", "src_toks")
    u = F.floor(uniform(F.col("tgt"), F.lit("corrupt")) * 100)
    kinds = ["mispaired", "truncated", "copied", "wrong_lang", "markup", "long_token", "overlong", "duplicate"]
    kind = F.lit("clean")
    for i, name in enumerate(kinds):
        kind = F.when((u >= 3 * i) & (u < 3 * i + 3), F.lit(name)).otherwise(kind)
    near = Window.partitionBy(F.substring(F.md5("tgt"), 1, 2)).orderBy(F.md5("tgt"))
    pairs = pairs.withColumn("truth", kind).withColumn("h", F.substring(F.md5("tgt"), 1, 3)).withColumn("next", F.lead("tgt").over(near))
    german = sentences(spark, sf_dir).filter("lang = 'de' AND text LIKE '% % %'").groupBy(F.substring(F.md5("text"), 1, 3).alias("h")).agg(F.min("text").alias("german"))
    pairs = pairs.join(german, "h", "left")
    t = F.col("truth")
    truth = F.when((t == "wrong_lang") & F.col("german").isNull(), "clean").when((t == "mispaired") & F.col("next").isNull(), "clean").otherwise(t)
    pairs = pairs.withColumn("truth", truth)
    src = F.when(t == "truncated", F.array_join(F.slice("src_toks", 1, F.greatest(F.lit(1), F.floor(F.size("src_toks") / 5).cast("int"))), " ")).when(t == "copied", F.col("tgt")).otherwise(F.col("src"))
    tgt = (
        F.when(t == "mispaired", F.col("next")).when(t == "wrong_lang", F.col("german")).when(t == "markup", F.concat(F.lit("<b>"), "tgt", F.lit("</b>")))
        .when(t == "long_token", F.concat("tgt", F.lit(" "), F.repeat(F.lit("x"), 45))).when(t == "overlong", F.array_join(F.array_repeat("tgt", 45), " ")).otherwise(F.col("tgt"))
    )
    out = pairs.select(src.alias("src"), tgt.alias("tgt"), "truth", F.explode(F.when(t == "duplicate", F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0)))).alias("copy"))
    return out.select(pair_id(F.col("src"), F.col("tgt")).alias("pair_id"), "src", "tgt", "truth", "copy")


def dialogue_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(conv_id, turn, src, tgt): a user's turn and the assistant's answer behind it."""
    by = Window.partitionBy("conv_id").orderBy("turn")
    rows = table(spark, sf_dir, "conversations").withColumn("next_role", F.lead("role").over(by)).withColumn("tgt", F.lead("text").over(by))
    return rows.filter("role = 'user' AND next_role = 'assistant'").select("conv_id", "turn", F.col("text").alias("src"), "tgt")


def split_portions(pairs: DataFrame, n: int = 6, seed: str = "portion") -> DataFrame:
    """pairs with portion in [0, n), by hash."""
    return pairs.withColumn("portion", F.floor(uniform(F.col("pair_id"), F.lit(seed)) * n).cast("int"))


def mixture_sample(parts: dict[str, DataFrame], rates: dict[str, float], seed: str = "mix") -> DataFrame:
    """Union of the parts (pair_id, src, tgt), each thinned to its rate by hash, with column origin."""
    out = None
    for name, df in parts.items():
        thin = df.filter(uniform(F.col("pair_id"), F.lit(seed), F.lit(name)) < rates.get(name, 1.0)).select("pair_id", "src", "tgt", F.lit(name).alias("origin"))
        out = thin if out is None else out.unionByName(thin)
    return out


def mixture_by_origin(pairs: DataFrame, origin: Column, rates: dict[str, float], seed: str = "mix") -> DataFrame:
    """As mixture_sample, for parts that a column tells apart (null: in none), in one pass over pairs."""
    rate = F.lit(1.0)
    for name, x in rates.items():
        rate = F.when(F.col("origin") == name, x).otherwise(rate)
    marked = pairs.select("pair_id", "src", "tgt", origin.alias("origin"))
    return marked.filter(F.col("origin").isNotNull() & (uniform(F.col("pair_id"), F.lit(seed), F.col("origin")) < rate))


def tag_origin(pairs: DataFrame, origin: str, generation: int) -> DataFrame:
    return pairs.withColumns({"origin": F.lit(origin), "generation": F.lit(generation)})
