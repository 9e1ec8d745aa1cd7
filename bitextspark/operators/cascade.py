"""The whole filtering cascade: row rules, then duplicates, language, language model and alignment of what they leave."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import pair_id
from ..functions.text import squeeze, words
from . import classify, filters, lexical, ngram

SCORED = ("duplicate", "language", "language_model", "alignment")


def _side(name: str) -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def _key() -> Column:
    return F.md5(F.concat(squeeze(F.lower(_side("src"))), F.lit("\x01"), squeeze(F.lower(_side("tgt")))))


def later_copies(df: DataFrame, order: str) -> DataFrame:
    """df with duplicate: true on all but the row with the least order of each pair. The least is found by partial sums, so no key is ranked."""
    keyed = df.withColumn("__key", _key())
    first = keyed.groupBy("__key").agg(F.min(order).alias("__first"))
    return keyed.join(first, "__key").withColumn("duplicate", F.col(order) != F.col("__first")).drop("__key", "__first")


def pair_scores(pairs: DataFrame, lang_model: DataFrame, counts: DataFrame, lexicon: DataFrame, order: int = 2) -> DataFrame:
    """(pair_id, lang_pred, lm, align) of every distinct pair: the target's language and mean log probability, and how well it follows from the source."""
    kinds = pairs.select(_side("src").alias("src"), _side("tgt").alias("tgt")).distinct().select(pair_id(F.col("src"), F.col("tgt")).alias("pair_id"), "src", "tgt", words(F.col("src")).alias("src_toks"), words(F.col("tgt")).alias("tgt_toks"))
    kinds = lexical.keep_table(kinds, "kinds")
    lang = classify.predict_lang(kinds, "pair_id", lang_model, text="tgt").select("pair_id", "lang_pred")
    lm = ngram.scores(kinds, "pair_id", "tgt_toks", counts, order, "lm")
    align = lexical.alignment_score(kinds, lexicon).withColumnRenamed("score", "align")
    return kinds.select("pair_id").join(lang, "pair_id", "left").join(lm, "pair_id", "left").join(align, "pair_id", "left")


def annotate(df: DataFrame, lang_model: DataFrame, counts: DataFrame, lexicon: DataFrame, wanted: str = "en", lm_share: float = 0.02, align_share: float = 0.04, row_id: str = "row_id") -> DataFrame:
    """df (row_id unique, src, tgt) with reasons, an array that is empty where a pair passes everything.

    Row rules come first and cost no shuffle; only pairs that they leave are
    compared and scored, so a rejected pair has row reasons alone. Thresholds
    of the two scores are the quantiles lm_share and align_share of those
    pairs. A pair without a score (an empty side) is not rejected
    for it; a null side counts as empty.
    """
    noted = lexical.keep_table(filters.FilterCascade.bilingual().annotate(df), "row-rules")
    left = noted.filter(F.size("reasons") == 0).drop("reasons").withColumn("__pair", pair_id(_side("src"), _side("tgt")))
    scores = pair_scores(left, lang_model, counts, lexicon).withColumnRenamed("pair_id", "__pair")
    left = lexical.keep_table(later_copies(left, row_id).join(scores, "__pair"), "scored")
    rules = [F.col("duplicate"), filters.rule_lang(F.col("lang_pred"), wanted)]
    for score, share in (("lm", lm_share), ("align", align_share)):
        least = filters.quantile_threshold(left, score, share)
        rules.append(filters.rule_below(F.col(score), least) if least is not None else F.lit(False))
    reasons = F.array_compact(F.array(*(F.when(rule, F.lit(name)) for name, rule in zip(SCORED, rules, strict=True))))
    return noted.filter(F.size("reasons") > 0).unionByName(left.withColumn("reasons", reasons).select(noted.columns))


def report(noted: DataFrame, *by: str) -> DataFrame:
    """Rows per reason, kept under kept."""
    shown = F.when(F.size("reasons") == 0, F.array(F.lit("kept"))).otherwise(F.col("reasons"))
    return noted.select(*by, F.explode(shown).alias("reason")).groupBy(*by, "reason").agg(F.count("*").alias("n_rows"))
