"""Text functions as Spark expressions: normalising, tokenising, casing, numerals."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Typographic marks and what they are written as.
MARKS = {"“": '"', "”": '"', "„": '"', "«": '"', "»": '"', "‘": "'", "’": "'", "‚": "'", "´": "'", "–": "-", "—": "-", "‐": "-", "−": "-", "，": ",", "。": ".", "：": ":", "；": ";", "？": "?", "！": "!", "（": "(", "）": ")", "％": "%", " ": " ", "　": " "}
FULL_DIGITS = {chr(0xFF10 + i): str(i) for i in range(10)}


def normalize_punct(text: Column) -> Column:
    """Unify quotes, dashes and full-width marks (translate), ellipses and spaces (regular expressions)."""
    out = F.translate(text, "".join(MARKS), "".join(MARKS.values()))
    out = F.regexp_replace(out, "…", "...")
    out = F.regexp_replace(out, r" +([.,;:!?])", "$1")
    return F.trim(F.regexp_replace(out, r"\s+", " "))


def normalize_numerals(text: Column) -> Column:
    """Full-width digits to ASCII; a comma or blank between groups of three digits goes."""
    out = F.translate(text, "".join(FULL_DIGITS), "".join(FULL_DIGITS.values()))
    return F.regexp_replace(out, r"(\d)[, ](\d{3})\b", "$1$2")


def squeeze(text: Column) -> Column:
    return F.trim(F.regexp_replace(text, r"\s+", " "))


def words(text: Column) -> Column:
    """White-space tokens; an empty text has none."""
    return F.filter(F.split(squeeze(text), " "), lambda t: t != "")


def tokenize(text: Column, unit: str = "word") -> Column:
    """Words with their punctuation apart, or characters without white space."""
    if unit == "char":
        return F.filter(F.split(F.regexp_replace(text, r"\s+", ""), ""), lambda t: t != "")
    return words(F.regexp_replace(text, r"([.,;:!?()\"])", " $1 "))


def detokenize(tokens: Column) -> Column:
    return F.regexp_replace(F.array_join(tokens, " "), r" +([.,;:!?)])", "$1")


def mark_unknown(tokens: Column, known: Column, mark: str = "<unk>") -> Column:
    """Tokens outside the array known become the mark."""
    return F.transform(tokens, lambda t: F.when(F.array_contains(known, t), t).otherwise(mark))


def drop_unknown(tokens: Column, mark: str = "<unk>") -> Column:
    return F.array_remove(tokens, mark)


def reverse_source(df: DataFrame, col: str = "src_toks") -> DataFrame:
    return df.withColumn(col, F.reverse(col))


def segment(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ("lang", "source")) -> DataFrame:
    """Sentences of documents: id, kept columns, pos (from 1), text. A sentence ends at .!? before white space, or at a line's end."""
    cut = F.split(F.regexp_replace(F.col(text_col), r"([.!?])\s+", "$1\n"), "\n")
    out = docs.select(id_col, *keep, F.posexplode(cut).alias("p", "raw"))
    return out.select(id_col, *keep, (F.col("p") + 1).alias("pos"), squeeze(F.col("raw")).alias("text")).filter("text <> ''")
