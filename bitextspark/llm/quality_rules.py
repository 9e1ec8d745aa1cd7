"""Quality rules whose cutoffs come from mergeable quantile sketches per language and source.

One pass reads every text and counts; the counts are small and cut to a
table. KLL sketches over the documents that pass the base rules are built per
(language, source), merged per language and merged over all, so thresholds of
a new batch come from merging, not from reading again. A cutoff is a Tukey
fence: the outer quartile plus some interquartile ranges. A margin is the least
distance from the quartile, for ratios that are zero in most documents and so
have no range; it is below what word lengths usually spread, so there the
quantiles decide (reaches tells which). A group with few documents takes its language's fence, a
language with few takes the fence of all, which holds whatever their number. The fences are joined to the counts
and decide.
"""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, cut, slices, tidy

SYMBOLS = b"#*$%&|<>"
CAPITALS = bytes(range(65, 91))
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
#: A group with fewer documents takes the next wider group's fences; that of all has none wider.
LEAST_DOCS = 200
SKETCH_K = 800
#: Fences up to so many rows are broadcast; more are joined by shuffle.
BROADCAST_ROWS = 100_000

COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
_OWN = ["n_lines", "n_capitals"]


@dataclass(frozen=True)
class Rule:
    """A ratio with an upper fence and, where asked, a lower one."""

    name: str
    over: str
    under: str
    ranges: float
    margin: float
    both: bool = False

    def value(self) -> Column:
        return F.coalesce(F.try_divide(F.col(self.over).cast("double"), F.col(self.under).cast("double")), F.lit(0.0))


RULES = (
    Rule("symbols", "n_symbols", "n_words", 6.0, 0.15),
    Rule("dup_lines", "n_dup_lines", "n_lines", 6.0, 0.3),
    Rule("repeats", "n_repeat_words", "n_words", 6.0, 0.3),
    Rule("capitals", "n_capitals", "word_chars", 6.0, 0.05),
    Rule("word_length", "word_chars", "n_words", 6.0, 0.5, both=True),
)


def repeat_words(words: list[bytes], width: int = 3) -> int:
    """Words that lie in a window of width words which the text holds twice or more."""
    windows = list(zip(*(words[i:] for i in range(width)), strict=False))
    if len(set(windows)) == len(windows):
        return 0
    first: dict[tuple, int] = {}
    hit = bytearray(len(words))
    for i, w in enumerate(windows):
        j = first.setdefault(w, i)
        if j != i:
            hit[j : j + width] = hit[i : i + width] = b"\x01" * width
    return sum(hit)


def counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """(i, lang, source, key, counts) of every row; null texts have no words. key is a hash of the row's text."""

    def run(batches):
        for whole in batches:
            for batch in slices(whole, "t"):
                texts = as_bytes(batch.column("t"))
                rows = []
                for t, points in zip(texts, pc.utf8_length(batch.column("t")).to_pylist(), strict=True):
                    if not t:
                        rows.append((0, 0, 0, 0, 0, 0, 0))
                        continue
                    words = t.split()
                    lines = [x for x in t.split(b"\n") if x.strip()]
                    rows.append((
                        len(words), points - len(t) + sum(map(len, words)), len(t) - len(t.translate(None, SYMBOLS)), len(lines) - len(set(lines)),
                        repeat_words(words), len(lines), len(t) - len(t.translate(None, CAPITALS)),
                    ))
                out = [pa.array(x, pa.int64()) for x in zip(*rows, strict=True)]
                yield pa.RecordBatch.from_arrays([*(batch.column(x) for x in ("i", "lang", "source", "key")), *out], names=["i", "lang", "source", "key", *COUNTS, *_OWN])

    kind = docs.schema[id_col].dataType.simpleString()
    read = docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t"), F.col(lang_col).cast("string").alias("lang"), F.col(source_col).cast("string").alias("source"), F.xxhash64(text_col).alias("key"))
    return read.mapInArrow(tidy(run), f"i {kind}, lang string, source string, key long, " + ", ".join(f"{c} long" for c in COUNTS + _OWN))


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))


def sketches(counted: DataFrame) -> DataFrame:
    """One row per (lang, source): documents and a KLL sketch per rule, over what passes the base rules."""
    good = counted.filter(~base_failed()).select("lang", "source", *(r.value().alias(r.name) for r in RULES))
    return good.groupBy("lang", "source").agg(F.count("*").alias("n"), *(F.kll_sketch_agg_double(r.name, F.lit(SKETCH_K)).alias(r.name) for r in RULES))


def _fences(groups: DataFrame, least: int = LEAST_DOCS) -> DataFrame:
    """lo_ and hi_ of every rule from the sketches of groups of least documents or more."""
    out = []
    for r in RULES:
        low, high = (F.kll_sketch_get_quantile_double(r.name, F.lit(q)) for q in (0.25, 0.75))
        reach = F.greatest(r.ranges * (high - low), F.lit(r.margin))
        out += [(low - reach if r.both else F.lit(float("-inf"))).alias(f"lo_{r.name}"), (high + reach).alias(f"hi_{r.name}")]
    keys = [c for c in ("lang", "source") if c in groups.columns]
    return groups.filter(F.col("n") >= least).select(*keys, F.struct(*out).alias("fence"))


def reaches(made: DataFrame, least: int = LEAST_DOCS) -> DataFrame:
    """(lang, source, rule, reach, by_margin) of the sketches of least documents or more: how far the fence lies from the quartile, and whether the margin set it."""
    out = []
    for r in RULES:
        spread = r.ranges * (F.kll_sketch_get_quantile_double(r.name, F.lit(0.75)) - F.kll_sketch_get_quantile_double(r.name, F.lit(0.25)))
        out.append(F.struct(F.lit(r.name).alias("rule"), F.greatest(spread, F.lit(r.margin)).alias("reach"), (spread <= r.margin).alias("by_margin")))
    return made.filter(F.col("n") >= least).select("lang", "source", F.inline(F.array(*out)))


def fences(made: DataFrame) -> DataFrame:
    """One row per (lang, source) of the sketches with the fence that holds for it (null: no document passes the base rules)."""
    merged = [F.kll_merge_agg_double(r.name).alias(r.name) for r in RULES]
    by_lang = _fences(made.groupBy("lang").agg(F.sum("n").alias("n"), *merged)).withColumnRenamed("fence", "lang_fence")
    of_all = _fences(made.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), *merged), 1).withColumnRenamed("fence", "all_fence")
    own = _fences(made).withColumnRenamed("fence", "own_fence")
    keys = made.select("lang", "source")
    out = keys.alias("k").join(own.alias("o"), F.col("k.lang").eqNullSafe(F.col("o.lang")) & F.col("k.source").eqNullSafe(F.col("o.source")), "left")
    out = out.join(by_lang.alias("l"), F.col("k.lang").eqNullSafe(F.col("l.lang")), "left").join(F.broadcast(of_all), F.lit(True), "left")
    return out.select(F.col("k.lang").alias("f_lang"), F.col("k.source").alias("f_source"), F.coalesce("own_fence", "lang_fence", "all_fence").alias("fence"))


def verdicts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """(id, counts, base_failed, kept, reasons, key) of every row of docs.

    A document is held against the fence of its (language, source), of its
    language where that has under LEAST_DOCS documents that pass the base
    rules, or of all where the language has too; the last holds at any number
    above zero. Null texts count as empty and fail the base rules. A null language or
    source is a group of its own. Repeated rows each get their verdict; ties
    don't matter, as nothing is ranked; an empty table gives an empty result;
    other columns of docs are not read.
    """
    counted = cut(counts(docs, id_col, text_col, lang_col, source_col), "counts")
    made = cut(fences(cut(sketches(counted), "sketches")), "fences")
    small = made.count() <= BROADCAST_ROWS
    on = F.col("lang").eqNullSafe(F.col("f_lang")) & F.col("source").eqNullSafe(F.col("f_source"))
    judged = counted.join(F.broadcast(made) if small else made, on, "left")
    reasons = [F.when((r.value() > F.col(f"fence.hi_{r.name}")) | (r.value() < F.col(f"fence.lo_{r.name}")), F.lit(r.name)) for r in RULES]
    judged = judged.withColumn("base_failed", base_failed()).withColumn("reasons", F.array_compact(F.array(*reasons)))
    return judged.select(F.col("i").alias(id_col), *COUNTS, "base_failed", (~F.col("base_failed") & (F.size("reasons") == 0)).alias("kept"), "reasons", F.col("key").alias("__text_key"))


def keep(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """The rows of docs that pass, with all their columns. Rows that repeat an id and text stay or go together, if one passes."""
    good = verdicts(docs, id_col, text_col, lang_col, source_col).filter("kept").select(F.col(id_col).alias("__id"), "__text_key").distinct()
    return docs.join(good, docs[id_col].eqNullSafe(F.col("__id")) & (F.xxhash64(docs[text_col]) == F.col("__text_key")), "left_semi")
