"""Queries of the filters, noise and corpus statistics, each with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import noise
from ..functions.text import normalize_numerals, normalize_punct, words
from ..operators import cascade, classify, filters, lexical, ngram, selection
from ..sources import bitext
from . import sql

QUERIES, SQL = {}, {}


def query(name: str, text: str | None = None):
    def register(f):
        QUERIES[name] = f
        if text:
            SQL[name] = text
        return f

    return register


def sents(spark: SparkSession, d: str, where: str = "lang = 'en'") -> DataFrame:
    return bitext.sentences(spark, d).filter(where).withColumn("toks", words(F.col("text")))


SENTS = f"WITH {sql.SENT}, s AS (SELECT *, {sql.words('text')} AS toks FROM sent)"


@query("filter_rules_report", f"WITH {sql.CORRUPT}, a AS (SELECT {sql.REASONS} AS r FROM cc) SELECT reason, count(*) AS n_rows FROM (SELECT unnest(CASE WHEN len(r) = 0 THEN ['kept'] ELSE r END) AS reason FROM a) GROUP BY reason")
def filter_rules_report(spark, d):
    return filters.FilterCascade.bilingual().report(bitext.corrupted_bitext(spark, d))


@query("filter_cascade_apply", f"WITH {sql.CORRUPT} SELECT pair_id, truth, copy FROM cc WHERE len({sql.REASONS}) = 0")
def filter_cascade_apply(spark, d):
    return filters.FilterCascade.bilingual().apply(bitext.corrupted_bitext(spark, d)).select("pair_id", "truth", "copy")


@query("filter_quality", f"""WITH {sql.CORRUPT}, a AS (SELECT len({sql.REASONS}) > 0 AS hit, truth <> 'clean' AS bad FROM cc),
c AS (SELECT count(*) FILTER (hit AND bad) AS tp, count(*) FILTER (hit AND NOT bad) AS fp, count(*) FILTER (NOT hit AND bad) AS fn FROM a)
SELECT tp, fp, fn, round(tp / (tp + fp), 6) AS precision, round(tp / (tp + fn), 6) AS recall, round(2 * (tp / (tp + fp)) * (tp / (tp + fn)) / (tp / (tp + fp) + tp / (tp + fn)), 6) AS f1 FROM c""")
def filter_quality(spark, d):
    return filters.filter_quality(filters.FilterCascade.bilingual().annotate(bitext.corrupted_bitext(spark, d)))


@query("compare_filters", f"WITH {sql.CORRUPT}, a AS (SELECT {sql.REASONS} AS r FROM cc) " + " UNION ALL ".join(f"SELECT '{k}' AS left_out, count(*) FILTER (len(list_filter(r, lambda x: x <> '{k}')) = 0) AS kept FROM a" for k in [*sql.RULES, "none"]))
def compare_filters(spark, d):
    """Survivors of the cascade and of the cascade without each rule: one pass over the pairs."""
    noted = filters.FilterCascade.bilingual().annotate(bitext.corrupted_bitext(spark, d))
    names = [*(n for n, _ in filters.FilterCascade.bilingual().rules), "none"]
    kept = F.array(*(F.struct(F.lit(n).alias("left_out"), (F.size(F.array_remove("reasons", n)) == 0).cast("long").alias("k")) for n in names))
    return noted.select(F.explode(kept).alias("x")).groupBy("x.left_out").agg(F.sum("x.k").alias("kept"))


@query("monolingual_filter", f"""{SENTS} SELECT lang, count(*) AS n, count(*) FILTER (len(toks) <= 120 AND NOT regexp_matches(text, '\\S{{41,}}') AND NOT regexp_matches(text, '{sql._MARKUP}')) AS kept FROM s GROUP BY lang""")
def monolingual_filter(spark, d):
    noted = filters.FilterCascade.monolingual().annotate(bitext.sentences(spark, d))
    return noted.groupBy("lang").agg(F.count("*").alias("n"), F.sum((F.size("reasons") == 0).cast("long")).alias("kept"))


def _whole_cascade(spark, d):
    """Damaged pairs with the reasons of all nine rules: language model and lexicon are fitted on the undamaged text."""
    pairs = bitext.corrupted_bitext(spark, d).withColumn("row_id", F.concat_ws(":", "pair_id", "copy", F.md5("truth")))
    every = sents(spark, d, "true")
    langs = lexical.keep_table(classify.train_langid(every.filter(F.size("toks") >= 5)), "langs")
    counts = lexical.keep_table(ngram.fit_counts(every.filter("lang = 'en'"), "toks", 2), "counts")
    return cascade.annotate(pairs, langs, counts, lexical.keep_table(lexical.fit_alignment(bitext.cipher_bitext(spark, d).filter("split = 'train'"), 3), "lexicon"))


@query("filter_cascade_whole")
def filter_cascade_whole(spark, d):
    """Rows by kind of damage and reason, with duplicates, language, language model and alignment among the rules."""
    return cascade.report(_whole_cascade(spark, d), "truth")


@query("filter_quality_whole")
def filter_quality_whole(spark, d):
    return filters.filter_quality(_whole_cascade(spark, d))


DIALOGUE = "d AS (SELECT * FROM (SELECT conv_id, turn, role, text AS src, lead(role) OVER w AS nr, lead(text) OVER w AS tgt FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND nr = 'assistant')"


@query("dialogue_length_ratio", f"WITH {DIALOGUE} SELECT conv_id, turn, len({sql.words('src')}) AS n_src, len({sql.words('tgt')}) AS n_tgt, {sql.RULES['length_ratio']} AS rejected FROM d")
def dialogue_length_ratio(spark, d):
    pairs = bitext.dialogue_pairs(spark, d)
    return pairs.select("conv_id", "turn", F.size(words(F.col("src"))).cast("long").alias("n_src"), F.size(words(F.col("tgt"))).cast("long").alias("n_tgt"), filters.rule_length_ratio(F.col("src"), F.col("tgt")).alias("rejected"))


@query("markup_rule_pages", rf"WITH {sql.SENT} SELECT 'pages' AS tab, count(*) AS n, count(*) FILTER (regexp_matches(html, '{sql._MARKUP}')) AS rejected FROM pages UNION ALL SELECT 'sentences', count(*), count(*) FILTER (regexp_matches(text, '{sql._MARKUP}')) FROM sent")
def markup_rule_pages(spark, d):
    pages = bitext.table(spark, d, "pages").select(F.lit("pages").alias("tab"), F.col("html").alias("t"))
    both = pages.unionByName(bitext.sentences(spark, d).select(F.lit("sentences").alias("tab"), F.col("text").alias("t")))
    return both.groupBy("tab").agg(F.count("*").alias("n"), F.sum(F.col("t").rlike(filters.MARKUP).cast("long")).alias("rejected"))


@query("dedup_pairs", f"WITH {sql.CORRUPT} SELECT count(*) AS n, count(DISTINCT md5({sql.squeeze('lower(src)')} || chr(1) || {sql.squeeze('lower(tgt)')})) AS kept FROM cc")
def dedup_pairs(spark, d):
    pairs = bitext.corrupted_bitext(spark, d)
    kept = filters.one_of_each(pairs).agg(F.count("*").alias("kept"))
    return pairs.agg(F.count("*").alias("n")).join(kept, F.lit(True))


_KEYS = {"pair": f"{sql.squeeze('lower(src)')} || chr(1) || {sql.squeeze('lower(tgt)')}", "source": sql.squeeze("lower(src)"), "target": sql.squeeze("lower(tgt)")}


@query("dedup_modes", f"WITH {sql.CORRUPT} " + " UNION ALL ".join(f"SELECT '{m}' AS mode, count(*) - count(DISTINCT md5({k})) AS rejected FROM cc" for m, k in _KEYS.items()) + f" UNION ALL SELECT 'copy', count(*) FILTER ({sql.RULES['copy']}) FROM cc")
def dedup_modes(spark, d):
    pairs, out = bitext.corrupted_bitext(spark, d), None
    for mode in ("pair", "source", "target", "copy"):
        part = filters.duplicates(pairs, mode).agg(F.lit(mode).alias("mode"), F.sum(F.col("duplicate").cast("long")).alias("rejected"))
        out = part if out is None else out.unionByName(part)
    return out.select("mode", "rejected")


@query("langid_confusion", rf"""{SENTS}, split AS (SELECT doc_id || ':' || pos AS id, lang, lower(text) AS t, substr(md5(CAST(doc_id AS VARCHAR)), 1, 1) < 'c' AS train FROM s WHERE len(toks) >= 5),
g AS (SELECT id, lang, train, unnest(list_concat(list_transform(range(1, length(t) + 3), lambda i: substr(' ' || t || ' ', i, 1)), list_transform(range(1, length(t) + 2), lambda i: substr(' ' || t || ' ', i, 2)), list_transform(range(1, length(t) + 1), lambda i: substr(' ' || t || ' ', i, 3)))) AS g FROM split),
c AS (SELECT lang, g, count(*) AS c FROM g WHERE train GROUP BY ALL), v AS (SELECT count(DISTINCT g) AS v FROM c), t AS (SELECT lang, sum(c) AS t FROM c GROUP BY lang),
known AS (SELECT DISTINCT g FROM c),
test AS (SELECT id, g.g AS g, count(*) AS n FROM g JOIN known ON g.g = known.g WHERE NOT train GROUP BY ALL),
s2 AS (SELECT test.id, t.lang AS lang_pred, sum(n * ln((coalesce(c.c, 0) + 0.5) / (t.t + 0.5 * v.v))) AS s FROM test CROSS JOIN t CROSS JOIN v LEFT JOIN c ON c.lang = t.lang AND c.g = test.g GROUP BY ALL),
best AS (SELECT id, arg_max(lang_pred, s) AS lang_pred FROM s2 GROUP BY id)
SELECT split.lang, best.lang_pred, count(*) AS n FROM split JOIN best USING (id) GROUP BY ALL""")
def langid_confusion(spark, d):
    s = sents(spark, d, "true").filter(F.size("toks") >= 5).select(F.concat_ws(":", "doc_id", "pos").alias("id"), "lang", "text", (F.substring(F.md5(F.col("doc_id").cast("string")), 1, 1) < "c").alias("train"))
    model = classify.train_langid(s.filter("train"))
    test = s.filter("NOT train")
    return test.select("id", "lang").join(classify.predict_lang(test.select("id", "text"), "id", model), "id").groupBy("lang", "lang_pred").agg(F.count("*").alias("n"))


_D = f"list_filter(list_transform(toks, lambda t, i: CASE WHEN {sql.u('k', 'i - 1', chr(39) + 'del' + chr(39))} >= 0.05 THEN t END), lambda t: t IS NOT NULL)"
_B = f"list_transform(toks, lambda t, i: CASE WHEN {sql.u('k', 'i - 1', chr(39) + 'blank' + chr(39))} < 0.05 THEN '<blank>' ELSE t END)"
_O = "(CASE WHEN i % 2 = 1 THEN i + 1 ELSE i - 1 END)"
_S = f"list_transform(toks, lambda t, i: CASE WHEN {sql.u('k', '(i - 1) // 2', chr(39) + 'swap' + chr(39))} < 0.05 AND {_O} <= len(toks) THEN toks[{_O}] ELSE t END)"
_L = f"list_transform(list_sort(list_transform(toks, lambda t, i: {{'k': (i - 1) + 4 * {sql.u('k', 'i - 1', chr(39) + 'swap' + chr(39))}, 'i': i, 't': t}})), lambda x: x.t)"


def _noise_sql(expr: str) -> str:
    return f"{SENTS}, e AS (SELECT doc_id, pos, toks, doc_id || ':' || pos AS k FROM s WHERE lang = 'en') SELECT doc_id, pos, array_to_string({expr}, ' ') AS noised FROM e"


def _noise(apply):
    def run(spark, d):
        return sents(spark, d).select("doc_id", "pos", F.array_join(apply(F.col("toks"), F.concat_ws(":", "doc_id", "pos")), " ").alias("noised"))

    return run


query("noise_delete", _noise_sql(_D))(_noise(noise.noise_delete))
query("noise_blank", _noise_sql(_B))(_noise(noise.noise_blank))
query("noise_swap", _noise_sql(_S))(_noise(noise.noise_swap))
query("noise_swap_local", _noise_sql(_L))(_noise(lambda t, k: noise.noise_swap(t, k, style="local")))
query("noise_composite", f"""{SENTS}, e AS (SELECT doc_id, pos, toks, doc_id || ':' || pos AS k FROM s WHERE lang = 'en'), kept AS (SELECT doc_id, pos, k, {_D} AS toks FROM e),
blank AS (SELECT doc_id, pos, k, {_B} AS toks FROM kept) SELECT doc_id, pos, array_to_string({_S}, ' ') AS noised FROM blank""")(_noise(noise.add_noise))


@query("reverse_source", f"{SENTS} SELECT doc_id, pos, array_to_string(list_reverse(toks), ' ') AS reversed FROM s")
def reverse_source(spark, d):
    return sents(spark, d, "true").select("doc_id", "pos", F.array_join(F.reverse("toks"), " ").alias("reversed"))


@query("normalize_text", r"""WITH p AS (SELECT doc_id, chr(8220) || text || chr(8221) || ' 1,234 567 ' || chr(8230) || ' end !' AS t FROM documents)
SELECT doc_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(translate(t, '“”–', '""-'), '…', '...', 'g'), ' +([.,;:!?])', '\1', 'g'), '\s+', ' ', 'g'))) AS punct,
  md5(regexp_replace(t, '([0-9])[, ]([0-9]{3})\b', '\1\2', 'g')) AS numerals FROM p""")
def normalize_text(spark, d):
    t = F.concat(F.lit("“"), "text", F.lit("” 1,234 567 … end !"))
    return bitext.table(spark, d, "documents").select("doc_id", F.md5(normalize_punct(t)).alias("punct"), F.md5(normalize_numerals(t)).alias("numerals"))


@query("corpus_stats", f"""{SENTS} SELECT lang, count(*) AS n_sents, CAST(sum(len(toks)) AS BIGINT) AS n_tokens, CAST(sum(length(text)) AS BIGINT) AS n_chars, max(len(toks)) AS longest,
  (SELECT count(DISTINCT w) FROM (SELECT unnest(toks) AS w FROM s x WHERE x.lang = s.lang)) AS n_types FROM s GROUP BY lang""")
def corpus_stats(spark, d):
    s = sents(spark, d, "true")
    types = s.select("lang", F.explode("toks").alias("w")).groupBy("lang").agg(F.count_distinct("w").alias("n_types"))
    sums = s.groupBy("lang").agg(F.count("*").alias("n_sents"), F.sum(F.size("toks")).alias("n_tokens"), F.sum(F.length("text")).cast("long").alias("n_chars"), F.max(F.size("toks")).cast("long").alias("longest"))
    return sums.join(types, "lang")


_BENCH = sql.SENT.replace("FROM documents", "FROM (SELECT item_id AS doc_id, 'en' AS lang, 'b' AS source, text FROM benchmark)").replace("raw AS", "braw AS", 1).replace("FROM raw", "FROM braw").replace("sent AS", "bsent AS")


@query("contamination_overlap", f"WITH {sql.SENT}, {_BENCH} SELECT doc_id, count(*) AS n_hits FROM sent WHERE md5(lower(text)) IN (SELECT md5(lower(text)) FROM bsent) GROUP BY doc_id")
def contamination_overlap(spark, d):
    return selection.contamination(bitext.sentences(spark, d), benchmark_sentences(spark, d)).groupBy("doc_id").agg(F.count("*").alias("n_hits"))


def benchmark_sentences(spark, d):
    items = bitext.table(spark, d, "benchmark").select(F.col("item_id").alias("doc_id"), F.lit("en").alias("lang"), F.lit("b").alias("source"), "text")
    return bitext.segment(items)


@query("portion_split", f"WITH {sql.cipher()} SELECT CAST(floor({sql.u('pair_id', chr(39) + 'portion' + chr(39))} * 6) AS INTEGER) AS portion, count(*) AS n FROM cb GROUP BY 1")
def portion_split(spark, d):
    return bitext.split_portions(bitext.cipher_bitext(spark, d)).groupBy("portion").agg(F.count("*").alias("n"))


@query("mixture_sample", f"""WITH {sql.cipher()}, m AS (SELECT pair_id, 'bitext' AS origin FROM cb WHERE split = 'train' AND {sql.u('pair_id', "'mix'", "'bitext'")} < 0.5
UNION ALL SELECT pair_id, 'bt' FROM cb WHERE split = 'spare' AND {sql.u('pair_id', "'mix'", "'bt'")} < 0.9) SELECT origin, count(*) AS n, min(pair_id) AS first_id FROM m GROUP BY origin""")
def mixture_sample(spark, d):
    origin = F.when(F.col("split") == "train", "bitext").when(F.col("split") == "spare", "bt")
    out = bitext.mixture_by_origin(bitext.cipher_bitext(spark, d), origin, {"bitext": 0.5, "bt": 0.9})
    return out.groupBy("origin").agg(F.count("*").alias("n"), F.min("pair_id").alias("first_id"))


#: Words of the vocabulary that drop_unk keeps, the published size of the smaller side.
VOCABULARY = 27_800


@query("drop_unk", f"""{SENTS}, top AS (SELECT w FROM (SELECT unnest(toks) AS w FROM s WHERE lang = 'en') GROUP BY w ORDER BY count(*) DESC, w LIMIT {VOCABULARY}),
k AS (SELECT doc_id, pos, array_to_string(list(w ORDER BY i), ' ') AS t FROM (SELECT doc_id, pos, unnest(toks) AS w, generate_subscripts(toks, 1) AS i FROM s WHERE lang = 'en') JOIN top USING (w) GROUP BY ALL)
SELECT doc_id, pos, coalesce(t, '') AS kept FROM s LEFT JOIN k USING (doc_id, pos) WHERE lang = 'en'""")
def drop_unk(spark, d):
    """Words outside the vocabulary go; each word meets it by a join."""
    from ..operators.subword import build_vocab

    s = sents(spark, d)
    known = F.broadcast(build_vocab(s, "toks", VOCABULARY).select("tok"))
    met = s.select("doc_id", "pos", F.posexplode("toks").alias("i", "tok")).join(known, "tok", "left_semi")
    kept = met.groupBy("doc_id", "pos").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("i", "tok"))), lambda x: x["tok"]), " ").alias("t"))
    return s.select("doc_id", "pos").join(kept, ["doc_id", "pos"], "left").select("doc_id", "pos", F.coalesce("t", F.lit("")).alias("kept"))


@query("agg_rollup_reasons", f"""WITH {sql.CORRUPT}, a AS (SELECT truth, unnest(CASE WHEN len({sql.REASONS}) = 0 THEN ['kept'] ELSE {sql.REASONS} END) AS reason FROM cc)
SELECT truth, reason, count(*) AS n FROM a GROUP BY ROLLUP (truth, reason)""")
def agg_rollup_reasons(spark, d):
    noted = filters.FilterCascade.bilingual().annotate(bitext.corrupted_bitext(spark, d))
    shown = F.when(F.size("reasons") == 0, F.array(F.lit("kept"))).otherwise(F.col("reasons"))
    return noted.select("truth", F.explode(shown).alias("reason")).rollup("truth", "reason").agg(F.count("*").alias("n"))
