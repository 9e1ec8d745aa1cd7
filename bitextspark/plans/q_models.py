"""Queries of language models, selection, alignment, subwords and casing, each with its SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import classify, lexical, ngram, packed, selection, subword
from ..operators.aligned import Alignment
from ..sources import bitext
from . import sql
from .q_filters import _BENCH, SENTS, benchmark_sentences, sents

QUERIES, SQL = {}, {}


def query(name: str, text: str | None = None):
    def register(f):
        QUERIES[name] = f
        if text:
            SQL[name] = text
        return f

    return register


def grams_sql(src: str, key: str, toks: str, n: int, extra: str = "") -> str:
    begin = ", ".join(["'<s>'"] * (n - 1))
    return f"(SELECT {key}, {extra} i, array_to_string(p[i + 1:i + {n - 1}], ' ') AS ctx, p[i + {n}] AS tok FROM (SELECT {key}, {extra} p, unnest(range(0, len(p) - {n - 1})) AS i FROM (SELECT {key}, {extra} list_concat(CAST([{begin}] AS VARCHAR[]), {toks}, ['</s>']) AS p FROM {src})))"


def counts_sql(name: str, src: str, key: str, toks: str, n: int, by: str = "") -> str:
    """CTEs name1..namen with (by, ctx, tok, q) and name_v with the vocabulary."""
    comma = f"{by}, " if by else ""
    out = [f"{name}{k} AS (SELECT {comma}ctx, tok, count(*) AS cnt, count(*) / sum(count(*)) OVER (PARTITION BY {comma}ctx) AS q FROM {grams_sql(src, key, toks, k, comma)} GROUP BY {comma}ctx, tok)" for k in range(1, n + 1)]
    out.append(f"{name}_v AS (SELECT {comma}count(*) AS v FROM {name}1 {'GROUP BY ' + by if by else ''})")
    return ", ".join(out)


def score_sql(name: str, src: str, key: str, toks: str, n: int) -> str:
    w = ngram.FIXED[n]
    tails = {k: "''" if k == 1 else ("g.ctx" if k == n else f"array_to_string(string_split(g.ctx, ' ')[{n - k + 1}:{n - 1}], ' ')") for k in range(1, n + 1)}
    joins = " ".join(f"LEFT JOIN {name}{k} c{k} ON c{k}.ctx = {tails[k]} AND c{k}.tok = g.tok" for k in range(n, 0, -1))
    p = " + ".join([f"{w[n - k]} * coalesce(c{k}.q, 0)" for k in range(n, 0, -1)] + [f"{w[-1]} / v"])
    return f"(SELECT g.{key}, avg(ln({p})) AS score FROM {grams_sql(src, key, toks, n)} g CROSS JOIN {name}_v {joins} GROUP BY g.{key})"


KEYED = f"{SENTS}, k AS (SELECT doc_id || ':' || pos AS id, lang, source, text, toks, doc_id FROM s)"


def keyed(spark, d, where="true"):
    return sents(spark, d, where).withColumn("id", F.concat_ws(":", "doc_id", "pos"))


@query("lm_token_trigram_score", f"""{KEYED}, en AS (SELECT * FROM k WHERE lang = 'en'), {counts_sql('c', 'en', 'id', 'toks', 3)} SELECT id, round(score, 5) AS score FROM {score_sql('c', 'en', 'id', 'toks', 3)}""")
def lm_token_trigram_score(spark, d):
    _, scored = packed.scores(packed.sliced(keyed(spark, d, "lang = 'en'"), "id", "toks"), 3)
    return scored.select("id", F.round(F.get("scores", F.lit(0)), 5).alias("score"))


_CH = "list_filter(string_split(regexp_replace(text, '\\s+', '', 'g'), ''), lambda c: c <> '')"


# every language but English has a model of its own; ids don't repeat over languages
@query("lm_char_bigram_score", f"""{KEYED}, other AS (SELECT id, lang, {_CH} AS chars FROM k WHERE lang <> 'en'), {counts_sql('c', 'other', 'id', 'chars', 2, 'lang')}
SELECT g.id, round(avg(ln(0.6 * coalesce(b.q, 0) + 0.3 * coalesce(a.q, 0) + 0.1 / m.v)), 5) AS score FROM {grams_sql('other', 'id', 'chars', 2, 'lang,')} g JOIN c_v m ON m.lang = g.lang
LEFT JOIN c2 b ON b.lang = g.lang AND b.ctx = g.ctx AND b.tok = g.tok LEFT JOIN c1 a ON a.lang = g.lang AND a.ctx = '' AND a.tok = g.tok GROUP BY g.id""")
def lm_char_bigram_score(spark, d):
    from ..functions.text import tokenize

    other = keyed(spark, d, "lang <> 'en'").withColumn("chars", tokenize(F.col("text"), "char"))
    counts = lexical.keep_table(ngram.fit_counts(other, "chars", 2, ("lang",)), "counts")
    return ngram.scores(other, "id", "chars", counts, 2, by=("lang",)).select("id", F.round("score", 5).alias("score"))


@query("lm_perplexity", f"""{KEYED}, en AS (SELECT * FROM k WHERE lang = 'en'), tr AS (SELECT * FROM en WHERE substr(md5(id), 1, 1) < '8'), te AS (SELECT * FROM en WHERE substr(md5(id), 1, 1) >= '8'),
{counts_sql('c', 'tr', 'id', 'toks', 2)}, a AS (SELECT 'train' AS part, sum(score * (len(toks) + 1)) AS s, sum(len(toks) + 1) AS n FROM tr JOIN {score_sql('c', 'tr', 'id', 'toks', 2)} USING (id)
UNION ALL SELECT 'held_out', sum(score * (len(toks) + 1)), sum(len(toks) + 1) FROM te JOIN {score_sql('c', 'te', 'id', 'toks', 2)} USING (id)) SELECT part, round(exp(-s / n), 4) AS perplexity FROM a""")
def lm_perplexity(spark, d):
    en = keyed(spark, d, "lang = 'en'").withColumn("h", F.substring(F.md5("id"), 1, 1))
    counts = ngram.fit_counts(en.filter("h < '8'"), "toks", 2)
    part = lambda name, where: ngram.perplexity(en.filter(where), "id", "toks", counts, 2).select(F.lit(name).alias("part"), F.round("perplexity", 4).alias("perplexity"))
    return part("train", "h < '8'").unionByName(part("held_out", "h >= '8'"))


@query("lm_smoothing", f"""{KEYED}, en AS (SELECT * FROM k WHERE lang = 'en'), {counts_sql('c', 'en', 'id', 'toks', 2)}, t AS (SELECT ctx, sum(cnt) AS n, count(*) AS kinds FROM c2 GROUP BY ctx),
l AS (SELECT tok, count(*) / sum(count(*)) OVER () AS low FROM c2 GROUP BY tok)
SELECT 'addk' AS smoothing, ctx, tok, round((cnt + 0.1) / (n + 0.1 * v), 7) AS p FROM c2 JOIN t USING (ctx) CROSS JOIN c_v WHERE cnt >= 5
UNION ALL SELECT 'kn', ctx, tok, round(greatest(cnt - 0.75, 0) / n + 0.75 * kinds / n * low, 7) FROM c2 JOIN t USING (ctx) JOIN l USING (tok) WHERE cnt >= 5""")
def lm_smoothing(spark, d):
    """Bigram probabilities of frequent pairs under additive and Kneser-Ney smoothing."""
    counts = ngram.fit_counts(keyed(spark, d, "lang = 'en'"), "toks", 2)
    often = counts.filter("n = 2 AND cnt >= 5").select("ctx", "tok")
    out = None
    for name in ("addk", "kn"):
        part = ngram.probabilities(counts, 2, name).join(often, ["ctx", "tok"]).select(F.lit(name).alias("smoothing"), "ctx", "tok", F.round("p", 7).alias("p"))
        out = part if out is None else out.unionByName(part)
    return out


_GENRE = f"""{KEYED}, te AS (SELECT * FROM k WHERE len(toks) >= 3), {counts_sql('c', 'te', 'id', 'toks', 2, 'lang')},
sc AS (SELECT g.id, m.lang AS lm_id, avg(ln(0.6 * coalesce(b.q, 0) + 0.3 * coalesce(a.q, 0) + 0.1 / m.v)) AS score FROM {grams_sql('te', 'id', 'toks', 2)} g CROSS JOIN c_v m
LEFT JOIN c2 b ON b.lang = m.lang AND b.ctx = g.ctx AND b.tok = g.tok LEFT JOIN c1 a ON a.lang = m.lang AND a.ctx = '' AND a.tok = g.tok GROUP BY ALL)"""


def _genres(spark, d):
    """(id, by_lm): each sentence's scores under the models of all languages, as structs in their order."""
    labels, scored = packed.scores(packed.sliced(keyed(spark, d).filter(F.size("toks") >= 3), "id", "toks", "lang"), 2)
    return scored.select("id", F.array(*(F.struct(F.lit(x).cast("string").alias("lm_id"), F.get("scores", F.lit(i)).alias("score")) for i, x in enumerate(labels))).alias("by_lm"))


@query("genre_top_sentences", f"{_GENRE} SELECT lm_id, id, CAST(r AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY lm_id ORDER BY round(score, 6) DESC, id) AS r FROM sc) WHERE r <= 20")
def genre_top_sentences(spark, d):
    """One model per language stands for a genre; the 20 sentences that each likes best."""
    scored = _genres(spark, d).select("id", F.explode("by_lm").alias("x")).select("id", "x.lm_id", F.round("x.score", 6).alias("score"))
    return selection.top_per_group(scored, "lm_id", "score", 20, "id").select("lm_id", "id", "rank")


@query("genre_confusion", f"{_GENRE} SELECT lang, lm_id, count(*) AS n FROM (SELECT id, arg_max(lm_id, score) AS lm_id FROM sc GROUP BY id) JOIN te USING (id) GROUP BY ALL")
def genre_confusion(spark, d):
    # of equal scores the first in the order of languages, as lists compare; the language travels with the id, so nothing is joined
    s = keyed(spark, d).filter(F.size("toks") >= 3).withColumn("id", F.to_json(F.struct("id", "lang")))
    labels, scored = packed.scores(packed.sliced(s, "id", "toks", "lang"), 2)
    best = F.array_min(F.array(*(F.struct((-F.get("scores", F.lit(i))).alias("q"), F.lit(x).cast("string").alias("lm_id")) for i, x in enumerate(labels))))
    return scored.select(F.get_json_object("id", "$.lang").alias("lang"), best["lm_id"].alias("lm_id")).groupBy("lang", "lm_id").agg(F.count("*").alias("n"))


# in-domain: the benchmark's sentences and their cipher; out-of-domain: all of the documents' pairs
_CE_BASE = f"""WITH {sql.cipher()}, {_BENCH},
ien AS (SELECT text AS tgt, {sql.words('text')} AS tgt_toks FROM bsent GROUP BY text),
ic AS (SELECT *, list_transform(tgt_toks, lambda t: 'c' || substr(md5(lower(t)), 1, 4)) AS codes FROM ien WHERE len(tgt_toks) BETWEEN 3 AND 120),
icb AS (SELECT tgt, tgt_toks, list_transform(codes, lambda c, i: CASE WHEN (CASE WHEN i % 2 = 1 THEN i + 1 ELSE i - 1 END) <= len(codes) AND substr(md5(codes[((i - 1) // 2) * 2 + 1] || codes[((i - 1) // 2) * 2 + 2]), 1, 1) < '4'
  THEN codes[CASE WHEN i % 2 = 1 THEN i + 1 ELSE i - 1 END] ELSE c END) AS src_toks FROM ic),
inn AS (SELECT tgt AS id, tgt_toks, list_filter(string_split(array_to_string(src_toks, ''), ''), lambda c: c <> '') AS chars FROM icb),
pool AS (SELECT pair_id AS id, tgt_toks, list_filter(string_split(array_to_string(src_toks, ''), ''), lambda c: c <> '') AS chars FROM cb),
{counts_sql('it', 'inn', 'id', 'tgt_toks', 3)}, {counts_sql('ot', 'pool', 'id', 'tgt_toks', 3)}, {counts_sql('is_', 'inn', 'id', 'chars', 2)}, {counts_sql('os_', 'pool', 'id', 'chars', 2)},
a AS {score_sql('it', 'pool', 'id', 'tgt_toks', 3)}, b AS {score_sql('ot', 'pool', 'id', 'tgt_toks', 3)}, c AS {score_sql('is_', 'pool', 'id', 'chars', 2)}, d AS {score_sql('os_', 'pool', 'id', 'chars', 2)},
ce AS (SELECT a.id AS pair_id, round((b.score - a.score) + (d.score - c.score), 6) AS ce FROM a JOIN b USING (id) JOIN c USING (id) JOIN d USING (id))"""


def _ce_pairs(spark, d):
    """The pool and the in-domain pairs; the whole pool is the out-of-domain corpus."""
    return bitext.cipher_bitext(spark, d), bitext.cipher_pairs(benchmark_sentences(spark, d).select("text", F.lit("b").alias("genre")))


def _ce_parts(spark, d):
    """The pool and its models as tables of counts, the source side by characters."""
    from ..functions.text import tokenize

    pool, inside = (p.withColumn("src_toks", tokenize(F.array_join("src_toks", ""), "char")) for p in _ce_pairs(spark, d))
    fit = ngram.fit_counts
    return pool, {"in_src": fit(inside, "src_toks", 2), "out_src": fit(pool, "src_toks", 2), "in_tgt": fit(inside, "tgt_toks", 3), "out_tgt": fit(pool, "tgt_toks", 3)}


def _ce(spark, d, form="difference", sides=("src", "tgt")):
    """(pair_id, ce) of the pool, as selection.bilingual_ce has it; both models of a side are counted in one pass."""
    columns = {"src": "chars", "tgt": "tgt_toks"}
    # both sides in one pass, as the cipher costs more than the counts
    pool, inside = (packed.sliced_sides(p.withColumns({"chars": F.array_join("src_toks", ""), "model": F.lit(x)}), "pair_id", {columns[side]: side == "src" for side in sides}, "model") for p, x in zip(_ce_pairs(spark, d), ("out", "in"), strict=True))
    out = None
    for side in sides:
        n, mine = 2 if side == "src" else 3, F.col("side") == columns[side]
        labels, scored = packed.scores(pool.filter(mine).drop("side"), n, inside.filter(mine).drop("side"), side == "src", ("in", "out") if form == "literal" else None)
        of = lambda x: F.get("scores", F.lit(labels.index(x))) if x in labels else F.lit(None).cast("double")  # noqa: B023, E731
        ce = F.get("scores", F.lit(0)) if form == "literal" else of("out") - of("in")
        part = scored.select(F.col("id").alias("pair_id"), ce.alias("ce"))
        out = part if out is None else out.unionByName(part)
    return out if len(sides) == 1 else out.groupBy("pair_id").agg(F.sum("ce").alias("ce"))


@query("bilingual_ce_scores", f"{_CE_BASE} SELECT pair_id, ce FROM ce")
def bilingual_ce_scores(spark, d):
    return _ce(spark, d).select("pair_id", F.round("ce", 6).alias("ce"))


@query("select_bilingual_ce", f"{_CE_BASE} SELECT pair_id FROM ce ORDER BY ce, pair_id LIMIT (SELECT CAST(ceil(0.06 * count(*)) AS BIGINT) FROM ce)")
def select_bilingual_ce(spark, d):
    """The six lowest in a hundred, the share that 600 thousand of 10 million pairs are."""
    return _lowest_ce(spark, d)


def _lowest_ce(spark, d):
    scored = lexical.keep_table(_ce(spark, d).withColumn("ce", F.round("ce", 6)), "ce")
    k = -(-6 * scored.count() // 100)
    return selection.select_lowest(scored, "ce", k).select("pair_id")


@query("select_literal_ce")
def select_literal_ce(spark, d):
    """The other reading of the score: cross entropy between the two models' distributions, added over the sides."""
    scored = lexical.keep_table(_ce(spark, d, "literal").withColumn("ce", F.round("ce", 6)), "ce")
    return selection.select_lowest(scored, "ce", -(-6 * scored.count() // 100))


@query("select_monolingual_ce")
def select_monolingual_ce(spark, d):
    scored = lexical.keep_table(_ce(spark, d, sides=("tgt",)).withColumn("ce", F.round("ce", 6)), "ce")
    return selection.select_lowest(scored, "ce", -(-6 * scored.count() // 100))


@query("select_similar")
def select_similar(spark, d):
    """Pairs whose score lies within the band of the in-domain sentences that they hold."""
    scored = lexical.keep_table(_ce(spark, d), "ce")
    planted = bitext.cipher_bitext(spark, d).join(benchmark_sentences(spark, d).select(F.col("text").alias("tgt")).distinct(), "tgt", "left_semi").select("pair_id")
    return selection.select_similar(scored, "ce", scored.join(planted, "pair_id", "left_semi"))


def _classified(spark, d):
    pairs = bitext.cipher_bitext(spark, d)
    inside = bitext.cipher_pairs(benchmark_sentences(spark, d).select("text", F.lit("b").alias("genre")))
    share = min(1.0, inside.count() * 3 / max(1, pairs.count()))
    model = classify.train_domain_classifier(inside, pairs, share)
    return pairs, lexical.keep_table(classify.score_domain(pairs, model), "prob")


@query("select_classifier")
def select_classifier(spark, d):
    _, scored = _classified(spark, d)
    return selection.select_highest(scored, "prob", -(-6 * scored.count() // 100))


@query("selector_overlap")
def selector_overlap(spark, d):
    """Cross entropy against the classifier, the classifier against a random pick of as many."""
    pairs, scored = _classified(spark, d)
    k = -(-6 * scored.count() // 100)
    a, b = _lowest_ce(spark, d), selection.select_highest(scored, "prob", k)
    c = selection.hash_order(pairs.select("pair_id"), k, "random")
    x = selection.selector_overlap(a, b).withColumn("selectors", F.lit("ce-classifier"))
    return x.unionByName(selection.selector_overlap(b, c).withColumn("selectors", F.lit("classifier-random")))


@query("in_domain_union")
def in_domain_union(spark, d):
    _, scored = _classified(spark, d)
    k = -(-6 * scored.count() // 100)
    return selection.in_domain_union(("ce", _lowest_ce(spark, d)), ("classifier", selection.select_highest(scored, "prob", k)))


@query("topk_global", f"{SENTS} SELECT doc_id, pos, length(text) AS n FROM s ORDER BY n DESC, doc_id || ':' || pos LIMIT 500")
def topk_global(spark, d):
    s = keyed(spark, d).select("doc_id", "pos", F.length("text").cast("long").alias("n"), "id")
    return selection.select_highest(s, "n", 500, "id").drop("id")


@query("random_selection", f"WITH {sql.cipher()} SELECT pair_id FROM cb ORDER BY substr(md5('random' || pair_id), 1, 12), pair_id LIMIT 300")
def random_selection(spark, d):
    return selection.hash_order(bitext.cipher_bitext(spark, d).select("pair_id"), 300, "random")


_PAIRS = f"{sql.cipher()}, p AS (SELECT * FROM cb), prod AS (SELECT pair_id, j, e, unnest(list_concat(['<null>'], src_toks)) AS f FROM (SELECT pair_id, src_toks, unnest(tgt_toks) AS e, generate_subscripts(tgt_toks, 1) AS j FROM p))"


def _em_sql(rounds: int) -> str:
    out = [_PAIRS]
    for r in range(1, rounds + 1):
        x = "1.0" if r == 1 else "l.p"
        join = "" if r == 1 else f"JOIN l{r - 1} l USING (f, e)"
        out.append(f"c{r} AS (SELECT f, e, sum(c) AS c FROM (SELECT f, e, {x} / sum({x}) OVER (PARTITION BY pair_id, j) AS c FROM prod {join}) GROUP BY f, e), l{r} AS (SELECT f, e, c / sum(c) OVER (PARTITION BY f) AS p FROM c{r})")
    return "WITH " + ", ".join(out)


def _pairs(spark, d):
    return bitext.cipher_bitext(spark, d)


@query("align_em3", f"{_em_sql(3)} SELECT f, e, round(p, 5) AS p FROM l3 WHERE p > 0.0500001")
def align_em3(spark, d):
    return Alignment(_pairs(spark, d), 3).table(0.0500001).select("f", "e", F.round("p", 5).alias("p"))


@query("align_scores", f"{_em_sql(3)} SELECT pair_id, round(avg(ln(greatest(q, 1e-9))), 5) AS score FROM (SELECT pair_id, j, avg(coalesce(p, 0)) AS q FROM prod LEFT JOIN l3 USING (f, e) GROUP BY ALL) GROUP BY pair_id")
def align_scores(spark, d):
    return Alignment(_pairs(spark, d), 3).scores().select("pair_id", F.round("score", 5).alias("score"))


@query("align_viterbi", f"{_em_sql(3)} SELECT f, count(*) AS links FROM (SELECT pair_id, j, min({{'q': round(-p, 9), 'f': f}}).f AS f FROM prod JOIN l3 USING (f, e) GROUP BY pair_id, j) GROUP BY f HAVING count(*) >= 20")
def align_viterbi(spark, d):
    return Alignment(_pairs(spark, d), 3).link_counts().filter("links >= 20")


@query("align_diagonal")
def align_diagonal(spark, d):
    """Symmetrised scores under the diagonal prior: true pairs against the same pairs with another's target."""
    pairs = _pairs(spark, d).select("pair_id", "src_toks", "tgt_toks")
    wrong = classify.make_negatives(pairs, ("mispaired",)).drop("kind")
    marked = lambda df, label: df.withColumn("pair_id", F.concat_ws("-", F.lit(label), "pair_id"))
    sides = None
    for flip in (False, True):
        turned = [df.select("pair_id", F.col("tgt_toks").alias("src_toks"), F.col("src_toks").alias("tgt_toks")) if flip else df for df in (marked(pairs, "1"), marked(wrong, "0"))]
        # scored by the mean of the table alone, as lexical.symmetric_score has it
        part = Alignment(turned[0], 3, "diagonal", asked=turned[1]).scores()
        sides = part if sides is None else sides.unionByName(part)
    out = sides.groupBy("pair_id").agg((F.sum("score") / 2).alias("score")).withColumn("label", F.substring("pair_id", 1, 1).cast("int"))
    return classify.binary_metrics(out, "label", "score")


@query("acceptability_auc")
def acceptability_auc(spark, d):
    """Both poolings of the pair classifier on held-out pairs, true against damaged."""
    pairs = _pairs(spark, d).select("pair_id", "src_toks", "tgt_toks", "split")
    train, test = pairs.filter("split = 'train'"), pairs.filter("split = 'dev_a'")
    lex = lexical.fit_alignment(train, 3)
    out = None
    bad = classify.make_negatives(train)
    for pooling in ("cnn", "cls"):
        model = classify.train_acceptability(train, bad, pooling, lex)
        rows = test.select("pair_id", "src_toks", "tgt_toks", F.lit(1).alias("label")).unionByName(classify.make_negatives(test, ("mispaired", "truncated")).select("pair_id", "src_toks", "tgt_toks", F.lit(0).alias("label"))).withColumn("pair_id", F.concat_ws("-", "pair_id", "label", F.size("tgt_toks")))
        part = classify.binary_metrics(rows.join(classify.acceptability(rows, model), "pair_id"), "label", "prob").withColumn("pooling", F.lit(pooling))
        out = part if out is None else out.unionByName(part)
    return out


_FEATS = r"""f AS (SELECT doc_id, quality, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) / greatest(length(text), 1) AS x FROM documents JOIN labels USING (doc_id)),
r AS (SELECT quality, rank() OVER (ORDER BY x) + (count(*) OVER (PARTITION BY x) - 1) / 2 AS mid FROM f)"""


@query("quality_feature_auc", f"WITH {_FEATS} SELECT round((sum(mid) FILTER (quality = 0) - sum(1 - quality) * (sum(1 - quality) + 1) / 2) / (sum(1 - quality) * sum(quality)), 6) AS auc, CAST(sum(1 - quality) AS BIGINT) AS positives, CAST(sum(quality) AS BIGINT) AS negatives FROM r")
def quality_feature_auc(spark, d):
    """How well the share of symbols finds the documents labelled bad."""
    docs = bitext.table(spark, d, "documents").join(bitext.table(spark, d, "labels"), "doc_id")
    rows = docs.select((1 - F.col("quality")).alias("bad"), classify.surface_features(F.col("text"))["symbol_ratio"].alias("x"))
    return classify.binary_metrics(rows, "bad", "x")


_TYPES = f"{SENTS}, t AS (SELECT w AS word, count(*) AS cnt FROM (SELECT unnest(toks) AS w FROM s WHERE lang = 'en') GROUP BY w)"


@query("bpe_pair_counts", f"{_TYPES}, y AS (SELECT cnt, list_append(string_split(word, ''), '</w>') AS y FROM t) SELECT l AS \"left\", r AS \"right\", CAST(sum(cnt) AS BIGINT) AS cnt FROM (SELECT cnt, unnest(y[1:len(y) - 1]) AS l, unnest(y[2:]) AS r FROM y) GROUP BY l, r")
def bpe_pair_counts(spark, d):
    return subword.pair_counts(subword.symbols(subword.word_types(sents(spark, d))))


@query("bpe_learn")
def bpe_learn(spark, d):
    merges = subword.learn_bpe(subword.word_types(sents(spark, d)))
    return spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(merges)], "rank int, left string, right string")


@query("bpe_apply")
def bpe_apply(spark, d):
    """Pieces a sentence, and whether they read back as it."""
    s = keyed(spark, d, "lang = 'en'")
    merges = subword.learn_bpe(subword.word_types(s))
    out = subword.apply_bpe(s, merges, "id")
    return out.join(s.select("id", F.array_join("toks", " ").alias("t")), "id").select("id", F.size("pieces").alias("n_pieces"), (subword.decode_pieces("pieces") == F.col("t")).alias("same"))


@query("vocab_topk", f"{SENTS}, c AS (SELECT lang, w, count(*) AS cnt FROM (SELECT lang, unnest(toks) AS w FROM s) GROUP BY ALL) SELECT lang, CAST(r - 1 AS INTEGER) AS id, w AS tok, cnt FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY cnt DESC, w) AS r FROM c) WHERE r <= 300")
def vocab_topk(spark, d):
    out, s = None, sents(spark, d, "true")
    for lang in ("de", "en", "es", "fr"):
        part = subword.build_vocab(s.filter(F.col("lang") == lang), "toks", 300).withColumn("lang", F.lit(lang))
        out = part if out is None else out.unionByName(part)
    return out


@query("truecase_table", f"{SENTS}, c AS (SELECT form, count(*) AS cnt FROM (SELECT unnest(toks[2:]) AS form FROM s WHERE lang = 'en') GROUP BY form) SELECT lower(form) AS low, min({{'q': -cnt, 'f': form}}).f AS form, max(cnt) AS cnt FROM c GROUP BY 1")
def truecase_table(spark, d):
    return subword.fit_truecase(sents(spark, d))


@query("truecase_apply", f"{SENTS}, c AS (SELECT form, count(*) AS cnt FROM (SELECT unnest(toks[2:]) AS form FROM s WHERE lang = 'en') GROUP BY form), t AS (SELECT lower(form) AS low, min({{'q': -cnt, 'f': form}}).f AS form FROM c GROUP BY 1) SELECT doc_id || ':' || pos AS id, array_to_string(list_concat([coalesce(form, toks[1])], toks[2:]), ' ') AS cased FROM s LEFT JOIN t ON t.low = lower(toks[1]) WHERE lang = 'en'")
def truecase_apply(spark, d):
    s = keyed(spark, d, "lang = 'en'")
    return subword.truecase(s, subword.fit_truecase(s), "id").select("id", F.array_join("toks", " ").alias("cased"))


@query("langid_hashed_lr")
def langid_hashed_lr(spark, d):
    s = sents(spark, d, "true").filter(F.size("toks") >= 5).withColumn("train", F.substring(F.md5(F.col("doc_id").cast("string")), 1, 1) < "c")
    model = classify.hashed_lr(s.filter("train").select("text", "lang"))
    test = s.filter("NOT train").select("text", "lang").withColumn("__g", classify.char_ngrams(F.col("text")))
    return model.transform(test).groupBy((F.col("__y") == F.col("prediction")).alias("right")).agg(F.count("*").alias("n"))

