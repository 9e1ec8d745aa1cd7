"""Relational and streaming companions of the methods over the given tables, each with its SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.text import words
from ..operators import selection
from ..operators.filters import FilterCascade
from ..sources.bitext import sentences, table
from ..streaming import ingest
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


def both(name: str, spark_sql: str, duck_sql: str | None = None, *tables: str):
    """A query that both engines read from SQL text; duck_sql where the dialects differ."""

    def run(spark, d):
        text = spark_sql
        for t in tables:
            text = text.replace(f"{{{t}}}", f"parquet.`{d}/{t}.parquet`")
        return spark.sql(text)

    duck = duck_sql or spark_sql
    for t in tables:
        duck = duck.replace(f"{{{t}}}", t)
    query(name, duck)(run)


@query("scan_project_filter", "SELECT doc_id, source, n_chars FROM documents WHERE lang = 'en' AND n_chars BETWEEN 500 AND 5000")
def scan_project_filter(spark, d):
    return table(spark, d, "documents").filter("lang = 'en' AND n_chars BETWEEN 500 AND 5000").select("doc_id", "source", "n_chars")


@query("join_broadcast_labels", "SELECT lang, quality, toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY ALL")
def join_broadcast_labels(spark, d):
    return table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").groupBy("lang", "quality", "toxic").agg(F.count("*").alias("n"))


both("join_sortmerge_orders", "SELECT /*+ MERGE(o) */ o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM {lineitem} l JOIN {orders} o ON l_orderkey = o_orderkey GROUP BY o_orderpriority", None, "lineitem", "orders")
both("join_shuffle_hash_orders", "SELECT /*+ SHUFFLE_HASH(o) */ o_orderstatus, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l_orderkey = o_orderkey GROUP BY o_orderstatus", None, "lineitem", "orders")
both("join_left_outer_unlabelled", "SELECT d.source, count(*) AS n FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.doc_id IS NULL GROUP BY d.source", None, "documents", "labels")
both("join_full_outer_labels", "SELECT count(d.doc_id) AS docs, count(l.doc_id) AS labelled, count(*) AS n FROM {documents} d FULL OUTER JOIN {labels} l ON d.doc_id = l.doc_id", None, "documents", "labels")
both("join_nested_loop_small", "SELECT r_name, n_name FROM {region} r JOIN {nation} n ON length(r_name) > length(n_name)", None, "region", "nation")


@query("join_semi_contaminated", f"WITH {sql.SENT}, {_BENCH} SELECT DISTINCT doc_id FROM sent SEMI JOIN bsent ON md5(lower(sent.text)) = md5(lower(bsent.text))")
def join_semi_contaminated(spark, d):
    return selection.contamination(sentences(spark, d), benchmark_sentences(spark, d)).select("doc_id").distinct()


@query("join_anti_clean", f"WITH {sql.SENT}, {_BENCH} SELECT lang, count(*) AS n FROM sent ANTI JOIN bsent ON md5(lower(sent.text)) = md5(lower(bsent.text)) GROUP BY lang")
def join_anti_clean(spark, d):
    b = benchmark_sentences(spark, d).select(F.md5(F.lower("text")).alias("h")).distinct()
    s = sentences(spark, d)
    return s.join(b, F.md5(F.lower(s["text"])) == b["h"], "left_anti").groupBy("lang").agg(F.count("*").alias("n"))


@query("join_band_length", "SELECT count(*) AS n, CAST(sum(abs(a.n_chars - b.n_chars)) AS BIGINT) AS total FROM (SELECT * FROM documents WHERE lang = 'en') a JOIN (SELECT * FROM documents WHERE lang = 'fr') b ON abs(a.n_chars - b.n_chars) <= 20")
def join_band_length(spark, d):
    """Pairs of documents whose lengths differ by 20 at most: equal bands of 21 meet, with their neighbours, and the rest is checked; no cross join."""
    docs = table(spark, d, "documents")
    a = docs.filter("lang = 'en'").select(F.col("n_chars").alias("x"), F.explode(F.array(*((F.floor(F.col("n_chars") / 21) + i) for i in (-1, 0, 1)))).alias("band"))
    b = docs.filter("lang = 'fr'").select(F.col("n_chars").alias("y"), F.floor(F.col("n_chars") / 21).alias("band"))
    met = a.join(b, "band").filter(F.abs(F.col("x") - F.col("y")) <= 20)
    return met.agg(F.count("*").alias("n"), F.sum(F.abs(F.col("x") - F.col("y"))).alias("total"))


both(
    "join_interval_events",
    "SELECT a.event_type AS before, count(*) AS n FROM {events} a JOIN {events} b ON a.user_id = b.user_id AND b.event_type = 'purchase' AND a.event_type <> 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '10' MINUTE GROUP BY a.event_type",
    None, "events",
)


@query("join_asof_events", "SELECT p.event_id, max({'t': e.ts, 'i': e.event_id}).i AS previous FROM events p LEFT JOIN events e ON e.user_id = p.user_id AND e.ts < p.ts WHERE p.event_type = 'purchase' GROUP BY p.event_id")
def join_asof_events(spark, d):
    """The last event of the same user before each purchase, in one window pass."""
    e = table(spark, d, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(Window.unboundedPreceding, -1)
    return e.withColumn("x", F.max(F.struct("t", "event_id")).over(w)).filter("event_type = 'purchase'").select("event_id", F.col("x.event_id").alias("previous"))


@query("join_lateral_tokens", f"WITH d AS (SELECT lang, unnest({sql.words('text')}) AS w FROM documents) SELECT lang, length(w) AS len, count(*) AS n FROM d GROUP BY ALL")
def join_lateral_tokens(spark, d):
    docs = table(spark, d, "documents")
    lateral = docs.lateralJoin(spark.tvf.explode(words(F.col("text").outer())).toDF("w"))
    return lateral.groupBy("lang", F.length("w").cast("long").alias("len")).agg(F.count("*").alias("n"))


both("agg_cube_lang_source", "SELECT lang, source, count(*) AS n, sum(n_chars) AS chars FROM {documents} GROUP BY CUBE (lang, source)", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY CUBE (lang, source)", "documents")
both("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())", None, "lineitem")
both("agg_distinct_multi", "SELECT lang, count(DISTINCT source) AS sources, count(DISTINCT n_chars) AS lengths, count(DISTINCT md5(text)) AS texts FROM {documents} GROUP BY lang", None, "documents")
both("agg_percentiles", "SELECT lang, percentile(n_chars, 0.5) AS p50, percentile(n_chars, 0.9) AS p90 FROM {documents} GROUP BY lang", "SELECT lang, quantile_cont(n_chars, 0.5) AS p50, quantile_cont(n_chars, 0.9) AS p90 FROM documents GROUP BY lang", "documents")


@query("agg_approx_distinct_tokens")
def agg_approx_distinct_tokens(spark, d):
    """Sketches against exact counts: distinct tokens by HLL, and the median length by KLL."""
    s = sents(spark, d, "true").select("lang", F.explode("toks").alias("w"))
    out = s.groupBy("lang").agg(F.hll_sketch_estimate(F.hll_sketch_agg("w")).alias("estimate"), F.count_distinct("w").alias("exact"), F.kll_sketch_get_quantile_bigint(F.kll_sketch_agg_bigint(F.length("w").cast("long")), F.lit(0.5)).alias("median_length"))
    return out.withColumn("error", F.abs(F.col("estimate") - F.col("exact")) / F.col("exact"))


@query("agg_pivot_quality", "SELECT source, count(*) FILTER (quality = 0) AS bad, count(*) FILTER (quality = 1) AS good FROM documents JOIN labels USING (doc_id) GROUP BY source")
def agg_pivot_quality(spark, d):
    rows = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").withColumn("q", F.when(F.col("quality") == 0, "bad").otherwise("good"))
    return rows.groupBy("source").pivot("q", ["bad", "good"]).agg(F.count(F.lit(1))).na.fill(0)


@query("agg_argmax_source", "SELECT source, min({'q': -n_chars, 'i': doc_id}).i AS longest FROM documents GROUP BY source")
def agg_argmax_source(spark, d):
    return table(spark, d, "documents").groupBy("source").agg(F.min(F.struct((-F.col("n_chars")).alias("q"), "doc_id")).alias("x")).select("source", F.col("x.doc_id").alias("longest"))


both(
    "win_rank_family",
    "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, ntile(4) OVER w AS nt FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)",
    "SELECT o_orderkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, round(percent_rank() OVER w, 6) AS pr, CAST(ntile(4) OVER w AS INTEGER) AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)",
    "orders",
)
both("win_lag_turns", "SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after FROM {conversations} WINDOW w AS (PARTITION BY conv_id ORDER BY turn)", None, "conversations")
both("win_running_sum", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 2) AS running FROM {orders}", None, "orders")
both(
    "win_range_frame",
    "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY datediff(o_orderdate, DATE'1970-01-01') RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS n FROM {orders}",
    "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY datediff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE)) RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS n FROM orders",
    "orders",
)
both(
    "win_first_last",
    "SELECT event_id, first_value(IF(value > 50, event_id, NULL)) IGNORE NULLS OVER w AS first_large, last_value(IF(value > 50, event_id, NULL)) IGNORE NULLS OVER w AS last_large FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)",
    "SELECT event_id, first_value(CASE WHEN value > 50 THEN event_id END IGNORE NULLS) OVER w AS first_large, last_value(CASE WHEN value > 50 THEN event_id END IGNORE NULLS) OVER w AS last_large FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)",
    "events",
)


@query("topk_per_group", "SELECT lang, doc_id, CAST(r AS INTEGER) AS rank FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 10")
def topk_per_group(spark, d):
    return selection.top_per_group(table(spark, d, "documents").select("lang", "doc_id", "n_chars"), "lang", "n_chars", 10, "doc_id").select("lang", "doc_id", "rank")


@query("set_union_intersect_except", f"""WITH {sql.SENT}, {_BENCH}, a AS (SELECT text FROM sent WHERE lang = 'en'), b AS (SELECT text FROM bsent)
SELECT 'union' AS op, count(*) AS n FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'union_all', count(*) FROM (SELECT * FROM a UNION ALL SELECT * FROM b)
UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'intersect_all', count(*) FROM (SELECT * FROM a INTERSECT ALL SELECT * FROM b)
UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'except_all', count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b)""")
def set_union_intersect_except(spark, d):
    a, b = sentences(spark, d).filter("lang = 'en'").select("text"), benchmark_sentences(spark, d).select("text")
    ops = {"union": a.union(b).distinct(), "union_all": a.union(b), "intersect": a.intersect(b), "intersect_all": a.intersectAll(b), "except": a.subtract(b), "except_all": a.exceptAll(b)}
    out = None
    for name, df in ops.items():
        part = df.agg(F.lit(name).alias("op"), F.count("*").alias("n"))
        out = part if out is None else out.unionByName(part)
    return out


both(
    "str_regex_suite",
    r"SELECT doc_id, regexp_extract(text, '([A-Z][a-z]+)', 1) AS first_cap, length(regexp_replace(text, '[aeiou]', '')) AS no_vowels, size(split(text, ' ')) AS parts, translate(substring(text, 1, 20), 'abc', 'xyz') AS tr, levenshtein(lang, source) AS lev, text LIKE '%the%' AS has_the, upper(lang) AS up, instr(text, 'e') AS at FROM {documents}",
    r"SELECT doc_id, coalesce(regexp_extract(text, '([A-Z][a-z]+)', 1), '') AS first_cap, CAST(length(regexp_replace(text, '[aeiou]', '', 'g')) AS INTEGER) AS no_vowels, CAST(len(string_split(text, ' ')) AS INTEGER) AS parts, translate(substr(text, 1, 20), 'abc', 'xyz') AS tr, CAST(levenshtein(lang, source) AS INTEGER) AS lev, text LIKE '%the%' AS has_the, upper(lang) AS up, CAST(instr(text, 'e') AS INTEGER) AS at FROM documents",
    "documents",
)
both(
    "url_parts",
    r"SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host, regexp_extract(url, '://[^/]*/([a-z]{2})/', 1) AS lang, regexp_extract(url, '[?&]page=([0-9]+)', 1) AS page FROM {pages}",
    None, "pages",
)
both(
    "html_to_text",
    r"SELECT page_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' '), '<[^>]*>', ' '), '&amp;', '&'), '\\s+', ' '))) AS text_md5 FROM {pages}",
    r"SELECT page_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '&amp;', '&', 'g'), '\s+', ' ', 'g'))) AS text_md5 FROM pages",
    "pages",
)


@query("arr_hof_suite", f"""{SENTS} SELECT doc_id, pos, array_to_string(list_transform(toks, lambda t: lower(t)), ' ') AS low, len(list_filter(toks, lambda t: length(t) > 5)) AS n_long, CAST(list_sum(list_transform(toks, lambda t: length(t))) AS BIGINT) AS chars,
len(list_filter(toks, lambda t: t = 'the')) > 0 AS has_the, array_to_string(toks[2:3], ' ') AS mid, array_to_string(list_sort(list_distinct(toks)), ' ') AS kinds FROM s""")
def arr_hof_suite(spark, d):
    t = F.col("toks")
    return sents(spark, d, "true").select("doc_id", "pos", F.array_join(F.transform(t, F.lower), " ").alias("low"), F.size(F.filter(t, lambda x: F.length(x) > 5)).cast("long").alias("n_long"), F.aggregate(t, F.lit(0).cast("long"), lambda a, x: a + F.length(x)).alias("chars"), F.exists(t, lambda x: x == "the").alias("has_the"), F.array_join(F.slice(t, 2, 2), " ").alias("mid"), F.array_join(F.array_sort(F.array_distinct(t)), " ").alias("kinds"))


@query("map_token_counts", f"{SENTS}, c AS (SELECT doc_id, w, count(*) AS n FROM (SELECT doc_id, unnest(toks) AS w FROM s) GROUP BY ALL) SELECT doc_id, string_agg(w || '=' || n, ',' ORDER BY w) FILTER (n >= 5) AS often FROM c GROUP BY doc_id")
def map_token_counts(spark, d):
    c = sents(spark, d, "true").select("doc_id", F.explode("toks").alias("w")).groupBy("doc_id", "w").agg(F.count("*").alias("n"))
    m = c.groupBy("doc_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("w", "n")))).alias("m"))
    often = F.map_entries(F.map_filter("m", lambda k, v: v >= 5))
    return m.select("doc_id", F.when(F.size(often) > 0, F.array_join(F.transform(often, lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string"))), ",")).alias("often"))


@query("json_props", """SELECT 'OBJECT<' || array_to_string(list_transform(list_sort(json_keys(props)), lambda k: k || ': ' || CASE json_type(props, '$.' || k)
  WHEN 'UBIGINT' THEN 'BIGINT' WHEN 'VARCHAR' THEN 'STRING' WHEN 'DOUBLE' THEN 'DECIMAL' ELSE json_type(props, '$.' || k) END), ', ') || '>' AS shape, count(*) AS n FROM events GROUP BY 1""")
def json_props(spark, d):
    """Semi-structured properties as VARIANT: schema and count."""
    e = table(spark, d, "events").withColumn("v", F.try_parse_json("props"))
    return e.groupBy(F.schema_of_variant("v").alias("shape")).agg(F.count("*").alias("n"))


both(
    "date_bucket_orders",
    "SELECT date_format(o_orderdate, 'yyyy-MM') AS month, count(*) AS n, max(datediff(DATE'1998-12-31', o_orderdate)) AS oldest FROM {orders} GROUP BY 1",
    "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n, CAST(max(datediff('day', CAST(o_orderdate AS DATE), DATE '1998-12-31')) AS INTEGER) AS oldest FROM orders GROUP BY 1",
    "orders",
)
both(
    "math_suite",
    "SELECT l_linenumber, round(avg(ln(l_extendedprice)), 5) AS l, round(avg(exp(l_discount)), 6) AS e, round(avg(pow(l_tax + 1, 3)), 6) AS p, round(avg(sin(l_quantity)), 5) AS s, max(greatest(l_quantity, 10.0)) AS g, round(avg(l_quantity / nullif(l_discount, 0)), 3) AS d FROM {lineitem} GROUP BY l_linenumber",
    None, "lineitem",
)


@query("stream_row_rules", rf"SELECT doc_id FROM documents WHERE len({sql.words('text')}) <= 120 AND NOT regexp_matches(text, '\S{{41,}}') AND NOT regexp_matches(text, '{sql._MARKUP}')")
def stream_row_rules(spark, d):
    return ingest.drain(ingest.filtered(ingest.read_stream(spark, d, "documents"), FilterCascade.monolingual()).select("doc_id"))


def _events(spark, d):
    return ingest.read_stream(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@query("stream_tumbling", "SELECT epoch(time_bucket(INTERVAL '1 hour', ts))::BIGINT AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    out = ingest.drain(ingest.tumbling(_events(spark, d), "ts", "1 hour", by=("event_type",)), "complete")
    return out.select(F.unix_seconds("start").alias("start"), "event_type", "n", F.round("total", 4).alias("total"))


@query("stream_sliding", "SELECT epoch(time_bucket(INTERVAL '30 minutes', ts) - i * INTERVAL '30 minutes')::BIGINT AS start, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS i) GROUP BY ALL")
def stream_sliding(spark, d):
    return ingest.drain(ingest.sliding(_events(spark, d), "ts", "1 hour", "30 minutes"), "complete").select(F.unix_seconds("start").alias("start"), "n")


@query("stream_session", """WITH o AS (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL '2 hours' THEN 1 ELSE 0 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
g AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM o) SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, count(*) AS n FROM g GROUP BY user_id, g""")
def stream_session(spark, d):
    return ingest.drain(ingest.sessions(_events(spark, d), "ts", "user_id", "2 hours"), "complete").select("user_id", F.unix_seconds("start").alias("start"), "n")


@query("stream_dedup_watermark", "SELECT count(DISTINCT (user_id, event_type)) AS n FROM events")
def stream_dedup_watermark(spark, d):
    """The table as one batch under a watermark longer than it, so the stream gives what a batch would."""
    return ingest.drain(ingest.deduplicated(_events(spark, d), ["user_id", "event_type"], "ts", "3650 days").select("user_id", "event_type")).agg(F.count("*").alias("n"))


@query("stream_static_join", "SELECT quality, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY quality")
def stream_static_join(spark, d):
    joined = ingest.read_stream(spark, d, "documents").join(table(spark, d, "labels"), "doc_id").select("doc_id", "quality")
    return ingest.drain(joined).groupBy("quality").agg(F.count("*").alias("n"))


@query("stream_interval_join", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '10 minutes'")
def stream_interval_join(spark, d):
    e = _events(spark, d)
    left, right = e.filter("event_type = 'click'").select("user_id", F.col("ts").alias("l_ts")), e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("r_ts"))
    return ingest.drain(ingest.interval_join(left, right, "user_id")).agg(F.count("*").alias("n"))


@query("stream_stateful_stats", "SELECT user_id, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY user_id")
def stream_stateful_stats(spark, d):
    out = ingest.drain(ingest.running_stats(_events(spark, d), "user_id"), "update")
    return out.groupBy("user_id").agg(F.max(F.struct("n", "total")).alias("x")).select("user_id", "x.n", F.round("x.total", 4).alias("total"))


@query("udf_scalar_arrow", f"SELECT doc_id, len({sql.words('text')}) AS n FROM documents")
def udf_scalar_arrow(spark, d):
    @F.pandas_udf("long")
    def count(s: pd.Series) -> pd.Series:
        return s.fillna("").str.split().str.len()

    return table(spark, d, "documents").select("doc_id", count("text").alias("n"))


@query("udf_grouped_agg", "SELECT o_orderpriority, median(o_totalprice) AS med FROM orders GROUP BY o_orderpriority")
def udf_grouped_agg(spark, d):
    @F.pandas_udf("double")
    def med(s: pd.Series) -> float:
        return float(s.median())

    return table(spark, d, "orders").groupBy("o_orderpriority").agg(med("o_totalprice").alias("med"))


@query("udf_grouped_map", "SELECT o_orderkey, o_totalprice > max(o_totalprice) OVER (PARTITION BY o_custkey) / 2 AS large FROM orders")
def udf_grouped_map(spark, d):
    def large(f: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"o_orderkey": f["o_orderkey"], "large": f["o_totalprice"] > f["o_totalprice"].max() / 2})

    return table(spark, d, "orders").groupBy("o_custkey").applyInPandas(large, "o_orderkey long, large boolean")


@query("udtf_segments", f"WITH {sql.SENT} SELECT lang, count(*) AS n FROM sent GROUP BY lang")
def udtf_segments(spark, d):
    """Segmentation as a Python table function beside the native one."""
    import re

    @F.udtf(returnType="text string")
    class Segments:
        def eval(self, text: str):
            for part in re.sub(r"([.!?])[ \t\n\x0b\f\r]+", "\\1\n", text or "").split("\n"):
                if part.strip(" \t\n\x0b\f\r"):
                    yield (part,)

    docs = table(spark, d, "documents")
    return docs.lateralJoin(Segments(F.col("text").outer())).groupBy("lang").agg(F.count("*").alias("n"))


both(
    "pricing_summary",
    "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS disc, count(*) AS n FROM {lineitem} WHERE l_shipdate <= DATE'1998-09-02' GROUP BY l_returnflag, l_linestatus",
    None, "lineitem",
)
both(
    "revenue_by_nation",
    "SELECT n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM {customer} JOIN {orders} ON c_custkey = o_custkey JOIN {lineitem} ON l_orderkey = o_orderkey JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey WHERE r_name LIKE 'A%' GROUP BY n_name",
    None, "customer", "orders", "lineitem", "nation", "region",
)
both("top_customers", "SELECT c_custkey, round(sum(o_totalprice), 2) AS total FROM {customer} JOIN {orders} ON c_custkey = o_custkey GROUP BY c_custkey ORDER BY total DESC, c_custkey LIMIT 20", None, "customer", "orders")
both("priority_counts", "SELECT o_orderpriority, count(*) AS n FROM {orders} o WHERE EXISTS (SELECT 1 FROM {lineitem} l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 45) GROUP BY o_orderpriority", None, "orders", "lineitem")
