"""DuckDB fragments that mirror the derived sources, for the SQL side of the queries."""


def u(*parts: str) -> str:
    """SQL of functions.hashing.uniform over text expressions."""
    key = " || ':' || ".join(f"CAST({p} AS VARCHAR)" for p in parts)
    return f"(CAST('0x' || substr(md5({key}), 1, 8) AS BIGINT) / 4294967296.0)"


def squeeze(x: str) -> str:
    return f"trim(regexp_replace({x}, '\\s+', ' ', 'g'))"


def words(x: str) -> str:
    return f"list_filter(string_split({squeeze(x)}, ' '), lambda w: w <> '')"


SENT = rf"""
raw AS (
  SELECT doc_id, lang, source, generate_subscripts(parts, 1) AS pos, unnest(parts) AS raw
  FROM (SELECT doc_id, lang, source, string_split(regexp_replace(text, '([.!?])\s+', '\1' || chr(10), 'g'), chr(10)) AS parts FROM documents)
), sent AS (SELECT doc_id, lang, source, CAST(pos AS INTEGER) AS pos, {squeeze('raw')} AS text FROM raw WHERE {squeeze('raw')} <> '')
"""


def cipher(digits: int = 4, longest: int = 120) -> str:
    return rf"""{SENT},
en AS (SELECT text, min(source) AS genre, {words('text')} AS tgt_toks FROM sent WHERE lang = 'en' GROUP BY text),
coded AS (SELECT *, list_transform(tgt_toks, lambda t: 'c' || substr(md5(lower(t)), 1, {digits})) AS codes FROM en WHERE len(tgt_toks) BETWEEN 3 AND {longest}),
moved AS (
  SELECT *, list_transform(codes, lambda c, i: CASE WHEN (CASE WHEN i % 2 = 1 THEN i + 1 ELSE i - 1 END) <= len(codes)
      AND substr(md5(codes[((i - 1) // 2) * 2 + 1] || codes[((i - 1) // 2) * 2 + 2]), 1, 1) < '4'
    THEN codes[CASE WHEN i % 2 = 1 THEN i + 1 ELSE i - 1 END] ELSE c END) AS src_toks FROM coded
),
cb AS (
  SELECT md5(array_to_string(src_toks, ' ') || chr(1) || text) AS pair_id, array_to_string(src_toks, ' ') AS src, text AS tgt, src_toks, tgt_toks, genre,
    CASE WHEN s < 0.80 THEN 'train' WHEN s < 0.85 THEN 'dev_a' WHEN s < 0.90 THEN 'dev_b' WHEN s < 0.95 THEN 'test' ELSE 'spare' END AS split
  FROM (SELECT *, {u('text', "'split'")} AS s FROM moved)
)"""


CORRUPT = rf"""{cipher()},
kinds AS (
  SELECT src, tgt, src_toks, substr(md5(tgt), 1, 3) AS h, CAST(floor({u('tgt', "'corrupt'")} * 100) AS INTEGER) AS k,
    lead(tgt) OVER (PARTITION BY substr(md5(tgt), 1, 2) ORDER BY md5(tgt)) AS nxt FROM cb
), german AS (SELECT substr(md5(text), 1, 3) AS h, min(text) AS german FROM sent WHERE lang = 'de' AND text LIKE '% % %' GROUP BY 1),
judged AS (
  SELECT kinds.*, german, CASE
    WHEN k < 3 THEN CASE WHEN nxt IS NULL THEN 'clean' ELSE 'mispaired' END WHEN k < 6 THEN 'truncated' WHEN k < 9 THEN 'copied'
    WHEN k < 12 THEN CASE WHEN german IS NULL THEN 'clean' ELSE 'wrong_lang' END WHEN k < 15 THEN 'markup' WHEN k < 18 THEN 'long_token' WHEN k < 21 THEN 'overlong'
    WHEN k < 24 THEN 'duplicate' ELSE 'clean' END AS truth FROM kinds LEFT JOIN german USING (h)
), damaged AS (
  SELECT CASE truth WHEN 'truncated' THEN array_to_string(src_toks[1:greatest(1, len(src_toks) // 5)], ' ') WHEN 'copied' THEN tgt ELSE src END AS src,
    CASE truth WHEN 'mispaired' THEN nxt WHEN 'wrong_lang' THEN german WHEN 'markup' THEN '<b>' || tgt || '</b>' WHEN 'long_token' THEN tgt || ' ' || repeat('x', 45)
      WHEN 'overlong' THEN array_to_string(list_transform(range(45), lambda i: tgt), ' ') ELSE tgt END AS tgt,
    truth, unnest(CASE WHEN truth = 'duplicate' THEN [0, 1] ELSE [0] END) AS copy FROM judged
), cc AS (SELECT md5(src || chr(1) || tgt) AS pair_id, * FROM damaged)"""

_MARKUP = r"</?[A-Za-z][^<>]*>|<!--"

RULES = {
    "max_words": f"(len({words('src')}) > 120 OR len({words('tgt')}) > 120)",
    "long_word": r"(regexp_matches(src, '\S{41,}') OR regexp_matches(tgt, '\S{41,}'))",
    "markup": f"(regexp_matches(src, '{_MARKUP}') OR regexp_matches(tgt, '{_MARKUP}'))",
    "copy": f"({squeeze('lower(src)')} = {squeeze('lower(tgt)')})",
    "length_ratio": f"(len({words('src')}) * 3 < len({words('tgt')}) OR len({words('tgt')}) * 3 < len({words('src')}))",
}
REASONS = "list_filter([" + ", ".join(f"CASE WHEN {r} THEN '{k}' END" for k, r in RULES.items()) + "], lambda r: r IS NOT NULL)"
