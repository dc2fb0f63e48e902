"""DuckDB SQL for the queries that SQL can express; written from the definitions, not from the operators."""

ORACLES = {
    "op2_warc_shards": """
WITH p AS (
  SELECT page_id, CAST(strlen(coalesce(html, '')) AS BIGINT) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages
),
f AS (SELECT payload_digest, min(page_id) AS first_id FROM p WHERE payload_bytes >= 100 GROUP BY payload_digest)
SELECT page_id, payload_bytes, payload_digest,
  CASE WHEN first_id <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN first_id <> page_id THEN first_id END AS refers_to
FROM p LEFT JOIN f USING (payload_digest)""",
    "op5_rule_ledger": r"""
WITH t AS (SELECT doc_id, row_number() OVER () AS k, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, k, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words FROM t),
l AS (SELECT k, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM t),
each_word AS (SELECT k, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS i FROM w),
windows AS (
  SELECT k, i, list(word) OVER (PARTITION BY k ORDER BY i ROWS BETWEEN CURRENT ROW AND 7 FOLLOWING) AS g FROM each_word
),
twice AS (SELECT k, i, count(*) OVER (PARTITION BY k, g) AS n FROM windows WHERE len(g) = 8),
hit AS (SELECT DISTINCT k, unnest(range(i, i + 8)) AS i FROM twice WHERE n > 1),
repeated AS (SELECT k, count(*) AS n FROM hit GROUP BY k),
m AS (
  SELECT doc_id, CAST(len(words) AS BIGINT) AS n_words,
    CAST(length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g')) AS BIGINT) AS word_chars,
    CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
    CAST(len(lines) AS BIGINT) AS n_lines, CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines,
    CAST(coalesce(r.n, 0) AS BIGINT) AS n_repeat_words
  FROM w JOIN l USING (k) LEFT JOIN repeated r USING (k)
),
f AS (
  SELECT *,
    CASE WHEN n_words < 20 THEN 1 ELSE 0 END AS f0, CASE WHEN 100 * n_repeat_words > 30 * n_words THEN 2 ELSE 0 END AS f1,
    CASE WHEN n_dup_lines >= 3 AND 100 * n_dup_lines > 60 * n_lines THEN 4 ELSE 0 END AS f2,
    CASE WHEN 100 * n_symbols > 25 * word_chars THEN 8 ELSE 0 END AS f3,
    CASE WHEN n_words > 0 AND (word_chars < 2 * n_words - n_words // 2 OR word_chars > 20 * n_words) THEN 16 ELSE 0 END AS f4
  FROM m
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  f0 + f1 > 0 AS base_failed, f0 + f1 + f2 + f3 + f4 = 0 AS kept, CAST(f0 + f1 + f2 + f3 + f4 AS BIGINT) AS failures
FROM f""",
    "op7_pareto_mix": r"""
WITH d AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size FROM documents
),
s AS (
  SELECT source, CAST(sum(size) AS DOUBLE) AS n,
    CAST([5, 2, 1][(row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1] AS DOUBLE) AS w
  FROM d GROUP BY source
),
b AS (
  SELECT *, 1.5::DOUBLE * sum(n) OVER () - coalesce(sum(2 * n) OVER before, 0) AS remaining,
    sum(w) OVER () - coalesce(sum(w) OVER before, 0) AS w_left
  FROM s WINDOW before AS (ORDER BY 2 * n / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
),
c AS (SELECT *, 2 * n <= w * (remaining / w_left) AS is_full FROM b),
v AS (SELECT min({'k': 2 * n / w, 'part': remaining / w_left}) AS x FROM c WHERE NOT is_full),
g AS (SELECT source, n, CASE WHEN is_full THEN 2 * n ELSE w * (SELECT x.part FROM v) END AS target FROM c),
h AS (SELECT *, least(floor(target / greatest(n, 1)), 2) AS whole FROM g),
r AS (SELECT *, target - whole * n AS rest, (target - whole * n) / greatest(n, 1) AS f FROM h),
q AS (
  SELECT d.doc_id, d.source, d.size, r.n, r.target, r.whole, r.rest,
    (('0x' || substr(md5(d.doc_id || '/17'), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0::DOUBLE AS u,
    CASE WHEN f > 0 AND f < 1 THEN f / (1 - f) * (4096.0::DOUBLE / (4096.0::DOUBLE + d.size)) END AS odds
  FROM d JOIN r ON d.source IS NOT DISTINCT FROM r.source
),
p AS (SELECT *, CASE WHEN size > 0 THEN (u / (1 - u)) / odds END AS rank FROM q),
z AS (SELECT *, sum(size) OVER (PARTITION BY source, rank IS NULL ORDER BY rank, doc_id ROWS UNBOUNDED PRECEDING) AS run FROM p)
SELECT doc_id, size, CAST(n AS BIGINT) AS source_size, round(target, 6) AS target,
  CAST((whole + CASE WHEN rank IS NOT NULL AND run - size / 2.0 <= rest THEN 1 ELSE 0 END) * size AS BIGINT) AS taken
FROM z""",
}
