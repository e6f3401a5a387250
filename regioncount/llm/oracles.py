"""DuckDB SQL that gives the same rows as the queries."""

SQL: dict[str, str] = {}

#: crc32 of the UTF-8 bytes: a table by recursion, then a fold over the bytes.
_CRC = """
RECURSIVE crc_bits(b, c, k) AS (
  SELECT range, range, 0 FROM range(256)
  UNION ALL SELECT b, CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END, k + 1 FROM crc_bits WHERE k < 8
),
crc_table AS (SELECT list(c ORDER BY b) AS t FROM crc_bits WHERE k = 8),
"""
#: Eight hexadecimal digits of an attempt's md5 as a number, and the least exponential draw after all attempts.
_BITS = "('0x' || substr(h, {}, 8))::BIGINT"
_DRAW = "-ln((('0x' || substr(md5(coalesce(doc_id::VARCHAR, '') || ':leaf:' || s), 1, 13))::BIGINT + 0.5) / 4503599627370496.0)"

SQL["op1_sharding"] = f"""
WITH {_CRC}
d AS (SELECT doc_id, coalesce(text, '') AS text, (coalesce(strlen(text), 0) + 8)::BIGINT AS size, row_number() OVER () AS rid FROM documents),
hexed AS (SELECT rid, regexp_extract_all(hex(encode(text)), '..') AS h FROM d),
crc AS (
  SELECT rid, xor(list_reduce(
    list_prepend(4294967295::BIGINT, list_transform(h, lambda x: ('0x' || x)::BIGINT)),
    lambda c, x: xor(c >> 8, t[(xor(c, x) & 255) + 1])), 4294967295::BIGINT) AS c
  FROM hexed, crc_table
),
attempts AS (SELECT rid, k, md5(coalesce(doc_id::VARCHAR, '') || ':' || k) AS h FROM d, range(12) r(k)),
places AS (
  SELECT rid, k, (({_BITS.format(1)} * 3) >> 32) * 12 + (({_BITS.format(9)} * 3) >> 32) * 4 + (({_BITS.format(17)} * 4) >> 32) AS place FROM attempts
),
taken AS (SELECT rid, arg_min(place, k) FILTER (WHERE place < 24) AS s24, arg_min(place, k) FILTER (WHERE place < 25) AS s25 FROM places GROUP BY rid),
draws AS (SELECT rid, s, {_DRAW} AS e FROM d JOIN taken USING (rid), range(25) r(s) WHERE s24 IS NULL),
flat AS (SELECT rid, arg_min(s, (e, s)) FILTER (WHERE s < 24) AS f24, arg_min(s, (e, s)) AS f25 FROM draws GROUP BY rid),
best AS (SELECT rid, coalesce(s24, f24) AS shard, coalesce(s25, f25) AS grown FROM taken LEFT JOIN flat USING (rid))
SELECT doc_id, size, c::BIGINT AS text_crc32, 'key' AS law, shard::INTEGER AS shard,
  (row_number() OVER (PARTITION BY shard ORDER BY doc_id NULLS FIRST, c, size) - 1)::BIGINT AS slot,
  grown::INTEGER AS grown_shard, (shard // 12)::INTEGER AS region, (shard // 4)::INTEGER AS rack
FROM d JOIN best USING (rid) JOIN crc USING (rid)
"""

_WORDS = "regexp_extract_all({}, '[^\\x20\\x09-\\x0D]+')"

SQL["op7_quality"] = rf"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
lines AS (SELECT rid, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
at3 AS (SELECT rid, w, unnest(range(1, len(w) - 1)) AS i FROM d),
win AS (SELECT rid, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM at3),
dup AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, g) AS c FROM win) WHERE c >= 2),
pos AS (SELECT DISTINCT rid, i + k AS p FROM dup, range(3) s(k)),
rep AS (SELECT rid, count(*) AS n FROM pos GROUP BY rid),
m AS (
  SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
    length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
    (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, coalesce(n, 0)::BIGINT AS n_repeat_words, len(l) AS n_lines,
    len(list_filter(l, lambda x: regexp_matches(x, '(\.\.\.|\x{{2026}})[\x20\x09-\x0D]*\z'))) AS n_ends,
    len(list_filter(l, lambda x: regexp_matches(x, '^[\x20\x09-\x0D]*[-*\x{{2022}}]'))) AS n_starts,
    len(list_filter(w, lambda x: regexp_matches(x, '[A-Za-z\x{{80}}-\x{{10FFFF}}]'))) AS n_letters, len(list_distinct(w)) AS n_distinct
  FROM d JOIN lines USING (rid) LEFT JOIN rep USING (rid)
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
  NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words OR n_words > 100000 OR word_chars < 2 * n_words
    OR word_chars > 15 * n_words OR n_symbols * 10 > n_words OR n_dup_lines * 100 > 30 * n_lines
    OR n_ends * 100 > 30 * n_lines OR n_starts * 100 > 90 * n_lines OR n_letters * 100 < 50 * n_words OR n_distinct * 100 < 10 * n_words) AS kept
FROM m
"""

SQL["op9_decontamination"] = r"""
WITH q AS (SELECT row_number() OVER () AS uid, item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM benchmark),
d AS (SELECT row_number() OVER () AS rid, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
q5 AS (SELECT uid, item_id, w, unnest(range(1, len(w) - 3)) AS i FROM q),
qs AS (SELECT DISTINCT uid, item_id, array_to_string(w[i:i + 4], ' ') AS g FROM q5
       UNION SELECT uid, item_id, array_to_string(w, ' ') FROM q WHERE len(w) BETWEEN 1 AND 4),
sizes AS (SELECT uid, count(*) AS n FROM qs GROUP BY uid),
lens AS (SELECT DISTINCT least(len(w), 5) AS k FROM q WHERE len(w) > 0),
dk AS (SELECT rid, doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM d, lens),
ds AS (SELECT DISTINCT rid, doc_id, array_to_string(w[i:i + k - 1], ' ') AS g FROM dk)
SELECT doc_id, item_id, n::BIGINT AS n_shingles, count(*)::BIGINT AS n_shared
FROM ds JOIN qs USING (g) JOIN sizes USING (uid) GROUP BY rid, doc_id, uid, item_id, n HAVING count(*) >= ceil(n * 0.8 - 1e-9)
"""
