"""DuckDB SQL for the operators that SQL can express, over whole tables."""

from __future__ import annotations

WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"
ASCII_LOWER = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

SHARDING = """
WITH RECURSIVE d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
hexed AS (SELECT doc_id, hex(encode(t)) AS h, strlen(t) AS n FROM d),
tbl AS (SELECT list_transform(range(256), lambda i: list_reduce([i, 0, 0, 0, 0, 0, 0, 0, 0], lambda c, z: CASE WHEN c % 2 = 1 THEN xor(3988292384, c // 2) ELSE c // 2 END)) AS t),
crc AS (SELECT doc_id, n + 16 AS size,
  xor(4294967295, list_reduce([4294967295] || list_transform(range(n), lambda k: CAST('0x' || substr(h, 2 * k + 1, 2) AS BIGINT)),
    lambda a, b: xor(a // 256, t[CAST(xor(a % 256, b) AS INTEGER) + 1]))) AS text_crc32 FROM hexed, tbl),
jump AS (
  SELECT doc_id, CAST((doc_id + 18446744073709551616::HUGEINT) % 18446744073709551616::HUGEINT AS UHUGEINT) AS key, 0::BIGINT AS b, 0 AS step FROM d
  UNION ALL
  SELECT doc_id, k, CAST(floor((b + 1)::DOUBLE * (2147483648.0::DOUBLE / ((k // 8589934592)::DOUBLE + 1.0::DOUBLE))) AS BIGINT), step + 1
  FROM (SELECT *, (key * 2862933555777941757::UHUGEINT + 1::UHUGEINT) % 18446744073709551616::UHUGEINT AS k FROM jump WHERE b < 41)),
placed AS (SELECT doc_id, CAST(max(b) FILTER (b < 40) AS INTEGER) AS shard, CAST(max(b) FILTER (b < 41) AS INTEGER) AS grown_shard FROM jump GROUP BY 1)
SELECT doc_id, size, text_crc32, 'key' AS law, shard, row_number() OVER (PARTITION BY shard ORDER BY doc_id) - 1 AS slot, grown_shard FROM placed JOIN crc USING (doc_id)"""

QUALITY = rf"""
WITH d AS (SELECT doc_id, coalesce(source, '') AS source, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, {WORDS} AS w FROM d),
size AS (SELECT doc_id, len(w) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars FROM w),
win AS (SELECT doc_id, i, array_to_string(w[i:i + 4], chr(32)) AS x FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM w WHERE len(w) >= 5)),
twice AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, x) AS c FROM win) WHERE c > 1),
rep AS (SELECT doc_id, count(*) AS n_repeat_words FROM (SELECT DISTINCT doc_id, unnest(range(i, i + 5)) AS p FROM twice) GROUP BY 1),
lines AS (SELECT doc_id, source, text, k, ls[k] AS line FROM (SELECT *, unnest(range(1, len(ls) + 1)) AS k FROM (SELECT *, string_split(text, chr(10)) AS ls FROM d))),
full_lines AS (SELECT *, regexp_extract_all(line, '[^\x20\x09-\x0D]+') AS lw FROM lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]')),
dup AS (SELECT doc_id, count(*) AS n_dup_lines FROM (SELECT doc_id, row_number() OVER (PARTITION BY doc_id, line ORDER BY k) AS r FROM full_lines) WHERE r > 1 GROUP BY 1),
norm AS (SELECT doc_id, source, text, {ASCII_LOWER.format("array_to_string(lw, chr(32))")} AS line, len(lw) AS n FROM full_lines),
freq AS (SELECT source, line, count(DISTINCT text) AS n_docs FROM norm GROUP BY 1, 2),
host AS (SELECT source, count(DISTINCT text) AS host_docs FROM d GROUP BY 1),
hot AS (SELECT source, line FROM freq JOIN host USING (source) WHERE n_docs > 20 AND n_docs > 0.08 * host_docs),
lost AS (SELECT doc_id, CAST(sum(n) AS BIGINT) AS lost FROM norm JOIN hot USING (source, line) GROUP BY 1),
m AS (SELECT doc_id, n_words, word_chars, length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines,
  coalesce(n_repeat_words, 0) AS n_repeat_words, coalesce(lost, 0) AS lost FROM d JOIN size USING (doc_id) LEFT JOIN rep USING (doc_id) LEFT JOIN dup USING (doc_id) LEFT JOIN lost USING (doc_id)),
b AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND n_words - lost >= 0.2 * n_words AS kept, lost AS n_line_words_removed FROM b"""

SUBSTRING = f"""
WITH w AS (SELECT doc_id, {WORDS} AS w FROM documents),
win AS (SELECT doc_id, i, array_to_string(w[i:i + 19], chr(32)) AS x FROM (SELECT doc_id, w, unnest(range(1, len(w) - 18)) AS i FROM w WHERE len(w) >= 20)),
later AS (SELECT doc_id, i FROM (SELECT *, row_number() OVER (PARTITION BY x ORDER BY doc_id, i) AS r FROM win) WHERE r > 1),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 20)) AS p FROM later),
cut AS (SELECT doc_id, count(*) AS n_removed, list(p) AS ps FROM gone GROUP BY 1),
pos AS (SELECT doc_id, p, w[p] AS word FROM (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS p FROM w)),
kept AS (SELECT doc_id, string_agg(word, chr(32) ORDER BY p) AS t FROM pos ANTI JOIN gone USING (doc_id, p) GROUP BY 1)
SELECT doc_id, len(w) AS n_words, coalesce(n_removed, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM w LEFT JOIN cut USING (doc_id) LEFT JOIN kept USING (doc_id)"""

NEAR = f"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all({ASCII_LOWER.format("coalesce(text, '')")}, '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, x FROM (
  SELECT doc_id, array_to_string(w[i:i + 4], chr(32)) AS x FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM w WHERE len(w) >= 5)
  UNION ALL SELECT doc_id, array_to_string(w, chr(32)) FROM w WHERE len(w) BETWEEN 1 AND 4)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
hit AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY 1, 2),
link AS (SELECT a, b FROM hit JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * c >= 85 * (na.n + nb.n - c)),
both_ways AS (SELECT a, b FROM link UNION ALL SELECT b, a FROM link),
reach AS (SELECT DISTINCT a AS node, a AS seen FROM both_ways UNION SELECT r.node, e.b FROM reach r JOIN both_ways e ON e.a = r.seen),
comp AS (SELECT node, min(seen) AS c FROM reach GROUP BY 1),
rep AS (SELECT doc_id, min(o) AS class_id FROM (SELECT x.doc_id, y.doc_id AS o FROM (SELECT doc_id, list(x ORDER BY x) AS l FROM s GROUP BY 1) x JOIN (SELECT doc_id, list(x ORDER BY x) AS l FROM s GROUP BY 1) y ON x.l = y.l) GROUP BY 1)
SELECT w.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(c, w.doc_id) AS component_id, coalesce(c, w.doc_id) = w.doc_id AS kept, coalesce(class_id, w.doc_id) AS class_id
FROM w LEFT JOIN n USING (doc_id) LEFT JOIN comp ON comp.node = w.doc_id LEFT JOIN rep ON rep.doc_id = w.doc_id"""

SQL = {"op2_quality_rules": QUALITY, "op3_substring_dedup": SUBSTRING, "op5_minhash_near_dedup": NEAR, "op6_sharding": SHARDING}
