"""DuckDB twins of the operators' queries, for what SQL can express over whole tables."""

from __future__ import annotations

#: Words of a text, in RE2 syntax.
_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

OP1 = r"""
WITH said AS (
  SELECT conv_id, turn, role, text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
t AS (SELECT conv_id, turn, role AS r0, text AS t0, coalesce(role, '') AS role, coalesce(text, '') AS text FROM said),
e AS (SELECT *, length(role) + length(text) + length(regexp_replace(role || text, '[^\\<>]', '', 'g')) + 17 AS written FROM t)
SELECT conv_id::BIGINT AS conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, r0 NULLS FIRST, t0 NULLS FIRST)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, r0 NULLS FIRST, t0 NULLS FIRST) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(written)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id"""

_LUHN = "list_sum([CASE WHEN i % 2 = 0 THEN d[len(d) - i]::INT WHEN d[len(d) - i]::INT > 4 THEN 2 * d[len(d) - i]::INT - 9 ELSE 2 * d[len(d) - i]::INT END for i in range(0, len(d))]) % 10 = 0"

PII_COUNTS = rf"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
cards AS (SELECT doc_id, string_split(regexp_replace(unnest(regexp_extract_all(text, '[0-9](?:[\x20-]?[0-9])+')), '[^0-9]', '', 'g'), '') AS d FROM t),
good AS (SELECT doc_id, count(*) AS n FROM cards WHERE len(d) BETWEEN 14 AND 19 AND {_LUHN} GROUP BY doc_id)
SELECT t.doc_id::BIGINT AS doc_id,
  len(regexp_extract_all(text, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+'))::BIGINT AS n_email,
  len(list_filter(regexp_extract_all(text, '[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)'), lambda x: len(list_filter(string_split(x, '.'), lambda p: length(ltrim(p, '0')) > 3 OR coalesce(try_cast(right(p, 3) AS INT), 0) > 255)) = 0))::BIGINT AS n_ip,
  coalesce(good.n, 0)::BIGINT AS n_card,
  len(list_filter(regexp_extract_all(text, '\+[0-9][\x20().0-9-]+[0-9]'), lambda x: length(regexp_replace(x, '[^0-9]', '', 'g')) BETWEEN 10 AND 15))::BIGINT AS n_phone
FROM t LEFT JOIN good USING (doc_id)"""

BASE_STATISTICS = rf"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text, {_WORDS} AS w FROM documents),
l AS (SELECT doc_id, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines FROM t),
win AS (SELECT doc_id, i, array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM t)),
again AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, s) AS n FROM win) WHERE n > 1),
cover AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM again) GROUP BY doc_id),
s AS (SELECT t.doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
    length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
    (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, coalesce(cover.n, 0)::BIGINT AS n_repeat_words
  FROM t JOIN l USING (doc_id) LEFT JOIN cover USING (doc_id))
SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM s"""

OP5 = """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
w AS (SELECT doc_id, i, hash(substr(h, 2 * i + 1, 800)) AS k FROM (SELECT doc_id, h, unnest(range(0, greatest(0, len(h) // 2 - 399))) AS i FROM d)),
hot AS (SELECT doc_id, i FROM w JOIN (SELECT k FROM w GROUP BY k HAVING count(*) > 1) USING (k)),
marks AS (SELECT doc_id, i, (coalesce(i > lag(i) OVER (PARTITION BY doc_id ORDER BY i) + 400, true))::INT AS fresh FROM hot),
spans AS (SELECT doc_id, min(i) AS a, max(i) + 400 AS b FROM (SELECT *, sum(fresh) OVER (PARTITION BY doc_id ORDER BY i) AS g FROM marks) GROUP BY doc_id, g),
pieces AS (SELECT doc_id, a, b, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS since FROM spans),
kept AS (SELECT doc_id, sum(b - a)::BIGINT AS n_removed, count(*)::BIGINT AS n_spans, string_agg(substr(h, 2 * since + 1, 2 * (a - since)), '' ORDER BY a) || substr(max(h), 2 * max(b) + 1) AS rest FROM pieces JOIN d USING (doc_id) GROUP BY doc_id)
SELECT d.doc_id::BIGINT AS doc_id, (len(h) // 2)::BIGINT AS n_bytes, coalesce(n_removed, 0)::BIGINT AS n_removed, coalesce(n_spans, 0)::BIGINT AS n_spans, sha256(unhex(coalesce(rest, h))) AS kept_sha256
FROM d LEFT JOIN kept USING (doc_id)"""

OP6 = """
WITH p AS (SELECT page_id::BIGINT AS page_id, encode(coalesce(html, '')) AS body FROM pages),
h AS (SELECT page_id, octet_length(body)::BIGINT AS payload_bytes, sha1(body) AS digest, max(page_id) OVER (PARTITION BY sha256(body)) AS most FROM p)
SELECT page_id, payload_bytes,
  array_to_string([substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((('0x' || substr(digest, 1 + 10 * (j // 8), 10))::BIGINT >> (35 - 5 * (j % 8))::INT) & 31)::INT, 1) for j in range(0, 32)], '') AS payload_digest,
  CASE WHEN page_id = most THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> most THEN most END AS refers_to, CASE WHEN page_id = most THEN true END AS digest_ok
FROM h"""

OP8 = """
WITH RECURSIVE t AS (SELECT doc_id::BIGINT AS doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
sets AS (SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')] ELSE [array_to_string(w[i:i + 2], ' ') for i in range(1, len(w) - 1)] END) AS s FROM t),
x AS MATERIALIZED (SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets),
links AS MATERIALIZED (SELECT a.doc_id AS a, b.doc_id AS b FROM x a JOIN x b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id HAVING 100 * count(*) >= 85 * (any_value(a.n) + any_value(b.n) - count(*))),
both_ways AS MATERIALIZED (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach AS (SELECT a AS doc_id, a AS other FROM both_ways UNION SELECT r.doc_id, l.b FROM reach r JOIN both_ways l ON l.a = r.other),
root AS (SELECT doc_id, min(other) AS root FROM reach GROUP BY doc_id)
SELECT doc_id, len(s)::BIGINT AS n_shingles, coalesce(root, doc_id) AS component_id, coalesce(root, doc_id) = doc_id AS kept FROM sets LEFT JOIN root USING (doc_id)"""

#: The standard reflected polynomial of crc32, bit by bit over the digits of the id.
HOLD_OUT = """
WITH d AS (SELECT doc_id, doc_id::VARCHAR AS s FROM documents),
c AS (SELECT doc_id, list_reduce(list_concat([4294967295::BIGINT], range(0, 8 * length(s))), lambda a, i:
    CASE WHEN ((CASE WHEN i % 8 = 0 THEN xor(a, ascii(substr(s, (i // 8 + 1)::INT, 1))::BIGINT) ELSE a END) & 1) = 1
      THEN xor((CASE WHEN i % 8 = 0 THEN xor(a, ascii(substr(s, (i // 8 + 1)::INT, 1))::BIGINT) ELSE a END) >> 1, 3988292384::BIGINT)
      ELSE (CASE WHEN i % 8 = 0 THEN xor(a, ascii(substr(s, (i // 8 + 1)::INT, 1))::BIGINT) ELSE a END) >> 1 END) AS v FROM d)
SELECT doc_id::BIGINT AS doc_id, xor(v, 4294967295::BIGINT) % 5 = 0 AS held_out FROM c"""

MIXING_TARGETS = f"""
WITH d AS (SELECT doc_id::BIGINT AS doc_id, source, len({_WORDS})::BIGINT AS size FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size, [5, 2, 1][((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT]::DOUBLE AS weight FROM d GROUP BY source),
r AS (SELECT *, 3.0 * source_size AS most, 3.0 * source_size / weight AS ratio FROM s),
l AS (SELECT *, ((SELECT sum(source_size) FROM r) - coalesce(sum(most) OVER o, 0)) / ((SELECT sum(weight) FROM r) - coalesce(sum(weight) OVER o, 0)) AS level FROM r WINDOW o AS (ORDER BY ratio, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
water AS (SELECT first(level ORDER BY ratio, source NULLS LAST) AS w, first(ratio ORDER BY ratio, source NULLS LAST) AS at FROM l WHERE level <= ratio),
targets AS (SELECT source, source_size, CASE WHEN (SELECT w FROM water) IS NULL OR ratio < (SELECT w FROM water) THEN most ELSE least(most, weight * (SELECT w FROM water)) END AS target FROM l)
SELECT doc_id, size, source_size, round(target, 6) AS target FROM d JOIN targets ON d.source IS NOT DISTINCT FROM targets.source"""

ORACLES = {
    "op1_chat_formatting": OP1, "op5_suffix_array_dedup": OP5, "op6_warc_transactions": OP6, "op8_minhash_near_duplicates": OP8,
    "pii_base_counts": PII_COUNTS, "base_text_statistics": BASE_STATISTICS, "quality_hold_out": HOLD_OUT, "mixing_targets": MIXING_TARGETS,
}
