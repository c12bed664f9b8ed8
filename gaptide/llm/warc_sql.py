"""DuckDB SQL of the WARC derivatives."""

WARC = r"""
WITH p AS (SELECT page_id, coalesce(page_id::VARCHAR, '') AS page, coalesce(url, '') AS target, coalesce(html, '') AS body FROM pages),
t1 AS (SELECT *, regexp_replace(regexp_replace(regexp_replace(body, '(?s)<!--.*?-->', '', 'g'), '(?is)<script\b[^>]*>.*?</script\s*>', '', 'g'), '(?is)<style\b[^>]*>.*?</style\s*>', '', 'g') AS t FROM p),
t2 AS (SELECT * EXCLUDE t, regexp_replace(regexp_replace(t, '(?i)</?(?:p|div|br|hr|li|ul|ol|dl|dt|dd|h[1-6]|tr|td|th|table|article|section|nav|aside|header|footer|main|title|head|body|html|form|pre|blockquote)\b[^>]*>', chr(10), 'g'), '<[a-zA-Z/!?][^>]*>', '', 'g') AS t FROM t1),
t3 AS (SELECT * EXCLUDE t, string_split(replace(replace(replace(replace(replace(t, '&nbsp;', ' '), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&apos;', chr(39)), '&#') AS s FROM t2),
t4 AS (SELECT * EXCLUDE s, s[1] || array_to_string(list_transform(s[2:], lambda x: CASE
    WHEN regexp_matches(x, '^[0-9]{1,7};') AND coalesce(try_cast(regexp_extract(x, '^([0-9]{1,7});', 1) AS INT), 0) BETWEEN 1 AND 1114111 AND coalesce(try_cast(regexp_extract(x, '^([0-9]{1,7});', 1) AS INT), 0) NOT BETWEEN 55296 AND 57343
      THEN chr(try_cast(regexp_extract(x, '^([0-9]{1,7});', 1) AS INT)) || regexp_replace(x, '^[0-9]{1,7};', '')
    WHEN regexp_matches(x, '^[xX][0-9a-fA-F]{1,6};') AND coalesce(try_cast('0x' || regexp_extract(x, '^[xX]([0-9a-fA-F]{1,6});', 1) AS INT), 0) BETWEEN 1 AND 1114111 AND coalesce(try_cast('0x' || regexp_extract(x, '^[xX]([0-9a-fA-F]{1,6});', 1) AS INT), 0) NOT BETWEEN 55296 AND 57343
      THEN chr(try_cast('0x' || regexp_extract(x, '^[xX]([0-9a-fA-F]{1,6});', 1) AS INT)) || regexp_replace(x, '^[xX][0-9a-fA-F]{1,6};', '')
    ELSE '&#' || x END), '') AS t FROM t3),
t5 AS (SELECT * EXCLUDE t, regexp_replace(regexp_replace(regexp_replace(regexp_replace(replace(t, '&amp;', '&'), '[ \t\r\f]+', ' ', 'g'), ' ?\n[ \n]*', chr(10), 'g'), '^[ \n]+', ''), '[ \n]+$', '') AS plain FROM t4),
t6 AS (SELECT *, 'sha256:' || sha256(body) AS payload_digest, chr(13) || chr(10) AS nl FROM t5),
r AS (
  SELECT page_id, page, target, payload_digest, 'response' AS kind, 'HTTP/1.1 200 OK' || nl || 'Content-Type: text/html; charset=utf-8' || nl || 'Content-Length: ' || strlen(body) || nl || nl || body AS block FROM t6
  UNION ALL
  SELECT page_id, page, target, payload_digest, 'metadata', 'title: ' || regexp_replace(regexp_extract(body, '(?is)<title[^>]*>(.*?)</title', 1), '[\r\n\t]+', ' ', 'g') || nl || 'outlinks: ' || len(regexp_extract_all(body, '(?i)<a\b[^>]*\bhref'))
         || nl || 'source-length: ' || strlen(body) || nl || 'text-length: ' || strlen(plain) || nl || 'source-payload-digest: ' || payload_digest || nl FROM t6
  UNION ALL
  SELECT page_id, page, target, payload_digest, 'conversion', plain FROM t6),
ids AS (SELECT *, md5(kind || ':' || page || ':' || target) AS h, md5('response:' || page || ':' || target) AS g FROM r)
SELECT page_id, kind, '<urn:uuid:' || h[1:8] || '-' || h[9:12] || '-' || h[13:16] || '-' || h[17:20] || '-' || h[21:32] || '>' AS record_id,
  CASE WHEN kind <> 'response' THEN '<urn:uuid:' || g[1:8] || '-' || g[9:12] || '-' || g[13:16] || '-' || g[17:20] || '-' || g[21:32] || '>' END AS refers_to,
  target AS target_uri, strlen(block)::BIGINT AS content_length, 'sha256:' || sha256(block) AS block_digest, payload_digest FROM ids
"""
