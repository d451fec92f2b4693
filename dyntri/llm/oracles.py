"""DuckDB SQL of the queries that SQL can express."""

_WORDS = r"regexp_extract_all({}, '[^\x20\x09-\x0D]+')"

#: Measures by unnested windows; the host prior and verdicts as in the operator.
OP4 = rf"""
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id, source, coalesce(text, '') AS t FROM documents
), w AS (
  SELECT *, {_WORDS.format("t")} AS w, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d
), g AS (
  SELECT r, i, list_slice(w, i, i + 4) AS g FROM w, unnest(range(1, len(w) - 3)) AS u(i) WHERE len(w) >= 5
), twice AS (
  SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS n FROM g) WHERE n > 1
), covered AS (
  SELECT r, count(DISTINCT i + k) AS n FROM twice, unnest(range(5)) AS u(k) GROUP BY r
), m AS (
  SELECT w.r, doc_id, source, len(w) AS n_words, length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g')) AS word_chars,
    length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS n_symbols, len(l) - len(list_distinct(l)) AS n_dup_lines,
    coalesce(n, 0) AS n_repeat_words, len(l) AS n_lines, length(t) AS n_chars, length(t) - length(regexp_replace(t, '[A-Z]', '', 'g')) AS capitals
  FROM w LEFT JOIN covered ON covered.r = w.r
), s AS (
  SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
    greatest(n_symbols / greatest(n_words, 1) / 0.2, n_dup_lines / greatest(n_lines, 1) / 0.5, capitals / greatest(n_chars, 1) / 0.4, word_chars / greatest(n_words, 1) / 15.0) AS severity
  FROM m
), h AS (
  SELECT source, count(*) AS n, sum(CASE WHEN base_failed OR severity > 1 THEN 1 ELSE 0 END)::BIGINT AS bad FROM s GROUP BY source
), sums AS (
  SELECT sum(n) AS n, sum(bad) / sum(n) AS m, sum(bad * bad / n) AS s, count(*) AS hosts FROM h
), prior AS (
  SELECT m, CASE WHEN v > 0 THEN greatest(1.0, least(10000.0, m * (1 - m) / v - 1)) ELSE 10000.0 END AS k
  FROM (SELECT m, s / n - m * m - m * (1 - m) * (hosts - 1) / n AS v FROM sums)
), verdict AS (
  SELECT source, greatest(0.75, least(2.0, 1 - 0.25 * CASE WHEN m * (1 - m) > 0 THEN ((bad + m * k) / (n + k) - m) / sqrt(m * (1 - m) / (k + 1)) ELSE 0.0 END)) AS allowed FROM h, prior
)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines,
  n_repeat_words::BIGINT AS n_repeat_words, base_failed,
  NOT base_failed AND severity <= allowed AS kept
FROM s JOIN verdict ON s.source IS NOT DISTINCT FROM verdict.source
"""

#: Every window of every item joined to every window of every document.
OP10 = r"""
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), b AS (
  SELECT coalesce(item_id::VARCHAR, 'null') AS item, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark
), p AS (
  SELECT DISTINCT item, least(10, len(w)) AS k, list_slice(w, i, i + least(10, len(w)) - 1) AS g
  FROM b, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS u(i) WHERE len(w) > 0
), sizes AS (
  SELECT DISTINCT k FROM p
), g AS (
  SELECT r, k, i, list_slice(w, i, i + k - 1) AS g FROM d, sizes, unnest(range(1, len(w) - k + 2)) AS u(i) WHERE len(w) >= k
), hits AS (
  SELECT r, g.k, i, item FROM g JOIN p ON p.k = g.k AND p.g = g.g
), words AS (
  SELECT r, count(DISTINCT i + j) AS n FROM hits, unnest(range(k)) AS u(j) GROUP BY r
), items AS (
  SELECT r, count(*) AS n, string_agg(item, ',' ORDER BY item COLLATE "C") AS ids FROM (SELECT DISTINCT r, item FROM hits) GROUP BY r
)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(words.n, 0)::BIGINT AS n_hit, coalesce(items.n, 0)::BIGINT AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(words.n, 0) > 0 AS contaminated
FROM d LEFT JOIN words ON words.r = d.r LEFT JOIN items ON items.r = d.r
"""

#: Turns by order, control strings escaped by one backslash, lengths of the marks of each role.
OP1 = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'
), e AS (
  SELECT *, length(regexp_replace(text, '([\[<])(\\*)(/?(?:INST|ROLE|TEXT)\]|/?s>|</?SYS>>)', '\1\\\2\3', 'g')) AS n,
    CASE role WHEN 'user' THEN 15 WHEN 'assistant' THEN 9 WHEN 'system' THEN 17
      ELSE 23 + length(regexp_replace(role, '([\[<])(\\*)(/?(?:INST|ROLE|TEXT)\]|/?s>|</?SYS>>)', '\1\\\2\3', 'g')) END AS marks
  FROM c
), g AS (
  SELECT conv_id, count(*) AS turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text) AS said,
    coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, text) FILTER (WHERE role = 'assistant'), '') AS loss, sum(n + marks) AS chars
  FROM e GROUP BY conv_id
)
SELECT conv_id, turns::BIGINT AS n_turns, sha256(said) AS turns_sha256, length(loss)::BIGINT AS loss_chars, sha256(loss) AS loss_sha256, chars::BIGINT AS formatted_chars
FROM g
"""

#: All pairs that share a shingle, exact sizes, and reachability over the links.
OP2 = r"""
WITH RECURSIVE d AS (
  SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), s AS MATERIALIZED (
  SELECT DISTINCT r, md5(array_to_string(list_slice(w, i, i + 3), ' ')) AS g FROM d, unnest(range(1, greatest(len(w) - 2, 2))) AS u(i) WHERE len(w) > 0
), n AS MATERIALIZED (
  SELECT r, count(*) AS n FROM s GROUP BY r
), i AS (
  SELECT x.r AS a, y.r AS b, count(*) AS n FROM s x JOIN s y ON x.g = y.g AND x.r < y.r GROUP BY 1, 2
), l AS MATERIALIZED (
  SELECT a, b FROM i JOIN n p ON p.r = a JOIN n q ON q.r = b WHERE 100 * i.n >= 85 * (p.n + q.n - i.n)
), ways AS MATERIALIZED (
  SELECT a, b FROM l UNION ALL SELECT b, a FROM l
), reach AS (
  SELECT r, r AS m FROM d UNION SELECT b, m FROM reach JOIN ways ON a = reach.r
)
SELECT o.doc_id, coalesce(any_value(n.n), 0)::BIGINT AS n_shingles, min(t.doc_id) AS component_id
FROM reach JOIN d o ON o.r = reach.r JOIN d t ON t.r = reach.m LEFT JOIN n ON n.r = o.r GROUP BY o.r, o.doc_id
"""

#: Five hexadecimal digits of the digest are four characters of base32.
OP3 = """
WITH p AS (
  SELECT page_id, strlen(coalesce(html, '')) AS n, sha1(coalesce(html, '')) AS h FROM pages
), o AS (
  SELECT *, min(page_id) OVER (PARTITION BY h) AS owner FROM p
)
SELECT page_id, n::BIGINT AS payload_bytes,
  array_to_string(list_transform(range(32), lambda j: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((('0x' || substr(h, (1 + 5 * (j // 4))::INT, 5))::BIGINT >> (15 - 5 * (j % 4))) & 31)::INT, 1)), '') AS payload_digest,
  CASE WHEN page_id > owner THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN page_id > owner THEN owner END AS refers_to
FROM o
"""

SQL: dict[str, str] = {"op1_chat_format": OP1, "op2_ngram_jaccard": OP2, "op3_warc": OP3, "op4_quality_rules": OP4, "op10_decontamination": OP10.replace(' COLLATE "C"', "")}
