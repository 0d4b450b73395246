"""DuckDB SQL for the queries that SQL can express; written apart from the operators."""

_LOW = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = rf"regexp_extract_all({_LOW}, '[0-9a-z\x{{80}}-\x{{10FFFF}}]+')"

# crc32 of a string from its hexadecimal digits, by the table of the reflected polynomial 0xEDB88320.
_CRC = """
crc_table AS (
  SELECT list(c ORDER BY i) AS t FROM (
    SELECT i, list_reduce(list_prepend(i, range(8)), lambda c, k: CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END) AS c
    FROM (SELECT unnest(range(256)) AS i))),
crc AS (
  SELECT doc_id, xor(list_reduce(list_prepend(4294967295::BIGINT, [('0x' || substr(h, 2 * j + 1, 2))::BIGINT for j in range(length(h) // 2)]),
      lambda c, b: xor(c >> 8, t[(xor(c, b) & 255) + 1])), 4294967295) AS text_crc32
  FROM (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents), crc_table)
"""

# The characters stripped from a line's ends, and the ids after which documents follow each other.
_BLANK = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"



def _license_sql() -> str:
    from .licenses import LABEL_OF, PHRASES, TEMPLATES

    quoted = ", ".join(f"('{n}', '{LABEL_OF.get(n, n)}', '{t}')" for n, t in TEMPLATES.items())
    bases = ", ".join(f"('{p}', '{label}')" for p, label in PHRASES.items())
    return rf"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
tw AS (SELECT name, label, {_WORDS} AS w FROM (VALUES {quoted}) v(name, label, text)),
tg AS (SELECT name, label, i, len(w) - 3 AS size, array_to_string(w[i + 1:i + 4], ' ') AS g FROM (SELECT name, label, w, unnest(range(0, len(w) - 3)) AS i FROM tw)),
dg AS (SELECT doc_id, i, array_to_string(w[i + 1:i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(0, len(w) - 3)) AS i FROM d)),
met AS (SELECT doc_id, name, label, size, dg.i - tg.i AS diag, tg.i AS t FROM dg JOIN tg ON dg.g = tg.g),
runs AS (SELECT doc_id, name, label, size, diag, t, sum(fresh) OVER (PARTITION BY doc_id, name ORDER BY diag) AS run
         FROM (SELECT *, CASE WHEN diag - lag(diag) OVER (PARTITION BY doc_id, name ORDER BY diag) <= 8 THEN 0 ELSE 1 END AS fresh FROM met)),
spans AS (SELECT doc_id, label, count(DISTINCT t) / any_value(size) AS share FROM runs GROUP BY doc_id, name, label, run HAVING count(DISTINCT t) / any_value(size) >= 0.6),
places AS (SELECT doc_id, label, i FROM (SELECT doc_id, w, unnest(range(0, len(w))) AS i FROM d), (VALUES {bases}) b(phrase, label)
           WHERE w[i + 1] = string_split(phrase, ' ')[1] AND array_to_string(w[i + 1:i + len(string_split(phrase, ' '))], ' ') = phrase),
base AS (SELECT doc_id, count(*) AS n, min(i) AS lo, max(i) AS hi, list(DISTINCT label) AS labels FROM places GROUP BY doc_id),
best AS (SELECT doc_id, max(share) AS share, list(DISTINCT label) AS labels FROM spans GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n, 0) AS n_base, lo AS first_word, hi AS last_word,
       array_to_string(list_sort(coalesce(base.labels, [])), ',') AS base_labels,
       array_to_string(list_sort(list_distinct(coalesce(base.labels, []) || coalesce(best.labels, []))), ',') AS labels,
       greatest(coalesce(share, 0.0), CASE WHEN n > 0 THEN 1.0 ELSE 0.0 END)::DOUBLE AS score
FROM d LEFT JOIN base ON d.doc_id = base.doc_id LEFT JOIN best ON d.doc_id = best.doc_id"""


ORACLE_SQL: dict[str, str] = {
    "op2_license_scan": _license_sql(),
    "op3_line_dedup": f"""
WITH lines AS (SELECT doc_id, i, l[i] AS line, trim(translate(l[i], 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), {_BLANK}) AS k
               FROM (SELECT doc_id, l, unnest(range(1, len(l) + 1)) AS i FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents))),
hot AS (SELECT k FROM lines WHERE k <> '' GROUP BY k HAVING count(DISTINCT doc_id) >= 10)
SELECT doc_id, count(*) AS n_lines, count(hot.k) AS n_dropped, sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE hot.k IS NULL), '')) AS kept_sha256
FROM lines LEFT JOIN hot ON lines.k = hot.k GROUP BY doc_id""",
    "op4_sharding": f"""
WITH {_CRC},
sized AS (SELECT doc_id, strlen(coalesce(text, '')) + 1 AS size FROM documents),
run AS (SELECT doc_id, size, sum(size) OVER (ORDER BY doc_id ROWS UNBOUNDED PRECEDING) - size AS start, sum(size) OVER () AS whole FROM sized),
cut AS (SELECT doc_id, size, CAST(start * 8 // whole AS INTEGER) AS shard FROM run)
SELECT cut.doc_id, CAST(size AS BIGINT) AS size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'bytes' AS law, shard,
       CAST(row_number() OVER (PARTITION BY shard ORDER BY cut.doc_id) - 1 AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard
FROM cut JOIN crc ON cut.doc_id = crc.doc_id""",
    "op5_jaccard_join": rf"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({_LOW}, '[^\x20\x09-\x0D]+') AS w FROM documents),
sets AS (SELECT DISTINCT doc_id, array_to_string(w[s:s + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 5, 0) + 2)) AS s FROM d WHERE len(w) > 0)),
sizes AS (SELECT doc_id, count(*) AS n FROM sets GROUP BY doc_id),
met AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM sets x JOIN sets y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2),
pairs AS (SELECT a, b FROM met JOIN sizes p ON a = p.doc_id JOIN sizes q ON b = q.doc_id WHERE 100 * shared >= 75 * (p.n + q.n - shared)),
links AS (SELECT a, b FROM pairs UNION ALL SELECT b, a FROM pairs),
reach AS (SELECT doc_id AS a, doc_id AS b FROM sizes UNION SELECT reach.a, links.b FROM reach JOIN links ON reach.b = links.a)
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, coalesce(least, d.doc_id) AS component_id
FROM d LEFT JOIN sizes ON d.doc_id = sizes.doc_id LEFT JOIN (SELECT a, min(b) AS least FROM reach GROUP BY a) r ON d.doc_id = r.a""",
    "op6_decontamination": f"""
WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item, {_WORDS} AS w FROM benchmark),
win AS (SELECT DISTINCT item, array_to_string(w[s:s + 9], ' ') AS phrase, least(10, len(w)) AS k
        FROM (SELECT item, w, unnest(range(1, greatest(len(w) - 10, 0) + 2)) AS s FROM b WHERE len(w) > 0)),
grams AS (SELECT doc_id, s, k, array_to_string(w[s:s + k - 1], ' ') AS phrase
          FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS s FROM d, (SELECT DISTINCT k FROM win))),
met AS (SELECT doc_id, s, grams.k, item FROM grams JOIN win ON grams.phrase = win.phrase AND grams.k = win.k),
hit AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + k)) AS p FROM (SELECT DISTINCT doc_id, s, k FROM met)) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item FROM met) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, n_hit IS NOT NULL AS contaminated
FROM d LEFT JOIN hit ON d.doc_id = hit.doc_id LEFT JOIN its ON d.doc_id = its.doc_id""",
}
