"""DuckDB SQL for the queries that SQL can express."""

from __future__ import annotations

_WORDS = r"[^\x20\x09-\x0D]+"

QUALITY = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '{_WORDS}') AS w FROM documents),
g AS (SELECT doc_id, unnest(range(1, len(w) - 1)) AS i, w FROM d WHERE len(w) >= 3),
t AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w[i], w[i + 1], w[i + 2]) AS n FROM g),
c AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM t WHERE n > 1) GROUP BY doc_id),
l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM d),
f AS (SELECT doc_id, sum(n - 1) AS dup, sum(n) AS full_lines FROM (SELECT doc_id, line, count(*) AS n FROM l WHERE regexp_matches(line, '{_WORDS}') GROUP BY doc_id, line) GROUP BY doc_id),
b AS (SELECT d.doc_id, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars,
      length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS n_symbols, coalesce(f.dup, 0) AS n_dup_lines, coalesce(c.n, 0) AS n_repeat_words,
      coalesce(f.full_lines, 0) AS full_lines, length(text) AS chars, length(regexp_replace(text, '[^!?]', '', 'g')) AS marks,
      length(regexp_replace(text, '[^A-Z]', '', 'g')) AS upper_n, length(regexp_replace(text, '[^a-z]', '', 'g')) AS lower_n,
      length(regexp_replace(text, '[^0-9]', '', 'g')) AS digits, length(regexp_replace(text, '[^{{}}\[\]\\_=]', '', 'g')) AS braces
      FROM d LEFT JOIN c ON c.doc_id = d.doc_id LEFT JOIN f ON f.doc_id = d.doc_id),
v AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM b)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols,
       CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words, base_failed,
       NOT base_failed AND NOT (100 * n_symbols > 20 * n_words OR word_chars < 2 * n_words OR word_chars > 25 * n_words OR 100 * marks > 40 * n_words
           OR 100 * upper_n > 60 * (upper_n + lower_n) OR 100 * n_dup_lines > 50 * full_lines OR 100 * digits > 40 * chars OR 100 * braces > 10 * chars) AS kept
FROM v"""


NEAR_DUPLICATES = rf"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_WORDS}') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, CASE WHEN len(w) < 3 THEN array_to_string(w, ' ') ELSE w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] END AS g
      FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 1, 2))) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
r AS (SELECT doc_id AS node, doc_id AS root FROM documents UNION SELECT l.b AS node, r.root FROM r JOIN l ON l.a = r.node),
m AS (SELECT node, min(root) AS root FROM r GROUP BY node)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, m.root AS component_id, d.doc_id = m.root AS kept
FROM documents d JOIN m ON m.node = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id"""


#: The table of the reflected 32-bit cyclic redundancy check, from its polynomial.
_CRC_TABLE = "crc AS (SELECT list(list_reduce(list_prepend(n, range(8)), lambda c, i: CASE WHEN c & 1 = 1 THEN xor(CAST(3988292384 AS BIGINT), c >> 1) ELSE c >> 1 END) ORDER BY n) AS tab FROM range(256) t(n))"


def _crc(values: str) -> str:
    """crc32 of a list of byte values, given the table as `tab`."""
    return f"xor(list_reduce(list_prepend(CAST(4294967295 AS BIGINT), {values}), lambda c, b: xor(tab[(xor(c, b) & 255) + 1], c >> 8)), CAST(4294967295 AS BIGINT))"


BASE_SCORES = rf"""
WITH {_CRC_TABLE},
d AS (SELECT doc_id, {_crc("list_transform(string_split(coalesce(CAST(doc_id AS VARCHAR), ''), ''), lambda x: CAST(ascii(x) AS BIGINT))")} % 5 = 1 AS held_out,
      list_append(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_WORDS}'), chr(10)) AS w FROM documents, crc),
t AS (SELECT doc_id, held_out, unnest(w) AS token FROM d),
c AS (SELECT token, count(*) AS c FROM t WHERE NOT held_out GROUP BY token),
n AS (SELECT CAST(sum(c) AS BIGINT) AS n, count(*) AS v FROM c)
SELECT doc_id, held_out, count(*) AS n_tokens, count(c.c) AS n_known, any_value(n) AS train_tokens, round(sum(log10((coalesce(c.c, 0) + 0.5) / (n + 0.5 * (v + 1)))), 4) + 0.0 AS base_score
FROM t LEFT JOIN c ON c.token = t.token, n GROUP BY doc_id, held_out"""


def sharding(keys: list[tuple[int, int]], prime: int, shards: int) -> str:
    """Row numbers in order of id, size and digest; a network over the next power of four, walked on until it lands below the count."""
    step = "SELECT row_number, n, half, mask, x >> half AS l, x & mask AS r FROM {rows}"
    for a, b in keys:
        scrambled = f"((((r + {a}) % {prime}) * ((r + {a}) % {prime})) % {prime} * {b} + {a}) % {prime} & mask"
        step = f"SELECT row_number, n, half, mask, r AS l, xor(l, {scrambled}) AS r FROM ({step})"
    step = f"SELECT row_number, n, half, mask, (l << half) | r AS x FROM ({step})"
    return rf"""
WITH RECURSIVE {_CRC_TABLE},
b AS (SELECT doc_id, coalesce(text, '') AS t, list_transform(string_split(hex(encode(coalesce(text, ''))), ''), lambda x: CAST(instr('0123456789ABCDEF', x) - 1 AS BIGINT)) AS h FROM documents),
e AS (SELECT doc_id, CAST(octet_length(encode(t)) + 1 AS BIGINT) AS size,
      {_crc("CASE WHEN t = '' THEN CAST([] AS BIGINT[]) ELSE list_transform(range(1, octet_length(encode(t)) + 1), lambda i: 16 * h[2 * i - 1] + h[2 * i]) END")} AS text_crc32 FROM b, crc),
o AS (SELECT *, row_number() OVER (ORDER BY doc_id NULLS FIRST, size, text_crc32) - 1 AS row_number, count(*) OVER () AS n FROM e),
s AS (SELECT row_number, n, half, (1 << half) - 1 AS mask, row_number AS x FROM (SELECT row_number, n, CAST((length(bin(greatest(n - 1, 1))) + 1) // 2 AS BIGINT) AS half FROM o)),
w AS ({step.format(rows="s")} UNION ALL SELECT * FROM ({step.format(rows="w WHERE x >= n")})),
f AS (SELECT row_number, x FROM w WHERE x < n)
SELECT doc_id, size, text_crc32, 'rows' AS law, CAST(x % {shards} AS INT) AS shard, x // {shards} AS slot, CAST(NULL AS INT) AS grown_shard, o.row_number FROM o JOIN f ON f.row_number = o.row_number"""
