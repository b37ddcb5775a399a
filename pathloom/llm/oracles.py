"""DuckDB SQL for those operators that it can express."""

from __future__ import annotations

from .licenses import DIGESTS, SPELLINGS, known_texts

#: The checksum's table and steps, from its polynomial.
CRC32 = """
xor(list_reduce(list_prepend(CAST(4294967295 AS BIGINT), list_transform(regexp_extract_all(hex(encode(body)), '..'), lambda x: CAST('0x' || x AS BIGINT))),
    lambda c, b: xor(c >> 8, steps[(xor(c, b) & 255) + 1])), CAST(4294967295 AS BIGINT))
""".strip()

OP9 = f"""
WITH crc AS (SELECT list_transform(range(256), lambda i: list_reduce(list_prepend(CAST(i AS BIGINT), CAST([0, 0, 0, 0, 0, 0, 0, 0] AS BIGINT[])),
        lambda c, z: CASE WHEN c & 1 = 1 THEN xor(CAST(3988292384 AS BIGINT), c >> 1) ELSE c >> 1 END)) AS steps),
d AS (SELECT doc_id, source, COALESCE(text, '') AS body FROM documents),
r AS (SELECT doc_id, source, CAST(strlen(body) + 16 AS BIGINT) AS size, CAST({CRC32} AS BIGINT) AS text_crc32, COALESCE('s' || source, 'n') AS stratum FROM d, crc),
t AS (SELECT *, md5('17|' || COALESCE(CAST(doc_id AS VARCHAR), '') || '|' || CAST(text_crc32 AS VARCHAR)) AS token FROM r),
s AS (SELECT *, CAST(2 * ROW_NUMBER() OVER (PARTITION BY stratum ORDER BY token, doc_id, text_crc32, size) - 1 AS DOUBLE) / (2 * COUNT(*) OVER (PARTITION BY stratum)) AS share FROM t),
p AS (SELECT *, ROW_NUMBER() OVER (ORDER BY share, stratum, token, doc_id, text_crc32, size) - 1 AS rank, COUNT(*) OVER () AS n FROM s)
SELECT doc_id, size, text_crc32, 'rows' AS law, CAST(rank * 40 // n AS INTEGER) AS shard, CAST(rank - ((rank * 40 // n) * n + 39) // 40 AS BIGINT) AS slot, CAST(NULL AS INTEGER) AS grown_shard, source FROM p
""".strip()


def _text(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


def canonical_sql(x: str) -> str:
    """The canonical form of a text."""
    x = f"regexp_replace({x}, {_text('(?im)^[ ' + chr(9) + ']*(?:copyright|[(]c[)]|©)[^' + chr(10) + ']*(?:[0-9]{4}|<year>|[[]year[]])[^' + chr(10) + ']*$|^[ ' + chr(9) + ']*all rights reserved[.]?[ ' + chr(9) + ']*$')}, '', 'g')"
    x = f"regexp_replace(lower({x}), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')"
    for a, b in SPELLINGS:
        x = f"replace({x}, {_text(a)}, {_text(b)})"
    return f"trim({x})"


def digest_sql(x: str) -> str:
    return f"(CASE WHEN {canonical_sql(x)} <> '' THEN sha256({canonical_sql(x)}) END)"


_KNOWN = " UNION ALL ".join(f"SELECT {_text(i)} AS license_id, {_text(t)} AS text" for i, t in known_texts())
_LONG = " UNION ALL ".join(f"SELECT {_text(i)} AS license_id, {_text(d)} AS digest" for i, d in DIGESTS)
OP10 = f"""
WITH notice AS (SELECT digest, MIN(license_id) AS license_id FROM (SELECT license_id, {digest_sql('text')} AS digest FROM ({_KNOWN}) k) x GROUP BY 1),
known AS (SELECT digest, MIN(license_id) AS license_id FROM (SELECT license_id, digest FROM notice UNION ALL {_LONG}) y GROUP BY 1),
d AS (SELECT doc_id, text, {digest_sql('text')} AS text_digest FROM documents),
l AS (SELECT doc_id, UNNEST(string_split(text, chr(10))) AS line FROM documents),
n AS (SELECT doc_id, list_sort(list(DISTINCT license_id)) AS notices FROM (SELECT doc_id, {digest_sql('line')} AS digest FROM l) y JOIN notice USING (digest) GROUP BY 1)
SELECT d.doc_id, d.text_digest, known.license_id, COALESCE(n.notices, []) AS notices FROM d LEFT JOIN known ON d.text_digest = known.digest LEFT JOIN n ON d.doc_id = n.doc_id
""".strip()

OP1 = """
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(COALESCE(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[ \\x09-\\x0D]+'), lambda x: x <> '') AS words FROM documents),
g AS (SELECT DISTINCT doc_id, shingle FROM (SELECT doc_id, UNNEST(CASE WHEN len(words) = 0 THEN [] WHEN len(words) < 5 THEN [array_to_string(words, ' ')] ELSE list_transform(range(1, len(words) - 3), lambda i: array_to_string(words[i:i + 4], ' ')) END) AS shingle FROM w) u),
n AS (SELECT w.doc_id, CAST(COUNT(g.shingle) AS BIGINT) AS n_shingles FROM w LEFT JOIN g ON w.doc_id = g.doc_id GROUP BY 1),
m AS (SELECT a.doc_id AS a, b.doc_id AS b, COUNT(*) AS shared FROM g a JOIN g b ON a.shingle = b.shingle AND a.doc_id < b.doc_id GROUP BY 1, 2),
e AS (SELECT m.a, m.b FROM m JOIN n x ON x.doc_id = m.a JOIN n y ON y.doc_id = m.b WHERE 100 * shared >= 75 * (x.n_shingles + y.n_shingles - shared)),
s AS (SELECT a, b FROM e UNION SELECT b, a FROM e),
r AS (SELECT doc_id AS node, doc_id AS seen FROM documents UNION SELECT r.node, s.b FROM r JOIN s ON r.seen = s.a),
c AS (SELECT node, MIN(seen) AS component FROM r GROUP BY 1)
SELECT n.doc_id, n.n_shingles, c.component AS component_id, n.doc_id = c.component AS kept FROM n JOIN c ON n.doc_id = c.node
""".strip()

OP7 = """
WITH d AS (SELECT doc_id, COALESCE(text, '') AS body, hex(encode(COALESCE(text, ''))) AS h FROM documents),
p AS (SELECT doc_id, UNNEST(range(CAST(length(h) / 2 AS BIGINT))) AS i, h FROM d),
q AS (SELECT doc_id, i, substr(h, CAST(2 * i + 1 AS BIGINT), 2) AS byte, CASE WHEN 2 * i + 200 <= length(h) THEN md5(substr(h, CAST(2 * i + 1 AS BIGINT), 200)) END AS string FROM p),
f AS (SELECT doc_id, i, byte, CASE WHEN string IS NOT NULL AND ROW_NUMBER() OVER (PARTITION BY string ORDER BY doc_id, i) > 1 THEN 1 ELSE 0 END AS later FROM q),
c AS (SELECT doc_id, i, byte, MAX(later) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 99 PRECEDING AND CURRENT ROW) AS gone FROM f),
b AS (SELECT *, LAG(gone, 1, 0) OVER (PARTITION BY doc_id ORDER BY i) AS before FROM c),
k AS (SELECT doc_id, SUM(gone) AS n_removed, SUM(CASE WHEN gone = 1 AND before = 0 THEN 1 ELSE 0 END) AS n_spans, COALESCE(string_agg(CASE WHEN gone = 0 THEN byte END, '' ORDER BY i), '') AS kept FROM b GROUP BY 1)
SELECT d.doc_id, CAST(length(h) / 2 AS BIGINT) AS n_bytes, CAST(COALESCE(n_removed, 0) AS BIGINT) AS n_removed, CAST(COALESCE(n_spans, 0) AS BIGINT) AS n_spans, sha256(unhex(COALESCE(kept, ''))) AS kept_sha256 FROM d LEFT JOIN k ON d.doc_id = k.doc_id
""".strip()

SQL = {"op1_circulant_near_duplicates": OP1, "op7_difference_cover_repeats": OP7, "op9_proportional_shards": OP9, "op10_license_digests": OP10}
