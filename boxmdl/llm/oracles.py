"""DuckDB SQL for corpus queries, written from the definitions by other means than the operators."""

from __future__ import annotations


def _remainder(nibble: int) -> int:
    """Table entry of the reflected CRC-32 for four bits."""
    for _ in range(4):
        nibble = (nibble >> 1) ^ (0xEDB88320 if nibble & 1 else 0)
    return nibble


_TABLE = "[" + ", ".join(str(_remainder(i)) for i in range(16)) + "]::BIGINT[]"
_LOW = f"xor(a >> 4, ({_TABLE})[(xor(a, v) & 15) + 1])"

#: All pairs that share a shingle, then every document reachable by links.
OP2_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
i AS (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 3, least(len(ws), 1) + 1))) AS k FROM w),
s AS (SELECT DISTINCT doc_id, array_to_string(ws[k:k + 4], ' ') AS shingle FROM i),
n AS (SELECT doc_id, count(*) AS size FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS both_have FROM s a JOIN s b ON a.shingle = b.shingle AND a.doc_id < b.doc_id GROUP BY ALL),
l AS (SELECT x, y FROM p JOIN n nx ON nx.doc_id = x JOIN n ny ON ny.doc_id = y WHERE 100 * both_have >= 75 * (nx.size + ny.size - both_have)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r AS (SELECT doc_id, doc_id AS root FROM w UNION SELECT e.y, r.root FROM r JOIN e ON e.x = r.doc_id)
SELECT w.doc_id, coalesce(n.size, 0)::BIGINT AS n_shingles, c.component_id, w.doc_id = c.component_id AS kept
FROM w LEFT JOIN n USING (doc_id) JOIN (SELECT doc_id, min(root) AS component_id FROM r GROUP BY doc_id) c USING (doc_id)
"""

#: The checksum is taken nibble by nibble.
OP4_SQL = rf"""
WITH h AS (SELECT doc_id, coalesce(strlen(text), 0) + 16 AS size, hex(encode(coalesce(text, ''))) AS x FROM documents),
b AS (SELECT doc_id, size, list_prepend(4294967295::BIGINT, list_transform(range(0, length(x), 2), lambda i: ('0x' || substr(x, i + 1, 2))::BIGINT)) AS bytes FROM h),
c AS (SELECT doc_id, size, xor(list_reduce(bytes, lambda a, v: xor({_LOW} >> 4, ({_TABLE})[(xor({_LOW}, v >> 4) & 15) + 1])), 4294967295) AS text_crc32 FROM b),
p AS (SELECT *, sum(size) OVER (ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before, sum(size) OVER () AS total FROM c),
s AS (SELECT *, least(39, ((2 * coalesce(before, 0) + size) * 40) // (2 * total))::INT AS shard FROM p)
SELECT doc_id, size::BIGINT AS size, text_crc32::BIGINT AS text_crc32, 'bytes' AS law, shard, (row_number() OVER (PARTITION BY shard ORDER BY doc_id) - 1)::BIGINT AS slot, NULL::INT AS grown_shard FROM s
"""

#: Every window of 200 bytes, grouped.
OP7_SQL = r"""
WITH h AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x, coalesce(strlen(text), 0) AS n FROM documents),
w AS (SELECT doc_id, i, md5(substr(x, 2 * i + 1, 400)) AS m FROM (SELECT doc_id, x, unnest(range(0, n - 199)) AS i FROM h WHERE n >= 200)),
r AS (SELECT m FROM w GROUP BY m HAVING count(*) > 1),
s AS (SELECT doc_id, i, i > coalesce(lag(i) OVER (PARTITION BY doc_id ORDER BY i) + 200, -1) AS opens FROM w SEMI JOIN r USING (m)),
g AS (SELECT doc_id, i, sum(opens::INT) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM s),
cut AS (SELECT doc_id, run, min(i) AS lo, max(i) + 200 AS hi FROM g GROUP BY doc_id, run),
gaps AS (SELECT doc_id, lo, hi, coalesce(lag(hi) OVER (PARTITION BY doc_id ORDER BY lo), 0) AS since FROM cut),
kept AS (SELECT doc_id, string_agg(substr(x, 2 * since + 1, 2 * (lo - since)), '' ORDER BY lo) AS k, sum(hi - lo) AS removed, count(*) AS runs, max(hi) AS last FROM gaps JOIN h USING (doc_id) GROUP BY doc_id)
SELECT h.doc_id, h.n::BIGINT AS n_bytes, coalesce(removed, 0)::BIGINT AS n_removed, coalesce(runs, 0)::BIGINT AS n_spans,
       sha256(unhex(CASE WHEN kept.doc_id IS NULL THEN x ELSE k || substr(x, 2 * last + 1) END)) AS kept_sha256
FROM h LEFT JOIN kept USING (doc_id)
"""
