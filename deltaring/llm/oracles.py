"""DuckDB SQL for the corpus queries that SQL can express."""

from __future__ import annotations

WORD = r"[^\x20\x09-\x0D]+"

NEAR_DUPLICATES = f"""WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{WORD}') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 5 THEN list_transform(generate_series(1, len(w) - 4), lambda i: array_to_string(w[i:i + 4], ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS shingle FROM w),
n AS (SELECT doc_id, COUNT(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, COUNT(*) AS common FROM s a JOIN s b ON a.shingle = b.shingle AND a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id),
e AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * common >= 75 * (x.n + y.n - common)),
reach(a, b) AS (SELECT doc_id, doc_id FROM documents UNION SELECT reach.a, e.b FROM reach JOIN e ON e.a = reach.b),
c AS (SELECT a AS doc_id, MIN(b) AS component_id FROM reach GROUP BY a)
SELECT c.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, c.component_id, c.doc_id = c.component_id AS kept FROM c LEFT JOIN n ON n.doc_id = c.doc_id"""


def _hash(seed: int, *parts: str) -> str:
    return f"CAST('0x' || substr(md5(concat_ws(':', '{seed}', {', '.join(parts)})), 1, 15) AS BIGINT)"


def mixing(seed: int = 11, words: int = 16, shard: int = 1024) -> str:
    per = words * shard
    high, low = f"least((k + 1) * {shard}, blocks)", f"(k * {shard})"
    upto = "CAST(CAST(extra AS HUGEINT) * {} // blocks AS BIGINT)"
    return f"""WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '{WORD}')) AS BIGINT) AS size FROM documents),
s AS (SELECT source, CAST(SUM(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS rank FROM d GROUP BY source),
f AS (SELECT *, [5.0, 2.0, 1.0][(rank - 1) % 3 + 1]::DOUBLE AS weight, CAST(SUM(source_size) OVER () AS BIGINT) AS total FROM s),
g AS (SELECT *, 3 * source_size / weight AS fill FROM f),
h AS (SELECT *, (total - coalesce(SUM(3 * source_size) OVER (ORDER BY fill, rank ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / SUM(weight) OVER (ORDER BY fill, rank ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM g),
t AS (SELECT *, least(CAST(3 * source_size AS DOUBLE), (SELECT level FROM h WHERE fill >= level ORDER BY fill, rank LIMIT 1) * weight) AS target FROM h),
q AS (SELECT *, floor(total / {float(words)} + 0.5) AS seats, COUNT(*) OVER () / 2.0 AS half FROM t),
u AS (SELECT *, CAST(CASE WHEN seats > half AND total > 0 THEN greatest(0, floor(target * (seats - half) / total + 0.499999999)) ELSE 0 END AS BIGINT) AS sure, CAST(CASE WHEN total > 0 THEN floor(target * (seats + half) / total + 0.5) + 1 ELSE 0 END AS BIGINT) AS most FROM q),
v AS (SELECT *, seats - SUM(sure) OVER () AS open FROM u),
o AS (SELECT rank, open, target, unnest(generate_series(sure, most - 1)) AS seat FROM v WHERE most > sure AND target > 0),
p AS (SELECT rank, COUNT(*) AS more FROM (SELECT rank, open, row_number() OVER (ORDER BY target / (2 * seat + 1) DESC, rank) AS place FROM o) WHERE place <= open GROUP BY rank),
b AS (SELECT v.rank, source, source_size, target, CAST(ceil(source_size / {float(words)}) AS BIGINT) AS blocks, CAST(sure + coalesce(more, 0) AS BIGINT) AS seats FROM v LEFT JOIN p ON p.rank = v.rank),
c AS (SELECT *, least(seats, 3 * blocks) AS quota FROM b),
e AS (SELECT d.doc_id, d.size, c.source_size, c.target, c.rank, c.blocks, CASE WHEN blocks > 0 THEN quota % blocks ELSE 0 END AS extra, CASE WHEN blocks > 0 THEN quota // blocks ELSE 0 END AS copies, {_hash(seed, "d.doc_id")} AS place FROM d JOIN c ON d.source IS NOT DISTINCT FROM c.source),
x AS (SELECT *, CAST(SUM(size) OVER (PARTITION BY rank ORDER BY place, doc_id, size ROWS UNBOUNDED PRECEDING) - size AS BIGINT) AS begin FROM e),
y AS (SELECT *, unnest(generate_series(begin // {per}, (begin + size - 1) // {per})) AS k FROM x WHERE size > 0 AND extra > 0),
z AS (SELECT *, {high} - {low} AS m, {upto.format(high)} - {upto.format(low)} AS part, {_hash(seed + 1, "rank", "k")} % ({high} - {low}) AS first_block FROM y),
r AS (SELECT doc_id, place, greatest(0, least(k * {per} - begin + greatest(first_block + part - m, 0) * {words}, size) - greatest(k * {per} - begin, 0))
 + greatest(0, least(k * {per} - begin + least(first_block + part, m) * {words}, size) - greatest(k * {per} - begin + first_block * {words}, 0)) AS words FROM z)
SELECT x.doc_id, x.size, x.source_size, x.target, CAST(x.copies * x.size + coalesce((SELECT SUM(words) FROM r WHERE r.doc_id = x.doc_id), 0) AS BIGINT) AS taken FROM x"""


def oracle_sql() -> dict[str, str]:
    return {"op2_near_duplicates": NEAR_DUPLICATES, "op9_mixing": mixing()}
