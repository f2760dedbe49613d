"""DuckDB SQL for the mix, from the same definitions as the operator."""

from __future__ import annotations

from .mixing import CELL_BITS, GOLDEN, LEAST_BLOCK, MOST_BLOCK, MOST_REPEATS, POINT_BITS, SEED, WEIGHTS


def words_taken_sql(documents: str = "documents") -> str:
    points = 1 << POINT_BITS
    weights = ", ".join(map(str, WEIGHTS))
    assert CELL_BITS < POINT_BITS
    return rf"""
WITH sizes AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size FROM {documents}
), per AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sizes GROUP BY source
), weighed AS (
  SELECT *, row_number() OVER (ORDER BY source IS NULL, source) - 1 AS sid FROM per
), capped AS (
  SELECT *, [{weights}][CAST(sid % {len(WEIGHTS)} AS INT) + 1] AS w, {MOST_REPEATS} * source_size AS cap, CAST(sum(source_size) OVER () AS BIGINT) AS total FROM weighed
), sorted AS (
  SELECT *, CAST(coalesce(sum(cap) OVER (ORDER BY cap / w, sid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS below,
         CAST(sum(w) OVER (ORDER BY cap / w, sid ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS BIGINT) AS rest FROM capped
), level AS (
  SELECT max_by((total - below) / rest, rest) AS level FROM sorted WHERE (total - below) / rest <= cap / w
), targets AS (
  SELECT sid, source, source_size, total, coalesce(least(CAST(cap AS DOUBLE), level * w), CAST(cap AS DOUBLE)) AS target,
         greatest({LEAST_BLOCK}, least({MOST_BLOCK}, total // {1 << 16})) AS block FROM sorted LEFT JOIN level ON true
), shares AS (
  SELECT *, CAST(floor(target / total * {points}) AS BIGINT) AS q FROM targets WHERE target > 0
), spans AS (
  SELECT sid, CAST(sum(q) OVER (ORDER BY sid) AS BIGINT) - q AS lo,
         CASE WHEN row_number() OVER (ORDER BY sid DESC) = 1 THEN {points} ELSE CAST(sum(q) OVER (ORDER BY sid) AS BIGINT) END AS hi FROM shares
), points AS (
  SELECT i AS slot, ((i % {points}) * {GOLDEN}) % {points} AS u FROM (SELECT unnest(range(CAST(coalesce((SELECT max((total + block - 1) // block) FROM targets), 0) AS BIGINT))) AS i)
), slots AS (
  SELECT sid, count(*) AS n FROM points JOIN spans ON lo <= u AND u < hi GROUP BY sid
), ends AS (
  SELECT sid, source, source_size, target, least(coalesce(n, 0) * block, {MOST_REPEATS} * source_size) AS stop FROM targets LEFT JOIN slots USING (sid)
), placed AS (
  SELECT s.doc_id, s.size, e.*, CAST(coalesce(sum(s.size) OVER (PARTITION BY e.sid ORDER BY md5('{SEED}-' || coalesce(CAST(s.doc_id AS VARCHAR), '')), s.doc_id, s.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS begins
  FROM sizes s JOIN ends e ON s.source IS NOT DISTINCT FROM e.source
)
SELECT doc_id, size, source_size, target,
       CAST({" + ".join(f"greatest(0, least({t} * source_size + begins + size, stop) - ({t} * source_size + begins))" for t in range(MOST_REPEATS))} AS BIGINT) AS taken
FROM placed
"""
