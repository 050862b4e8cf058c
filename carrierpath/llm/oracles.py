"""DuckDB SQL with the same rows as the registered queries, where SQL can express them."""

from __future__ import annotations

OP3 = r"""
WITH t AS (
  SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS body FROM documents
)
SELECT doc_id,
       min(doc_id) OVER w AS keep_id,
       count(*) OVER w AS group_size,
       doc_id = min(doc_id) OVER w AS kept,
       sha256(body) AS text_sha256
FROM t WINDOW w AS (PARTITION BY body)
"""

#: From a relation ``docs`` (doc_id, source, size, weight) to the mix of it; shared with the pipeline.
MIX = r"""
sums AS (SELECT source, sum(size)::BIGINT AS source_size FROM docs GROUP BY source),
weighted AS (
  SELECT *, ((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::DOUBLE AS share,
         3.0::DOUBLE * source_size AS most, (sum(source_size) OVER ())::DOUBLE AS total
  FROM sums
),
walk AS (
  SELECT *, most / share AS ratio,
         (total - coalesce(sum(most) OVER (ORDER BY most / share, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
           / sum(share) OVER (ORDER BY most / share, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM weighted
),
first AS (SELECT ratio AS edge, level AS final FROM walk WHERE level <= ratio ORDER BY ratio, level DESC LIMIT 1),
targets AS (
  SELECT source, source_size, CASE WHEN edge IS NULL OR ratio < edge THEN most ELSE share * final END AS target
  FROM walk LEFT JOIN first ON true
),
plan AS (
  SELECT *, CASE WHEN source_size > 0 THEN least(floor(target / source_size), 3) ELSE 0 END::BIGINT AS epochs FROM targets
),
keyed AS (
  SELECT d.*, p.source_size, p.target, p.epochs, p.target - p.epochs * p.source_size AS budget,
         -ln((('0x' || substr(md5(coalesce(d.doc_id::VARCHAR, chr(0)) || '|' || d.size::VARCHAR), 1, 13))::BIGINT + 0.5::DOUBLE) / 4503599627370496.0::DOUBLE) / d.weight AS key
  FROM docs d JOIN plan p ON d.source IS NOT DISTINCT FROM p.source
),
chosen AS (
  SELECT *, least(3, epochs + (coalesce(sum(size) OVER (PARTITION BY source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)
                      + size / 2.0 <= budget)::BIGINT) AS copies
  FROM keyed
)
"""

OP6 = (
    r"""
WITH best AS (SELECT doc_id, max(quality) AS quality FROM labels GROUP BY doc_id),
docs AS (
  SELECT d.doc_id, d.source, len(regexp_extract_all(coalesce(d.text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
         CASE quality WHEN 1 THEN 1.0 WHEN 0 THEN 0.5 ELSE 0.75 END::DOUBLE AS weight
  FROM documents d LEFT JOIN best USING (doc_id)
),"""
    + MIX
    + """
SELECT doc_id, size, source_size, round(target, 6) AS target, (copies * size)::BIGINT AS taken FROM chosen
"""
)


def oracle_sql() -> dict[str, str]:
    return {"op3_exact_dedup": OP3, "op6_mix_sources": OP6}
