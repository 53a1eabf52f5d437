"""SQL for queries whose result is fixed by their contract, however it is found."""

from __future__ import annotations

WORDS = r"list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '')"

#: Windows of 20 words in the order of their starts; all but the first of equal ones are covered.
OP5_SQL = rf"""
WITH d AS MATERIALIZED (SELECT doc_id, {WORDS} AS w FROM documents),
win AS MATERIALIZED (SELECT doc_id, s, md5(array_to_string(w[s + 1:s + 20], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(0, len(w) - 19)) AS s FROM d WHERE len(w) >= 20)),
again AS (SELECT doc_id, s FROM (SELECT doc_id, s, row_number() OVER (PARTITION BY h ORDER BY doc_id, s) AS r FROM win) WHERE r > 1),
gone AS (SELECT DISTINCT doc_id, s + i AS p FROM again, range(0, 20) t(i)),
word AS (SELECT doc_id, unnest(range(0, len(w))) AS p, unnest(w) AS x FROM d),
kept AS (SELECT word.doc_id, count(gone.p) AS n_removed, string_agg(x, ' ' ORDER BY word.p) FILTER (gone.p IS NULL) AS t FROM word LEFT JOIN gone ON gone.doc_id = word.doc_id AND gone.p = word.p GROUP BY word.doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id)
"""

#: All strings of 50 bytes (100 hex digits, cut from blocks of 500 bytes); those a smaller document has too join to runs.
OP7_SQL = r"""
WITH d AS MATERIALIZED (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x FROM documents),
b AS MATERIALIZED (SELECT doc_id, k * 500 AS base, substring(x, k * 1000 + 1, 1098) AS part FROM (SELECT doc_id, x, unnest(range(0, length(x) // 1000 + 1)) AS k FROM d)),
win AS MATERIALIZED (SELECT doc_id, base + i AS s, md5(substring(part, 2 * i + 1, 100)) AS h FROM (SELECT doc_id, base, part, unnest(range(0, least(500, length(part) // 2 - 49))) AS i FROM b WHERE length(part) >= 100)),
hit AS (SELECT doc_id, s FROM (SELECT doc_id, s, min(doc_id) OVER (PARTITION BY h) AS lo FROM win) WHERE lo < doc_id),
step AS (SELECT doc_id, s, CASE WHEN s > lag(s) OVER w + 50 THEN 1 WHEN lag(s) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM hit WINDOW w AS (PARTITION BY doc_id ORDER BY s)),
run AS (SELECT doc_id, min(s) AS a, max(s) + 50 AS e FROM (SELECT doc_id, s, sum(new) OVER (PARTITION BY doc_id ORDER BY s) AS g FROM step) GROUP BY doc_id, g),
gap AS (
  SELECT doc_id, coalesce(lag(e) OVER (PARTITION BY doc_id ORDER BY a), 0) AS a, a AS e FROM run
  UNION ALL SELECT d.doc_id, max(e), any_value(length(x) // 2) FROM run JOIN d ON d.doc_id = run.doc_id GROUP BY d.doc_id),
rest AS (SELECT gap.doc_id, string_agg(substring(x, 2 * a + 1, 2 * (e - a)), '' ORDER BY a) AS t FROM gap JOIN d ON d.doc_id = gap.doc_id GROUP BY gap.doc_id),
total AS (SELECT doc_id, sum(e - a) AS n_removed, count(*) AS n_spans FROM run GROUP BY doc_id)
SELECT d.doc_id, CAST(length(x) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(n_spans, 0) AS BIGINT) AS n_spans, sha256(unhex(coalesce(t, x))) AS kept_sha256
FROM d LEFT JOIN total ON total.doc_id = d.doc_id LEFT JOIN rest ON rest.doc_id = d.doc_id
"""
