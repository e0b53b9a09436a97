"""DuckDB SQL of the operators that SQL can express."""

from __future__ import annotations

_OP1 = r"""
WITH d AS (SELECT doc_id, source, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, source, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws FROM d),
lines AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM d),
dups AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup_lines FROM lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY doc_id),
win AS (SELECT doc_id, i, array_to_string(ws[i:i+7], ' ') AS g FROM w, unnest(range(1, len(ws) - 6)) AS r(i) WHERE len(ws) >= 8),
rep AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) WHERE c > 1),
cov AS (SELECT doc_id, count(DISTINCT i + k) AS n_repeat_words FROM rep, unnest(range(0, 8)) AS r(k) GROUP BY doc_id),
base AS (
  SELECT w.doc_id, source, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars,
         length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
         coalesce(n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words
  FROM w LEFT JOIN dups USING (doc_id) LEFT JOIN cov USING (doc_id)),
judged AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM base),
hosts AS (SELECT source, count(*) AS n, sum(base_failed::BIGINT)::BIGINT AS bad FROM judged WHERE source IS NOT NULL GROUP BY source),
o AS (SELECT sum(n) AS total, sum(bad) AS bads, count(*) AS m, sum(n * n)::DOUBLE AS sq, sum(bad * bad / n) AS bad2 FROM hosts),
o2 AS (SELECT *, bads / total AS p, total - sq / total - (m - 1) AS room FROM o),
o3 AS (SELECT p, least(greatest(CASE WHEN p * (1 - p) > 0 AND room > 0
         THEN (bad2 - p * bads - p * (1 - p) * (m - 1)) / (p * (1 - p) * room) ELSE 0 END, 0.0001), 0.9999) AS rho FROM o2),
v AS (SELECT source, (bad + p * (1 / rho - 1)) / (n + (1 / rho - 1)) >= 0.5 AS failed FROM hosts, o3)
SELECT j.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND NOT coalesce(v.failed, false) AS kept, coalesce(v.failed, false) AS host_failed
FROM judged j LEFT JOIN v ON j.source = v.source
"""


_OP4 = r"""
WITH l AS (SELECT doc_id, source, text, pos, line, trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)) AS k
           FROM (SELECT doc_id, source, text, generate_subscripts(ls, 1) AS pos, unnest(ls) AS line
                 FROM (SELECT doc_id, source, text, string_split(text, chr(10)) AS ls FROM documents WHERE text IS NOT NULL))),
bad AS (SELECT k FROM l WHERE k <> '' AND source IS NOT NULL GROUP BY k HAVING count(DISTINCT source) >= 10 AND count(DISTINCT text) >= 10),
m AS (SELECT l.*, bad.k IS NOT NULL AS gone FROM l LEFT JOIN bad ON l.k = bad.k),
r AS (SELECT doc_id, text, count(DISTINCT pos) AS n_lines, count(DISTINCT pos) FILTER (gone) AS n_gone,
             string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone) AS cut FROM m GROUP BY doc_id, text)
SELECT d.doc_id, coalesce(n_lines, 0)::BIGINT AS n_lines, coalesce(n_gone, 0)::BIGINT AS n_removed,
       CASE WHEN n_gone IS NULL OR n_gone = 0 THEN d.text ELSE coalesce(cut, '') END AS text
FROM documents d LEFT JOIN r ON d.doc_id = r.doc_id AND d.text = r.text
"""

_OP6 = r"""
WITH s AS (SELECT doc_id, source AS src, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size FROM documents),
t AS (SELECT src, sum(size)::BIGINT AS source_size FROM s GROUP BY src),
r AS (SELECT *, [5, 2, 1][((row_number() OVER (ORDER BY src NULLS LAST) - 1) % 3 + 1)::INT] AS weight, (2 * source_size)::DOUBLE AS cap FROM t),
b AS (SELECT *, (1.5::DOUBLE * sum(source_size) OVER () - coalesce(sum(cap) OVER o, 0)) / (sum(weight) OVER () - coalesce(sum(weight) OVER o, 0)) AS level
      FROM r WINDOW o AS (ORDER BY cap / weight, src NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
f AS (SELECT *, level * weight >= cap AS is_full FROM b),
g AS (SELECT *, CASE WHEN is_full THEN cap ELSE least(cap, arg_min(CASE WHEN NOT is_full THEN level END, CASE WHEN NOT is_full THEN cap / weight END) OVER () * weight) END AS target FROM f),
p AS (SELECT s.*, g.source_size, g.target, sum(size) OVER w AS upto, row_number() OVER w AS nth
      FROM s JOIN g ON s.src IS NOT DISTINCT FROM g.src
      WINDOW w AS (PARTITION BY s.src ORDER BY md5(doc_id::VARCHAR), doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)),
q AS (SELECT p.*, e, (e * source_size + upto) / target AS finish FROM p, unnest([0, 1]) AS u(e) WHERE size > 0),
c AS (SELECT *, sum(size) OVER (ORDER BY finish, src NULLS LAST, nth, e ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS served FROM q),
k AS (SELECT src, nth, count(*) AS copies FROM c WHERE served <= (SELECT floor(1.5 * sum(size)) FROM s) GROUP BY src, nth)
SELECT p.doc_id, p.size, p.source_size, p.target, (p.size * coalesce(k.copies, 0))::BIGINT AS taken
FROM p LEFT JOIN k ON p.src IS NOT DISTINCT FROM k.src AND p.nth = k.nth
"""


_OP8 = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS e FROM embeddings
           WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NOT NULL AND isfinite(x))) = len(embedding)),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.e, c.e)::BIGINT AS score
      FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e) WHERE q.vec_id % 20 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_host_quality": _OP1, "op4_line_spread": _OP4, "op6_fair_queue_mix": _OP6, "op8_mtree_topk": _OP8}
