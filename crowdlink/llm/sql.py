"""DuckDB SQL for the queries that SQL can express."""

from __future__ import annotations

ORACLES: dict[str, str] = {}

ORACLES["op4_url_filters"] = """
WITH rules(h, p, v) AS (VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'),
                               ('net', '/es/', 'block'), ('net', '/fr/', 'block')),
rest AS (SELECT row_number() OVER () AS n, page_id,
                CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS r FROM pages),
parsed AS (SELECT n, page_id, translate(regexp_extract(r, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
                  regexp_extract(r, '^[^/?#]*(/[^?#]*)', 1) AS path FROM rest),
fit AS (SELECT n, arg_max(h || p, length(h || p)) AS rule, arg_max(v, length(h || p)) AS verdict
        FROM parsed JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY n)
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM parsed LEFT JOIN fit USING (n)
"""

ORACLES["op10_chat"] = r"""
WITH rows AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
              UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
sized AS (SELECT *, length(role) + length(text) + 11 + length(regexp_replace(role || text, '[^\\<>]', '', 'g')) AS shown FROM rows)
SELECT conv_id, count(*)::BIGINT AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
       coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
       sum(shown)::BIGINT AS formatted_chars
FROM sized GROUP BY conv_id
"""

ORACLES["op1_decontamination"] = r"""
WITH d AS (SELECT row_number() OVER () AS n, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
wins AS (SELECT DISTINCT item_id, list_aggregate(w[k:k+9], 'string_agg', ' ') AS s, len(w[k:k+9]) AS m
         FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS k FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT m FROM wins),
dw AS (SELECT n, m, k, list_aggregate(w[k:k+m-1], 'string_agg', ' ') AS s
       FROM (SELECT n, w, m, unnest(range(1, len(w) - m + 2)) AS k FROM d, sizes WHERE len(w) >= m)),
occ AS (SELECT n, item_id, k, m FROM dw JOIN wins USING (s, m)),
hit AS (SELECT n, count(DISTINCT p) AS n_hit FROM (SELECT n, unnest(range(k, k + m)) AS p FROM occ) GROUP BY n),
its AS (SELECT n, count(*) AS n_items, string_agg(i, ',' ORDER BY i) AS l FROM (SELECT DISTINCT n, item_id::VARCHAR AS i FROM occ) GROUP BY n)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(l, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN hit USING (n) LEFT JOIN its USING (n)
"""

#: Rows of one document id and text are treated alike; the given tables repeat no id, so the order is that of ids.
ORACLES["op2_line_dedup"] = r"""
WITH d AS (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents),
l AS (SELECT doc_id, k - 1 AS no, trim(ls[k]) AS line FROM (SELECT doc_id, ls, unnest(range(1, len(ls) + 1)) AS k FROM d)),
f AS (SELECT row_number() OVER (ORDER BY doc_id, no) AS place, doc_id, no, string_split(line, ' ') AS w
      FROM (SELECT line, min_by(doc_id, (doc_id, no)) AS doc_id, min_by(no, (doc_id, no)) AS no FROM l WHERE line <> '' GROUP BY line)),
e AS (SELECT place, w, len(w) AS n, unnest(range(1, len(w) + 1)) AS i FROM f WHERE len(w) >= 8),
cutout AS (SELECT place, n, i, array_to_string(list_concat(w[1:i-1], w[i+1:n]), ' ') AS s FROM e),
whole AS (SELECT place, array_to_string(w, ' ') AS s, len(w) AS n FROM f WHERE len(w) >= 8),
near AS (SELECT a.place FROM cutout a JOIN cutout b USING (n, i, s) WHERE b.place < a.place
         UNION SELECT a.place FROM cutout a JOIN whole b ON a.s = b.s AND b.n = a.n - 1 WHERE b.place < a.place
         UNION SELECT b.place FROM cutout a JOIN whole b ON a.s = b.s AND b.n = a.n - 1 WHERE a.place < b.place),
j AS (SELECT f.doc_id, f.no, near.place IS NOT NULL AS near FROM f LEFT JOIN near ON f.place = near.place),
k AS (SELECT doc_id, count(*) FILTER (NOT near) AS n_kept, count(*) FILTER (near) AS n_near,
             coalesce(string_agg(no, ',' ORDER BY no) FILTER (NOT near), '') AS kept_lines FROM j GROUP BY doc_id),
c AS (SELECT doc_id, count(*) FILTER (line <> '') AS n_lines FROM l GROUP BY doc_id)
SELECT doc_id, coalesce(n_lines, 0)::BIGINT AS n_lines, coalesce(n_kept, 0)::BIGINT AS n_kept, coalesce(n_near, 0)::BIGINT AS n_near, coalesce(kept_lines, '') AS kept_lines
FROM documents LEFT JOIN c USING (doc_id) LEFT JOIN k USING (doc_id)
"""
