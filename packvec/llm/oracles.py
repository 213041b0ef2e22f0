"""DuckDB SQL for the operators that SQL can express on whole tables."""

from __future__ import annotations

def op4() -> str:
    return """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS e FROM embeddings
           WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.e, c.e)::BIGINT AS score FROM v q JOIN v c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank, vec_id, score FROM s)
SELECT * FROM r WHERE rank <= 5"""


def op7() -> str:
    words = r"regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
    return f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce({words}, []) AS w FROM documents),
i AS (SELECT item_id, {words} AS w FROM benchmark WHERE text IS NOT NULL),
wi AS (SELECT DISTINCT item_id, n, array_to_string(list_slice(w, first_at, first_at + n - 1), ' ') AS phrase
       FROM (SELECT item_id, w, least(13, len(w)) AS n, unnest(range(1, len(w) - least(13, len(w)) + 2)) AS first_at FROM i WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM wi),
p AS (SELECT r, n, first_at, array_to_string(list_slice(w, first_at, first_at + n - 1), ' ') AS phrase FROM (SELECT r, w, n, unnest(range(1, len(w) - n + 2)) AS first_at FROM d, sizes WHERE len(w) >= n)),
h AS (SELECT DISTINCT p.r, p.first_at, p.n, wi.item_id FROM p JOIN wi USING (n, phrase)),
hit AS (SELECT r, count(DISTINCT pos) AS n_hit FROM (SELECT r, unnest(range(first_at, first_at + n)) AS pos FROM h) GROUP BY r),
its AS (SELECT r, list_sort(list(DISTINCT item_id::VARCHAR) FILTER (item_id IS NOT NULL)) AS ids FROM h GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(len(ids), 0)::BIGINT AS n_items,
       sha256(coalesce(array_to_string(ids, ','), '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN hit USING (r) LEFT JOIN its USING (r)"""


def op8() -> str:
    return r"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size,
                  md5('7:' || coalesce(doc_id::VARCHAR, '') || ':' || coalesce(text, '')) AS place FROM documents),
s AS (SELECT source, sum(size)::DOUBLE AS n, row_number() OVER (ORDER BY source NULLS LAST) AS first_at FROM d GROUP BY source),
w AS (SELECT source, n, 2 * n AS cap, CASE (first_at - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS w FROM s),
l AS (SELECT a.cap / a.w AS full_at, (1.5 * (SELECT sum(n) FROM s) - coalesce(sum(b.cap) FILTER (b.cap / b.w < a.cap / a.w), 0)) / sum(b.w) FILTER (b.cap / b.w >= a.cap / a.w) AS level FROM w a, w b GROUP BY a.source, a.cap, a.w),
t AS (SELECT source, n, least(cap, (SELECT min_by(level, full_at) FROM l WHERE level < full_at) * w) AS target FROM w),
e AS (SELECT *, CASE WHEN n > 0 THEN floor(target / n) ELSE 0 END AS times FROM t),
u AS (SELECT source, place, sum(size) AS n FROM d GROUP BY ALL),
m AS (SELECT source, place, sum(n) OVER (PARTITION BY source ORDER BY place) - n / 2 AS middle FROM u)
SELECT d.doc_id, d.size, e.n::BIGINT AS source_size, e.target, (d.size * (e.times + CASE WHEN e.target - e.times * e.n > 0 AND m.middle <= e.target - e.times * e.n THEN 1 ELSE 0 END))::BIGINT AS taken
FROM d JOIN e ON d.source IS NOT DISTINCT FROM e.source JOIN m ON m.source IS NOT DISTINCT FROM d.source AND m.place = d.place"""


SQL = {"op4_exact_topk": op4(), "op7_decontamination": op7(), "op8_mixing": op8()}
