"""DuckDB SQL for the queries that SQL can express over whole tables."""

from __future__ import annotations

TOP_K = """WITH v AS (SELECT vec_id, list_transform(CAST(embedding AS DOUBLE[]), lambda x: floor(256*x)) x FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL),
s AS (SELECT q.vec_id query_id, c.vec_id, CAST(list_inner_product(q.x, c.x) AS BIGINT) score FROM v q JOIN v c ON q.vec_id<>c.vec_id WHERE q.vec_id%50=0),
r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) rank, vec_id, score FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank<=5"""

WINDOWS = r"""WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text,''), '[^\x20\x09-\x0D]+') ws FROM documents),
win AS (SELECT doc_id, i, array_to_string(list_slice(ws, i, i+12), ' ') k FROM (SELECT doc_id, ws, unnest(range(1, len(ws)-11)) i FROM w WHERE len(ws)>=13)),
low AS (SELECT k, min(doc_id) m FROM win GROUP BY k),
gone AS (SELECT DISTINCT doc_id, i+j AS p FROM win JOIN low USING (k), (SELECT range j FROM range(13)) WHERE doc_id>m),
words AS (SELECT doc_id, unnest(ws) word, unnest(range(1, len(ws)+1)) p FROM w),
kept AS (SELECT a.doc_id, string_agg(word, ' ' ORDER BY p) s FROM words a ANTI JOIN gone g ON g.doc_id=a.doc_id AND g.p=a.p GROUP BY 1)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) n_words, CAST(coalesce(c,0) AS BIGINT) n_removed, sha256(coalesce(s,'')) kept_sha256
FROM w LEFT JOIN (SELECT doc_id, count(*) c FROM gone GROUP BY 1) x ON x.doc_id=w.doc_id LEFT JOIN kept ON kept.doc_id=w.doc_id"""


def oracles() -> dict[str, str]:
    return {"op4_substring_dedup": WINDOWS, "op5_exact_top_k": TOP_K}
