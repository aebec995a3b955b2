"""DuckDB SQL of the corpus queries that SQL can express on whole tables.

The others have none: tokenizers, trained models, robust estimates and the draws of a mix
are tested in ``tests/llm`` against libraries, brute force and held-out rows.
"""

from __future__ import annotations

_SPLIT = r"regexp_extract_all({0}, '[^\x20\x09-\x0D]+')"
_LOWER = "translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def substring_dedup(window: int = 13) -> str:
    """Words of windows that start in a document of smaller id, cut."""
    wnd = " || ' ' || ".join(["word"] + [f"lead(word, {j}) OVER o" for j in range(1, window)])
    return f"""WITH w AS (SELECT doc_id, {_SPLIT.format("coalesce(text, '')")} AS words FROM documents),
p AS (SELECT doc_id, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS pos FROM w),
k AS (SELECT doc_id, pos, word, {wnd} AS wnd FROM p WINDOW o AS (PARTITION BY doc_id ORDER BY pos)),
o AS (SELECT wnd, min(doc_id) AS least FROM k WHERE wnd IS NOT NULL GROUP BY wnd),
b AS (SELECT k.doc_id, k.pos, k.word, coalesce(o.least < k.doc_id, false) AS bad FROM k LEFT JOIN o USING (wnd)),
c AS (SELECT doc_id, pos, word, bool_or(bad) OVER (PARTITION BY doc_id ORDER BY pos ROWS BETWEEN {window - 1} PRECEDING AND CURRENT ROW) AS cut FROM b),
d AS (SELECT doc_id, count(*) FILTER (cut) AS n_removed, string_agg(word, ' ' ORDER BY pos) FILTER (NOT cut) AS kept FROM c GROUP BY doc_id)
SELECT w.doc_id, len(w.words)::BIGINT AS n_words, coalesce(d.n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(d.kept, '')) AS kept_sha256 FROM w LEFT JOIN d USING (doc_id)"""


def warc(least: int = 1000) -> str:
    """Digests of payloads, and which record the copies of large ones refer to."""
    return f"""WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
r AS (SELECT page_id, strlen(html)::BIGINT AS payload_bytes, sha1(html) AS payload_digest FROM p),
m AS (SELECT *, CASE WHEN payload_bytes >= {least} THEN max(page_id) OVER (PARTITION BY payload_digest) ELSE page_id END AS holder FROM r)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN holder = page_id THEN 'response' ELSE 'revisit' END AS record_type, nullif(holder, page_id) AS refers_to FROM m"""


def _components(node: str, source: str, links: str) -> str:
    """CTEs that give ``reach``: every node with each node that links lead to."""
    return f"""both_ways AS (SELECT a, b FROM {links} UNION ALL SELECT b, a FROM {links}),
reach AS (SELECT a, b FROM both_ways UNION SELECT r.a, l.b FROM reach r JOIN both_ways l ON r.b = l.a),
comp AS (SELECT s.{node}, least(s.{node}, coalesce(min(r.b), s.{node})) AS component_id FROM {source} s LEFT JOIN reach r ON s.{node} = r.a GROUP BY s.{node})"""


def near_dedup(k: int = 4, percent: int = 80) -> str:
    """Components of links between shingle sets, from all pairs that share a shingle."""
    return f"""WITH RECURSIVE w AS (SELECT doc_id, {_SPLIT.format(_LOWER)} AS words FROM documents WHERE doc_id IS NOT NULL),
g AS (SELECT DISTINCT doc_id, array_to_string(words[pos:pos + least({k}, len(words)) - 1], ' ') AS shingle FROM (SELECT doc_id, words, unnest(range(1, greatest(len(words) - {k - 1}, least(len(words), 1)) + 1)) AS pos FROM w)),
n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
s AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM g x JOIN g y ON x.shingle = y.shingle AND x.doc_id < y.doc_id GROUP BY ALL),
links AS (SELECT a, b FROM s JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * shared >= {percent} * (x.n + y.n - shared)),
{_components("doc_id", "documents", "links")}
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, c.component_id, c.component_id = d.doc_id AS kept FROM documents d LEFT JOIN n USING (doc_id) JOIN comp c USING (doc_id)"""


def embedding_dedup(least: float = 0.98) -> str:
    """Components of links between vectors of a label, from all pairs of the label."""
    return f"""WITH RECURSIVE v AS (SELECT vec_id, label, embedding::DOUBLE[] AS x FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
u AS (SELECT vec_id, label, x FROM v WHERE len(x) = list_count(x) AND isfinite(list_sum(x)) AND (list_max(x) > 0 OR list_min(x) < 0)),
links AS (SELECT p.vec_id AS a, q.vec_id AS b FROM u p JOIN u q ON p.label = q.label AND p.vec_id < q.vec_id AND len(p.x) = len(q.x) WHERE list_cosine_similarity(p.x, q.x) >= {least}),
{_components("vec_id", "embeddings", "links")},
deg AS (SELECT a AS vec_id, count(*) AS n FROM both_ways GROUP BY a)
SELECT e.vec_id, coalesce(deg.n, 0)::BIGINT AS n_links, c.component_id, c.component_id = e.vec_id AS kept FROM embeddings e LEFT JOIN deg USING (vec_id) JOIN comp c USING (vec_id)"""


def oracle_sql() -> dict[str, str]:
    return {"op2_substring_dedup": substring_dedup(), "op3_warc": warc(), "op4_near_dedup": near_dedup(), "op9_embedding_dedup": embedding_dedup()}
