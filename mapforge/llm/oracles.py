"""DuckDB SQL for the operators whose whole result SQL can express on whole tables."""

from __future__ import annotations

_REACH = """e AS (SELECT a, b FROM links), reach(a, b) AS (SELECT a, a FROM (SELECT DISTINCT a FROM links) UNION SELECT r.a, e.b FROM reach r JOIN e ON r.b = e.a),
    least AS (SELECT a, min(b) AS least FROM reach GROUP BY 1), many AS (SELECT a, count(*) AS n FROM links GROUP BY 1)"""

#: Lines within one edit agree in their first or last eight code points; the edit itself is looked for at every place.
LINES = r"""WITH cut AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents WHERE text IS NOT NULL),
    lines AS (SELECT * FROM cut WHERE regexp_matches(line, '\S')),
    firsts AS (SELECT line, min((doc_id, pos)) AS at, length(line) AS n FROM lines GROUP BY line),
    long_ AS (SELECT *, substr(line, 1, 8) AS head, right(line, 8) AS tail FROM firsts WHERE n >= 16),
    met AS (SELECT a.line AS x, a.at AS xat, a.n AS n, b.line AS y, b.at AS yat, b.n AS m FROM long_ a JOIN long_ b ON a.head = b.head AND a.line <> b.line AND b.n IN (a.n, a.n - 1)
      UNION SELECT a.line, a.at, a.n, b.line, b.at, b.n FROM long_ a JOIN long_ b ON a.tail = b.tail AND a.line <> b.line AND b.n IN (a.n, a.n - 1)),
    same AS (SELECT * FROM met WHERE len(list_filter(range(1, n + 1), lambda i: CASE WHEN n = m THEN substr(x, 1, i - 1) = substr(y, 1, i - 1) AND substr(x, i + 1) = substr(y, i + 1) ELSE substr(x, 1, i - 1) || substr(x, i + 1) = y END)) > 0),
    near AS (SELECT x AS line FROM same WHERE yat < xat UNION SELECT y FROM same WHERE xat < yat),
    judged AS (SELECT c.doc_id, c.pos, c.line, regexp_matches(c.line, '\S') AND near.line IS NOT NULL AS is_near, regexp_matches(c.line, '\S') AND near.line IS NULL AND (c.doc_id, c.pos) <> f.at AS is_copy
      FROM cut c LEFT JOIN firsts f ON f.line = c.line LEFT JOIN near ON near.line = c.line),
    done AS (SELECT doc_id, count(*) FILTER (coalesce(is_near, false) OR coalesce(is_copy, false)) AS removed, count(*) FILTER (coalesce(is_near, false)) AS removed_near,
      coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT (coalesce(is_near, false) OR coalesce(is_copy, false))), '') AS text FROM judged GROUP BY 1)
    SELECT d.doc_id, coalesce(removed, 0) AS removed, coalesce(removed_near, 0) AS removed_near, length(done.text) AS n_chars, sha256(done.text) AS text_sha256 FROM documents d LEFT JOIN done USING (doc_id)"""

VECTORS = f"""WITH RECURSIVE usable AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings WHERE len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
    links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM usable a JOIN usable b ON a.vec_id <> b.vec_id AND len(a.v) = len(b.v) AND list_cosine_similarity(a.v, b.v) >= 0.95), {_REACH}
    SELECT vec_id, coalesce(n, 0) AS n_links, coalesce(least, vec_id) AS component_id, coalesce(least, vec_id) = vec_id AS kept FROM embeddings LEFT JOIN many ON many.a = vec_id LEFT JOIN least ON least.a = vec_id"""

#: Runs of five words as strings; texts of fewer words have one run of all of them.
NEAR_DUPLICATES = rf"""WITH RECURSIVE said AS (SELECT doc_id, regexp_extract_all(lower(text), '[\p{{L}}\p{{N}}_]+') AS w FROM documents WHERE text IS NOT NULL),
    runs AS (SELECT DISTINCT doc_id, hash(array_to_string(w[i : i + 4], ' ')) AS run FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM said WHERE len(w) > 0)),
    sizes AS (SELECT doc_id, count(*) AS n FROM runs GROUP BY 1),
    common AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM runs x JOIN runs y ON x.run = y.run AND x.doc_id <> y.doc_id GROUP BY 1, 2),
    links AS (SELECT a, b FROM common JOIN sizes p ON p.doc_id = a JOIN sizes q ON q.doc_id = b WHERE 5 * c >= 4 * (p.n + q.n - c)), {_REACH}
    SELECT d.doc_id, coalesce(least, d.doc_id) AS class_id, coalesce(n, 0) AS n_links FROM documents d LEFT JOIN many ON many.a = d.doc_id LEFT JOIN least ON least.a = d.doc_id"""

SQL: dict[str, str] = {"op3_lines": LINES, "op5_embeddings": VECTORS, "op7_near_duplicates": NEAR_DUPLICATES}
