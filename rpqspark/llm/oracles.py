"""DuckDB SQL of the registered queries that SQL can express.

Without SQL: op1 and the pipeline (XXH64), op3 (approximate), op4 (a fitted model),
op5 and op6 (tokenizers), op7 (HTML) and op10 (bytes); tests hold those against brute force.
"""

from __future__ import annotations

# Words are runs of characters other than ASCII white space; a window is named by its words.
SUBSTRINGS = r"""
WITH docs AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
starts AS (SELECT doc_id, unnest(range(1, len(w) - 11)) AS i FROM docs WHERE len(w) >= 13),
windows AS (SELECT s.doc_id, s.i, array_to_string(list_slice(d.w, s.i, s.i + 12), ' ') AS k FROM starts s JOIN docs d USING (doc_id)),
first AS (SELECT k, min(doc_id) AS least FROM windows GROUP BY k HAVING count(DISTINCT doc_id) > 1),
hits AS (SELECT doc_id, i FROM windows JOIN first USING (k) WHERE doc_id > least),
gone AS (SELECT DISTINCT doc_id, i + j AS i FROM hits, range(0, 13) r(j)),
words AS (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS i FROM docs),
kept AS (SELECT w.doc_id, string_agg(w.word, ' ' ORDER BY w.i) AS t, count(*) AS n FROM words w ANTI JOIN gone g ON w.doc_id = g.doc_id AND w.i = g.i GROUP BY w.doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, (len(d.w) - coalesce(k.n, 0))::BIGINT AS n_removed, sha256(coalesce(k.t, '')) AS kept_sha256
FROM docs d LEFT JOIN kept k ON d.doc_id = k.doc_id"""

PRODUCTS = """
WITH v AS (SELECT vec_id, [floor(256 * x::DOUBLE) for x in embedding] AS e FROM embeddings WHERE embedding IS NOT NULL AND len([x for x in embedding if x IS NULL OR NOT isfinite(x)]) = 0),
p AS (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.e, c.e)::BIGINT AS score FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e) WHERE q.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank FROM p)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5"""


def _secrets() -> str:
    """Places by the lengths of what lies between matches; entropy by counting every window anew."""
    from . import secrets

    q = lambda p: "'" + p.replace("'", "''") + "'"
    kinds = [(0, secrets.ASSIGN, 1, "length(v) >= 6"), (1, "AKIA[A-Z0-9]+", 0, "length(hit) >= 20"), (2, "[0-9a-f]+", 0, "length(hit) >= 24"), (3, "[A-Za-z0-9+/_=-]+", 0, "length(hit) >= 20")]
    parts = " UNION ALL ".join(
        f"""SELECT doc_id, {k} AS kind, hit, (upto - length(hit))::BIGINT AS a, upto::BIGINT AS b FROM (
            SELECT *, sum(length(gap) + length(hit)) OVER (PARTITION BY doc_id ORDER BY i) AS upto FROM (
                SELECT doc_id, unnest(h) AS hit, unnest(list_slice(string_split_regex(text, {q(p)}), 1, len(h))) AS gap, unnest(regexp_extract_all(text, {q(p)}, {group})) AS v, unnest(range(len(h))) AS i
                FROM (SELECT doc_id, text, regexp_extract_all(text, {q(p)}) AS h FROM d))) WHERE {keep}"""
        for k, p, group, keep in kinds
    )
    allowed = " OR ".join(f"regexp_matches(hit, {q(a)})" for a in secrets.ALLOWED)
    names = "[" + ", ".join(f"'{k}'" for k in secrets.KINDS) + "]"
    w = secrets.WINDOW
    x, y, z = secrets.BOUNDS
    joined = lambda only: f"coalesce(string_agg({names}[kind + 1] || ':' || a || ':' || b, ',' ORDER BY a, kind, b) FILTER (WHERE {only}), '')"
    return f"""
    WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents), m AS ({parts}), base AS (SELECT * FROM m WHERE kind < 3),
    c AS (SELECT row_number() OVER () AS id, * FROM m WHERE kind = 3 AND regexp_matches(hit, '[0-9]') AND regexp_matches(hit, '[A-Za-z]') AND NOT ({allowed})
        AND NOT EXISTS (SELECT 1 FROM base WHERE base.doc_id = m.doc_id AND base.a <= m.a AND m.b <= base.b)),
    letters AS (SELECT id, i, unnest(string_split(substr(hit, i::INT + 1, {w}), '')) AS ch FROM (SELECT id, hit, unnest(range(0, length(hit) - {w - 1})) AS i FROM c)),
    windows AS (SELECT id, i, log2({w}) - sum(n * log2(n)) / {w} AS h FROM (SELECT id, i, ch, count(*) AS n FROM letters GROUP BY ALL) GROUP BY id, i),
    more AS (SELECT c.doc_id, kind, hit, a, b FROM c JOIN (SELECT id, max(h) AS h FROM windows GROUP BY id) USING (id)
        WHERE h >= CASE WHEN regexp_matches(hit, '^([0-9a-f]+|[0-9A-F]+)$') THEN {x} WHEN regexp_matches(hit, '^([0-9a-z]+|[0-9A-Z]+)$') THEN {y} ELSE {z} END),
    spans AS (SELECT * FROM base UNION ALL SELECT * FROM more)
    SELECT d.doc_id, count(*) FILTER (WHERE kind = 0) AS n_assign, count(*) FILTER (WHERE kind = 1) AS n_access, count(*) FILTER (WHERE kind = 2) AS n_hex,
        sha256({joined("kind < 3")}) AS base_sha256, {joined("kind >= 0")} AS spans
    FROM d LEFT JOIN spans s ON d.doc_id = s.doc_id GROUP BY d.doc_id"""


def oracle_sql() -> dict[str, str]:
    return {"op2_substrings": SUBSTRINGS, "op8_products": PRODUCTS, "op9_secrets": _secrets()}
