"""DuckDB SQL of the path workload. Transitions are written by hand here, apart from the
automaton code; recursion with UNION gives set semantics."""

from __future__ import annotations

from .table1 import QUERIES

LEAD = "lead(user_id) OVER (ORDER BY ts, event_id)"
GRAPHS = {
    "trade": """SELECT 'customer:' || c_custkey AS s, 'lives_in' AS p, 'nation:' || c_nationkey AS o FROM customer
        UNION SELECT 'nation:' || n_nationkey, 'in_region', 'region:' || n_regionkey FROM nation
        UNION SELECT 'supplier:' || s_suppkey, 'based_in', 'nation:' || s_nationkey FROM supplier
        UNION SELECT 'order:' || o_orderkey, 'placed_by', 'customer:' || o_custkey FROM orders
        UNION SELECT 'order:' || l_orderkey, 'has_part', 'part:' || l_partkey FROM lineitem
        UNION SELECT 'part:' || l_partkey, 'supplied_by', 'supplier:' || l_suppkey FROM lineitem
        UNION SELECT 'part:' || p_partkey, 'of_brand', 'brand:' || p_brand FROM part""",
    "flow": f"""SELECT DISTINCT 'user:' || user_id AS s, event_type AS p, 'user:' || nxt AS o
        FROM (SELECT user_id, event_type, {LEAD} AS nxt FROM events) WHERE nxt IS NOT NULL""",
    "pulse": f"""SELECT DISTINCT 'user:' || user_id AS s, event_type || '_' || (CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS INT) // 10) AS p, 'user:' || nxt AS o
        FROM (SELECT user_id, event_type, props, {LEAD} AS nxt FROM events) WHERE nxt IS NOT NULL""",
    "web": """SELECT 'page:' || page_id AS s, 'on_host' AS p, 'host:' || regexp_extract(url, 'https?://([^/]+)', 1) AS o FROM pages
        UNION SELECT 'host:' || h, 'parent', 'host:' || substr(h, strpos(h, '.') + 1) FROM (
            SELECT array_to_string(list_slice(string_split(h, '.'), i, 100), '.') AS h FROM (
                SELECT h, unnest(range(1, len(string_split(h, '.')) + 1)) AS i FROM (SELECT DISTINCT regexp_extract(url, 'https?://([^/]+)', 1) AS h FROM pages))) WHERE h LIKE '%.%'
        UNION SELECT 'page:' || page_id, 'in_lang', 'lang:' || regexp_extract(url, 'https?://[^/]+/([a-z]{2})/', 1) FROM pages WHERE regexp_extract(url, 'https?://[^/]+/([a-z]{2})/', 1) <> ''
        UNION SELECT 'page:' || page_id, 'links_to', 'term:' || unnest(regexp_extract_all(html, '<a href="/([^"]*)"', 1)) FROM pages""",
    "chat": """SELECT DISTINCT 'turn:' || conv_id || '.' || turn AS s, role AS p, 'turn:' || conv_id || '.' || nxt AS o
        FROM (SELECT conv_id, turn, role, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL""",
    "succ": """SELECT DISTINCT 'part:' || l_partkey AS s, l_returnflag AS p, 'part:' || nxt AS o
        FROM (SELECT l_partkey, l_returnflag, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS nxt FROM lineitem) WHERE nxt IS NOT NULL""",
    "docs": """SELECT 'doc:' || doc_id AS s, 'in_lang' AS p, 'lang:' || lang AS o FROM documents
        UNION SELECT 'doc:' || doc_id, 'from_source', 'source:' || source FROM documents
        UNION SELECT 'doc:' || doc_id, 'same_text', 'doc:' || nxt FROM (SELECT doc_id, lead(doc_id) OVER (PARTITION BY text ORDER BY doc_id) AS nxt FROM documents) WHERE nxt IS NOT NULL
        UNION SELECT 'doc:' || doc_id, 'quality', 'quality:' || quality FROM labels""",
    "knn": """SELECT 'vec:' || a AS s, 'near_' || label AS p, 'vec:' || b AS o FROM (
        SELECT x.vec_id AS a, x.label, y.vec_id AS b, row_number() OVER (PARTITION BY x.vec_id ORDER BY list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) DESC, y.vec_id) AS k
        FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) WHERE k <= 5""",
}

# Transitions (state, label, state) of the workload, start state 0; then the final states.
_STARS = ["view_0", "click_1", "purchase_2", "signup_3", "error_4"]
TRANSITIONS = {
    "w01": ("0 on_host 1, 1 parent 1", "1"),
    "w02": ("0 parent 0", "0"),
    "w02b": ("0 click_1 0", "0"),
    "w03": ("0 error 1, 1 error 1", "1"),
    "w03b": ("0 error_3 1, 1 error_3 1", "1"),
    "w04": ("0 click_1 0", "0"),
    "w04b": ("0 click 0", "0"),
    "w05": ("0 on_host 1, 1 parent 1", "1"),
    "w06": ("0 placed_by 1, 1 lives_in 2", "2"),
    "w07": ("0 click_1 0, 0 view_2 1, 1 view_2 1", "0, 1"),
    "w07b": ("0 user 0, 0 assistant 1, 1 assistant 1", "0, 1"),
    "w08": ("0 lives_in 1, 1 in_region 2", "2"),
    "w09": ("0 error_3 0, 0 click_1 0", "0"),
    "w09b": ("0 user 0, 0 assistant 0", "0"),
    "w10": ("0 lives_in 1, 0 based_in 1", "1"),
    "w11": (", ".join(f"{i} {_STARS[j]} {j}" for i in range(5) for j in range(i, 5)), "0, 1, 2, 3, 4"),
    "w12": ("0 ^supplied_by 1", "1"),
    "w13": ("0 on_host 1, 1 parent 1", "1"),
    "w14": ("0 user 0, 0 assistant 0", "0"),
    "w14b": ("0 error_3 0", "0"),
    "w15": ("0 lives_in 1, 1 in_region 2", "1, 2"),
    "w16": ("0 error_3 1, 1 error_3 1", "1"),
    "w16b": ("0 error 1, 1 error 1", "1"),
    "w17": ("0 on_host 1, 1 parent 2, 2 parent 2", "2"),
    "w18": ("0 lives_in 1, 0 based_in 1, 0 in_region 1", "1"),
    "w19": ("0 lives_in 1, 0 based_in 1", "1"),
    "w20": ("0 based_in 1, 1 ^lives_in 2", "2"),
    "w21": ("0 placed_by 1, 1 lives_in 2, 2 ^based_in 3", "3"),
    "w22": ("0 error_3 1, 1 ^error_3 0", "0"),
    "w23": ("0 ^of_brand 1, 1 supplied_by 2, 2 based_in 3", "3"),
    "w24": ("0 A 1, 0 R 1, 1 A 1, 1 R 1, 1 N 2", "2"),
}


def recursion(graph: str, transitions: str, finals: str, s: str | None, o: str | None, select: str | None = None) -> str:
    """SQL of the answers; ``select`` replaces the last projection over reach(origin, node, q)."""
    rows = []
    for t in transitions.split(", "):
        q, label, r = t.split(" ")
        rows.append(f"({q}, '{label.lstrip('^')}', {'true' if label[0] == '^' else 'false'}, {r})")
    head = f"""WITH RECURSIVE g AS ({GRAPHS[graph]}),
    trans(q, label, inv, r) AS (VALUES {', '.join(rows)}),
    step AS (SELECT DISTINCT t.q, t.r, CASE WHEN t.inv THEN g.o ELSE g.s END AS x, CASE WHEN t.inv THEN g.s ELSE g.o END AS y FROM g JOIN trans t ON g.p = t.label),
    nodes AS (SELECT s AS n FROM g UNION SELECT o FROM g),"""
    if s is None and o is not None:
        seeds = " UNION ".join(f"SELECT n, n, {f} FROM nodes WHERE n = '{o}'" for f in finals.split(", "))
        return f"""{head}
    reach(origin, node, q) AS ({seeds} UNION SELECT reach.origin, step.x, step.q FROM reach JOIN step ON step.y = reach.node AND step.r = reach.q)
    {select or "SELECT DISTINCT node AS s FROM reach WHERE q = 0"}"""
    where = f"WHERE n = '{s}'" if s is not None else ""
    last = "SELECT DISTINCT origin AS s, node AS o" if s is None else "SELECT DISTINCT node AS o"
    if s is not None and o is not None:
        last, finals = "SELECT count(*) > 0 AS found", f"{finals}) AND node IN ('{o}'"
    return f"""{head}
    reach(origin, node, q) AS (SELECT n, n, 0 FROM nodes {where} UNION SELECT reach.origin, step.y, step.r FROM reach JOIN step ON step.x = reach.node AND step.q = reach.q)
    {select or f"{last} FROM reach WHERE q IN ({finals})"}"""


def of(query_id: str) -> str:
    q = QUERIES[query_id]
    return recursion(q.graph, *TRANSITIONS[query_id], q.s, q.o)


def model(query_id: str, pattern: str, kind: str, n: int) -> str:
    """SQL of the answers of a model's n queries; constants are the first nodes of a kind by the hash of their names."""
    q, (transitions, finals) = QUERIES[query_id], TRANSITIONS[query_id]
    if not kind:
        return f"SELECT '{query_id}' AS model, '{pattern}' AS pattern, NULL::VARCHAR AS constant, {n}::BIGINT AS queries, (SELECT count(*) FROM ({of(query_id)})) AS answers"
    rows = ", ".join(f"({a}, '{label.lstrip('^')}', {'true' if label[0] == '^' else 'false'}, {r})" for a, label, r in (t.split(" ") for t in transitions.split(", ")))
    forward = q.o is None
    seeds = " UNION ".join(f"SELECT n, n, {f} FROM consts" for f in (["0"] if forward else finals.split(", ")))
    step = "step.y, step.r FROM reach JOIN step ON step.x = reach.node AND step.q = reach.q" if forward else "step.x, step.q FROM reach JOIN step ON step.y = reach.node AND step.r = reach.q"
    return f"""(WITH RECURSIVE g AS ({GRAPHS[q.graph]}), trans(q, label, inv, r) AS (VALUES {rows}),
        step AS (SELECT DISTINCT t.q, t.r, CASE WHEN t.inv THEN g.o ELSE g.s END AS x, CASE WHEN t.inv THEN g.s ELSE g.o END AS y FROM g JOIN trans t ON g.p = t.label),
        consts AS (SELECT n FROM (SELECT s AS n FROM g UNION SELECT o FROM g) WHERE split_part(n, ':', 1) = '{kind}' ORDER BY md5(n) LIMIT {n}),
        reach(origin, node, q) AS ({seeds} UNION SELECT reach.origin, {step})
        SELECT '{query_id}' AS model, '{pattern}' AS pattern, consts.n AS constant, 1::BIGINT AS queries, (SELECT count(DISTINCT node) FROM reach WHERE origin = consts.n AND q IN ({finals if forward else 0})) AS answers FROM consts)"""
