"""The data graphs in DuckDB's SQL, and helpers that write the SQL of whole searches from patterns."""

from __future__ import annotations

from collections.abc import Iterable

from .model.contain import Fold
from .model.pattern import Pattern
from .model.query import TreeQuery, to_sql

_KEYED = "SELECT event_id, ts, user_id, event_type, CAST(props->>'$.k' AS BIGINT) AS k FROM events"
_LINKS = "SELECT 'l:' || page_id AS src, 'l:' || unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS dst FROM pages"


def _step(days: int, below: int | None = None) -> str:
    inner = f"SELECT k, lead(k) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nk, ts FROM ({_KEYED}) q"
    bound = f" AND k < {below} AND nk < {below}" if below else ""
    return f"SELECT CAST(k AS VARCHAR) AS src, CAST(nk AS VARCHAR) AS dst FROM ({inner}) s WHERE nk IS NOT NULL AND k IS NOT NULL AND ts < TIMESTAMP '2024-01-01 00:00:00' + INTERVAL {days} DAY{bound}"


_NEAR = """SELECT CAST(a AS VARCHAR) AS a, CAST(b AS VARCHAR) AS b FROM (SELECT x.vec_id AS a, y.vec_id AS b, row_number() OVER (PARTITION BY x.vec_id
 ORDER BY round(list_cosine_similarity(CAST(x.embedding AS DOUBLE[]), CAST(y.embedding AS DOUBLE[])), 6) DESC, y.vec_id) AS place
 FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) q WHERE place <= 5"""
_WORDS = "SELECT ws[i] AS src, ws[i + 1] AS dst FROM (SELECT regexp_extract_all(lower(text), '[a-z0-9_]+') AS ws FROM conversations) c, LATERAL (SELECT unnest(generate_series(1, len(ws) - 1)) AS i) g"
_LINES = "SELECT 'd:' || doc_id AS src, md5(line) AS dst FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) q WHERE length(line) >= 40"

_PARTS: dict[str, str] = {
    "supply_chain": "SELECT 'root' AS src, 'r:' || r_regionkey AS dst FROM region UNION ALL SELECT 'r:' || n_regionkey, 'n:' || n_nationkey FROM nation UNION ALL SELECT 'n:' || s_nationkey, 's:' || s_suppkey FROM supplier UNION ALL SELECT 's:' || l_suppkey, 'p:' || l_partkey FROM lineitem UNION ALL SELECT 'p:' || p_partkey, 'b:' || p_brand FROM part",
    "supplier_part": "SELECT 's:' || l_suppkey AS src, 'p:' || l_partkey AS dst FROM lineitem",
    "customer_part": "SELECT 'c:' || o_custkey AS src, 'p:' || l_partkey AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "order_part": "SELECT 'o:' || l_orderkey AS src, 'p:' || l_partkey AS dst FROM lineitem",
    "nation_trade": "SELECT 'n:' || s_nationkey AS src, 'n:' || c_nationkey AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey",
    "user_key": f"SELECT 'u:' || user_id AS src, 'k:' || k AS dst FROM ({_KEYED}) q",
    "embedding_neighbors": f"WITH near AS ({_NEAR}) SELECT a AS src, b AS dst FROM near UNION ALL SELECT b, a FROM near",
    "key_step_3d": _step(3), "key_step_3d_51": _step(3, 51), "key_step_3d_22": _step(3, 22), "key_step_30d": _step(30),
    "page_links": _LINKS,
    "site_graph": f"{_LINKS} UNION ALL SELECT 'h:' || regexp_extract(url, '^https?://([^/]+)', 1), 'l:' || page_id FROM pages",
    "doc_attributes": "SELECT source AS src, 'd:' || doc_id AS dst FROM documents UNION ALL SELECT 'd:' || doc_id, 'lang:' || lang FROM documents UNION ALL SELECT 'd:' || doc_id, 'quality:' || quality FROM labels UNION ALL SELECT 'd:' || doc_id, 'toxic:' || toxic FROM labels",
    "event_reified": f"SELECT 'u:' || user_id AS src, 'e:' || event_id AS dst FROM ({_KEYED}) q UNION ALL SELECT 'e:' || event_id, 'k:' || k FROM ({_KEYED}) q UNION ALL SELECT 'e:' || event_id, 'type:' || event_type FROM ({_KEYED}) q",
    "word_next": _WORDS,
    "purchase_tree": "SELECT 'n:' || c_nationkey AS src, 'c:' || c_custkey AS dst FROM customer UNION ALL SELECT 'c:' || o_custkey, 'o:' || o_orderkey FROM orders UNION ALL SELECT 'o:' || l_orderkey, 'p:' || l_partkey FROM lineitem",
    "doc_lines": _LINES,
    "benchmark_lines": _LINES + " UNION ALL SELECT 'i:' || item_id AS src, md5(line) AS dst FROM (SELECT item_id, unnest(string_split(text, chr(10))) AS line FROM benchmark) q WHERE length(line) >= 40",
    "conv_roles": "SELECT 'v:' || conv_id AS src, role AS dst FROM conversations",
}


def edge_sql(graph: str) -> str:
    return f"SELECT DISTINCT src, dst FROM ({_PARTS[graph]}) e0 WHERE src IS NOT NULL AND dst IS NOT NULL"


def with_edges(graph: str, body: str) -> str:
    return f"WITH edge AS MATERIALIZED ({edge_sql(graph)}) {body}"


def tall_sql(patterns: Iterable[Pattern], minsup: int, most_pins: int) -> str:
    """pattern_key, pin1..pinK (null padded), freq of canonical patterns, each by its full join: nothing is pruned."""
    parts = []
    for p in patterns:
        k = len(p.pins)
        pins = ", ".join(f"CAST({f'pin{i}' if i <= k else 'NULL'} AS VARCHAR) AS pin{i}" for i in range(1, most_pins + 1))
        parts.append(f"SELECT '{p.refined()}' AS pattern_key, {pins + ', ' if pins else ''}freq FROM ({to_sql(p, minsup=minsup)}) t WHERE freq >= {minsup}")
    return " UNION ALL ".join(parts)


def rules_sql(lhs: TreeQuery, folds: list[tuple[Pattern, Fold]], minsup: int, num: int, den: int, most_pins: int) -> str:
    """Confident instances of each fold by joining both sides' full counts."""
    left = to_sql(lhs.body)
    parts = []
    for p, f in folds:
        on = " AND ".join(f"l.pin{k} = r.pin{p.pins.index(f[i]) + 1}" for k, i in enumerate(lhs.body.pins, 1)) or "TRUE"
        lpins = ", ".join(f"l.pin{k} AS lhs_pin{k}" for k in range(1, len(lhs.body.pins) + 1))
        rpins = ", ".join(f"CAST({f'r.pin{i}' if i <= len(p.pins) else 'NULL'} AS VARCHAR) AS pin{i}" for i in range(1, most_pins + 1))
        parts.append(f"SELECT '{p.canonize()[0].refined()}' AS rhs_key, '{','.join(map(str, f))}' AS fold, {lpins + ', ' if lpins else ''}{rpins}, r.freq, l.freq AS lhs_freq, round(CAST(r.freq AS DOUBLE) / l.freq, 6) AS conf FROM ({left}) l JOIN ({to_sql(p, minsup=minsup)}) r ON {on} WHERE r.freq >= {minsup} AND r.freq * {den} >= {num} * l.freq")
    return " UNION ALL ".join(parts)
