"""The same graph as ANSI SQL (DuckDB), for oracles."""

from __future__ import annotations

from collections.abc import Iterable

from .build import BASE, LABELS, SYMMETRIC


def _edge(code: int, local: str, s: str, p: str, o: str, source: str) -> str:
    return f"SELECT CAST({code * BASE} + {local} AS BIGINT) AS edge_id, {s} AS s, {p} AS p, {o} AS o, false AS inverse FROM {source}"


def _previous(code: int, event: str, label: str) -> str:
    source = f"(SELECT event_id, user_id, lag(user_id) OVER (PARTITION BY json_extract_string(props, '$.k') ORDER BY ts, event_id) AS before_id FROM events WHERE event_type = '{event}') WHERE before_id <> user_id"
    return _edge(code, "event_id", "'cust:' || user_id", f"'{label}'", "'cust:' || before_id", source)


_LINES = "(SELECT *, l_orderkey * 1000 + row_number() OVER (PARTITION BY l_orderkey ORDER BY l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS local_id FROM lineitem)"
FAMILY_SQL = {
    1: _previous(1, "purchase", "followed"),
    2: _previous(2, "click", "coActive"),
    3: _edge(3, "c_custkey", "'cust:' || c_custkey", "'locatedIn'", "'nation:' || c_nationkey", "customer"),
    4: _edge(4, "s_suppkey", "'supp:' || s_suppkey", "'locatedIn'", "'nation:' || s_nationkey", "supplier"),
    5: _edge(5, "n_nationkey", "'nation:' || n_nationkey", "'locatedIn'", "'region:' || n_regionkey", "nation"),
    6: _edge(6, "c_custkey", "'cust:' || c_custkey", "'inSegment'", "'lit:' || c_mktsegment", "customer"),
    7: _edge(7, "o_orderkey", "'order:' || o_orderkey", "'placedBy'", "'cust:' || o_custkey", "orders"),
    8: _edge(8, "local_id", "'order:' || l_orderkey", "'hasPart'", "'part:' || l_partkey", _LINES),
    9: _edge(9, "local_id", "'order:' || l_orderkey", "'shippedFrom'", "'supp:' || l_suppkey", _LINES),
    10: _edge(10, "p_partkey", "'part:' || p_partkey", "'hasBrand'", "'lit:' || p_brand", "part"),
    11: _edge(11, "p_partkey", "'part:' || p_partkey", "'hasType'", "'lit:' || p_type", "part"),
    12: _edge(12, "o_orderkey", "'order:' || o_orderkey", "'hasStatus'", "'lit:' || o_orderstatus", "orders"),
    13: _edge(13, "o_orderkey", "'order:' || o_orderkey", "'hasPriority'", "'lit:' || o_orderpriority", "orders"),
    14: _edge(14, "event_id", "'cust:' || user_id", "event_type", "'topic:' || json_extract_string(props, '$.k')", "events WHERE event_type <> 'error'"),
    15: _edge(15, "page_id * 1000 + pos", "'page:' || page_id", "'linksTo'", "'path:' || href", "(SELECT page_id, href, dense_rank() OVER (PARTITION BY page_id ORDER BY first_at) - 1 AS pos FROM (SELECT page_id, href, min(k) AS first_at FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href, generate_subscripts(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1), 1) AS k FROM pages) GROUP BY page_id, href))"),
    16: _edge(16, "doc_id", "'doc:' || doc_id", "'writtenIn'", "'lit:' || lang", "documents WHERE lang IS NOT NULL"),
    17: _edge(17, "doc_id", "'doc:' || doc_id", "'fromSource'", "'lit:' || source", "documents WHERE source IS NOT NULL"),
    18: _edge(18, "doc_id", "'doc:' || doc_id", "'judged'", "CASE WHEN quality = 1 THEN 'lit:good' ELSE 'lit:bad' END", "labels WHERE quality IS NOT NULL"),
    19: _edge(19, "conv_id * 1000 + turn", "'turn:' || conv_id || '/' || turn", "'repliesTo'", "'turn:' || conv_id || '/' || before_turn", "(SELECT conv_id, turn, lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS before_turn FROM conversations) WHERE before_turn IS NOT NULL"),
    20: _edge(20, "vec_id", "'vec:' || vec_id", "'inCluster'", "'lit:' || label", "embeddings"),
    21: _edge(21, "doc_id * 1000 + item_id", "'doc:' || doc_id", "'mentions'", "'item:' || item_id", "(SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text))"),
}


def graph_cte(families: Iterable[int], where: str = "true", extra: str = "") -> str:
    """Text of the CTE members `base_g` and `g` (symmetric rows included); `where` filters edges, `extra` adds rows."""
    codes = sorted(families)
    one = " UNION ALL ".join(f"({FAMILY_SQL[c]})" for c in codes) + extra
    mirrored = sorted({x for c in codes for x in LABELS[c]} & SYMMETRIC)
    both = f" UNION ALL SELECT edge_id, o, p, s, true FROM base_g WHERE p IN ({', '.join(repr(x) for x in mirrored)})" if mirrored else ""
    return f"base_g AS MATERIALIZED (SELECT * FROM ({one}) WHERE {where}), g AS MATERIALIZED (SELECT * FROM base_g{both})"
