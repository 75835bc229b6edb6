"""DuckDB SQL: fixtures as common table expressions, for the twins of queries."""

from __future__ import annotations

_SALES = """sales AS (
  SELECT l_orderkey, l_linenumber, 'C' || o_custkey AS c, 'S' || l_suppkey AS u, 'P' || l_partkey AS p, l_partkey,
         'trade_' || l_returnflag || l_linestatus AS deal,
         date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS ordered,
         date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS shipped
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"""

FACTS = {
    "trade": _SALES + """,
facts AS (
  SELECT c AS s, 'orders_' || p_type AS r, p AS o, ordered AS t FROM sales JOIN part ON l_partkey = p_partkey
  UNION SELECT u, 'ships_' || p_type, p, shipped FROM sales JOIN part ON l_partkey = p_partkey
  UNION SELECT c, deal, u, shipped FROM sales
  UNION SELECT 'C' || c_custkey, 'based_in', 'N' || c_nationkey, coalesce((SELECT min(ordered) FROM sales WHERE c = 'C' || c_custkey), 0) FROM customer
  UNION SELECT 'S' || s_suppkey, 'registered_in', 'N' || s_nationkey, coalesce((SELECT min(shipped) FROM sales WHERE u = 'S' || s_suppkey), 0) FROM supplier)""",
    "clicks": """facts AS (
  SELECT DISTINCT 'U' || user_id AS s, event_type || '_' || CASE WHEN value < 15 THEN 0 WHEN value < 35 THEN 1 WHEN value < 70 THEN 2 ELSE 3 END AS r,
         'K' || json_extract_string(props, '$.k') AS o, CAST(floor((epoch(ts) - epoch(TIMESTAMP '2024-01-01')) / 3600) AS BIGINT) AS t FROM events)""",
    "lifecycle": _SALES + """,
facts AS (
  SELECT c AS s, 'want' AS r, p AS o, ordered AS t FROM sales
  UNION SELECT u, 'stock', p, ordered FROM sales
  UNION SELECT c, 'request', u, ordered + 1 FROM sales
  UNION SELECT c, 'confirm', u, ordered + 2 + l_orderkey % 3 FROM sales WHERE (7 * l_orderkey + l_linenumber) % 20 <> 0
  UNION SELECT c, 'receive', u, ordered + 10 + l_linenumber % 5 FROM sales)""",
    "dialogue": """facts AS (
  SELECT DISTINCT 'V' || conv_id AS s, 'says_' || CASE WHEN len(coalesce(text, '')) < 100 THEN 'short' WHEN len(coalesce(text, '')) < 500 THEN 'medium' ELSE 'long' END AS r, 'R' || role AS o, turn AS t FROM conversations)""",
    "links": r"""hrefs AS (SELECT page_id, regexp_extract(url, '^([a-z]+)://([^/]+)', 2) AS host, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages),
facts AS (
  SELECT DISTINCT 'H' || host AS s, 'links_' || CASE WHEN regexp_matches(href, '^https?://') THEN regexp_extract(href, '^([a-z]+):', 1) ELSE 'local' END || '_' || regexp_extract(regexp_extract(href, '^(?:[a-z]+://[^/]+)?(.*)$', 1), '^/?([A-Za-z]*)', 1) AS r,
         'A' || regexp_extract(href, '^(?:[a-z]+://[^/]+)?(.*)$', 1) AS o, page_id AS t FROM hrefs)""",
    "mentions": """facts AS (
  SELECT DISTINCT 'D' || source AS s, CASE WHEN quality IS NULL THEN 'publishes_unlabelled' ELSE 'publishes_q' || quality || '_t' || toxic END AS r, 'G' || lang AS o, d.doc_id AS t
  FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id)""",
    "near": "facts AS (SELECT DISTINCT 'X' || vec_id AS s, 'is_class' AS r, 'Y' || label AS o, 0 AS t FROM embeddings)",
    "validity": _SALES + """,
facts AS (SELECT DISTINCT c AS s, deal AS r, u AS o, ordered AS t_start, shipped AS t_end FROM sales WHERE ordered <= shipped)""",
}


def over(fixture: str, *steps: str, select: str) -> str:
    """A query over a fixture's facts with further common table expressions."""
    return "WITH " + ",\n".join([FACTS[fixture], *steps]) + "\n" + select


#: Steps shared by several twins: kinds as categories.
KINDS = "ents AS (SELECT s AS e FROM facts UNION SELECT o FROM facts)"
PATTERNS = "pats AS (SELECT substr(s, 1, 1) AS cs, r, substr(o, 1, 1) AS co, count(*) AS n FROM facts GROUP BY ALL)"


def draw(salt: str, *columns: str, digits: int = 8) -> str:
    text = " || '|' || ".join([f"'{salt}'", *[f"CAST({c} AS VARCHAR)" for c in columns]])
    return f"CAST('0x' || substr(md5({text}), 1, {digits}) AS BIGINT)"


def ln1p(x: str) -> str:
    return f"(CASE WHEN abs({x}) < 1e-4 THEN ({x}) - ({x}) * ({x}) / 2 + ({x}) * ({x}) * ({x}) / 3 - ({x}) * ({x}) * ({x}) * ({x}) / 4 ELSE ln(1 + ({x})) END)"


def choose(n: str, k: str) -> str:
    n, k = f"CAST({n} AS DOUBLE)", f"CAST({k} AS DOUBLE)"
    j = f"least({k}, {n} - {k})"
    return f"""(CASE WHEN {k} = 0 OR {k} = {n} THEN 0.0 WHEN {j} = 1 THEN log2({n}) ELSE
  ({j} * ln({n}) - {j} - ({n} - {j} + 0.5) * {ln1p(f'(-{j} / {n})')} + (1.0 / {n} - 1.0 / ({n} - {j})) / 12 - lgamma({j} + 1)) / ln(2) END)"""
