"""DuckDB SQL of the graphs on the given tables."""

from __future__ import annotations

_LINE = """SELECT DISTINCT doc_id, md5(line) AS key FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20"""

GRAPH_SQL = {
    "g_order_part": "SELECT DISTINCT l.l_orderkey * 8 + 3 AS src, l.l_partkey * 8 + 2 AS dst, o.o_orderdate AS ts FROM lineitem l JOIN orders o ON o.o_orderkey = l.l_orderkey",
    "g_cust_supp": "SELECT DISTINCT o.o_custkey * 8 AS src, l.l_suppkey * 8 + 1 AS dst FROM lineitem l JOIN orders o ON o.o_orderkey = l.l_orderkey",
    "g_cust_part": "SELECT DISTINCT o.o_custkey * 8 AS src, l.l_partkey * 8 + 2 AS dst FROM lineitem l JOIN orders o ON o.o_orderkey = l.l_orderkey",
    "g_part_supp": "SELECT DISTINCT l_partkey * 8 + 2 AS src, l_suppkey * 8 + 1 AS dst FROM lineitem",
    "g_events": "SELECT DISTINCT src, dst FROM (SELECT user_id AS src, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL AND src <> dst",
    "g_web": "SELECT DISTINCT page_id * 8 + 6 AS src, CAST('0x' || substr(md5(href), 1, 12) AS BIGINT) * 8 + 5 AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS href FROM pages)",
    "g_doc_line": f"SELECT d.doc_id * 8 + 4 AS src, CAST('0x' || substr(key, 1, 12) AS BIGINT) * 8 + 5 AS dst FROM ({_LINE}) d WHERE key IN (SELECT key FROM ({_LINE}) GROUP BY key HAVING count(*) >= 2)",
    "g_doc": f"""WITH d AS MATERIALIZED ({_LINE}), s AS (SELECT key FROM d GROUP BY key HAVING count(*) BETWEEN 2 AND 50)
SELECT DISTINCT a.doc_id * 8 + 4 AS src, b.doc_id * 8 + 4 AS dst FROM d a JOIN s USING (key) JOIN d b USING (key) WHERE a.doc_id < b.doc_id""",
    "g_geo": """SELECT (1000 + CAST(n_nationkey AS BIGINT)) * 8 + 7 AS src, CAST(n_regionkey AS BIGINT) * 8 + 7 AS dst FROM nation
UNION ALL SELECT c_custkey * 8, (1000 + CAST(c_nationkey AS BIGINT)) * 8 + 7 FROM customer
UNION ALL SELECT s_suppkey * 8 + 1, (1000 + CAST(s_nationkey AS BIGINT)) * 8 + 7 FROM supplier""",
    "g_conv": "SELECT DISTINCT a.conv_id * 100 + a.turn AS src, a.conv_id * 100 + a.turn + 1 AS dst FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
    "g_knn": """WITH v AS MATERIALIZED (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings)
SELECT src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(a.e, b.e) DESC, b.vec_id) AS r FROM v a JOIN v b ON a.vec_id <> b.vec_id) WHERE r <= 10""",
}
