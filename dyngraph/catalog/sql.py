"""DuckDB text of the graphs and of the relations that oracles start from; independent of the engine's code."""

from __future__ import annotations

MONTH = "CAST((year({0}) - 1995) * 12 + month({0}) - 1 AS INTEGER)"
DAY = "CAST(date_diff('day', DATE '2024-01-01', CAST({0} AS DATE)) AS INTEGER)"


def decile(key: str, table: str) -> str:
    return f"CAST(floor(({key} - (SELECT min({key}) FROM {table})) * 10 / (SELECT max({key}) - min({key}) + 1 FROM {table})) AS INTEGER)"


def pick(text: str) -> str:
    """52 bits of an MD5 digest."""
    return f"CAST(('0x' || substr(md5({text}), 1, 13)) AS BIGINT)"


_BOUGHT = f"SELECT l_partkey, l_suppkey, o_custkey, {MONTH.format('o_orderdate')} AS m FROM lineitem JOIN orders ON l_orderkey = o_orderkey"

EVENTS = {
    "buy": f"SELECT o_custkey * 8 AS x, o_orderkey * 8 + 1 AS y, {MONTH.format('o_orderdate')} AS snap FROM orders",
    "buy_week": "SELECT o_custkey * 8 AS x, o_orderkey * 8 + 1 AS y, CAST(floor(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) / 7) AS INTEGER) AS snap FROM orders",
    "copurchase": f"SELECT p.o_custkey * 8 AS x, q.o_custkey * 8 AS y, CAST(p.m // 8 AS INTEGER) AS snap FROM (SELECT DISTINCT l_partkey, m, o_custkey FROM ({_BOUGHT})) p JOIN (SELECT DISTINCT l_partkey, m, o_custkey FROM ({_BOUGHT})) q ON p.l_partkey = q.l_partkey AND p.m = q.m AND p.o_custkey < q.o_custkey",
    "ship": f"SELECT l_orderkey * 8 + 1 AS x, l_partkey * 8 + 2 AS y, {MONTH.format('l_shipdate')} AS snap FROM lineitem",
    "trade": f"SELECT o_custkey * 8 AS x, l_partkey * 8 + 2 AS y, m AS snap FROM ({_BOUGHT})",
    "talk": f"SELECT prev * 8 + 4 AS x, user_id * 8 + 4 AS y, {DAY.format('ts')} AS snap FROM (SELECT ts, user_id, lag(user_id) OVER (ORDER BY ts, event_id) AS prev FROM events) WHERE user_id <> prev",
    "userkey": f"SELECT user_id * 8 + 4 AS x, CAST(json_extract_string(props, '$.k') AS BIGINT) * 8 + 5 AS y, CAST(floor({DAY.format('ts')} / 3) AS INTEGER) AS snap FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL",
    "link": f"SELECT page_id * 8 + 6 AS x, {pick('href')} * 8 + 7 AS y, {decile('page_id', 'pages')} AS snap FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages)",
    "reply": f"SELECT (c.conv_id * 4096 + c.turn) * 8 + 6 AS x, (c.conv_id * 4096 + c.turn + 1) * 8 + 6 AS y, {decile('c.conv_id', 'conversations c')} AS snap FROM conversations c JOIN conversations n ON n.conv_id = c.conv_id AND n.turn = c.turn + 1",
    "docs": f"SELECT doc_id * 8 + 6 AS x, CAST(substr(source, 4) AS BIGINT) * 8 + 7 AS y, {decile('doc_id', 'documents')} AS snap FROM documents WHERE source IS NOT NULL",
    "vec": f"""SELECT vec_id * 8 + 6 AS x, other * 8 + 6 AS y, {decile('vec_id', 'embeddings')} AS snap FROM (
        SELECT p.vec_id, q.vec_id AS other, row_number() OVER (PARTITION BY p.vec_id ORDER BY list_cosine_similarity(CAST(p.embedding AS DOUBLE[]), CAST(q.embedding AS DOUBLE[])) DESC, q.vec_id) AS n
        FROM embeddings p JOIN embeddings q ON p.vec_id <> q.vec_id) WHERE n <= 3""",
}


def edges(name: str) -> str:
    return f"SELECT least(x, y) AS a, greatest(x, y) AS b, CAST(min(snap) AS INTEGER) AS first FROM ({EVENTS[name]}) WHERE x <> y GROUP BY 1, 2"


def base(name: str, m: int = 4, where: str = "true") -> str:
    """CTEs e (edges), s (both directions), v, asg (key modulo m), ee (s with clients), f (small integer feature), d (degrees)."""
    return f"""WITH RECURSIVE e AS MATERIALIZED (SELECT * FROM ({edges(name)}) WHERE {where}),
s AS MATERIALIZED (SELECT a AS src, b AS dst, first FROM e UNION ALL SELECT b, a, first FROM e),
v AS MATERIALIZED (SELECT DISTINCT src AS vid FROM s),
asg AS MATERIALIZED (SELECT vid, CAST((vid // 8) % {m} AS INTEGER) AS part FROM v),
ee AS MATERIALIZED (SELECT s.src, s.dst, s.first, p.part AS pu, q.part AS pv FROM s JOIN asg p ON p.vid = s.src JOIN asg q ON q.vid = s.dst),
f AS MATERIALIZED (SELECT vid, vid % 97 + 1 AS x FROM v),
d AS MATERIALIZED (SELECT src AS vid, count(*) AS deg FROM s GROUP BY 1)"""


#: Classes: customers by market segment, orders by status, in alphabetical order from 0.
SEGMENT = "SELECT c_custkey * 8 AS vid, CAST(dense_rank() OVER (ORDER BY c_mktsegment) - 1 AS INTEGER) AS y FROM customer"
STATUS = "SELECT o_orderkey * 8 + 1 AS vid, CAST(dense_rank() OVER (ORDER BY o_orderstatus) - 1 AS INTEGER) AS y FROM orders"

#: Local and global sums over one and two hops, and the corrections, on top of base().
SUMS = """,
loc AS MATERIALIZED (SELECT src, dst FROM ee WHERE pu = pv), cut AS MATERIALIZED (SELECT src, dst FROM ee WHERE pu <> pv),
h1 AS MATERIALIZED (SELECT vid, CAST(sum(x) AS BIGINT) AS x FROM (SELECT vid, x FROM f UNION ALL SELECT l.src, f.x FROM loc l JOIN f ON f.vid = l.dst) GROUP BY 1),
h2 AS MATERIALIZED (SELECT vid, CAST(sum(x) AS BIGINT) AS x FROM (SELECT vid, x FROM h1 UNION ALL SELECT l.src, h1.x FROM loc l JOIN h1 ON h1.vid = l.dst) GROUP BY 1),
g1 AS MATERIALIZED (SELECT vid, CAST(sum(x) AS BIGINT) AS x FROM (SELECT vid, x FROM f UNION ALL SELECT s.src, f.x FROM s JOIN f ON f.vid = s.dst) GROUP BY 1),
g2 AS MATERIALIZED (SELECT vid, CAST(sum(x) AS BIGINT) AS x FROM (SELECT vid, x FROM g1 UNION ALL SELECT s.src, g1.x FROM s JOIN g1 ON g1.vid = s.dst) GROUP BY 1),
d1 AS MATERIALIZED (SELECT c.src AS vid, CAST(sum(f.x) AS BIGINT) AS x FROM cut c JOIN f ON f.vid = c.dst GROUP BY 1),
excl AS MATERIALIZED (SELECT vid, CAST(sum(x) AS BIGINT) AS x FROM (SELECT c.src AS vid, h1.x + coalesce(d1.x, 0) AS x FROM cut c JOIN h1 ON h1.vid = c.dst LEFT JOIN d1 ON d1.vid = c.dst UNION ALL SELECT vid, x FROM d1) GROUP BY 1),
printed AS MATERIALIZED (SELECT excl.vid, CAST(excl.x + n.n * f.x AS BIGINT) AS x FROM excl JOIN f USING (vid) JOIN (SELECT src AS vid, count(*) AS n FROM cut GROUP BY 1) n USING (vid)),
complete AS MATERIALIZED (SELECT vid, CAST(sum(x) AS BIGINT) AS x FROM (SELECT vid, x FROM excl UNION ALL SELECT l.src, d1.x FROM loc l JOIN d1 ON d1.vid = l.dst) GROUP BY 1)"""
