"""SQL of the graphs and algorithms for DuckDB, written apart from the DataFrame code."""

from __future__ import annotations

EDGES: dict[str, str] = {
    "basket": "SELECT DISTINCT l_orderkey * 2 AS src, l_partkey * 2 + 1 AS dst FROM lineitem",
    "supply": "SELECT DISTINCT l_partkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM lineitem",
    "patron": """
SELECT o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst, sum(l_extendedprice * (1 - l_discount)) AS weight
FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL""",
    "nation_trade": """
SELECT CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst, sum(l_extendedprice * (1 - l_discount)) AS weight
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL""",
    "copurchase": """
SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst
FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey""",
    "copurchase_sparse": """
SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst
FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey
WHERE a.l_quantity > 45 AND b.l_quantity > 45""",
    "accounts": "SELECT DISTINCT o_custkey * 2 AS src, o_orderkey * 2 + 1 AS dst FROM orders",
    "event_chain": """
SELECT src, dst FROM (SELECT event_id AS src, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events)
WHERE dst IS NOT NULL""",
    "event_session": """
SELECT src, dst FROM (
  SELECT event_id AS src, lead(event_id) OVER w AS dst, lead(ts) OVER w < ts + INTERVAL 6 HOUR AS near
  FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))
WHERE near""",
    "event_flow": """
SELECT CAST(a.id AS BIGINT) AS src, CAST(b.id AS BIGINT) AS dst, CAST(count(*) AS DOUBLE) AS weight
FROM (SELECT event_type, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM events) e
JOIN (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS id FROM (SELECT DISTINCT event_type FROM events)) a ON a.event_type = e.event_type
JOIN (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS id FROM (SELECT DISTINCT event_type FROM events)) b ON b.event_type = e.nxt
GROUP BY ALL""",
    "user_relay": """
SELECT DISTINCT src, dst FROM (
  SELECT user_id AS src, lead(user_id) OVER (PARTITION BY event_type, date_trunc('month', ts) ORDER BY ts, event_id) AS dst FROM events)
WHERE dst IS NOT NULL AND src <> dst""",
    "page_links": """
SELECT DISTINCT page_id * 2 AS src, (dense_rank() OVER (ORDER BY href) - 1) * 2 + 1 AS dst
FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)""",
    "knn": """
SELECT src, dst, weight FROM (
  SELECT *, row_number() OVER (PARTITION BY src ORDER BY weight DESC, dst) AS r FROM (
    SELECT a.vec_id AS src, b.vec_id AS dst,
           round(list_inner_product(a.v, b.v) / (sqrt(list_inner_product(a.v, a.v)) * sqrt(list_inner_product(b.v, b.v))), 6) AS weight
    FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) a
    JOIN (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings) b ON a.vec_id <> b.vec_id))
WHERE r <= 5""",
    "doc_dup": """
SELECT DISTINCT src, dst FROM (
  SELECT doc_id AS src, min(doc_id) OVER (PARTITION BY text) AS dst FROM documents WHERE text IS NOT NULL
  UNION ALL
  SELECT doc_id, min(doc_id) OVER (PARTITION BY line) FROM (
    SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)
    WHERE length(line) > 60))
WHERE src <> dst""",
    "dialog": """
SELECT a.conv_id * 1000 + a.turn AS src, a.conv_id * 1000 + b.turn AS dst
FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1""",
    "geo": """
SELECT CAST(n_nationkey AS BIGINT) * 4 + 1 AS src, CAST(n_regionkey AS BIGINT) * 4 AS dst FROM nation
UNION SELECT c_custkey * 4 + 2, CAST(c_nationkey AS BIGINT) * 4 + 1 FROM customer
UNION SELECT s_suppkey * 4 + 3, CAST(s_nationkey AS BIGINT) * 4 + 1 FROM supplier""",
}

DIRECTED = {"patron", "nation_trade", "event_chain", "event_session", "event_flow", "user_relay", "knn", "dialog"}
WEIGHTED = {"patron", "nation_trade", "event_flow", "knn"}
_EXTRA_VERTICES = {
    "accounts": "SELECT c_custkey * 2 AS vid FROM customer UNION SELECT o_orderkey * 2 + 1 FROM orders",
    "event_chain": "SELECT event_id AS vid FROM events",
    "event_session": "SELECT event_id AS vid FROM events",
    "dialog": "SELECT conv_id * 1000 + turn AS vid FROM conversations",
}


def graph(name: str, direction: str = "both") -> str:
    """CTEs e (edges), a (arcs along which values travel) and v (vertices)."""
    cols = "src, dst" + (", weight" if name in WEIGHTED else "")
    back = "dst AS src, src AS dst" + (", weight" if name in WEIGHTED else "")
    if name not in DIRECTED:
        arcs = f"SELECT {cols} FROM e UNION ALL SELECT {back} FROM e WHERE src <> dst"
    elif direction == "both":
        arcs = f"SELECT {cols} FROM e UNION ALL SELECT {back} FROM e"
    else:
        arcs = f"SELECT {cols} FROM e"
    extra = f" UNION {_EXTRA_VERTICES[name]}" if name in _EXTRA_VERTICES else ""
    return f"""e AS MATERIALIZED ({EDGES[name]}),
a AS MATERIALIZED ({arcs}),
v AS MATERIALIZED (SELECT src AS vid FROM e UNION SELECT dst FROM e{extra})"""


def edges(name: str, places: int = 6) -> str:
    weight = f", round(weight, {places}) AS weight" if name in WEIGHTED else ""
    return f"SELECT src, dst{weight} FROM ({EDGES[name]})"


def wcc(name: str, tail: str = "SELECT id AS vid, l AS component FROM w") -> str:
    return f"""WITH RECURSIVE {graph(name)},
w(id, l) USING KEY (id) AS (
  SELECT vid, vid FROM v
  UNION
  SELECT a.dst, min(w.l) FROM w JOIN a ON a.src = w.id JOIN recurring.w r ON r.id = a.dst
  GROUP BY a.dst HAVING min(w.l) < any_value(r.l))
{tail}"""


UNREACHABLE = 9223372036854775807


def bfs(name: str, sources: str, tail: str | None = None, most: int | None = None) -> str:
    limit = f" WHERE w.d < {most}" if most is not None else ""
    tail = tail or f"SELECT vid, CAST(coalesce(d, {UNREACHABLE}) AS BIGINT) AS depth FROM v LEFT JOIN w ON id = vid"
    return f"""WITH RECURSIVE {graph(name, 'out')},
w(id, d) USING KEY (id) AS (
  SELECT vid, CAST(0 AS BIGINT) FROM v WHERE vid IN ({sources})
  UNION
  SELECT a.dst, min(w.d) + 1 FROM w JOIN a ON a.src = w.id LEFT JOIN recurring.w r ON r.id = a.dst{limit}
  GROUP BY a.dst HAVING count(r.id) = 0)
{tail}"""


def pagerank(name: str, iters: int = 10, weighted: bool = False, restart: str | None = None, tail: str | None = None, damping: float = 0.85) -> str:
    """A chain of materialized steps."""
    share = "p.r * a.weight / o.w" if weighted else "p.r / o.n"
    base = f"CASE WHEN vid IN ({restart}) THEN 1.0::DOUBLE / (SELECT count(*) FROM v WHERE vid IN ({restart})) ELSE 0 END" if restart else "1.0::DOUBLE / (SELECT count(*) FROM v)"
    weight = ", sum(weight) AS w" if weighted else ""
    ctes = [
        graph(name, "out"),
        f"o AS MATERIALIZED (SELECT src, count(*) AS n{weight} FROM a GROUP BY src)",
        f"b AS MATERIALIZED (SELECT vid, {base} AS base, vid NOT IN (SELECT src FROM o) AS sink FROM v)",
        "r0 AS MATERIALIZED (SELECT vid, base AS r FROM b)",
    ]
    for k in range(1, iters + 1):
        ctes.append(f"""r{k} AS MATERIALIZED (
  SELECT b.vid, (1 - {damping}) * b.base + {damping} * (coalesce(g.s, 0) + b.base * (SELECT coalesce(sum(r), 0) FROM r{k - 1} JOIN b USING (vid) WHERE sink)) AS r
  FROM b LEFT JOIN (SELECT a.dst, sum({share}) AS s FROM r{k - 1} p JOIN a ON a.src = p.vid JOIN o ON o.src = p.vid GROUP BY a.dst) g ON g.dst = b.vid)""")
    tail = tail or "SELECT vid, round(r * (SELECT count(*) FROM v), 6) AS rank FROM last"
    return f"WITH {', '.join(ctes)}, last AS (SELECT * FROM r{iters}) {tail}"


def cdlp(name: str, iters: int = 10, tail: str | None = None) -> str:
    ctes = [graph(name), "c0 AS MATERIALIZED (SELECT vid, vid AS l FROM v)"]
    for k in range(1, iters + 1):
        ctes.append(f"""c{k} AS MATERIALIZED (
  SELECT p.vid, coalesce(g.l, p.l) AS l FROM c{k - 1} p LEFT JOIN (
    SELECT dst, l FROM (SELECT a.dst, q.l, row_number() OVER (PARTITION BY a.dst ORDER BY count(*) DESC, q.l) AS r
      FROM a JOIN c{k - 1} q ON q.vid = a.src GROUP BY a.dst, q.l) WHERE r = 1) g ON g.dst = p.vid)""")
    tail = tail or "SELECT vid, l AS label FROM last"
    return f"WITH {', '.join(ctes)}, last AS (SELECT * FROM c{iters}) {tail}"


def sssp(name: str, source: int, places: int = 6) -> str:
    return f"""WITH RECURSIVE {graph(name, 'out')},
w(id, d) USING KEY (id) AS (
  SELECT vid, CAST(0 AS DOUBLE) FROM v WHERE vid = {source}
  UNION
  SELECT a.dst, min(w.d + a.weight) FROM w JOIN a ON a.src = w.id LEFT JOIN recurring.w r ON r.id = a.dst
  GROUP BY a.dst HAVING count(r.id) = 0 OR min(w.d + a.weight) < any_value(r.d))
SELECT vid, round(coalesce(d, CAST('Infinity' AS DOUBLE)), {places}) AS dist FROM v LEFT JOIN w ON id = vid"""


def degrees(name: str) -> str:
    """CTE deg (vid, out_deg, in_deg, degree); needs e, a, v."""
    if name in DIRECTED:
        return """deg AS (SELECT vid, (SELECT count(*) FROM e WHERE src = vid) AS out_deg, (SELECT count(*) FROM e WHERE dst = vid) AS in_deg,
  (SELECT count(*) FROM e WHERE src = vid) + (SELECT count(*) FROM e WHERE dst = vid) AS degree FROM v)"""
    return "deg AS (SELECT vid, (SELECT count(*) FROM a WHERE src = vid) AS out_deg, (SELECT count(*) FROM a WHERE src = vid) AS in_deg, (SELECT count(*) FROM a WHERE src = vid) AS degree FROM v)"


def placed(name: str, p: int) -> str:
    """CTEs up to pl (vid, pid by degree), x (arcs in both directions with both pids)."""
    return f"""{graph(name)}, {degrees(name)},
pre AS (SELECT vid, degree, coalesce(sum(degree) OVER (ORDER BY vid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before, sum(degree) OVER () AS total FROM deg),
pl AS MATERIALIZED (SELECT vid, CAST(least({p - 1}, floor(before * {p} / CAST(total AS DOUBLE))) AS INTEGER) AS pid FROM pre),
x AS MATERIALIZED (SELECT a.src, a.dst, s.pid AS src_pid, d.pid AS pid FROM a JOIN pl s ON s.vid = a.src JOIN pl d ON d.vid = a.dst),
ro AS MATERIALIZED (SELECT DISTINCT src_pid, src AS vid, pid AS dst_pid FROM x WHERE src_pid <> pid)"""


def wcc_trace(name: str, steps: int) -> str:
    """superstep, changed of synchronous sweeps, up to the first without a change; ``steps`` bounds the chain."""
    ctes = [graph(name), "s0 AS MATERIALIZED (SELECT vid, vid AS l, false AS c FROM v)"]
    for k in range(1, steps + 1):
        ctes.append(f"""s{k} AS MATERIALIZED (
  SELECT p.vid, least(p.l, coalesce(g.m, p.l)) AS l, coalesce(g.m < p.l, false) AS c
  FROM s{k - 1} p LEFT JOIN (SELECT a.dst, min(q.l) AS m FROM a JOIN s{k - 1} q ON q.vid = a.src GROUP BY a.dst) g ON g.dst = p.vid)""")
    rows = " UNION ALL ".join(f"SELECT CAST({k - 1} AS INTEGER) AS superstep, count(*) FILTER (c) AS changed FROM s{k}" for k in range(1, steps + 1))
    return f"""WITH {', '.join(ctes)}, t AS ({rows})
SELECT superstep, changed FROM t WHERE superstep <= (SELECT min(superstep) FROM t WHERE changed = 0)"""
