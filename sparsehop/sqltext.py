"""SQL of the same graphs and traversals, for comparison in DuckDB."""

from __future__ import annotations

PAIRS = {
    "g_ordpart": "SELECT 2 * l_orderkey AS src, 2 * l_partkey + 1 AS dst FROM lineitem",
    "g_custpart": "SELECT 2 * o_custkey AS src, 2 * l_partkey + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "g_partsupp": "SELECT 2 * l_partkey AS src, 2 * l_suppkey + 1 AS dst FROM lineitem",
    "g_copurchase": "SELECT x.l_partkey AS src, y.l_partkey AS dst FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) x JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey",
    "g_custorder": "SELECT 2 * o_custkey AS src, 2 * o_orderkey + 1 AS dst FROM orders",
    "g_geo": "SELECT CAST(n_regionkey AS BIGINT) AS src, 1000000000 + n_nationkey AS dst FROM nation UNION ALL SELECT 1000000000 + c_nationkey, 2000000000 + c_custkey FROM customer UNION ALL SELECT 1000000000 + s_nationkey, 3000000000 + s_suppkey FROM supplier",
    "g_word": "SELECT doc AS src, k.id AS dst FROM (SELECT DISTINCT doc_id AS doc, unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z]{3,}')) AS token FROM documents) t JOIN (SELECT token, row_number() OVER (ORDER BY token) - 1 + (SELECT max(doc_id) + 1 FROM documents) AS id FROM (SELECT DISTINCT unnest(regexp_extract_all(lower(coalesce(text, '')), '[a-z]{3,}')) AS token FROM documents)) k USING (token)",
    "g_userkey": "SELECT 2 * user_id AS src, 2 * CAST(json_extract(props, '$.k') AS BIGINT) + 1 AS dst FROM events",
    "g_chain": "SELECT event_id AS src, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events",
    "g_ladder": "SELECT event_id AS src, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events UNION ALL SELECT a.event_id, b.event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM events) a JOIN (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM events) b ON b.user_id = a.user_id + 1 AND a.n = b.n WHERE a.n % 10 = 0",
    "g_pages": "SELECT page_id AS src, k.id AS dst FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(coalesce(html, ''), 'href=\"([^\"]*)\"', 1)) AS href FROM pages) t JOIN (SELECT href, row_number() OVER (ORDER BY href) - 1 + (SELECT max(page_id) + 1 FROM pages) AS id FROM (SELECT DISTINCT unnest(regexp_extract_all(coalesce(html, ''), 'href=\"([^\"]*)\"', 1)) AS href FROM pages)) k USING (href)",
    "g_conv": "SELECT conv_id * 1000 + turn AS src, lead(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations",
    "g_toy": "SELECT * FROM (VALUES (0, 1), (0, 2), (0, 3), (1, 4), (2, 4), (2, 5), (3, 5), (4, 6), (5, 6), (6, 7)) AS v(src, dst)",
}
COS = "list_sum(list_transform(range(1, 65), lambda i: CAST(a.embedding[i] AS DOUBLE) * CAST(b.embedding[i] AS DOUBLE)))"
PAIRS["g_knn"] = f"SELECT src, dst, weight AS val FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY weight, dst) AS r FROM (SELECT a.vec_id AS src, b.vec_id AS dst, CAST(round(1e6 * (1 - {COS})) AS BIGINT) AS weight FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)) WHERE r <= 5"


def kron_pairs(scale: int, draws: str) -> str:
    return f"""WITH RECURSIVE k(i, h, src, dst, n) AS (SELECT i, (i * 2654435761 + 12345) % 2147483647, CAST(0 AS BIGINT), CAST(0 AS BIGINT), 0 FROM {draws} t(i)
 UNION ALL SELECT i, (h * 48271) % 2147483647, 2 * src + CASE WHEN h % 1000 >= 760 THEN 1 ELSE 0 END, 2 * dst + CASE WHEN (h % 1000 >= 570 AND h % 1000 < 760) OR h % 1000 >= 950 THEN 1 ELSE 0 END, n + 1 FROM k WHERE n < {scale})
 SELECT src, dst FROM k WHERE n = {scale}"""


PAIRS["g_kron10"] = kron_pairs(10, f"range({16 << 10})")


def graph(name: str) -> str:
    """CTEs p (raw pairs) and e (clean edges in both orientations)."""
    return f"p AS MATERIALIZED ({PAIRS[name]}), e AS MATERIALIZED (SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM p WHERE src <> dst UNION SELECT CAST(dst AS BIGINT), CAST(src AS BIGINT) FROM p WHERE src <> dst), vx AS MATERIALIZED (SELECT DISTINCT src AS id FROM e)"


def levels(source: str, bound: int) -> str:
    """CTEs r and lv (id, depth) of a search over e."""
    return f"r(id, depth) AS (SELECT CAST({source} AS BIGINT), 0 UNION SELECT e.dst, r.depth + 1 FROM r JOIN e ON e.src = r.id WHERE r.depth < {bound}), lv AS MATERIALIZED (SELECT id, CAST(min(depth) AS INTEGER) AS depth FROM r GROUP BY id)"


def bfs(name: str, source: str, bound: int = 14) -> str:
    return f"WITH RECURSIVE {graph(name)}, {levels(source, bound)} SELECT id, depth FROM lv"


TRACE = """dd AS MATERIALIZED (SELECT vx.id, lv.depth FROM vx LEFT JOIN lv USING (id)), l AS (SELECT DISTINCT depth AS l FROM lv),
dg AS MATERIALIZED (SELECT src AS id, count(*) AS g FROM e GROUP BY 1),
rk AS MATERIALIZED (SELECT e.dst, row_number() OVER (PARTITION BY e.dst ORDER BY e.src) AS place, f.depth AS fd, t.depth AS td, count(*) OVER (PARTITION BY e.dst) AS deg FROM e JOIN dd f ON f.id = e.src JOIN dd t ON t.id = e.dst),
c3 AS (SELECT l, sum(n) AS n FROM (SELECT l, dst, coalesce(min(CASE WHEN fd = l THEN place END), max(deg)) AS n FROM rk, l WHERE td IS NULL OR td > l GROUP BY l, dst) GROUP BY l),
tr AS MATERIALIZED (SELECT CAST(l.l + 1 AS INTEGER) AS iter, count(*) FILTER (dd.depth = l.l) AS nnz_f, count(*) FILTER (dd.depth IS NULL OR dd.depth > l.l) AS nnz_u,
  count(*) FILTER (dd.depth = l.l) / count(*) AS r, CAST(coalesce(sum(g) FILTER (dd.depth = l.l), 0) AS BIGINT) AS out_edges_f, CAST(coalesce(sum(g) FILTER (dd.depth IS NULL OR dd.depth > l.l), 0) AS BIGINT) AS in_edges_u,
  CAST(coalesce(max(c3.n), 0) AS BIGINT) AS parents_checked FROM l CROSS JOIN dd JOIN dg USING (id) LEFT JOIN c3 ON c3.l = l.l GROUP BY l.l)"""


def directions(alpha: str = "0.01", beta: str = "0.01", name: str = "dr") -> str:
    """CTE of the trace with the ratio rule's direction."""
    return f"""{name} AS MATERIALIZED (SELECT *, coalesce(last_value(move IGNORE NULLS) OVER (ORDER BY iter ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 'push') AS direction FROM (
 SELECT *, CASE WHEN r > prev AND r > {alpha} THEN 'pull' WHEN r < prev AND r < {beta} THEN 'push' END AS move FROM (SELECT *, coalesce(lag(r) OVER (ORDER BY iter), 0) AS prev FROM tr)))"""


def trace(name: str, source: str, bound: int = 14) -> str:
    return f"WITH RECURSIVE {graph(name)}, {levels(source, bound)}, {TRACE}"


def pagerank(name: str, iters: int) -> str:
    out = f"WITH {graph(name)}, dg AS (SELECT src AS id, count(*) AS g FROM e GROUP BY 1), m AS (SELECT count(*) AS m FROM vx), r0 AS (SELECT id, 1.0::DOUBLE / m AS x FROM vx, m)"
    for i in range(1, iters + 1):
        out += f", r{i} AS MATERIALIZED (SELECT vx.id, 0.15 / m + 0.85 * coalesce(y, 0) AS x FROM vx CROSS JOIN m LEFT JOIN (SELECT e.dst AS id, sum(x / g) AS y FROM e JOIN r{i - 1} q ON q.id = e.src JOIN dg ON dg.id = e.src GROUP BY 1) s USING (id))"
    return f"{out} SELECT id, round(x, 8) AS rank FROM r{iters}"


def pagerank_adaptive(name: str, iters: int, tol: float) -> str:
    out = f"WITH {graph(name)}, dg AS (SELECT src AS id, count(*) AS g FROM e GROUP BY 1), m AS (SELECT count(*) AS m FROM vx), r0 AS (SELECT id, 1.0::DOUBLE / m AS x, CAST(NULL AS INTEGER) AS z FROM vx, m)"
    for i in range(1, iters + 1):
        out += f""", r{i} AS MATERIALIZED (SELECT id, CASE WHEN z IS NULL THEN n ELSE x END AS x, CASE WHEN z IS NULL AND abs(n - x) < {tol} * x THEN {i} ELSE z END AS z FROM (
 SELECT o.id, o.x, o.z, 0.15 / m + 0.85 * coalesce(y, 0) AS n FROM r{i - 1} o CROSS JOIN m LEFT JOIN (SELECT e.dst AS id, sum(x / g) AS y FROM e JOIN r{i - 1} q ON q.id = e.src JOIN dg ON dg.id = e.src GROUP BY 1) s USING (id)))"""
    return f"{out} SELECT id, round(x, 8) AS rank, z AS frozen_at FROM r{iters}"


def personalized(name: str, seeds: str, iters: int) -> str:
    out = f"WITH {graph(name)}, dg AS (SELECT src AS id, count(*) AS g FROM e GROUP BY 1), sd AS ({seeds}), r0 AS (SELECT id, 1.0::DOUBLE / (SELECT count(*) FROM sd) AS x FROM sd)"
    for i in range(1, iters + 1):
        out += f", r{i} AS MATERIALIZED (SELECT id, sum(x) AS x FROM (SELECT e.dst AS id, 0.85 * x / g AS x FROM e JOIN r{i - 1} q ON q.id = e.src JOIN dg ON dg.id = e.src UNION ALL SELECT id, 0.15 / (SELECT count(*) FROM sd) FROM sd) GROUP BY id)"
    return f"{out} SELECT id, round(x, 8) AS rank FROM r{iters}"


def sssp(edges: str, source: str, rounds: int) -> str:
    """Bellman-Ford in unrolled rounds over weighted pairs."""
    out = f"WITH p AS MATERIALIZED ({edges}), e AS MATERIALIZED (SELECT src, dst, min(val) AS val FROM (SELECT src, dst, val FROM p UNION ALL SELECT dst, src, val FROM p) WHERE src <> dst GROUP BY 1, 2), d0 AS (SELECT CAST({source} AS BIGINT) AS id, 0.0::DOUBLE AS dist)"
    for i in range(1, rounds + 1):
        out += f", d{i} AS MATERIALIZED (SELECT id, min(dist) AS dist FROM (SELECT * FROM d{i - 1} UNION ALL SELECT e.dst, q.dist + e.val FROM d{i - 1} q JOIN e ON e.src = q.id) GROUP BY id)"
    return f"{out} SELECT id, dist FROM d{rounds}"


def betweenness(name: str, sources: str, depth: int) -> str:
    out = f"WITH RECURSIVE {graph(name)}, sc AS ({sources}), r(source, id, depth) AS (SELECT id, id, 0 FROM sc UNION SELECT r.source, e.dst, r.depth + 1 FROM r JOIN e ON e.src = r.id WHERE r.depth < {depth}), lv AS MATERIALIZED (SELECT source, id, min(depth) AS depth FROM r GROUP BY 1, 2), q0 AS (SELECT source, id, 1.0::DOUBLE AS paths FROM lv WHERE depth = 0)"
    for i in range(1, depth + 1):
        out += f", q{i} AS MATERIALIZED (SELECT q.source, e.dst AS id, sum(q.paths) AS paths FROM q{i - 1} q JOIN e ON e.src = q.id JOIN lv ON lv.source = q.source AND lv.id = e.dst AND lv.depth = {i} GROUP BY 1, 2)"
    out += f", b{depth} AS (SELECT source, id, paths, 0.0::DOUBLE AS delta FROM q{depth})"
    for i in range(depth - 1, -1, -1):
        out += f", b{i} AS MATERIALIZED (SELECT q.source, q.id, q.paths, q.paths * coalesce(sum((1 + b.delta) / b.paths), 0) AS delta FROM q{i} q LEFT JOIN e ON e.src = q.id LEFT JOIN b{i + 1} b ON b.source = q.source AND b.id = e.dst GROUP BY 1, 2, 3)"
    every = " UNION ALL ".join(f"SELECT source, id, delta FROM b{i}" for i in range(depth + 1))
    return f"{out} SELECT vx.id, round(coalesce(s, 0), 6) AS score FROM vx LEFT JOIN (SELECT id, sum(delta) AS s FROM ({every}) WHERE source <> id GROUP BY id) USING (id)"


def mis(name: str, rounds: int, tail: str | None = None) -> str:
    """Rounds as CTEs: c0, c1, ... the candidates and w1, w2, ... the chosen; all chosen, or what ``tail`` asks."""
    out = f"WITH {graph(name)}, c0 AS (SELECT id, ((id % 1000003) * 48271 + 12345) % 1000003 AS p FROM vx)"
    won = []
    for i in range(1, rounds + 1):
        out += f""", w{i} AS MATERIALIZED (SELECT c.id FROM c{i - 1} c WHERE NOT EXISTS (SELECT 1 FROM e JOIN c{i - 1} o ON o.id = e.src WHERE e.dst = c.id AND (o.p, o.id) > (c.p, c.id))),
 c{i} AS MATERIALIZED (SELECT * FROM c{i - 1} WHERE id NOT IN (SELECT id FROM w{i}) AND id NOT IN (SELECT e.dst FROM e JOIN w{i} ON w{i}.id = e.src))"""
        won.append(f"SELECT id FROM w{i}")
    return f"{out} {tail or ' UNION ALL '.join(won)}"
