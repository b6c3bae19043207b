"""SQL of the graph suite and of the problems on it, for DuckDB."""

from __future__ import annotations

#: Edge sets (a, b), a < b.
EDGES = {
    "copurchase": "SELECT DISTINCT x.l_partkey AS a, y.l_partkey AS b FROM lineitem x JOIN lineitem y USING (l_orderkey) WHERE x.l_partkey < y.l_partkey",
    "part_supplier": "SELECT DISTINCT least(2*l_partkey, 2*l_suppkey+1) AS a, greatest(2*l_partkey, 2*l_suppkey+1) AS b FROM lineitem",
    "page_link": """SELECT DISTINCT least(2*page_id, 2*h+1) AS a, greatest(2*page_id, 2*h+1) AS b FROM
        (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS link FROM pages) l
        JOIN (SELECT link, row_number() OVER (ORDER BY link) - 1 AS h FROM (SELECT DISTINCT unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS link FROM pages)) n USING (link)""",
    "order_chain": """SELECT DISTINCT least(o_orderkey, n) AS a, greatest(o_orderkey, n) AS b FROM
        (SELECT o_orderkey, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS n FROM orders) WHERE n IS NOT NULL AND n <> o_orderkey""",
    "event_chain": """SELECT DISTINCT least(event_id, n) AS a, greatest(event_id, n) AS b FROM
        (SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM events) WHERE n IS NOT NULL AND n <> event_id""",
    "geo_tree": """SELECT DISTINCT least(s, d) AS a, greatest(s, d) AS b FROM (SELECT 4*o_orderkey AS s, 4*o_custkey+1 AS d FROM orders
        UNION ALL SELECT 4*c_custkey+1, 4*c_nationkey::BIGINT+2 FROM customer UNION ALL SELECT 4*n_nationkey::BIGINT+2, 4*n_regionkey::BIGINT+3 FROM nation)""",
    "embed_cos": """SELECT x.vec_id AS a, y.vec_id AS b FROM embeddings x JOIN embeddings y ON x.vec_id < y.vec_id
        WHERE list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) >= 0.3""",
    "doc_line": """SELECT x.doc_id AS a, y.doc_id AS b FROM hashed x JOIN hashed y USING (h) JOIN held k USING (h) WHERE n <= 50 AND x.doc_id < y.doc_id
        UNION SELECT least, doc_id FROM hashed JOIN held USING (h) WHERE n > 50 AND doc_id > least""",
}
HASHED = "hashed AS (SELECT DISTINCT doc_id, md5(trim(line)) AS h FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line)) >= 40), held AS (SELECT h, count(*) AS n, min(doc_id) AS least FROM hashed GROUP BY h HAVING count(*) > 1)"


def graph(name: str, rest: str) -> str:
    """A statement over e(a, b), s(src, dst) in both directions and v(id)."""
    hashed = f"{HASHED}, " if name == "doc_line" else ""
    return f"WITH RECURSIVE {hashed}e AS ({EDGES[name]}), s AS (SELECT a AS src, b AS dst FROM e UNION ALL SELECT b, a FROM e), v AS (SELECT DISTINCT src AS id FROM s) {rest}"


def edges(name: str) -> str:
    return graph(name, "SELECT a::BIGINT AS src, b::BIGINT AS dst FROM e")


def degrees(name: str) -> str:
    return graph(name, "SELECT src::BIGINT AS id, count(*)::BIGINT AS degree FROM s GROUP BY src")


COMPONENTS = """, c(id, label) USING KEY (id) AS (SELECT id, id FROM v UNION
    SELECT s.dst, min(c.label) FROM c JOIN s ON s.src = c.id JOIN recurring.c AS o ON o.id = s.dst WHERE c.label < o.label GROUP BY s.dst)"""


def components(name: str) -> str:
    return graph(name, f"{COMPONENTS} SELECT id::BIGINT AS id, label::BIGINT AS component FROM c")


def pagerank(name: str, damping: float = 0.85, tol: float = 1e-4, most: int = 20) -> str:
    return graph(name, f""", d AS (SELECT src AS id, count(*) AS deg FROM s GROUP BY src), n AS (SELECT count(*)::DOUBLE AS n FROM v),
      r(step, id, rank) AS (SELECT 0, id, 1.0::DOUBLE / n FROM v, n
        UNION ALL SELECT r.step + 1, s.dst, {1 - damping:.2f} / any_value(n.n) + {damping} * sum(r.rank / d.deg) FROM r JOIN s ON s.src = r.id JOIN d ON d.id = r.id CROSS JOIN n
        WHERE r.step < {most} GROUP BY r.step, s.dst),
      g AS (SELECT x.step, sum(abs(x.rank - y.rank)) AS delta FROM r x JOIN r y ON y.id = x.id AND y.step = x.step - 1 GROUP BY x.step),
      t AS (SELECT coalesce(min(step) FILTER (WHERE delta < {tol}), {most}) AS step FROM g)
      SELECT id::BIGINT AS id, round(rank, 8) AS rank FROM r JOIN t USING (step)""")


def pagerank_exact(name: str, rounds: int = 5) -> str:
    return graph(name, f""", d AS (SELECT src AS id, count(*) AS deg FROM s GROUP BY src), n AS (SELECT count(*) AS n FROM v),
      r(step, id, u) AS (SELECT 0, id, 1000000000000000 // n FROM v, n
        UNION ALL SELECT r.step + 1, s.dst, (150000000000000 // any_value(n.n) + (85 * sum(r.u // d.deg)) // 100)::BIGINT FROM r JOIN s ON s.src = r.id JOIN d ON d.id = r.id CROSS JOIN n
        WHERE r.step < {rounds} GROUP BY r.step, s.dst)
      SELECT id::BIGINT AS id, u::BIGINT AS rank_units FROM r WHERE step = {rounds}""")


def _bfs(name: str, rest: str) -> str:
    return graph(name, f""", t(id, level) USING KEY (id) AS (SELECT min(id), 0 FROM v UNION
      SELECT s.dst, min(t.level) + 1 FROM t JOIN s ON s.src = t.id LEFT JOIN recurring.t AS o ON o.id = s.dst WHERE o.id IS NULL GROUP BY s.dst) {rest}""")


def bfs(name: str) -> str:
    return _bfs(name, "SELECT t.id::BIGINT AS id, (CASE WHEN t.level = 0 THEN t.id ELSE min(p.id) END)::BIGINT AS parent, t.level::INTEGER AS level FROM t LEFT JOIN s ON s.dst = t.id LEFT JOIN t p ON p.id = s.src AND p.level = t.level - 1 GROUP BY t.id, t.level")


def level_histogram(name: str) -> str:
    return _bfs(name, "SELECT level::INTEGER AS level, count(*)::BIGINT AS vertices FROM t GROUP BY level")


ORIENTED = """, d AS (SELECT src AS id, count(*) AS deg FROM s GROUP BY src),
  o AS (SELECT CASE WHEN (x.deg, a) < (y.deg, b) THEN a ELSE b END AS u, CASE WHEN (x.deg, a) < (y.deg, b) THEN b ELSE a END AS v FROM e JOIN d x ON x.id = a JOIN d y ON y.id = b),
  tri AS (SELECT x.u AS a, x.v AS b, y.v AS c FROM o x JOIN o y ON y.u = x.u JOIN o z ON z.u = x.v AND z.v = y.v)"""


def triangles(name: str) -> str:
    return graph(name, f"{ORIENTED} SELECT count(*)::BIGINT AS triangles FROM tri")


STATS = f"""{ORIENTED}, k AS (SELECT id, count(*) AS t FROM (SELECT unnest([a, b, c]) AS id FROM tri) GROUP BY id),
  st AS (SELECT d.id, coalesce(k.t, 0)::BIGINT AS triangles, (deg * (deg - 1) // 2)::BIGINT AS wedges FROM d LEFT JOIN k USING (id))"""


def triangle_stats(name: str) -> str:
    return graph(name, f"{STATS} SELECT id::BIGINT AS id, triangles, wedges, CASE WHEN wedges > 0 THEN round(triangles / wedges, 8) END AS clustering FROM st")


def transitivity(name: str) -> str:
    return graph(name, f"{STATS} SELECT (sum(triangles) // 3)::BIGINT AS triangles, sum(wedges)::BIGINT AS wedges, round(3 * (sum(triangles) // 3) / sum(wedges), 8) AS transitivity FROM st")


def k_clique4(name: str) -> str:
    return graph(name, f"""{ORIENTED} SELECT count(*)::BIGINT AS cliques FROM tri t JOIN o w ON w.u = t.a JOIN o x ON x.u = t.b AND x.v = w.v JOIN o y ON y.u = t.c AND y.v = w.v
      WHERE EXISTS (SELECT 1 FROM o q WHERE q.u = t.b AND q.v = t.c)""")


def butterflies(name: str) -> str:
    return graph(name, """, q AS (SELECT CASE WHEN a % 2 = 0 THEN a ELSE b END AS p, CASE WHEN a % 2 = 0 THEN b ELSE a END AS s FROM e),
      w AS (SELECT x.s AS s1, y.s AS s2, count(*) AS c FROM q x JOIN q y ON y.p = x.p AND x.s < y.s GROUP BY 1, 2) SELECT coalesce(sum(c * (c - 1) // 2), 0)::BIGINT AS butterflies FROM w""")


def _along_curve(side: int) -> list[tuple[int, int]]:
    """Cells of a Hilbert curve over a square, in order: four smaller curves, the first and the last one turned."""
    if side == 1:
        return [(0, 0)]
    half, small = side // 2, _along_curve(side // 2)
    return (
        [(y, x) for x, y in small] + [(x, y + half) for x, y in small] + [(x + half, y + half) for x, y in small] + [(side - 1 - y, half - 1 - x) for x, y in small]
    )


def manifest(name: str, p: int, order: str = "row") -> str:
    """Uniform cuts from 0: stripe = id p // (max + 1)."""
    number = {
        "row": f"i * {p} + j",
        "morton": " + ".join(f"((i >> {k}) & 1) * {2 << 2 * k} + ((j >> {k}) & 1) * {1 << 2 * k}" for k in range(max(1, (p - 1).bit_length()))),
        "hilbert": "CASE " + " ".join(f"WHEN i = {y} AND j = {x} THEN {k}" for k, (x, y) in enumerate(_along_curve(1 << max(1, (p - 1).bit_length())))) + " END",
    }[order]
    return graph(name, f""", m AS (SELECT max(src) + 1 AS m FROM s), b AS (SELECT src * {p} // m AS i, dst * {p} // m AS j, src, dst FROM s, m)
      SELECT ({number})::BIGINT AS block_id, i::INTEGER AS row, j::INTEGER AS col, ((i * any_value(m) + {p - 1}) // {p})::BIGINT AS src_lo, (((i + 1) * any_value(m) + {p - 1}) // {p})::BIGINT AS src_hi,
        ((j * any_value(m) + {p - 1}) // {p})::BIGINT AS dst_lo, (((j + 1) * any_value(m) + {p - 1}) // {p})::BIGINT AS dst_hi, count(*)::BIGINT AS n_edges,
        count(DISTINCT src)::BIGINT AS n_src, count(DISTINCT dst)::BIGINT AS n_dst, (16 * count(*))::BIGINT AS bytes FROM b, m GROUP BY i, j""")


def hits(name: str, rounds: int) -> str:
    """Half steps one after another, each scaled to length 1."""
    steps, hub = [], "SELECT id, 1.0::DOUBLE AS x FROM v"
    for k in range(rounds):
        for kind, by, to in (("a", "src", "dst"), ("h", "dst", "src")):
            before = f"({hub})" if not steps else steps[-1].split(" AS ")[0]
            steps.append(f"{kind}{k} AS MATERIALIZED (SELECT id, x / sqrt(sum(x * x) OVER ()) AS x FROM (SELECT s.{to} AS id, sum(r.x) AS x FROM s JOIN {before} r ON r.id = s.{by} GROUP BY s.{to}))")
    return graph(name, f", {', '.join(steps)} SELECT v.id::BIGINT AS id, round(h.x, 6) AS hub, round(a.x, 6) AS authority FROM v JOIN h{rounds - 1} h USING (id) JOIN a{rounds - 1} a USING (id)")


def lightest_first(weighed: str, bins: int) -> str:
    """Lists in falling weight, each into the lightest bin so far. ``weighed`` has (list_id, weight)."""
    return f"""WITH RECURSIVE w AS ({weighed}), o AS (SELECT weight, row_number() OVER (ORDER BY weight DESC, list_id) AS i FROM w),
      r(i, loads, lists) AS (SELECT 0, list_transform(range({bins}), lambda x: 0.0::DOUBLE), list_transform(range({bins}), lambda x: 0::BIGINT) UNION ALL
        SELECT r.i + 1, list_transform(range({bins}), lambda x: loads[x + 1] + CASE WHEN x + 1 = list_position(loads, list_min(loads)) THEN o.weight ELSE 0 END),
          list_transform(range({bins}), lambda x: lists[x + 1] + CASE WHEN x + 1 = list_position(loads, list_min(loads)) THEN 1 ELSE 0 END) FROM r JOIN o ON o.i = r.i + 1)
      SELECT k::INTEGER AS bin, lists[k + 1]::BIGINT AS lists, loads[k + 1] AS weight FROM (SELECT loads, lists FROM r ORDER BY i DESC LIMIT 1), range({bins}) t(k) WHERE lists[k + 1] > 0"""


def lists_triangle(name: str, p: int) -> str:
    return graph(name, f""", m AS (SELECT max(src) + 1 AS m FROM s), b AS (SELECT DISTINCT src * {p} // m AS i, dst * {p} // m AS j FROM s, m WHERE src * {p} // m <= dst * {p} // m)
      SELECT (x.i * {p} + x.j)::BIGINT AS first, (y.i * {p} + y.j)::BIGINT AS second, (z.i * {p} + z.j)::BIGINT AS third FROM b x JOIN b y ON y.i = x.i JOIN b z ON z.i = x.j AND z.j = y.j""")


def speeds(rest: str) -> str:
    """A statement over t(system, method, graph, speed) and r, which adds the ratio of the test's best speed to the system's."""
    return f"""WITH t AS (SELECT c_mktsegment AS system, o_orderpriority AS method, c_nationkey::VARCHAR AS graph, (count(*) FILTER (WHERE o_orderstatus = 'F'))::DOUBLE AS speed FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY ALL),
  r AS (SELECT *, CASE WHEN speed > 0 THEN max(speed) OVER (PARTITION BY method, graph) / speed END AS ratio FROM t) {rest}"""
