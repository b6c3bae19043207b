"""All queries of the graph engine, by name, and the SQL that DuckDB can check them by."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import generators, measures, oracles
from .algorithms import components as cc
from .algorithms import pagerank as pr
from .algorithms import traverse as tv
from .algorithms import triangles as tc
from .baselines import flat, models
from .operators.joins import asof_join, interval_join, range_join
from .operators.prepare import degrees, largest, orient, reorder_by_level, symmetric
from .plans import blocklists, cuts, planner, program, storage
from .plans.blocks import BlockedGraph, block_graph, coverage
from .plans.store import discard, fresh_path, stored
from .relational import ORACLES as RELATIONAL_ORACLES
from .relational import QUERIES as RELATIONAL
from .sources import files, graphs
from .streaming import edges as streams

P = 4
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _add(name: str, fn: Callable[[SparkSession, str], DataFrame], oracle: str | None = None) -> None:
    QUERIES[name] = fn
    if oracle:
        ORACLES[name] = oracle


def _edges(spark: SparkSession, sf_dir: str, g: str) -> DataFrame:
    return stored(graphs.edges(spark, sf_dir, g), g)


def _nodes(e: DataFrame) -> DataFrame:
    return e.select(F.explode(F.array("src", "dst")).alias("id")).distinct()


def _blocked(spark: SparkSession, sf_dir: str, g: str, **options) -> BlockedGraph:
    e = _edges(spark, sf_dir, g)
    return block_graph(e, _nodes(e), **({"p": P, "keep": True} | options))


# Preparation, blocks, lists, plans

for _g in graphs.EDGES:
    _add(f"edges_{_g}", lambda s, d, g=_g: graphs.edges(s, d, g), oracles.edges(_g))
    _add(f"degrees_{_g}", lambda s, d, g=_g: degrees(graphs.edges(s, d, g)), oracles.degrees(_g))
for _g, _t, _c in (("copurchase", "part", "p_partkey"), ("order_chain", "orders", "o_orderkey"), ("event_chain", "events", "event_id"), ("doc_line", "documents", "doc_id"), ("embed_cos", "embeddings", "vec_id")):
    _add(f"vertices_{_g}", lambda s, d, g=_g: graphs.vertices(s, d, g), f"SELECT {_c}::BIGINT AS id FROM {_t}")
for _g in ("part_supplier", "page_link", "geo_tree"):
    _add(f"vertices_{_g}", lambda s, d, g=_g: graphs.vertices(s, d, g), oracles.graph(_g, "SELECT id::BIGINT AS id FROM v"))
for _g in ("copurchase", "part_supplier"):
    _add(f"manifest_2d_{_g}", lambda s, d, g=_g: _blocked(s, d, g, keep=False).manifest, oracles.manifest(_g, P))
_add("block_ids_morton", lambda s, d: _blocked(s, d, "copurchase", order="morton", keep=False).manifest, oracles.manifest("copurchase", P, "morton"))
_add("block_ids_hilbert", lambda s, d: _blocked(s, d, "copurchase", order="hilbert", keep=False).manifest, oracles.manifest("copurchase", P, "hilbert"))


def _cuts_1d(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Greatest load of p contiguous groups of id ranges, by bisection, next to an even cut."""
    e = _edges(spark, sf_dir, "part_supplier")
    loads, low, width = cuts.histogram(e)
    best = cuts.optimal_1d(loads, P)
    sums = [int(loads[a:b].sum()) for a, b in zip(best, best[1:], strict=False)]
    return spark.createDataFrame([(i, low + width * a, n) for i, (a, n) in enumerate(zip(best, sums, strict=False))], "stripe int, lo long, load long")


_add("cuts_1d_optimal", _cuts_1d)


def _imbalance(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = _edges(spark, sf_dir, "part_supplier")
    out = None
    for method in cuts.METHODS:
        one = measures.imbalance(block_graph(e, p=P, cuts=method).manifest).withColumn("cuts", F.lit(method))
        out = one if out is None else out.unionByName(one)
    return out


_add("imbalance_by_cuts", _imbalance)
_add("block_coverage_check", lambda s, d: coverage(block_graph(e := _edges(s, d, "copurchase"), p=P, keep=True), e), oracles.graph("copurchase", "SELECT count(*)::BIGINT AS in_blocks, count(*)::BIGINT AS expected, 0::BIGINT AS missing, 0::BIGINT AS extra FROM s"))


def _storage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges that a round trip through each storage form loses or adds: all 0."""
    g = _blocked(spark, sf_dir, "copurchase")
    csr = storage.to_coo(storage.to_csr(g.blocks)).select("block_id", "src", "dst")
    compact = storage.from_compact(storage.to_compact(g.blocks, g.manifest)).select("block_id", "src", "dst")
    here = g.blocks.select("block_id", "src", "dst")
    out = None
    for name, other in (("csr", csr), ("compact", compact)):
        n = here.exceptAll(other).unionByName(other.exceptAll(here)).agg(F.count("*").alias("differing")).withColumn("form", F.lit(name))
        out = n if out is None else out.unionByName(n)
    return out


_add("storage_round_trips", _storage, "SELECT * FROM (VALUES ('csr', 0::BIGINT), ('compact', 0::BIGINT)) t(form, differing)")


def _block_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _blocked(spark, sf_dir, "copurchase", keep=False)
    path = fresh_path(spark, "store")
    files.write_blocks(g.blocks, path)
    return files.read_blocks(spark, path, [0, 1]).select("src", "dst")


_add("block_roundtrip", _block_store, oracles.graph("copurchase", f", m AS (SELECT max(src) + 1 AS m FROM s) SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM s, m WHERE src * {P} // m < 2"))
_add("lists_single", lambda s, d: blocklists.lists_single(_blocked(s, d, "copurchase", keep=False).manifest).select("list_id", F.col("blocks")[0].alias("block_id")), f"SELECT row_number() OVER (ORDER BY block_id) - 1 AS list_id, block_id FROM ({oracles.manifest('copurchase', P)})")


def _three() -> list:
    return [F.col("blocks")[k].alias(n) for k, n in enumerate(("first", "second", "third"))]


_add("lists_pattern_triangle", lambda s, d: blocklists.lists_pattern(_blocked(s, d, "copurchase", keep=False).manifest).select(*_three()), oracles.lists_triangle("copurchase", P))
_conformal = "m1.row <= m1.col and m2.row <= m2.col and m3.row <= m3.col and m2.row = m1.row and m3.row = m1.col and m3.col = m2.col"
_add("lists_generic_conformal", lambda s, d: blocklists.compose_where(_blocked(s, d, "copurchase", keep=False).manifest, 3, _conformal).select(*_three()), oracles.lists_triangle("copurchase", P))


def _active(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _blocked(spark, sf_dir, "event_chain")
    tree = tv.bfs(g, 0, "down", max_levels=3)
    stripes = [r.stripe for r in tree.where("level = 2").join(g.vertices, "id").select("stripe").distinct().collect()]
    return blocklists.lists_active(g.manifest, stripes).select(F.col("blocks")[0].alias("block_id"))


_add("lists_active_bfs_round2", _active, oracles._bfs("event_chain", f", m AS (SELECT max(src) + 1 AS m FROM s), f AS (SELECT DISTINCT t.id * {P} // m AS i FROM t, m WHERE level = 2) SELECT DISTINCT (src * {P} // m * {P} + dst * {P} // m)::BIGINT AS block_id FROM s, m WHERE src * {P} // m IN (SELECT i FROM f)"))


def _lanes(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _blocked(spark, sf_dir, "copurchase", keep=False)
    return planner.split(planner.weigh(blocklists.lists_single(g.manifest), g.manifest), "both").select("list_id", "weight", "lane")


_weighed = f"w AS (SELECT row_number() OVER (ORDER BY block_id) - 1 AS list_id, n_edges::DOUBLE AS weight, bytes FROM ({oracles.manifest('copurchase', P)}))"
_add("plan_lanes", _lanes, f"WITH {_weighed} SELECT list_id, weight, CASE WHEN sum(weight) OVER (ORDER BY weight DESC, list_id) - weight < 0.5 * sum(weight) OVER () THEN 'heavy' ELSE 'light' END AS lane FROM w")


def _waves(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _blocked(spark, sf_dir, "copurchase", keep=False)
    return planner.waves(planner.weigh(blocklists.lists_single(g.manifest), g.manifest), 1 << 20).select("list_id", "wave")


_add("plan_waves", _waves, f"WITH {_weighed} SELECT list_id, floor((sum(bytes) OVER (ORDER BY weight DESC, list_id) - bytes) / 1048576)::INTEGER AS wave FROM w")


def _bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = _blocked(spark, sf_dir, "copurchase", keep=False)
    return planner.bins_lpt(planner.weigh(blocklists.lists_pattern(g.manifest), g.manifest), 4).groupBy("bin").agg(F.count("*").alias("lists"), F.sum("weight").alias("weight"))


_TRIPLES = f"""SELECT row_number() OVER (ORDER BY first, second, third) - 1 AS list_id, (x.n_edges + y.n_edges + z.n_edges)::DOUBLE AS weight FROM ({oracles.lists_triangle('copurchase', P)}) l
  JOIN m x ON x.block_id = first JOIN m y ON y.block_id = second JOIN m z ON z.block_id = third"""
_add("plan_bins_lpt", _bins, oracles.lightest_first(f"WITH m AS ({oracles.manifest('copurchase', P)}) {_TRIPLES}", 4))
_add("plan_report", lambda s, d: program.explain(program.BlockProgram(light=lambda c, e: e, heavy=lambda c, e: e, lists=program.single), _blocked(s, d, "copurchase")))
_add("density_classes", lambda s, d: planner.classify_density(_blocked(s, d, "part_supplier", keep=False).manifest).groupBy("kind").agg(F.count("*").alias("blocks"), F.sum("n_edges").alias("edges")), f"""SELECT CASE WHEN n >= 0.1 THEN 'dense' WHEN n >= 0.001 THEN 'light' ELSE 'sparse' END AS kind, count(*)::BIGINT AS blocks, sum(n_edges)::BIGINT AS edges
  FROM (SELECT n_edges, n_edges / ((src_hi - src_lo) * (dst_hi - dst_lo)) AS n FROM ({oracles.manifest('part_supplier', P)})) GROUP BY 1""")

# PageRank and HITS


def _round(column: str = "rank", digits: int = 8):
    return F.round(column, digits).alias(column)



def _pagerank(s: SparkSession, d: str, g: str, layout: str = "2d", **options) -> DataFrame:
    return pr.pagerank(_blocked(s, d, g, layout=layout), **options).select("id", _round())


for _g in graphs.EDGES:
    _add(f"pagerank_{_g}", lambda s, d, g=_g: _pagerank(s, d, g), oracles.pagerank(_g))
_add("pagerank_push_copurchase", lambda s, d: _pagerank(s, d, "copurchase", direction="push"), oracles.pagerank("copurchase"))
_add("pagerank_1d_copurchase", lambda s, d: _pagerank(s, d, "copurchase", layout="1d"), oracles.pagerank("copurchase"))
_add("pagerank_exact_copurchase", lambda s, d: pr.pagerank_exact(_blocked(s, d, "copurchase")), oracles.pagerank_exact("copurchase"))
_add("pagerank_exact_page_link", lambda s, d: pr.pagerank_exact(_blocked(s, d, "page_link")), oracles.pagerank_exact("page_link"))
_add("pagerank_flat_copurchase", lambda s, d: flat.pagerank(e := _edges(s, d, "copurchase"), _nodes(e)).select("id", _round()), oracles.pagerank("copurchase"))


def _weighted(s: SparkSession, d: str) -> DataFrame:
    e = stored(graphs.part_supplier(s, d), "weighted")
    return pr.pagerank(block_graph(e, _nodes(e), p=P, keep=True), weight_col="w", max_iter=5, tol=0.0).select("id", _round())


_add("pagerank_weighted", _weighted, """WITH RECURSIVE e AS (SELECT least(2*l_partkey, 2*l_suppkey+1) AS a, greatest(2*l_partkey, 2*l_suppkey+1) AS b, sum(l_quantity) AS w FROM lineitem GROUP BY ALL),
  s AS (SELECT a AS src, b AS dst, w FROM e UNION ALL SELECT b, a, w FROM e), v AS (SELECT DISTINCT src AS id FROM s), d AS (SELECT src AS id, sum(w) AS deg FROM s GROUP BY src), n AS (SELECT count(*)::DOUBLE AS n FROM v),
  r(step, id, rank) AS (SELECT 0, id, 1.0::DOUBLE / n FROM v, n UNION ALL SELECT r.step + 1, s.dst, 0.15 / any_value(n.n) + 0.85 * sum(r.rank / d.deg * s.w) FROM r JOIN s ON s.src = r.id JOIN d ON d.id = r.id CROSS JOIN n WHERE r.step < 5 GROUP BY r.step, s.dst)
  SELECT id::BIGINT AS id, round(rank, 8) AS rank FROM r WHERE step = 5""")
_add("pagerank_personalised", lambda s, d: _pagerank(s, d, "copurchase", sources=[0, 1], max_iter=5, tol=0.0), oracles.graph("copurchase", """, d AS (SELECT src AS id, count(*) AS deg FROM s GROUP BY src), n AS (SELECT count(*)::DOUBLE AS n FROM v),
  r(step, id, rank) AS (SELECT 0, id, 1.0::DOUBLE / n FROM v, n UNION ALL SELECT r.step + 1, s.dst, CASE WHEN s.dst IN (0, 1) THEN 0.075 ELSE 0 END + 0.85 * sum(r.rank / d.deg) FROM r JOIN s ON s.src = r.id JOIN d ON d.id = r.id WHERE r.step < 5 GROUP BY r.step, s.dst)
  SELECT id::BIGINT AS id, round(rank, 8) AS rank FROM r WHERE step = 5"""))


def _rank_log(s: SparkSession, d: str) -> DataFrame:
    log: list = []
    pr.pagerank(_blocked(s, d, "copurchase"), log=log)
    return s.createDataFrame([(r, float(x)) for r, x in log], "round int, delta double").select("round", F.round("delta", 8).alias("delta"))


_add("pagerank_round_log", _rank_log, oracles.pagerank("copurchase").rpartition("SELECT id::BIGINT")[0] + "SELECT g.step::INTEGER AS round, round(delta, 8) AS delta FROM g, t WHERE g.step <= t.step")
_add("hits_page_link", lambda s, d: pr.hits(_blocked(s, d, "page_link"), 5).select("id", F.round("hub", 6).alias("hub"), F.round("authority", 6).alias("authority")), oracles.hits("page_link", 5))

# Components

for _g in graphs.EDGES:
    for _m in cc.METHODS:
        _add(f"components_{_m}_{_g}", lambda s, d, g=_g, m=_m: cc.METHODS[m](e := _edges(s, d, g), _nodes(e)), oracles.components(_g))
_add("components_block_local_copurchase", lambda s, d: models.block_local_components(_blocked(s, d, "copurchase")), oracles.components("copurchase"))
_add("components_vertex_program_doc_line", lambda s, d: models.vertex_program(symmetric(e := _edges(s, d, "doc_line")), _nodes(e).select("id", F.col("id").alias("value")), F.col("value"), F.min, F.least("value", F.coalesce("message", "value"))).withColumnRenamed("value", "component"), oracles.components("doc_line"))
_add("components_edge_program_embed_cos", lambda s, d: models.edge_program(symmetric(e := _edges(s, d, "embed_cos")), _nodes(e).select("id", F.col("id").alias("value")), F.col("a"), F.min).withColumnRenamed("value", "component"), oracles.components("embed_cos"))


def _round_counts(s: SparkSession, d: str) -> DataFrame:
    """Rounds of each method, jumps between hooks among them; the last, idle one counts."""
    out = []
    for g in ("doc_line", "order_chain"):
        e = _edges(s, d, g)
        v = stored(_nodes(e), "nodes")
        for m in ("hook", "fast_hook", "spread"):
            log: list = []
            cc.METHODS[m](e, v, log=log)
            for step in ("hook", "link", "spread"):
                if n := sum(x[1] == step for x in log):
                    out.append((g, m, step, n))
    return s.createDataFrame(out, "graph string, method string, step string, rounds int")


_add("components_round_counts", _round_counts)


def _skip_share(s: SparkSession, d: str) -> DataFrame:
    """Share of edges that the last phase of the sampled method does not read."""
    out = []
    for g in ("copurchase", "order_chain"):
        log: list = []
        e = _edges(s, d, g)
        cc.components_sampled(e, _nodes(e), log=log)
        seen = {step: n for _, step, n in log if step in ("skipped", "edges")}
        out.append((g, seen["skipped"] / max(seen["edges"], 1)))
    return s.createDataFrame(out, "graph string, skipped double").select("graph", F.round("skipped", 6).alias("skipped"))


_add("sampling_skip_share", _skip_share)

# Traversal


def _source(e: DataFrame) -> int:
    return int(e.agg(F.min("src")).first()[0] or 0)


def _bfs(s: SparkSession, d: str, g: str, direction: str) -> DataFrame:
    e = _edges(s, d, g)
    return tv.bfs(block_graph(e, _nodes(e), p=P, keep=True), _source(e), direction)


for _g in graphs.EDGES:
    _add(f"bfs_down_{_g}", lambda s, d, g=_g: _bfs(s, d, g, "down"), oracles.bfs(_g))
for _g in ("copurchase", "part_supplier", "geo_tree"):
    _add(f"bfs_level_histogram_{_g}", lambda s, d, g=_g: tv.level_histogram(_bfs(s, d, g, "down")), oracles.level_histogram(_g))
for _g in graphs.EDGES:
    for _m in ("auto", "up", "by_lane"):
        _add(f"bfs_{_m}_{_g}", lambda s, d, g=_g, m=_m: _bfs(s, d, g, m), oracles.bfs(_g))
_add("bfs_flat_copurchase", lambda s, d: flat.bfs(e := _edges(s, d, "copurchase"), _nodes(e), _source(e)), oracles.bfs("copurchase"))


def _bfs_work(s: SparkSession, d: str) -> DataFrame:
    """Edges that either direction reads on each level of the co-purchase graph: all of the frontier's; or, of every unvisited vertex,
    those into stripes that hold a part of the frontier, up to its first neighbour there."""
    e = _edges(s, d, "copurchase")
    g = block_graph(e, _nodes(e), p=P, keep=True)
    out = []
    for direction in ("down", "up"):
        log: list = []
        tv.bfs(g, _source(e), direction, log=log)
        out += [(direction, level, n) for level, step, n in log if step == "edges"]
    return s.createDataFrame(out, "direction string, level int, edges long")


_EXAMINED = f""", d AS (SELECT src AS id, count(*) AS deg FROM s GROUP BY src), k AS (SELECT max(level) AS last FROM t), n AS (SELECT unnest(range(last + 1)) AS level FROM k),
  m AS (SELECT max(src) + 1 AS m FROM s), f AS (SELECT DISTINCT level, id * {P} // m AS stripe FROM t, m),
  p AS (SELECT t.id, t.level, min(f.id) AS parent FROM t JOIN s ON s.src = t.id JOIN t f ON f.id = s.dst AND f.level = t.level - 1 GROUP BY t.id, t.level)
  SELECT 'down' AS direction, t.level::INTEGER AS level, sum(d.deg)::BIGINT AS edges FROM t JOIN d USING (id) GROUP BY t.level
  UNION ALL SELECT 'up', n.level::INTEGER, count(s.dst)::BIGINT FROM n LEFT JOIN (f CROSS JOIN m JOIN s ON s.dst * {P} // m = f.stripe LEFT JOIN t ON t.id = s.src LEFT JOIN p ON p.id = s.src)
    ON f.level = n.level AND coalesce(t.level, 1000000) > n.level AND (coalesce(t.level, 1000000) > n.level + 1 OR s.dst <= p.parent) GROUP BY n.level"""
_add("bfs_edges_examined", _bfs_work, oracles._bfs("copurchase", _EXAMINED))


def _bfs_saved(s: SparkSession, d: str) -> DataFrame:
    """Whether changing direction reads fewer edges than going down all the way."""
    e = _edges(s, d, "copurchase")
    g = block_graph(e, _nodes(e), p=P, keep=True)
    read = {}
    for direction in ("down", "auto"):
        log: list = []
        tv.bfs(g, _source(e), direction, log=log)
        read[direction] = sum(n for _, step, n in log if step == "edges")
    return s.createDataFrame([(read["auto"] < read["down"],)], "fewer boolean")


_add("bfs_auto_reads_fewer_edges", _bfs_saved, "SELECT true AS fewer")


def _sssp(s: SparkSession, d: str) -> DataFrame:
    e = stored(graphs.part_supplier(s, d), "weighted")
    return tv.shortest_paths(block_graph(e, _nodes(e), p=P, keep=True), 0, "w").select("id", "dist")


_add("sssp_part_supplier", _sssp, """WITH RECURSIVE e AS (SELECT least(2*l_partkey, 2*l_suppkey+1) AS a, greatest(2*l_partkey, 2*l_suppkey+1) AS b, sum(l_quantity) AS w FROM lineitem GROUP BY ALL),
  s AS (SELECT a AS src, b AS dst, w FROM e UNION ALL SELECT b, a, w FROM e),
  t(id, dist) USING KEY (id) AS (SELECT 0::BIGINT, 0.0::DOUBLE UNION SELECT s.dst, min(t.dist + s.w) FROM t JOIN s ON s.src = t.id LEFT JOIN recurring.t AS o ON o.id = s.dst WHERE o.id IS NULL OR t.dist + s.w < o.dist GROUP BY s.dst)
  SELECT id::BIGINT AS id, dist FROM t""")

# Patterns

for _g in graphs.EDGES:
    _add(f"triangles_{_g}", lambda s, d, g=_g: tc.triangles(_edges(s, d, g)), oracles.triangles(_g))
_add("triangles_merge_copurchase", lambda s, d: tc.triangles(_edges(s, d, "copurchase"), method="merge"), oracles.triangles("copurchase"))
_add("triangles_idorder_copurchase", lambda s, d: tc.triangles(_edges(s, d, "copurchase"), order="id"), oracles.triangles("copurchase"))
_add("triangles_csr_copurchase", lambda s, d: tc.triangles_csr(_edges(s, d, "copurchase")), oracles.triangles("copurchase"))
_add("triangles_flat_copurchase", lambda s, d: flat.triangles(_edges(s, d, "copurchase")), oracles.triangles("copurchase"))
_add("triangles_wedge_embed_cos", lambda s, d: flat.triangles_wedge(_edges(s, d, "embed_cos")), oracles.triangles("embed_cos"))
_add("udf_intersect", lambda s, d: tc.triangles_csr(_edges(s, d, "embed_cos"), "pandas"), oracles.triangles("embed_cos"))
_add("triangles_per_vertex", lambda s, d: tc.triangle_stats(_edges(s, d, "copurchase")).drop("clustering"), oracles.graph("copurchase", f"{oracles.STATS} SELECT id::BIGINT AS id, triangles, wedges FROM st"))
_add("clustering_coefficients", lambda s, d: tc.triangle_stats(_edges(s, d, "doc_line")).withColumn("clustering", F.round("clustering", 8)), oracles.triangle_stats("doc_line"))
_add("transitivity", lambda s, d: tc.transitivity(_edges(s, d, "embed_cos")).withColumn("transitivity", F.round("transitivity", 8)), oracles.transitivity("embed_cos"))
_add("kclique4_embed_cos", lambda s, d: tc.k_cliques(_edges(s, d, "embed_cos"), 4), oracles.k_clique4("embed_cos"))
_add("kclique4_copurchase", lambda s, d: tc.k_cliques(_edges(s, d, "copurchase"), 4), oracles.k_clique4("copurchase"))
_add("ktruss_copurchase", lambda s, d: tc.k_truss(_edges(s, d, "copurchase"), 5))
_add("ktruss3_embed_cos", lambda s, d: tc.k_truss(_edges(s, d, "embed_cos"), 3), oracles.graph("embed_cos", f"{oracles.ORIENTED} SELECT DISTINCT least(x, y)::BIGINT AS src, greatest(x, y)::BIGINT AS dst FROM (SELECT a AS x, b AS y FROM tri UNION ALL SELECT a, c FROM tri UNION ALL SELECT b, c FROM tri)"))
_add("butterflies_part_supplier", lambda s, d: tc.butterflies(_edges(s, d, "part_supplier")), oracles.butterflies("part_supplier"))
_add("butterflies_per_vertex", lambda s, d: tc.butterflies_per_vertex(_edges(s, d, "part_supplier")), oracles.graph("part_supplier", """, w AS (SELECT x.src AS id, y.src AS other, count(*) AS c FROM s x JOIN s y ON y.dst = x.dst AND y.src <> x.src GROUP BY ALL)
  SELECT id::BIGINT AS id, sum(c * (c - 1) // 2)::BIGINT AS butterflies FROM w GROUP BY id HAVING sum(c * (c - 1) // 2) > 0"""))
_add("wedges", lambda s, d: (u := orient(_edges(s, d, "doc_line"))).join(u.withColumnRenamed("v", "w"), "u").where("v < w").agg(F.count("*").alias("wedges")), oracles.graph("doc_line", f"{oracles.ORIENTED} SELECT count(*)::BIGINT AS wedges FROM o x JOIN o y ON x.u = y.u AND x.v < y.v"))

# Lanes agree


def _differing(results: dict[str, DataFrame]) -> DataFrame:
    """Rows in which any lane differs from the light one."""
    light, out = results["light"], None
    for lane in ("heavy", "both"):
        one = light.exceptAll(results[lane]).unionByName(results[lane].exceptAll(light))
        out = one if out is None else out.unionByName(one)
    return out.agg(F.count("*").alias("differing"))


def _lane_triangles(s: SparkSession, d: str) -> DataFrame:
    """Both kernels over the lists of one stored graph, whatever its size."""
    e = _edges(s, d, "copurchase")
    g = tc.ranked_blocks(e)
    return _differing({lane: tc.triangles(e, lane=lane, graph=g) for lane in planner.LANES})


def _lane_components(s: SparkSession, d: str, method: str) -> DataFrame:
    e = _edges(s, d, "copurchase")
    v = stored(_nodes(e), "nodes")
    return _differing({lane: cc.METHODS[method](e, v, lane=lane) for lane in planner.LANES})


def _lane_bfs(s: SparkSession, d: str) -> DataFrame:
    e = _edges(s, d, "copurchase")
    g = block_graph(e, _nodes(e), p=P, keep=True)
    return _differing({lane: tv.bfs(g, _source(e), m) for lane, m in (("light", "down"), ("heavy", "up"), ("both", "by_lane"))})


def _lane_pagerank(s: SparkSession, d: str) -> DataFrame:
    """In whole units, so that the order of sums cannot matter."""
    g = _blocked(s, d, "copurchase")
    return _differing({lane: pr.pagerank_exact(g, lane=lane) for lane in planner.LANES})


_LANES = {"triangles": _lane_triangles, "bfs": _lane_bfs, "pagerank": _lane_pagerank}
_LANES |= {f"components_{m}": lambda s, d, m=m: _lane_components(s, d, m) for m in ("hook", "fast_hook", "spread", "sampled")}
for _n, _f in _LANES.items():
    _add(f"lane_equivalence_{_n}", _f, "SELECT 0::BIGINT AS differing")
for _l in ("heavy", "both"):
    _add(f"pagerank_{_l}_copurchase", lambda s, d, lane=_l: _pagerank(s, d, "copurchase", lane=lane), oracles.pagerank("copurchase"))
    _add(f"pagerank_1d_{_l}_copurchase", lambda s, d, lane=_l: _pagerank(s, d, "copurchase", layout="1d", lane=lane), oracles.pagerank("copurchase"))
    _add(f"triangles_{_l}_copurchase", lambda s, d, lane=_l: tc.triangles(_edges(s, d, "copurchase"), lane=lane), oracles.triangles("copurchase"))
    for _m in ("hook", "sampled"):
        _add(f"components_{_m}_{_l}_copurchase", lambda s, d, lane=_l, m=_m: cc.METHODS[m](e := _edges(s, d, "copurchase"), _nodes(e), lane=lane), oracles.components("copurchase"))
_add("components_sampled_split_copurchase", lambda s, d: cc.components_sampled(e := _edges(s, d, "copurchase"), _nodes(e), lane="heavy", finish="light"), oracles.components("copurchase"))

# Synthetic graphs, speeds of systems, pipeline, applied components

_MYCIELSKI = """WITH RECURSIVE g(k, n, es) AS (SELECT 2, 2::BIGINT, [{'a': 0::BIGINT, 'b': 1::BIGINT}] UNION ALL SELECT k + 1, 2*n + 1,
  list_concat(list_concat(es, list_concat(list_transform(es, lambda e: {'a': e.a, 'b': e.b + n}), list_transform(es, lambda e: {'a': e.b, 'b': e.a + n}))), list_transform(range(n), lambda i: {'a': i + n, 'b': 2*n})) FROM g WHERE k < 8)"""
_add("mycielski_counts", lambda s, d: (e := stored(generators.mycielski(s, 8), "mycielski")).agg(F.count("*").alias("edges")).crossJoin(_nodes(e).agg(F.count("*").alias("vertices"))), f"{_MYCIELSKI} SELECT len(es)::BIGINT AS edges, n AS vertices FROM g WHERE k = 8")
_add("mycielski_triangles", lambda s, d: tc.triangles(stored(generators.mycielski(s, 8), "mycielski")), "SELECT 0::BIGINT AS triangles")
_add("mycielski_components", lambda s, d: cc.components_hook(e := stored(generators.mycielski(s, 8), "mycielski"), _nodes(e)).select("component").distinct(), "SELECT 0::BIGINT AS component")


def _hash_sql(x: str, seed: int, rounds: int) -> str:
    for r in range(rounds):
        x = f"(({x}) * 48271 + {seed + r}) % 2147483647"
    return x


def _kronecker_sql(scale: int, table: str, number: str, seed: int = 1) -> str:
    picks = ", ".join(f"({_hash_sql(f'({number} * 2654435 + {level * 97}) % 2147483647', seed + 7 * level, 3)}) % 100 AS h{level}" for level in range(scale))
    src = " + ".join(f"(h{k} >= 76)::BIGINT * {1 << (scale - 1 - k)}" for k in range(scale))
    dst = " + ".join(f"((h{k} >= 57 AND h{k} < 76) OR h{k} >= 95)::BIGINT * {1 << (scale - 1 - k)}" for k in range(scale))
    return f"WITH h AS (SELECT {picks} FROM {table}), p AS (SELECT {src} AS s, {dst} AS d FROM h), u AS (SELECT DISTINCT least(s, d) AS a, greatest(s, d) AS b FROM p WHERE s <> d) SELECT id::BIGINT AS id, count(*)::BIGINT AS degree FROM (SELECT a AS id FROM u UNION ALL SELECT b FROM u) GROUP BY id"


_add("kronecker_degrees", lambda s, d: degrees(stored(generators.kronecker_of(s.read.parquet(f"{d}/orders.parquet"), "o_orderkey", 8), "kronecker")), _kronecker_sql(8, "orders", "o_orderkey"))
_PRIORITIES = {"1-URGENT": "urgent", "2-HIGH": "high", "3-MEDIUM": "medium", "4-NOT SPECIFIED": "unspecified", "5-LOW": "low"}
_add("paper_speedup_medians", lambda s, d: measures.median_over(measures.order_speeds(s, d), "BUILDING").select("other", F.round("median", 6).alias("median"), "tests"), oracles.speeds("SELECT o.system AS other, round(median(m.speed / o.speed), 6) AS median, count(*)::BIGINT AS tests FROM t o JOIN t m USING (method, graph) WHERE m.system = 'BUILDING' AND o.system <> 'BUILDING' AND o.speed > 0 GROUP BY o.system"))
_add("paper_profile", lambda s, d: measures.profile(measures.order_speeds(s, d)), oracles.speeds("SELECT system, tau, count(*) FILTER (WHERE ratio <= tau)::BIGINT AS tests FROM r, (VALUES (1.0::DOUBLE), (1.5), (2.0), (4.0), (8.0)) x(tau) GROUP BY system, tau"))
_add("paper_wins", lambda s, d: measures.wins(measures.order_speeds(s, d)), oracles.speeds("SELECT system, count(*) FILTER (WHERE ratio = 1)::BIGINT AS wins, count(*)::BIGINT AS tests FROM r GROUP BY system"))
_add("paper_rank", lambda s, d: measures.rank(measures.order_speeds(s, d)), oracles.speeds("SELECT system, wins, rank() OVER (ORDER BY wins DESC) AS place FROM (SELECT system, count(*) FILTER (WHERE ratio = 1)::BIGINT AS wins FROM r GROUP BY system)"))
_add("pivot_speed", lambda s, d: measures.order_speeds(s, d).where("graph = '7'").groupBy("system").pivot("method", list(_PRIORITIES)).agg(F.first("speed")).withColumnsRenamed(_PRIORITIES), oracles.speeds("SELECT system, " + ", ".join(f"max(speed) FILTER (WHERE method = '{m}') AS {c}" for m, c in _PRIORITIES.items()) + " FROM t WHERE graph = '7' GROUP BY system"))
_add("degree_skew", lambda s, d: measures.degree_skew(degrees(_edges(s, d, "geo_tree"))).select("vertices", "max_degree", F.round("low_share", 6).alias("low_share")), oracles.graph("geo_tree", "SELECT count(*)::BIGINT AS vertices, max(n)::BIGINT AS max_degree, round(avg((n < 2)::INTEGER), 6) AS low_share FROM (SELECT src, count(*) AS n FROM s GROUP BY src)"))
_add("movement_2d", lambda s, d: measures.movement((g := _blocked(s, d, "copurchase", keep=False)).manifest, 1).select("attribute_rows", "bytes"), f"SELECT sum(n_src + n_dst)::BIGINT AS attribute_rows, (16 * sum(n_src + n_dst))::BIGINT AS bytes FROM ({oracles.manifest('copurchase', P)})")


def profile_graph(s: SparkSession, d: str, g: str) -> DataFrame:
    """Components, the largest one, its traversal order, triangles and clustering in the new order: one row."""
    e = _edges(s, d, g)
    # Only forests of the edges go into the rounds, and the edges of the core are picked by a bitmap: no edge is shuffled again.
    forest = stored(models.forest_links(e), "forest")
    labels = stored(cc.components_hook(forest, _nodes(forest)), "labels")
    core = stored(tv.edges_from(e, stored(largest(labels), "largest")), "core")
    discard(e)
    tree = stored(tv.bfs(block_graph(core, _nodes(core), p=P, keep=True), _source(core), "down"), "tree")
    again = stored(reorder_by_level(core, tree), "reordered")
    stats = tc.transitivity(again)
    return stats.select(F.lit(labels.select("component").distinct().count()).cast("long").alias("components"), F.lit(core.count()).cast("long").alias("core_edges"), F.lit(tree.agg(F.max("level")).first()[0]).cast("int").alias("levels"), "triangles")


_PROFILE = f"""{oracles.COMPONENTS}, top AS (SELECT label FROM c GROUP BY label ORDER BY count(*) DESC, label LIMIT 1), k AS (SELECT e.* FROM e JOIN c ON c.id = e.a WHERE label = (SELECT label FROM top)),
  ks AS (SELECT a AS src, b AS dst FROM k UNION ALL SELECT b, a FROM k), t(id, level) USING KEY (id) AS (SELECT min(src), 0 FROM ks UNION SELECT s.dst, min(t.level) + 1 FROM t JOIN ks s ON s.src = t.id LEFT JOIN recurring.t AS o ON o.id = s.dst WHERE o.id IS NULL GROUP BY s.dst),
  tri AS (SELECT count(*) AS n FROM k x JOIN k y ON y.a = x.b JOIN k z ON z.a = x.a AND z.b = y.b)
  SELECT (SELECT count(DISTINCT label) FROM c)::BIGINT AS components, (SELECT count(*) FROM k)::BIGINT AS core_edges, (SELECT max(level) FROM t)::INTEGER AS levels, (SELECT n FROM tri)::BIGINT AS triangles"""
for _g in ("copurchase", "doc_line"):
    _add(f"pipeline_{_g}", lambda s, d, g=_g: profile_graph(s, d, g), oracles.graph(_g, _PROFILE))


def _doc_clusters(s: SparkSession, d: str) -> DataFrame:
    e = _edges(s, d, "doc_line")
    labels = s.read.parquet(f"{d}/labels.parquet")
    c = cc.components_hook(e, _nodes(e))
    joined = c.join(labels, c.id == labels.doc_id, "left")
    return joined.groupBy("component").agg(F.count("id").alias("documents"), F.count("toxic").alias("labelled"), F.round(F.avg("quality"), 6).alias("quality"), F.round(F.avg("toxic"), 6).alias("toxic"))


_add("doc_clusters", _doc_clusters, oracles.graph("doc_line", f"{oracles.COMPONENTS} SELECT c.label::BIGINT AS component, count(*)::BIGINT AS documents, count(l.toxic)::BIGINT AS labelled, round(avg(l.quality), 6) AS quality, round(avg(l.toxic), 6) AS toxic FROM c LEFT JOIN labels l ON l.doc_id = c.id GROUP BY c.label"))


def _purity(s: SparkSession, d: str) -> DataFrame:
    e = _edges(s, d, "embed_cos")
    v = s.read.parquet(f"{d}/embeddings.parquet").select(F.col("vec_id").alias("id"), "label")
    c = cc.components_hook(e, _nodes(e)).join(v, "id").groupBy("component", "label").agg(F.count("*").alias("n"))
    return c.groupBy("component").agg(F.sum("n").alias("vectors"), F.max("n").alias("largest"))


_add("embedding_purity", _purity, oracles.graph("embed_cos", f"{oracles.COMPONENTS} SELECT component, sum(n)::BIGINT AS vectors, max(n)::BIGINT AS largest FROM (SELECT c.label::BIGINT AS component, m.label, count(*) AS n FROM c JOIN embeddings m ON m.vec_id = c.id GROUP BY c.label, m.label) GROUP BY component"))

# Algebra, joins, sources

_matrix = lambda e: symmetric(e).select(F.col("dst").alias("row"), F.col("src").alias("col"), F.lit(1.0).alias("val"))
# Below the diagonal alone: a triangle is one product there, and not six.
_lower = lambda e: e.select(F.greatest("src", "dst").alias("row"), F.least("src", "dst").alias("col"), F.lit(1.0).alias("val"))
_add("spmv_degrees", lambda s, d: models.spmv(_matrix(e := _edges(s, d, "copurchase")), _nodes(e).withColumn("value", F.lit(1.0))), oracles.graph("copurchase", "SELECT src::BIGINT AS id, count(*)::DOUBLE AS value FROM s GROUP BY src"))
_add("spgemm_triangles", lambda s, d: models.spgemm_masked_total(m := _lower(_edges(s, d, "embed_cos")), m, m).select(F.col("total").cast("long").alias("triangles")), oracles.triangles("embed_cos"))
_add("join_range_cuts", lambda s, d: range_join(s.read.parquet(f"{d}/part.parquet").select("p_partkey"), cuts.custom([0, 100, 500, 1000, 1_000_000]), "p_partkey").groupBy("stripe", "lo", "hi").agg(F.count("*").alias("n")), "SELECT k.stripe::INTEGER AS stripe, k.lo::BIGINT AS lo, k.hi::BIGINT AS hi, count(*)::BIGINT AS n FROM part JOIN (VALUES (0, 0, 100), (1, 100, 500), (2, 500, 1000), (3, 1000, 1000000)) k(stripe, lo, hi) ON p_partkey >= k.lo AND p_partkey < k.hi GROUP BY ALL")


def _interval(s: SparkSession, d: str) -> DataFrame:
    e = s.read.parquet(f"{d}/events.parquet").select("event_id", "user_id", "ts", "event_type")
    clicks = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("at"))
    buys = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("ts").alias("then"))
    return interval_join(clicks, buys, ["user_id"], "at", "then", 6 * 3600).select("user_id", "click", "purchase")


_add("join_interval_events", _interval, "SELECT c.user_id, c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON p.user_id = c.user_id AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 6 HOURS WHERE c.event_type = 'click'")


def _asof(s: SparkSession, d: str) -> DataFrame:
    e = s.read.parquet(f"{d}/events.parquet").select("user_id", F.col("ts").alias("at"), "event_id")
    o = s.read.parquet(f"{d}/orders.parquet").groupBy(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("at")).agg(F.max("o_orderkey").alias("o_orderkey"))
    return asof_join(e, o, "user_id", "at", ["o_orderkey"]).select("event_id", "o_orderkey")


_add("asof_orders", _asof, "WITH o AS (SELECT o_custkey, o_orderdate, max(o_orderkey) AS o_orderkey FROM orders GROUP BY ALL) SELECT event_id, o.o_orderkey FROM events ASOF LEFT JOIN o ON o.o_custkey = user_id AND o.o_orderdate <= ts")


def _text_round_trip(s: SparkSession, d: str) -> DataFrame:
    path = fresh_path(s, "edge-text")
    files.write_edge_text(graphs.edges(s, d, "embed_cos"), path)
    return files.read_edge_text(s, path).select("src", "dst")


_add("scan_csv_roundtrip", _text_round_trip, oracles.edges("embed_cos"))

# Streams

_stream_edges = lambda s, d, parts=3: streams.edge_stream(s, streams.source_folder(s, d, parts))
_K = "CAST(json_extract(props, '$.k') AS BIGINT)"
_add("stream_edges", lambda s, d: streams.replay(_stream_edges(s, d)).select("event_id", "user_id", "item"), f"SELECT event_id, user_id, {_K} AS item FROM events")
_add("stream_tumbling", lambda s, d: streams.replay(streams.tumbling(_stream_edges(s, d)), "complete"), "SELECT date_trunc('day', ts)::TIMESTAMP AS start, count(*)::BIGINT AS edges FROM events GROUP BY 1")
_add("stream_sliding", lambda s, d: streams.replay(streams.sliding(_stream_edges(s, d)), "complete"), "SELECT start, count(*)::BIGINT AS edges FROM (SELECT unnest([date_trunc('day', ts)::TIMESTAMP, date_trunc('day', ts)::TIMESTAMP - INTERVAL 1 DAY]) AS start FROM events) GROUP BY start")
_add("stream_session", lambda s, d: streams.replay(streams.sessions(_stream_edges(s, d)), "complete"), "WITH x AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 12 HOURS THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), y AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM x) SELECT user_id, min(ts) AS start, count(*)::BIGINT AS edges FROM y GROUP BY user_id, g")
_add("stream_dedup", lambda s, d: streams.replay(streams.dedup(_stream_edges(s, d))).select("event_id"), "SELECT event_id FROM events")
_LATE = """WITH e AS (SELECT ts, date_trunc('hour', ts)::TIMESTAMP AS start FROM events), m AS (SELECT max(ts) AS last FROM events)
  SELECT start, count(*)::BIGINT AS edges FROM e, m WHERE start + INTERVAL 1 HOUR <= last - INTERVAL 1 HOUR GROUP BY start"""
_add("stream_late_drop", lambda s, d: streams.replay(streams.late_drop(_stream_edges(s, d))), _LATE)
_add("stream_degree_state", lambda s, d: streams.latest_degrees(s, streams.source_folder(s, d, 3)), "SELECT user_id, count(*)::BIGINT AS degree FROM events GROUP BY user_id")
_add("stream_components", lambda s, d: streams.stream_components(s, streams.source_folder(s, d, 2)), f"WITH RECURSIVE s AS (SELECT 2 * user_id AS src, 2 * {_K} + 1 AS dst FROM events UNION ALL SELECT 2 * {_K} + 1, 2 * user_id FROM events), v AS (SELECT DISTINCT src AS id FROM s) {oracles.COMPONENTS} SELECT id::BIGINT AS id, label::BIGINT AS component FROM c")
_add("stream_static_join", lambda s, d: streams.replay(streams.with_static(_stream_edges(s, d), s.read.parquet(f"{d}/customer.parquet").select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id")).select("event_id", "c_mktsegment"), "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
_add("stream_interval_join", lambda s, d: streams.replay(streams.purchases_after_clicks(_stream_edges(s, d))), "SELECT c.user_id, c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON p.user_id = c.user_id AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click'")

QUERIES |= RELATIONAL
ORACLES |= RELATIONAL_ORACLES
