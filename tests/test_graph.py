"""Algorithms on hand-made graphs against brute force, goldens of the suite, and the traps of block geometry."""

import re

import numpy as np
import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from blockgraph import generators, measures, queries
from blockgraph.algorithms import components as cc
from blockgraph.algorithms import pagerank as pr
from blockgraph.algorithms import traverse as tv
from blockgraph.algorithms import triangles as tc
from blockgraph.baselines import brute, flat, models
from blockgraph.functions.bits import hilbert, morton
from blockgraph.operators.prepare import canonical, degrees, global_rank, symmetric
from blockgraph.plans import blocklists, cuts, planner, program, storage
from blockgraph.plans.blocks import block_graph, coverage
from blockgraph.sources import files, graphs

K5 = [(a, b) for a in range(5) for b in range(a + 1, 5)]
TWO_K4 = [(a, b) for s in (0, 4) for a in range(s, s + 4) for b in range(a + 1, s + 4)] + [(3, 4)]
PATH = [(i, i + 1) for i in range(9)]
STAR = [(0, i) for i in range(1, 12)]
FAR = [(0, 1), (5, 6)]
GRAPHS = {"k5": K5, "two_k4": TWO_K4, "path": PATH, "star": STAR, "far": FAR}


def frame(spark, pairs):
    return spark.createDataFrame([(int(a), int(b)) for a, b in pairs], "src long, dst long")


def ids(e):
    return e.select(F.explode(F.array("src", "dst")).alias("id")).distinct()


@pytest.mark.parametrize("name", GRAPHS)
def test_triangles(spark, name):
    e = frame(spark, GRAPHS[name])
    want = brute.triangles(GRAPHS[name])
    assert tc.triangles(e).first()[0] == want
    assert tc.triangles(e, method="merge", p=2).first()[0] == want
    assert tc.triangles(e, order="id", p=3, lane="both", bins=2, budget_bytes=64).first()[0] == want
    assert flat.triangles(e).first()[0] == flat.triangles_wedge(e).first()[0] == tc.triangles_csr(e).first()[0] == want


def test_cliques_and_truss(spark):
    e = frame(spark, TWO_K4)
    assert tc.k_cliques(e, 4).first()[0] == brute.cliques(TWO_K4, 4) == 2
    assert tc.k_truss(e, 4).count() == 12
    assert tc.k_cliques(frame(spark, K5), 5).first()[0] == 1
    assert tc.transitivity(frame(spark, K5)).first()["transitivity"] == 1.0


def test_butterflies(spark):
    pairs = [(2 * a, 2 * b + 1) for a in range(2) for b in range(3)]
    assert tc.butterflies(frame(spark, pairs)).first()[0] == brute.butterflies(pairs) == 3


@pytest.mark.parametrize("method", cc.METHODS)
def test_components(spark, method):
    for pairs in (TWO_K4[:-1], PATH, FAR):
        e = frame(spark, pairs)
        got = {r.id: r.component for r in cc.METHODS[method](e, ids(e)).collect()}
        assert got == brute.components(pairs)


def test_components_keep_isolated_vertices(spark):
    v = spark.createDataFrame([(i,) for i in range(8)], "id long")
    got = {r.id: r.component for r in cc.components_hook(frame(spark, FAR), v).collect()}
    assert got == brute.components(FAR, range(8))
    empty = frame(spark, [])
    assert cc.components_hook(empty, v).where("id <> component").count() == 0


def test_hooks_need_fewer_rounds_than_propagation(spark):
    e = frame(spark, [(i, i + 1) for i in range(40)])
    hook, spread = [], []
    cc.components_hook(e, ids(e), log=hook)
    cc.components_spread(e, ids(e), log=spread)
    assert len([x for x in hook if x[1] == "hook"]) <= 3 and len(hook) <= 10 and len(spread) >= 40


@pytest.mark.parametrize("direction", tv.DIRECTIONS)
def test_bfs(spark, direction):
    for pairs in (TWO_K4, PATH, FAR):
        e = frame(spark, pairs)
        got = {r.id: (r.parent, r.level) for r in tv.bfs(block_graph(e, ids(e), p=3), 0, direction).collect()}
        assert got == brute.bfs(pairs, 0)


def test_mixed_directions_lose_nothing(spark, sf):
    e = graphs.edges(spark, sf, "event_chain")
    near = e.where("src < 60 or dst < 60")
    g = block_graph(near, ids(near), p=4, keep=True)
    a, b = (tv.bfs(g, 0, d) for d in ("by_lane", "up"))
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0


def test_shortest_paths(spark):
    e = spark.createDataFrame([(0, 1, 5.0), (0, 2, 1.0), (1, 2, 1.0), (1, 3, 1.0)], "src long, dst long, w double")
    got = {r.id: (r.dist, r.parent) for r in tv.shortest_paths(block_graph(e, p=2), 0, "w").collect()}
    assert got == {0: (0.0, 0), 1: (2.0, 2), 2: (1.0, 0), 3: (3.0, 1)}


@pytest.mark.parametrize("layout,direction", [("2d", "pull"), ("1d", "pull"), ("2d", "push")])
def test_pagerank(spark, layout, direction):
    e = frame(spark, TWO_K4)
    log = []
    got = {r.id: r.rank for r in pr.pagerank(block_graph(e, ids(e), p=3, layout=layout), direction=direction, log=log).collect()}
    want = brute.pagerank(TWO_K4, range(8))
    assert all(abs(got[v] - want[v]) < 1e-12 for v in want) and log[-1][1] < 1e-4


def test_pagerank_sums_to_one_with_spread(spark):
    e = spark.createDataFrame([(0, 1), (1, 2)], "src long, dst long")
    g = block_graph(e, ids(e), p=2, directed=True)
    assert abs(pr.pagerank(g, dangling="spread").agg(F.sum("rank")).first()[0] - 1) < 1e-9


def test_blocks_cover_edges(spark):
    e = frame(spark, TWO_K4)
    for layout in ("2d", "1d"):
        for how in cuts.METHODS:
            r = coverage(block_graph(e, p=3, layout=layout, cuts=how), e).first()
            assert (r.in_blocks, r.missing, r.extra) == (2 * len(TWO_K4), 0, 0)


def test_storage_round_trips(spark):
    g = block_graph(frame(spark, TWO_K4), p=3)
    here = {(r.block_id, r.src, r.dst) for r in g.blocks.collect()}
    assert {(r.block_id, r.src, r.dst) for r in storage.to_coo(storage.to_csr(g.blocks, 2)).collect()} == here
    assert {(r.block_id, r.src, r.dst) for r in storage.from_compact(storage.to_compact(g.blocks, g.manifest, 2)).collect()} == here


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 30), min_size=1, max_size=12), st.integers(1, 5))
def test_optimal_cuts_are_optimal(loads, p):
    at = cuts.optimal_1d(loads, p)
    assert at[0] == 0 and at[-1] == len(loads) and len(at) == p + 1
    assert max(sum(loads[a:b]) for a, b in zip(at, at[1:], strict=False)) == cuts.optimal_1d_exact(loads, p)


def test_block_orders_are_permutations(spark):
    grid = spark.range(64).select((F.col("id") / 8).cast("int").alias("r"), (F.col("id") % 8).cast("int").alias("c"))
    for order in (morton, hilbert):
        rows = grid.select("r", "c", order(F.col("r"), F.col("c"), 8).alias("k")).orderBy("k").collect()
        assert [r.k for r in rows] == list(range(64))
        if order is hilbert:
            assert all(abs(a.r - b.r) + abs(a.c - b.c) == 1 for a, b in zip(rows, rows[1:], strict=False))


def test_triangle_geometry(spark, sf):
    e = graphs.edges(spark, sf, "copurchase")
    assert tc.triangles(e, order="id", p=4).first()[0] == 125968
    assert tc.triangles(e, order="id", p=4, lists=blocklists.lists_chained).first()[0] != 125968
    g = block_graph(e, p=4, directed=True)
    assert blocklists.lists_pattern(g.manifest).count() == 20


def test_goldens(spark, sf):
    for name, v, n in (("part_supplier", 210, 1905), ("order_chain", 1500, 1350), ("geo_tree", 1680, 1675), ("embed_cos", 488, 920), ("doc_line", 79, 466), ("page_link", 305, 279)):
        e = graphs.edges(spark, sf, name)
        assert e.count() == n and ids(e).count() == v


def test_generators(spark):
    for k, (v, n) in {2: (2, 1), 3: (5, 5), 5: (23, 71), 8: (191, 2360)}.items():
        e = generators.mycielski(spark, k)
        assert e.count() == n and ids(e).count() == v
    assert tc.triangles(generators.mycielski(spark, 6)).first()[0] == 0
    k = generators.kronecker(spark, 6, 4)
    assert k.count() > 50 and k.where("src >= dst").count() == 0


def test_messy_input(spark):
    e = canonical(frame(spark, [(1, 0), (0, 1), (2, 2), (-3, 1)]))
    assert {(r.src, r.dst) for r in e.collect()} == {(0, 1), (-3, 1)}
    assert block_graph(e, p=2).manifest.agg(F.sum("n_edges")).first()[0] == 4
    d = {r.id: r.degree for r in degrees(e).collect()}
    assert d == {0: 1, 1: 2, -3: 1}


def test_global_rank(spark):
    rows = global_rank(spark.range(100).select((F.col("id") * 37 % 101).alias("x")), ["x"], "k").orderBy("x").collect()
    assert [r.k for r in rows] == list(range(100))


def test_planner(spark):
    g = block_graph(frame(spark, TWO_K4), p=3)
    lists = planner.weigh(blocklists.lists_single(g.manifest), g.manifest)
    assert lists.agg(F.sum("weight")).first()[0] == 2 * len(TWO_K4)
    lanes = {r.lane for r in planner.split(lists, "both").collect()}
    assert lanes == {"light", "heavy"}
    bins = planner.bins_lpt(lists, 3).groupBy("bin").agg(F.sum("weight").alias("w")).collect()
    assert len(bins) == 3
    with pytest.raises(ValueError):
        planner.split(lists, "other")


def test_range_join_leaves_out_what_lies_beyond_the_cuts(spark):
    from blockgraph.operators.joins import range_join

    at = spark.createDataFrame([(x,) for x in (-1, 0, 9, 10, 19, 20, 500, None)], "x long")
    got = sorted((r.x, r.stripe, r.lo, r.hi) for r in range_join(at, cuts.custom([0, 10, 20]), "x").collect())
    assert got == [(0, 0, 0, 10), (9, 0, 0, 10), (10, 1, 10, 20), (19, 1, 10, 20)]


@pytest.mark.parametrize("p", [1, 4])
def test_many_edges_go_packed(spark, monkeypatch, p):
    import random

    from blockgraph.plans import packed

    draw = random.Random(5)
    pairs = sorted({(a, b) for a, b in ((draw.randrange(-20, 60), draw.randrange(-20, 60)) for _ in range(900)) if a < b} | {(0, 2**62)})
    e, want = frame(spark, pairs), brute.triangles(pairs)
    corners = {}
    for a, b in pairs:
        for c in range(b + 1, 60):
            if {(a, c), (b, c)} <= set(pairs):
                for x in (a, b, c):
                    corners[x] = corners.get(x, 0) + 1
    monkeypatch.setattr(packed, "WEDGES", 64)
    assert packed.triangle_count(e, p).first()[0] == want > 0
    assert {r.id: r.t for r in packed.triangle_corners(e, p).collect()} == corners
    assert packed.triangle_count(frame(spark, []), p).first()[0] == 0
    if p > 1:
        monkeypatch.setattr(packed, "MANY_EDGES", 1)
        monkeypatch.setattr(packed, "TASK_EDGES", 400)
        for found in (tc.triangles(e), tc.triangles(e, method="merge", lane="both"), flat.triangles(e), flat.triangles_wedge(e), tc.triangles_csr(e, "pandas")):
            assert found.first()[0] == want
            # What was stored is triangles of lists; no join of wedges.
            assert "Join" not in plan_of(found)
        assert {r.id: r.triangles for r in tc.triangle_stats(e).collect() if r.triangles} == corners


@pytest.mark.parametrize("p", [1, 3, 5])
def test_fours_of_many_edges_go_packed(spark, monkeypatch, p):
    import random

    from blockgraph.plans import packed

    draw = random.Random(6)
    pairs = sorted({(a, b) for a, b in ((draw.randrange(-20, 40), draw.randrange(-20, 40)) for _ in range(1500)) if a < b} | {(0, 2**62)})
    e, want = frame(spark, pairs), brute.cliques(pairs, 4)
    monkeypatch.setattr(packed, "CLIQUE_CELLS", 512)
    assert packed.clique4_count(e, p).first()[0] == want > 0
    assert packed.clique4_count(frame(spark, []), p).first()[0] == 0
    monkeypatch.setattr(packed, "MANY_EDGES", 1)
    assert "Join" not in plan_of(found := tc.k_cliques(e, 4)) and found.first()[0] == want


@pytest.mark.parametrize("p", [1, 3, 4])
def test_truss_of_many_edges_goes_packed(spark, monkeypatch, p):
    import os
    import random

    from blockgraph.plans import packed
    from blockgraph.plans.store import shared_folder

    scratch = shared_folder(spark).removeprefix("file://")

    draw = random.Random(7)
    pairs = sorted({(a, b) for a, b in ((draw.randrange(-20, 60), draw.randrange(-20, 60)) for _ in range(800)) if a < b} | {(0, 2**62)})

    def close(left):
        return {(a, b): sum({tuple(sorted((a, c))), tuple(sorted((b, c)))} <= left for c in range(-20, 60) if c not in (a, b)) for a, b in left}

    e, closed = frame(spark, pairs), close(set(pairs))
    monkeypatch.setattr(packed, "WEDGES", 16)
    for least in (1, 2, 3):
        assert {tuple(r) for r in packed.supported(e, least, p).collect()} == {x for x, n in closed.items() if n >= least}
    assert packed.supported(frame(spark, []), 1, p).count() == 0
    monkeypatch.setattr(packed, "MANY_EDGES", 1)
    monkeypatch.setattr(packed, "TASK_EDGES", 6 * len(pairs) // p**2)
    for k in (3, 4):
        made = set(os.listdir(scratch)) if os.path.isdir(scratch) else set()
        left = set(pairs)
        while (kept := {x for x, n in close(left).items() if n >= k - 2}) != left:
            left = kept
        found = tc.k_truss(e, k)
        assert {tuple(r) for r in found.collect()} == left and 0 < len(left) < len(pairs)
        # The rounds before the last one, and all packed blocks, are gone again.
        new = {x.rsplit("-", 1)[0] for x in set(os.listdir(scratch)) - made}
        assert new == {"blockgraph-of-lists"} and len(set(os.listdir(scratch)) - made) == 1
        # Rows of lists, and no join of wedges.
        assert "Join" not in plan_of(found)


@pytest.mark.parametrize("p", [1, 3])
def test_masked_products_are_summed_where_they_are_found(spark, monkeypatch, p):
    import numpy as np

    from blockgraph.plans import packed

    draw = np.random.default_rng(4)
    full = [draw.integers(-3, 4, (12, 12)) * (draw.random((12, 12)) < 0.5) for _ in range(3)]
    a, b, mask = (spark.createDataFrame([(int(r) - 4, int(c) - 4, float(x[r, c])) for r, c in zip(*np.nonzero(x), strict=True)], "row long, col long, val double") for x in full)
    want = float(((full[0] @ full[1]) * (full[2] != 0)).sum())
    monkeypatch.setattr(packed, "WEDGES", 8)
    assert packed.masked_total(a, b, mask, p).first()[0] == want == models.spgemm_masked_total(a, b, mask).first()[0] != 0
    assert packed.masked_total(a, a, a, p).first()[0] == float(((full[0] @ full[0]) * (full[0] != 0)).sum())
    monkeypatch.setattr(packed, "MANY_EDGES", 1)
    assert "Join" not in plan_of(found := models.spgemm_masked_total(a, b, mask)) and found.first()[0] == want


@pytest.mark.parametrize("p", [1, 3])
def test_butterflies_of_many_edges_go_packed(spark, monkeypatch, p):
    import random
    from itertools import combinations

    from blockgraph.plans import packed

    draw = random.Random(8)
    pairs = sorted({tuple(sorted((2 * draw.randrange(-8, 9), 2 * draw.randrange(14) + 1))) for _ in range(120)} | {(0, 2**62 + 1)})
    sides = {}
    for a, b in pairs:
        even, odd = (a, b) if a % 2 == 0 else (b, a)
        sides.setdefault(even, set()).add(odd)
    want = {}
    for a, b in combinations(sides, 2):
        for x, y in combinations(sides[a] & sides[b], 2):
            for v in (a, b, x, y):
                want[v] = want.get(v, 0) + 1
    monkeypatch.setattr(packed, "CLIQUE_CELLS", 40)
    e = frame(spark, pairs)
    for side, centre in (("even", "odd"), ("odd", "even")):
        both = spark.createDataFrame([(x, y) for x in sides for y in sides[x]], "even long, odd long").select(F.col(side).alias("side"), F.col(centre).alias("centre"))
        assert {r.id: r.butterflies for r in packed.butterfly_corners(both, p).collect()} == want
    monkeypatch.setattr(packed, "CLIQUE_EDGES", 1000)
    monkeypatch.setattr(packed, "MANY_EDGES", 1)
    found = tc.butterflies_per_vertex(e)
    assert "Join" not in plan_of(found) and {r.id: r.butterflies for r in found.collect()} == want and len(want) > 4
    assert packed.butterfly_corners(spark.createDataFrame([], "side long, centre long"), p).count() == 0


def test_lists_have_a_task_each(spark):
    from blockgraph.plans import packed
    from blockgraph.plans.store import side_by_side

    one = lambda k: spark.range(k, k + 5, 1, 3).coalesce(1)
    both = side_by_side([one(0), one(10), one(20)])
    assert both.count() == 15 and both.rdd.getNumPartitions() >= 3
    assert packed.triangle_count(frame(spark, K5), 3).first()[0] == 10


def test_vectors_are_stored_and_never_dealt_to_every_block(spark, sf, tmp_path, monkeypatch):
    import numpy as np

    rows = [(i, [float(x) for x in v]) for i, v in zip([*range(-5, 60), 7], np.random.default_rng(3).normal(size=(66, 5)), strict=True)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    x = np.array([v for _, v in rows], np.float32).astype(float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    near = x @ x.T >= graphs.COSINE
    want = sorted({(rows[a][0], rows[b][0]) for a, b in zip(*np.nonzero(near), strict=True) if rows[a][0] < rows[b][0]})
    for least, jobs in ((1024, 256), (10, 256), (10, 3)):
        monkeypatch.setattr(graphs, "BLOCK_VECTORS", least)
        monkeypatch.setattr(graphs, "PAIRS_PER_JOB", jobs)
        found = graphs.edges(spark, str(tmp_path), "embed_cos")
        assert sorted(tuple(r) for r in found.collect()) == want
        # Nothing is exchanged behind the store.
        assert "Exchange" not in plan_of(found)


def shuffled_paths(lengths, seed=7):
    import random

    names = list(range(sum(lengths)))
    random.Random(seed).shuffle(names)
    pairs, first = [], 0
    for n in lengths:
        pairs += [tuple(sorted(e)) for e in zip(names[first : first + n - 1], names[first + 1 : first + n], strict=True)]
        first += n
    return pairs


@pytest.mark.parametrize("lane", ["light", "heavy"])
def test_propagation_along_long_paths_is_contracted(spark, lane):
    pairs = shuffled_paths([400, 90, 3])
    e, log = frame(spark, pairs), []
    assert {r.id: r.component for r in cc.components_spread(e, ids(e), log=log, lane=lane).collect()} == brute.components(pairs)
    turns = [x[0] for x in log if x[1] == "spread"]
    assert turns == list(range(len(turns))) and cc.SPREAD_ROUNDS < len(turns) <= 3 * cc.SPREAD_ROUNDS
    log.clear()
    cc.components_spread(e, ids(e), log=log, max_rounds=7)
    assert len(log) == 7


@pytest.mark.parametrize("local", [0, 20, 1 << 18])
def test_balls_grow_as_far_as_they_reach(spark, monkeypatch, local):
    """Not as long as the starts spread, and by the kernel as in SQL."""
    pairs = shuffled_paths([90, 30, 3, 2]) + [(125, x) for x in range(126, 140)]
    monkeypatch.setattr(cc, "LOCAL_LINKS", local)
    e, log = frame(spark, pairs), []
    assert {r.id: r.component for r in cc.components_decompose(e, ids(e), log=log).collect()} == brute.components(pairs)
    assert [x[1] for x in log][-1:] == (["rest"] if local else ["balls"])
    assert (len(log) == 1) == (local > len(pairs))


@pytest.mark.parametrize("turns", [0, 60])
def test_balls_of_a_kernel_are_whole(turns):
    import pyarrow as pa

    pairs = shuffled_paths([200, 50, 2])
    parts = [pa.record_batch([pa.array(x) for x in zip(*pairs[k : k + 60], strict=True)], ["a", "b"]) for k in range(0, len(pairs), 60)]
    out = [r for b in cc._balls(0.4, 1, 0, turns)(iter(parts)) for r in b.to_pylist()]
    least = {}
    for r in out:
        least[r["centre"]] = min(r["id"], least.get(r["centre"], r["id"]))
    assert {r["id"]: least[r["centre"]] for r in out} == brute.components(pairs)


def test_blocks_are_solved_in_bounded_parts(spark, monkeypatch):
    import random

    import pyarrow as pa

    draw = random.Random(3)
    pairs = sorted({(a, b) for a, b in ((draw.randrange(200), draw.randrange(200)) for _ in range(170)) if a < b})
    rows = pa.record_batch([pa.array([a // 100 for a, _ in pairs]), pa.array([a for a, _ in pairs]), pa.array([b for _, b in pairs])], ["block_id", "src", "dst"])
    monkeypatch.setattr(models, "PIECE", 16)
    parts = [rows.slice(k, 5) for k in range(0, len(pairs), 5)]
    links = [tuple(r.values()) for out in models._forests(iter(parts)) for r in out.to_pylist()]
    assert brute.components(links, {x for e in pairs for x in e}) == brute.components(pairs)
    e = frame(spark, pairs)
    assert {r.id: r.component for r in models.block_local_components(block_graph(e, ids(e), p=2)).collect()} == brute.components(pairs)


@pytest.mark.parametrize("held", [4, 64, 1 << 22])
def test_forests_are_carried_through_a_task(spark, monkeypatch, held):
    import random

    import pyarrow as pa

    draw = random.Random(5)
    pairs = sorted({(a, b) for a, b in ((draw.randrange(150), draw.randrange(150)) for _ in range(300)) if a < b})
    monkeypatch.setattr(models, "CARRIED", held)
    parts = [pa.record_batch([pa.array(x) for x in zip(*pairs[k : k + 7], strict=True)], ["src", "dst"]) for k in range(0, len(pairs), 7)]
    links = [tuple(r.values()) for out in models._carried(iter(parts)) for r in out.to_pylist()]
    assert brute.components(links) == brute.components(pairs)
    assert held < 1 << 22 or len(links) < 150


@pytest.mark.parametrize("most", [0, 1 << 28])
def test_edges_from_some_sources(spark, monkeypatch, most):
    monkeypatch.setattr(tv, "MOST_BITS", most)
    e = frame(spark, [(-9, 4), (3, 40), (4, 5), (70000, 2), (1 << 40, 3)])
    pick = lambda *ids: sorted(tuple(r) for r in tv.edges_from(e, spark.createDataFrame([(i,) for i in ids], "id long")).collect())
    assert pick(-9, 4, 70000, 80000) == [(-9, 4), (4, 5), (70000, 2)]
    assert pick(3, 1 << 40) == [(3, 40), (1 << 40, 3)] and pick(6) == pick() == []


def test_profile_deals_edges_once(spark, sf, tmp_path, monkeypatch):
    """Lines are shuffled by their order alone, edges only to be told apart, and their table goes once the core is stored."""
    e = graphs.edges(spark, sf, "copurchase")
    assert "hashpartitioning(l_orderkey" in plan_of(e) and not re.search(r"hashpartitioning\(l_orderkey#\d+L, l_partkey", plan_of(e))
    assert "Exchange" not in plan_of(models.forest_links(frame(spark, PATH)))
    pairs = [tuple(r) for r in e.collect()]
    monkeypatch.setattr("blockgraph.plans.store.shared_folder", lambda _: f"file://{tmp_path}")
    got = queries.QUERIES["pipeline_copurchase"](spark, sf).first()
    found = brute.components(pairs)
    sizes = {c: list(found.values()).count(c) for c in set(found.values())}
    top = min(c for c in sizes if sizes[c] == max(sizes.values()))
    core = [p for p in pairs if found[p[0]] == top]
    assert (got.components, got.core_edges, got.triangles) == (len(sizes), len(core), brute.triangles(core))
    assert not list(tmp_path.glob("blockgraph-copurchase-*"))


def test_lateral_limit_ranks_by_its_order(spark, sf, tmp_path):
    from blockgraph.relational import QUERIES

    (tmp_path / "q").mkdir()
    spark.createDataFrame([(1,), (2,), (3,)], "c_custkey long").write.parquet(str(tmp_path / "q/customer.parquet"))
    rows = [(k, k % 2 + 1, float(k * 37 % 101 // 2)) for k in range(400)]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_totalprice double").repartition(8).write.parquet(str(tmp_path / "q/orders.parquet"))
    found = QUERIES["join_lateral"](spark, str(tmp_path / "q"))
    # The order must be the window's own; one from below does not survive a shuffle over several machines.
    assert "o_totalprice" in next(line for line in plan_of(found).split("\n") if "Window [" in line)
    best = {c: min((-p, k) for k, who, p in rows if who == c)[1] for c in (1, 2)}
    assert {r.c_custkey: r.o_orderkey for r in found.collect()} == best


def test_program_contract(spark):
    with pytest.raises(ValueError):
        program.BlockProgram(lists=program.single)
    with pytest.raises(ValueError):
        program.BlockProgram(light=lambda c, e: e)
    with pytest.raises(ValueError):
        program.merge(frame(spark, K5), ["src"], "dst", "other")
    with pytest.raises(Exception, match="several updates"):
        program.merge(frame(spark, K5), ["src"], "dst", None).collect()


def test_models(spark):
    e = symmetric(frame(spark, TWO_K4[:-1]))
    start = ids(e).select("id", F.col("id").alias("value"))
    want = brute.components(TWO_K4[:-1])
    got = models.edge_program(e, start, F.col("a"), F.min)
    assert {r.id: r.value for r in got.collect()} == want
    got = models.vertex_program(e, start, F.col("value"), F.min, F.least("value", F.coalesce("message", "value")))
    assert {r.id: r.value for r in got.collect()} == want
    g = block_graph(frame(spark, TWO_K4[:-1]), p=2)
    assert {r.id: r.component for r in models.block_local_components(g).collect()} == want


def test_files(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\n1 2\n3 4 0.5\n")
    (tmp_path / "a.txt").write_text("1: 2 3\n4: 5\n")
    assert files.read_edge_text(spark, str(tmp_path / "e.txt")).count() == 2
    assert files.read_adjacency_text(spark, str(tmp_path / "a.txt")).count() == 3
    g = block_graph(frame(spark, TWO_K4), p=3)
    files.write_blocks(g.blocks, str(tmp_path / "store"))
    some = files.read_blocks(spark, str(tmp_path / "store"), [0])
    assert "PartitionFilters: [isnotnull(row" in some._jdf.queryExecution().toString() or some.select("row").distinct().count() == 1
    assert files.read_blocks(spark, str(tmp_path / "store")).count() == 2 * len(TWO_K4)


def test_measures(spark):
    table = measures.speed_table(spark)
    won = {r.system: r.wins for r in measures.wins(table).collect()}
    assert won == {"CPU-A": 3, "CPU-B": 4, "CPU-C": 0, "CPU-D": 1, "GPU-E": 2, "GPU-F": 6, "REF-HYB": 20}
    profile = {(r.system, r.tau): r.tests for r in measures.profile(table).collect()}
    assert [profile["REF-HYB", t] for t in (1.5, 2.0, 4.0, 8.0)] == [27, 28, 32, 33]
    medians = {r.other: round(r.median, 2) for r in measures.median_over(table, "REF-HYB").collect()}
    assert medians["CPU-A"] == 1.90 and medians["CPU-B"] == 1.77 and medians["CPU-D"] == 3.46 and medians["GPU-F"] == 2.01


@pytest.mark.parametrize("name", ["kronecker_degrees", "paper_profile", "paper_rank", "paper_speedup_medians", "paper_wins", "pivot_speed"])
def test_speeds_and_kronecker_come_from_given_tables(spark, sf, monkeypatch, name):
    import duckdb

    from blockgraph import queries

    read = []
    keep = queries.stored
    monkeypatch.setattr(queries, "stored", lambda df, *a: read.extend(df.inputFiles()) or keep(df, *a))
    found = queries.QUERIES[name](spark, sf)
    assert any("orders.parquet" in f for f in read + found.inputFiles())
    con = duckdb.connect()
    for t in ("orders", "customer"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = con.execute(queries.ORACLES[name])
    assert [c[0] for c in want.description] == found.columns
    assert sorted(map(repr, map(tuple, found.collect()))) == sorted(map(repr, want.fetchall()))


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_rounds_move_attributes_and_never_edges(spark):
    from blockgraph.operators.exchange import gather

    e = frame(spark, TWO_K4)
    g = block_graph(e, ids(e), p=2, keep=True)
    before = {k: spark.conf.get(k) for k in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.enabled")}
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        plan = plan_of(gather(g.blocks, g.vertices.withColumn("x", F.lit(1.0)), "x").groupBy("dst").agg(F.sum("x")))
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    # Read upwards from the scan of the blocks: the join comes before any exchange.
    lines = plan.split("\n")
    at = next(i for i, line in enumerate(lines) if "Bucketed: true" in line)
    above = [line for line in lines[:at][::-1]]
    assert "Join" in next(line for line in above if "Join" in line or "Exchange" in line)


@pytest.mark.parametrize("lane", planner.LANES)
def test_lanes_agree(spark, lane):
    e = frame(spark, TWO_K4)
    g = block_graph(e, ids(e), p=3, keep=True)
    want = brute.pagerank(TWO_K4, range(8))
    got = {r.id: r.rank for r in pr.pagerank(g, lane=lane).collect()}
    assert all(abs(got[v] - want[v]) < 1e-12 for v in want)
    light = {r.id: r.rank_units for r in pr.pagerank_exact(g).collect()}
    assert {r.id: r.rank_units for r in pr.pagerank_exact(g, lane=lane).collect()} == light
    for method in ("hook", "fast_hook", "spread", "sampled"):
        for pairs in (TWO_K4[:-1], PATH, FAR):
            e = frame(spark, pairs)
            assert {r.id: r.component for r in cc.METHODS[method](e, ids(e), lane=lane).collect()} == brute.components(pairs)


def test_bottom_up_stops_early():
    import numpy as np

    n = 200
    frontier = np.zeros(n // 8 + 1, np.uint8)
    for v in (3, 150):
        frontier[v >> 3] |= 1 << (v & 7)
    runs = [[0, 1, 3, 5], [4, 5], list(range(4, 190)), [], [3]]
    ends = np.cumsum([len(r) for r in runs])
    found, read = tv.first_in_frontier(ends - [len(r) for r in runs], ends, np.array(sum(runs, [])), frontier)
    dst = sum(runs, [])
    assert [dst[i] if i >= 0 else None for i in found.tolist()] == [3, None, 150, None, 3]
    assert read == 3 + 2 + 147 + 0 + 1


def test_traversal_reads_only_active_stripes(spark):
    e = frame(spark, PATH)
    log = []
    tv.bfs(block_graph(e, ids(e), p=3, keep=True), 0, "down", log=log)
    assert [n for _, step, n in log if step == "edges"] == [1] + [2] * 8 + [1]
    assert {n for _, step, n in log if step == "down"} == {1}  # a path's frontier lies in one stripe
    e, read = frame(spark, STAR), {}
    for direction in ("down", "up"):
        log = []
        tv.bfs(block_graph(e, ids(e), p=3, keep=True), 0, direction, log=log)
        read[direction] = sum(n for _, step, n in log if step == "edges")
    assert read == {"down": 22, "up": 11}


def test_several_sources_and_wide_ids(spark, monkeypatch):
    e = frame(spark, PATH)
    got = {r.id: r.level for r in tv.bfs(block_graph(e, ids(e), p=2), [0, 9], "up").collect()}
    assert got == {i: min(i, 9 - i) for i in range(10)}
    monkeypatch.setattr(tv, "MOST_BITS", 0)
    assert {r.id: r.level for r in tv.bfs(block_graph(e, ids(e), p=2), [0, 9], "up").collect()} == got


def test_shortest_paths_over_edges_of_weight_zero(spark):
    e = spark.createDataFrame([(0, 1, 1.0), (1, 2, 0.0), (2, 3, 0.0), (1, 3, 0.0)], "src long, dst long, w double")
    got = {r.id: (r.dist, r.parent) for r in tv.shortest_paths(block_graph(e, p=2), 0, "w").collect()}
    assert got == {0: (0.0, 0), 1: (1.0, 0), 2: (1.0, 1), 3: (1.0, 1)}


def test_a_line_of_many_documents_keeps_them_together(spark, tmp_path):
    line = "a line that very many documents of this table do share"
    spark.createDataFrame([(i, f"text {i}\n{line}") for i in range(70)] + [(100, "x" * 50), (101, "x" * 50)], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    e = graphs.edges(spark, str(tmp_path), "doc_line")
    assert e.count() == 69 + 1
    assert {r.component for r in cc.components_hook(e, ids(e)).collect()} == {0, 100}


@pytest.mark.parametrize("reverse", [False, True])
def test_streams_equal_batches(spark, sf, reverse):
    from blockgraph.streaming import edges as streams

    path = streams.source_folder(spark, sf, 3, reverse)
    stream = lambda: streams.edge_stream(spark, path)
    batch = streams.batch_edges(spark, sf)
    assert sorted(r.event_id for r in streams.replay(stream()).collect()) == sorted(r.event_id for r in batch.collect())
    for windowed in (streams.tumbling, streams.sliding, streams.sessions):
        assert sorted(map(tuple, streams.replay(windowed(stream()), "complete").collect())) == sorted(map(tuple, windowed(batch).collect()))
    degrees_ = {r.user_id: r.degree for r in streams.latest_degrees(spark, path).collect()}
    assert degrees_ == {r.user_id: r["count"] for r in batch.groupBy("user_id").count().collect()}
    kept = {r.event_id for r in streams.replay(streams.dedup(stream())).collect()}
    # In order nothing is late; backwards all but the newest file is.
    assert (len(kept) == batch.count()) != reverse


def test_a_stream_goes_on_where_it_stopped(spark, sf, tmp_path):
    from blockgraph.streaming import edges as streams

    source, out, state = (str(tmp_path / x) for x in ("in", "out", "state"))
    events = spark.read.parquet(f"{sf}/events.parquet")

    def go():
        q = streams.edge_stream(spark, source).select("event_id").writeStream.format("parquet").option("checkpointLocation", state).trigger(availableNow=True).start(out)
        q.awaitTermination()
        return spark.read.parquet(out).count()

    events.where("event_id % 2 = 0").coalesce(1).write.mode("append").parquet(source)
    first = go()
    assert go() == first
    events.where("event_id % 2 = 1").coalesce(1).write.mode("append").parquet(source)
    assert go() == events.count()


def test_lanes_of_many_edges_run_their_own_kernels(spark, sf, monkeypatch):
    from blockgraph.plans import packed

    monkeypatch.setattr(packed, "MANY_EDGES", 1)
    monkeypatch.setattr(tc, "LIST_EDGES", 4000)
    seen = []
    heavy = tc._heavy
    monkeypatch.setattr(tc, "_heavy", lambda ctx, edges: seen.append(ctx.lane) or heavy(ctx, edges).withColumn("value", F.col("value") + 1))
    # Every heavy list counts one too many: the light lane has none of them, the others differ from it.
    assert queries.QUERIES["lane_equivalence_triangles"](spark, sf).first()[0] == 4
    assert {"heavy", "both"} <= set(seen)


def test_lists_in_folders_are_not_shuffled(spark, monkeypatch):
    import random

    draw = random.Random(7)
    pairs = sorted({(a, b) for a, b in ((draw.randrange(70), draw.randrange(70)) for _ in range(900)) if a < b})
    e, want = frame(spark, pairs), brute.triangles(pairs)
    monkeypatch.setattr(tc, "LIST_EDGES", 100)
    monkeypatch.setattr(program, "LISTS_PER_JOB", 20)
    g = tc.ranked_blocks(e)
    assert g.p > tc.LEAST_STRIPES and g.blocks.count() == len(pairs)
    assert [tc.triangles(e, lane=lane, graph=g).first()[0] for lane in planner.LANES] == [want] * 3
    assert tc.triangles(e, graph=tc.ranked_blocks(frame(spark, []))).first()[0] == 0
    ctx, one = program.Context(g), blocklists.lists_triangle(g.manifest).first()
    with program.lists_stay(spark):
        for kernel in (tc._light, tc._heavy):
            assert "Exchange" not in plan_of(kernel(ctx, program.edges_of_list(ctx, one.list_id, one.blocks)))


def test_udf_intersects_sorted_arrays_at_every_size(spark, monkeypatch):
    import pandas as pd

    from blockgraph.functions.arrays import merge_intersection_size
    from blockgraph.plans import packed

    sizes = merge_intersection_size.func
    far = [-(2**63), 5, 2**63 - 1]
    a, b = ([np.array(x, np.int64) for x in side] for side in ([[1, 2, 9], [], far, [4]], [[2, 3, 9], [1], far[1:], [1, 5]]))
    assert sizes(pd.Series(a), pd.Series(b)).tolist() == [2, 0, 2, 0]
    assert sizes(pd.Series(a[:2]), pd.Series(b[:2])).tolist() == [2, 0]
    assert sizes(pd.Series(a[1:2]), pd.Series(b[1:2])).tolist() == [0]

    monkeypatch.setattr(packed, "MANY_EDGES", 1)
    seen = []
    monkeypatch.setattr(tc, "merge_intersection_size", lambda x, y: seen.append(1) or merge_intersection_size(x, y))
    e = frame(spark, TWO_K4)
    assert tc.triangles_csr(e, "pandas").first()[0] == brute.triangles(TWO_K4) == 8
    assert seen
    g = tc.ranked_blocks(e)
    with program.lists_stay(spark):
        for one in blocklists.lists_triangle(g.manifest).limit(3).collect():
            assert "Exchange" not in plan_of(tc._intersect(program.Context(g), program.edges_of_list(program.Context(g), one.list_id, one.blocks)))
