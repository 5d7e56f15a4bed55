"""Stitching against brute force, the golden counts, and the invariants of tilings."""

import random

import duckdb
import pytest
from pyspark.sql import functions as F

from graphstitch.operators import baselines, execute, metrics, scoring
from graphstitch.operators.catalog import MotifCatalog
from graphstitch.plans import advisor, sqlgen
from graphstitch.plans.backtrack import adjacency, brute, find_one
from graphstitch.plans.decompose import ORDERS, decompose
from graphstitch.plans.motifs import LIBRARY, Motif
from graphstitch.plans.pattern import Pattern, path, ring, routed_star, sample_pattern, star
from graphstitch.sources import derive, lattice
from graphstitch.sources.graph import DataGraph, numbered

HH156 = lattice.HeavyHex(8, 16)


@pytest.fixture(scope="module")
def hh(spark):
    return lattice.of_range(spark, HH156).pin()


def graph_of(spark, edges):
    return DataGraph.from_edges(spark.createDataFrame(edges, "u long, v long"))


def test_lattices_have_the_published_sizes():
    sizes = {n: (s.vertices, 2 * len(s.pairs())) for n, (s, _, _) in lattice.LATTICES.items()}
    assert sizes == {"hh156": (156, 352), "hh1990": (1990, 4680), "hh4485": (4485, 10620), "sq1600": (1600, 6240), "sq3600": (3600, 14160)}


def test_lattice_edges_equal_their_pairs(spark, hh):
    assert {(r["u"], r["v"]) for r in hh.edges.collect()} == {e for a, b in HH156.pairs() for e in ((a, b), (b, a))}


def test_golden_motif_counts(hh):
    c = MotifCatalog.build(hh, ["edge", "path3", "path4", "path5", "claw4", "ring12", "sunhex18"])
    assert {m: c.count(m) for m in c.motifs} == {"edge": 352, "path3": 488, "path4": 612, "path5": 856, "claw4": 288, "ring12": 504, "sunhex18": 156}


def test_path5_recipes_agree(hh):
    a = MotifCatalog.build(hh, ["edge", "path3"]).add(LIBRARY["path5"], using=("path3",)).table("path5")
    b = MotifCatalog.build(hh, ["edge", "path4"]).add(LIBRARY["path5"], using=("path4", "edge")).table("path5")
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def test_worked_ring_example(spark):
    edges = [(i, (i + 1) % 6) for i in range(6)] + [(6, 0), (6, 3)]
    g = graph_of(spark, edges)
    rows = metrics.trace(g, ring(6), ["edge", "path4"]).collect()
    assert [(r["rows_joined"], r["rows_kept"]) for r in rows] == [(28, 28), (40, 12)]
    found = execute.match(g, ring(6), ["edge", "path4"]).collect()
    assert len(found) == 12 and {frozenset(r) for r in found} == {frozenset(range(6))}


@pytest.mark.parametrize("seed", range(3))
def test_random_graphs_against_brute_force(spark, seed):
    rng = random.Random(seed)
    n = rng.randint(6, 8)
    edges = [(i, j) for i in range(n) for j in range(i) if rng.random() < 0.45] or [(0, 1)]
    data = adjacency(edges)
    g = graph_of(spark, edges).pin()
    pattern = sample_pattern(adjacency([(i, j) for i in range(6) for j in range(i) if rng.random() < 0.7] + [(i, i + 1) for i in range(5)]), rng.randint(3, 5), seed)
    for semantics in ("induced", "monomorphism"):
        want = brute(pattern.n, pattern.edges, data, semantics == "induced")
        assert set(baselines.vf2(data, pattern, semantics)) == want
        got = execute.match(g, pattern, ("edge", "path3", "triangle", "claw4"), semantics_=semantics)
        assert sorted(map(tuple, got.collect())) == sorted(want)
        assert {tuple(r) for r in baselines.frontier_match(g, pattern, semantics).collect()} == want
        assert len(want) % len(pattern.automorphisms()) == 0


def test_tilings_partition_the_edges():
    data = adjacency(HH156.pairs())
    for seed in range(5):
        p = sample_pattern(data, 40, seed)
        for motifs in (["edge"], ["edge", "path4"], ["edge", "claw4", "ring12"]):
            for order in (*ORDERS, "user"):
                plan = decompose(p, motifs, order=order)
                assert sorted(e for t in plan.tiles for e in t.edges) == sorted(p.edges)
                assert all(t.seam for t in plan.tiles[1:])
        assert len(decompose(p, ["edge"]).tiles) == len(p.edges)


def test_all_ways_to_run_give_the_same_rows(spark, hh):
    p = sample_pattern(adjacency(HH156.pairs()), 10, 4)
    want = sorted(baselines.vf2(hh.local(), p))
    catalog = MotifCatalog.build(hh, ["edge", "path3", "path4", "claw4"])
    for options in ({}, {"induced": "antijoin"}, {"induced": "edgecount"}, {"seed_batches": 3}, {"cut_every": 2}, {"degree_filter": True}, {"strategy": "merge"}, {"distinct": "array"}, {"rotate": 2}):
        assert sorted(map(tuple, execute.match(hh, p, ["edge", "path4"], catalog=catalog, **options).collect())) == want, options
    assert sorted(map(tuple, baselines.vf2_distributed(hh, p).collect())) == want
    plan = advisor.ordered(p, ["edge", "path3", "path4", "claw4"], catalog)
    assert sorted(map(tuple, execute.run_plan(plan, catalog, "adjacency").collect())) == want
    broken = execute.match(hh, p, ["edge", "path4"], catalog=catalog, symmetry=True).count()
    assert broken * len(p.automorphisms()) == len(want)


def test_sql_text_agrees(hh):
    con = duckdb.connect()
    con.execute("create table part as select range as p_partkey from range(156)")
    p = sample_pattern(adjacency(HH156.pairs()), 9, 1)
    for induced in (True, False):
        want = sorted(baselines.vf2(hh.local(), p, "induced" if induced else "monomorphism"))
        assert sorted(con.sql(sqlgen.to_sql(p, lattice.lattice_sql("hh156"), induced)).fetchall()) == want


def test_scores_charge_each_vertex_and_edge_once(spark, hh):
    p = Pattern.of((0, 1), (1, 2), (2, 3), (1, 4))
    vq = hh.vertices.select("id", (1 - F.col("id") / 1000).alias("q"))
    eq = hh.edges.select("u", "v", (1 - (F.col("u") + F.col("v")) / 3000).alias("q"))
    a = scoring.score_layouts(hh, p, vq, eq).withColumn("score", F.round("score", 9))
    b = scoring.score_after(execute.match(hh, p), p, vq, eq).withColumn("score", F.round("score", 9))
    assert a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty() and not a.isEmpty()
    assert scoring.select_layouts(a, 5, 3).collect() == sorted(a.collect(), key=lambda r: (-r["score"], *r[:5]))[:3]


def test_edge_cases(spark, hh):
    with pytest.raises(ValueError):
        Pattern(3, frozenset([(0, 1)]))
    dirty = spark.createDataFrame([(1, 1), (1, 2), (2, 1), (None, 3), (2, 3), (2, 3)], "u long, v long")
    g = DataGraph.from_edges(dirty)
    assert sorted(map(tuple, g.edges.collect())) == [(1, 2), (2, 1), (2, 3), (3, 2)]
    assert sorted(r[0] for r in execute.match(g, Pattern(1, frozenset())).collect()) == [1, 2, 3]
    assert execute.match(g, path(2)).count() == 4
    assert execute.match(g, ring(5)).isEmpty()
    assert execute.match(hh, ring(4), ["edge", "ring4"]).isEmpty()
    empty = DataGraph.from_edges(spark.createDataFrame([], "u long, v long"))
    assert execute.match(empty, star(3)).isEmpty() and empty.fingerprint() == "0"
    with pytest.raises(execute.BudgetExceeded):
        execute.match(hh, path(4), ["edge"], max_rows=10)


def test_components_and_ids(spark):
    g = graph_of(spark, [(1, 2), (2, 3), (7, 8), (9, 10), (10, 7)])
    assert {r["id"]: r["component"] for r in g.components().collect()} == {1: 1, 2: 1, 3: 1, 7: 7, 8: 7, 9: 7, 10: 7}
    assert g.largest_component().vertices.count() == 4
    book = DataGraph.encode_ids(spark.createDataFrame([("b", "a"), ("c", None)], "x string, y string"), "x", "y")[1]
    assert sorted(map(tuple, book.collect())) == [("a", 0), ("b", 1), ("c", 2)]


def test_saved_catalog(spark, hh, tmp_path):
    MotifCatalog.build(hh, ["edge", "path3", Motif.from_edges("fork", [(0, 1), (0, 2), (2, 3)])]).save(str(tmp_path))
    c = MotifCatalog.load(spark, str(tmp_path), hh.fingerprint())
    assert c.table("path3").count() == 488 and c.table("fork").count() == 612
    with pytest.raises(ValueError):
        MotifCatalog.load(spark, str(tmp_path), "other")


def test_plans_refuse_reuse_inside_the_join(hh):
    c = MotifCatalog.build(hh, ["edge", "path4"])
    plan = execute.run_plan(decompose(ring(12), ["edge", "path4"]), c)._jdf.queryExecution().optimizedPlan().toString()
    assert "Cartesian" not in plan and plan.count("Join Inner") == 3 and "IN (" in plan
    closing = execute.run_plan(decompose(ring(4), ["edge"]), c)._jdf.queryExecution().optimizedPlan().toString()
    assert "LeftSemi" in closing


def test_a_stitch_is_one_join_on_small_graphs(spark):
    """Induced checks and scores look nothing up: no more joins than tiles."""
    g, data = lattice.of_range(spark, HH156).pin(), adjacency(HH156.pairs())
    p = sample_pattern(data, 8, 3)
    vq = g.vertices.select("id", (1 - F.col("id") / 1e4).alias("q"))
    eq = g.edges.select("u", "v", (1 - (F.col("u") + F.col("v")) / 1e5).alias("q"))
    tiles = len(decompose(p, ["edge", "path4"]).tiles)
    scored = scoring.score_layouts(g, p, vq, eq)
    plan = scored._jdf.queryExecution().optimizedPlan().toString()
    assert plan.split("InMemoryRelation")[0].count("Join ") <= tiles
    rows = {tuple(r)[:-1]: r["score"] for r in scored.collect()}
    after = {tuple(r)[:-1]: r["score"] for r in scoring.score_after(execute.match(g, p), p, vq, eq).collect()}
    assert rows.keys() == after.keys() and all(abs(rows[k] - after[k]) < 1e-12 for k in rows)
    least = sorted(rows.values())[len(rows) // 2]
    kept = scoring.score_layouts(g, p, vq, eq, min_score=least).collect()
    assert {tuple(r)[:-1] for r in kept} == {k for k, s in rows.items() if s >= least}
    g.unpin()


def test_numbering_and_blocked_neighbours(spark, tmp_path):
    df = spark.range(500).select((F.col("id") * 37 % 500).alias("x")).repartition(5)
    assert {r["x"]: r["k"] for r in numbered(df, ["x"], "k").collect()} == {i: i for i in range(500)}
    spark.range(60).select(F.col("id").alias("vec_id"), F.array(*[F.cos(F.col("id") * (k + 1)).cast("float") for k in range(4)]).alias("embedding")).write.parquet(f"{tmp_path}/embeddings.parquet")
    one, many = (derive.knn(spark, str(tmp_path), block=b).edges.collect() for b in (1000, 7))
    assert sorted(map(tuple, one)) == sorted(map(tuple, many)) and len(one) >= 180


def test_routed_stars_are_on_the_device():
    data = adjacency(HH156.pairs())
    for n in (10, 30, 70):
        p = routed_star(data, HH156.snake(), n)
        assert p.n == n and find_one(p.adj, data, set(), None) is not None


@pytest.mark.parametrize("name", ["tile_first_match", "tile_boundary", "automorphisms", "metric_iterations", "metric_iterations_path4", "metric_speedup", "brute_force", "stitch_join", "scan_lattice_grid", "scan_lattice_heavyhex"])
def test_queries_read_the_given_tables(spark, tmp_path, name):
    """On small tables of our own the rows follow the tables, as their SQL says."""
    from graphstitch import queries

    con = duckdb.connect()
    for t, sql in {
        "lineitem": "SELECT range // 3 AS l_orderkey, range * 7 % 11 AS l_partkey, range * 5 % 7 AS l_suppkey, CAST(range % 3 + 1 AS INTEGER) AS l_linenumber, 1e0 + range % 4 AS l_quantity, 1e1 + range AS l_extendedprice, 'R' AS l_returnflag FROM range(50)",
        "orders": "SELECT range AS o_orderkey, range * 3 % 13 AS o_custkey FROM range(90)", "customer": "SELECT range AS c_custkey, CAST(range % 5 + 10 AS INTEGER) AS c_nationkey FROM range(13)", "supplier": "SELECT range AS s_suppkey, CAST(range % 6 AS INTEGER) AS s_nationkey FROM range(7)",
    }.items():
        con.execute(f"CREATE TABLE {t} AS {sql}")
        con.execute(f"COPY {t} TO '{tmp_path}/{t}.parquet'")
    assert any(t in queries.SQL[name] for t in ("lineitem", "orders"))
    want = con.sql(queries.SQL[name]).fetchall()
    assert sorted(map(tuple, queries.QUERIES[name](spark, str(tmp_path)).collect())) == sorted(want) and want


def test_irregular_graphs_are_derived_once(spark, monkeypatch):
    """Motif tables name the edges several times: they find them stored, not as a plan of joins."""
    from graphstitch import workloads

    monkeypatch.setattr(derive, "GRAPHS", {n: derive.supply for n in ("copurchase", "knn", "pagelinks")})
    plans, count = [], MotifCatalog.count

    def seen(self, name):
        plans.append(self.graph.edges._jdf.queryExecution().optimizedPlan().toString())
        return count(self, name)

    monkeypatch.setattr(MotifCatalog, "count", seen)
    got = workloads.irregular(spark, "/root/testdata/sf0.001", shapes=("triangle",)).collect()
    assert [r["rows"] for r in got] == [0, 0, 0] and plans and not any("Union" in p or "Aggregate" in p for p in plans)


def test_motif_rows_are_counted_without_their_tables(spark):
    """Counts equal the tables' rows for any bound between light and heavy vertices; a catalog asks no table for them."""
    from graphstitch.operators.counting import Counts

    shapes = ["path3", "triangle", "claw4", "path4", "ring4", "star4"]
    for seed, (n, m, far) in enumerate([(12, 30, 1), (40, 150, 2**40), (9, 36, -7)]):
        rng = random.Random(seed)
        g = DataGraph.from_edges(spark.createDataFrame([(rng.randrange(n) - 5, min(rng.randrange(n), rng.randrange(n)) * far) for _ in range(m)], "u long, v long"))
        g = DataGraph(g.vertices, spark.createDataFrame(g.edges.collect(), "u long, v long"))
        c = MotifCatalog.build(g, ["edge", *shapes])
        want = {s: c.table(s).count() for s in shapes}
        assert want["ring4"] and want["triangle"]
        for light in (2, 6, 64):
            counts = Counts(g.edges, light=light, class_edges=20)
            assert {s: counts.of(c.motifs[s].pattern) for s in shapes} == want
        c._tables = {"edge": c.table("edge")}
        assert {s: c.count(s) for s in shapes} == want
    arcs = DataGraph.from_edges(spark.createDataFrame([(1, 2), (1, 3), (1, 4), (2, 3)], "u long, v long"), directed=True, symmetrize=False)
    c = MotifCatalog.build(arcs, ["edge", "path3", "triangle"])
    assert [c.count(s) for s in ("path3", "triangle")] == [c.table(s).count() for s in ("path3", "triangle")]


def test_rows_around_a_hub_are_counted(spark):
    """Two hubs over 20,000 leaves: more rows than could ever be listed."""
    n = 20_000
    edges = spark.range(n).select(F.explode(F.array(F.lit(-1), F.lit(-2)).cast("array<bigint>")).alias("u"), F.col("id").alias("v"))
    c = MotifCatalog.build(DataGraph.from_edges(edges), ["edge", "path3", "triangle", "claw4", "path4", "ring4"])
    assert c.count("claw4") == 2 * n * (n - 1) * (n - 2)
    assert c.count("ring4") == 4 * n * (n - 1) and c.count("triangle") == 0
    assert c.count("path4") == 2 * 2 * n * (n - 1)


def test_knn_by_slices(spark, tmp_path, monkeypatch):
    """Slices, ties of equal vectors and few vectors give the neighbours of a dense search; each vector is sent as stored."""
    import numpy as np

    monkeypatch.setattr(derive, "KNN_SLICE", 3)
    rng = np.random.default_rng(4)
    x = rng.normal(size=(40, 5)).astype(np.float32)
    x[10:18] = x[3]
    spark.createDataFrame([(i * 3, v.tolist(), 0) for i, v in enumerate(x)], "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    y = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    cos = np.round(y @ y.T, 9)
    want = set()
    for i in range(40):
        for j in sorted((j for j in range(40) if j != i), key=lambda j: (-cos[i, j], j))[:3]:
            want |= {(3 * i, 3 * j), (3 * j, 3 * i)}
    for block in (100, 6, 1):
        got = derive.knn(spark, str(tmp_path), block=block)
        assert {(r["u"], r["v"]) for r in got.edges.collect()} == want
    assert "array<double>" not in got.edges._jdf.queryExecution().optimizedPlan().treeString() and derive.KNN_BLOCK >= 16_384


def test_irregular_counts_every_shape_of_every_graph(spark):
    from graphstitch import workloads

    sf = "/root/testdata/sf0.001"
    got = workloads.irregular(spark, sf).collect()
    assert {(r["graph"], r["motif"]) for r in got} == {(g, m) for g in ("copurchase", "supply", "knn", "pagelinks") for m in ("triangle", "ring4", "path4", "claw4")}
    assert len(got) == 16 and all(r["seconds"] > 0 and r["derive_s"] > 0 for r in got)
    for name in ("supply", "pagelinks"):
        data = adjacency((r["u"], r["v"]) for r in derive.GRAPHS[name](spark, sf).edges.collect())
        degree = {v: len(near) for v, near in data.items()}
        rows = {r["motif"]: r["rows"] for r in got if r["graph"] == name}
        assert rows["claw4"] == sum(d * (d - 1) * (d - 2) for d in degree.values()) and rows["triangle"] == 0
        assert rows["path4"] == sum((degree[u] - 1) * (degree[v] - 1) for u in data for v in data[u])
        shared = [len(set(data[a]) & set(data[b])) for a in data for b in data if a < b]
        assert rows["ring4"] == 4 * sum(n * (n - 1) // 2 for n in shared)
