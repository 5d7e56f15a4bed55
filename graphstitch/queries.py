"""All queries by name, each with SQL for an independent engine where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphstitch import functions as fn
from graphstitch import streaming
from graphstitch.operators import baselines, execute, metrics, scoring, semantics
from graphstitch.operators.catalog import MotifCatalog
from graphstitch.plans import advisor, sqlgen
from graphstitch.plans.backtrack import adjacency, find_one
from graphstitch.plans.decompose import ORDERS, Tile, decompose
from graphstitch.plans.motifs import LIBRARY, Motif
from graphstitch.plans.pattern import Pattern, path, ring, sample_pattern, star
from graphstitch.session import shared_path
from graphstitch.sources import derive, io, lattice
from graphstitch.sources.graph import DataGraph

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

HH156 = adjacency(lattice.LATTICES["hh156"][0].pairs())
P8, P12, P20 = sample_pattern(HH156, 8, 3), sample_pattern(HH156, 12, 2), sample_pattern(HH156, 20, 2)
#: A ring of six with a seventh vertex tied to 0 and 3.
THETA = [(i, (i + 1) % 6) for i in range(6)] + [(6, 0), (6, 3)]
THETA_SQL = f"half AS (SELECT * FROM (VALUES {', '.join(map(str, THETA))}) t(u, v)), edges AS (SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v FROM half UNION SELECT v, u FROM half), ids AS (SELECT DISTINCT u AS id FROM edges)"
RING6_TILES = (Tile("path4", (2, 3, 4, 5), ((2, 3), (3, 4), (4, 5)), (), (2, 3, 4, 5), (2, 5)), Tile("path4", (5, 0, 1, 2), ((0, 1), (0, 5), (1, 2)), (5, 2), (0, 1), ()))
PAW = Motif.from_edges("paw", [(0, 1), (1, 2), (0, 2), (2, 3)])
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


_PINNED: dict[tuple, DataGraph] = {}


def graph(spark: SparkSession, sf_dir: str, name: str) -> DataGraph:
    """Device lattices and the hand-made graph are small and pinned once per session; derived graphs are built anew."""
    if name not in lattice.LATTICES and name != "theta7":
        return derive.GRAPHS[name](spark, sf_dir)
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _PINNED:
        _PINNED[key] = _small(spark, sf_dir, name).pin()
    return _PINNED[key]


def _small(spark: SparkSession, sf_dir: str, name: str) -> DataGraph:
    if name == "theta7":
        return DataGraph.from_edges(spark.createDataFrame(THETA, "u long, v long"))
    return lattice.lattice(spark, sf_dir, name)


def ctes(name: str) -> str:
    return THETA_SQL if name == "theta7" else lattice.lattice_sql(name) if name in lattice.LATTICES else derive.SQL[name]


def text(name: str, body: str, on: str | None = None, spark_body: str | None = None, duck_body: str | None = None, extra: str = "") -> None:
    """A query given as SQL for both engines, over a graph's edges and ids and over the tables. extra: further CTEs."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        # views of the given tables, and of the graph, under names of this package
        for t in TABLES:
            if t in (spark_body or body + extra):
                io.table(spark, sf_dir, t).createOrReplaceTempView(t)
        if on:
            g = graph(spark, sf_dir, on)
            g.edges.createOrReplaceTempView("edges")
            g.vertices.createOrReplaceTempView("ids")
        return spark.sql((f"WITH {extra} " if extra else "") + (spark_body or body))

    head = ", ".join(x for x in ((ctes(on) if on else ""), extra) if x)
    query(name, (f"WITH {head} " if head else "") + (duck_body or body))(run)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return execute.match(graph(spark, sf_dir, "hh156"), ring(12), ["edge", "path4"])


def _match(name: str, on: str, p: Pattern, induced: bool = True, style: str = "steps", **options) -> None:
    motifs = options.pop("motifs", ("edge", "path4"))

    def run(spark, sf_dir):
        return execute.match(graph(spark, sf_dir, on), p, motifs, semantics_="induced" if induced else "monomorphism", **options)

    query(name, sqlgen.to_sql(p, ctes(on), induced, style))(run)


# --- graphs and motif tables ---------------------------------------------------------------------------------------------
@query("graph_normalize", "WITH h AS (SELECT l_partkey % 50 AS u, l_suppkey % 50 AS v FROM lineitem) SELECT u, v FROM h WHERE u <> v UNION SELECT v, u FROM h WHERE u <> v")
def _(spark, sf_dir):
    return DataGraph.from_edges(io.table(spark, sf_dir, "lineitem").select((F.col("l_partkey") % 50).alias("u"), (F.col("l_suppkey") % 50).alias("v"))).edges


def _motif(name: str, on: str, m: Motif, using: tuple[str, ...] = (), build: tuple[str, ...] = ("edge",)) -> None:
    def run(spark, sf_dir):
        c = MotifCatalog.build(graph(spark, sf_dir, on), [b for b in build if b != m.name])
        return c.add(m, using=using or None).table(m.name) if m.name != "edge" else c.table("edge")

    cols = ", ".join(f"v{i} AS c{i}" for i in range(m.n))
    query(name, sqlgen.to_sql(m.pattern, ctes(on), False, "flat" if m.n <= 6 else "steps", cols))(run)


for _name, _on, _shape, _using, _build in [
    ("motif_edge", "hh156", "edge", (), ("edge",)), ("motif_path3", "hh1990", "path3", (), ("edge",)), ("motif_path4", "hh1990", "path4", (), ("edge", "path3")),
    ("motif_path5_a", "hh156", "path5", ("path3",), ("edge", "path3")), ("motif_path5_b", "hh156", "path5", ("path4", "edge"), ("edge", "path4")),
    ("motif_claw4", "hh1990", "claw4", (), ("edge", "path3")), ("motif_ring4", "sq1600", "ring4", (), ("edge", "path3")), ("motif_ring6", "sq1600", "ring6", (), ("edge", "path4")),
    ("motif_ring12", "hh156", "ring12", (), ("edge", "path4")), ("motif_ladder6", "sq1600", "ladder6", (), ("edge", "ring4")), ("motif_sunhex18", "hh156", "sunhex18", (), ("edge", "ring12", "path4")),
    ("motif_triangle", "copurchase", "triangle", (), ("edge",)), ("motif_star_k", "sq1600", "star4", (), ("edge", "path3")),
]:
    _motif(_name, _on, LIBRARY[_shape], _using, _build)
_motif("motif_custom", "copurchase", PAW, (), ("edge", "triangle"))

_SET = ("edge", "path3", "path4", "claw4")
_COUNTS = f"WITH {ctes('hh156')} " + " UNION ALL ".join(f"SELECT '{m}' AS motif, {LIBRARY[m].n} AS arity, count(*) AS rows, count(*) * {8 * LIBRARY[m].n} AS bytes FROM ({sqlgen.motif_sql(LIBRARY[m].pattern)}) q" for m in _SET)
for _name, _options in [("catalog_build", {}), ("catalog_build_noreuse", {"reuse": False}), ("catalog_parallel", {"parallel": 3, "persist": True}), ("metric_motif_rows", {})]:
    query(_name, _COUNTS)(lambda spark, sf_dir, o=_options: MotifCatalog.build(graph(spark, sf_dir, "hh156"), _SET, **o).stats())


def _count_sql(p: Pattern, on: str, induced: bool, tag: str, prefix: str) -> tuple[str, str]:
    body, last = sqlgen.steps(p, induced, prefix)
    return body, f"SELECT {tag}, count(*) AS mappings FROM {last}"


def _counts_sql(on: str, items: list[tuple[str, Pattern]], induced: bool) -> str:
    parts = [_count_sql(p, on, induced, tag, f"q{i}_") for i, (tag, p) in enumerate(items)]
    return f"WITH {ctes(on)}, {', '.join(b for b, _ in parts)} " + " UNION ALL ".join(s for _, s in parts)


_MANY = [P8, path(6), ring(12)]


@query("catalog_reuse", _counts_sql("hh156", [(f"{i} AS pattern", p) for i, p in enumerate(_MANY)], True))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "hh156")
    return execute.match_many(g, _MANY, MotifCatalog.build(g, ["edge", "path4"], persist=True), ["edge", "path4"])


# --- tiling ----------------------------------------------------------------------------------------------------------------
def _golden(rows: list[tuple], cols: str) -> str:
    values = ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else str(x) for x in r) + ")" for r in rows)
    return f"SELECT * FROM (VALUES {values}) t({cols})"


#: What tiling the 12-ring by 4-paths must give: the motif's vertex 1 is placed first, on vertex 0.
RING12_TILING = [(0, "path4", "11 0 1 2", "", "11 0 1 2"), (1, "path4", "2 3 4 5", "2", "3 4 5"), (2, "path4", "5 6 7 8", "5", "6 7 8"), (3, "path4", "8 9 10 11", "8 11", "9 10")]


@query("tile_pattern", _golden(RING12_TILING, "step, motif, verts, seam, fresh"))
def _(spark, sf_dir):
    return spark.createDataFrame(decompose(ring(12), ["edge", "path4"]).rows(), "step int, motif string, verts string, seam string, fresh string")


#: Orders by the number of their lines.
LINES_SQL = "lines AS (SELECT n, count(*) AS orders FROM (SELECT l_orderkey, count(DISTINCT l_linenumber) AS n FROM lineitem GROUP BY 1) q GROUP BY 1)"


def _lines(spark: SparkSession, sf_dir: str) -> list[tuple[int, int]]:
    """(lines, orders with so many): orders are patterns of their lines, told apart by how many there are."""
    n = io.table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.countDistinct("l_linenumber").alias("n")).groupBy("n").count()
    return sorted(map(tuple, n.where("n > 0").collect()))


@query("tile_first_match", f"WITH {ctes('trade')}, m AS ({sqlgen.flat(path(4), False)}), f AS (SELECT * FROM m ORDER BY v1, v2, v0, v3 LIMIT 1) " + " UNION ALL ".join(f"SELECT {j} AS position, v{j} AS vertex FROM f" for j in range(4)))
def _(spark, sf_dir):
    """Of a pattern given by a table: the motif's vertex 1 is placed first, then 2, 0 and 3, each as low as can be."""
    found = find_one(path(4).adj, graph(spark, sf_dir, "trade").local(1_000_000))
    return spark.createDataFrame(sorted((found or {}).items()), "position int, vertex long")


#: What the boundaries of chains of so many lines must be, as recorded once.
_BOUNDARIES = {2: [""], 3: ["1", ""], 4: [""], 5: ["3", ""], 6: ["3", "4", ""], 7: ["3", ""]}


@query("tile_boundary", f"WITH {LINES_SQL} SELECT pattern, step, boundary, orders FROM lines JOIN ({_golden([(n, i, b) for n, bs in _BOUNDARIES.items() for i, b in enumerate(bs)], 'pattern, step, boundary')}) g ON pattern = n")
def _(spark, sf_dir):
    """The lines of each order as a chain; orders of as many lines are one pattern."""
    rows = [(n, i, " ".join(map(str, t.boundary)), k) for n, k in _lines(spark, sf_dir) for i, t in enumerate(decompose(path(n), ["edge", "path4"]).tiles)]
    return spark.createDataFrame(rows, "pattern int, step int, boundary string, orders long")


@query("tile_orders", _counts_sql("hh156", [(f"'{o}' AS ordering", P8) for o in sorted(ORDERS)], True))
def _(spark, sf_dir):
    g, out = graph(spark, sf_dir, "hh156"), None
    c = MotifCatalog.build(g, ["edge", "path3", "claw4"], persist=True)
    for o in sorted(ORDERS):
        one = execute.match(g, P8, ["edge", "path3", "claw4"], catalog=c, order=o).agg(F.count("*").alias("mappings")).select(F.lit(o).alias("ordering"), "mappings")
        out = one if out is None else out.unionAll(one)
    return out


@query("tile_rotations", _counts_sql("theta7", [(f"{k} AS turn", ring(6)) for k in range(3)], True))
def _(spark, sf_dir):
    g, out = graph(spark, sf_dir, "theta7"), None
    for k in range(3):
        one = execute.match(g, ring(6), ["edge", "path4"], rotate=k).agg(F.count("*").alias("mappings")).select(F.lit(k).alias("turn"), "mappings")
        out = one if out is None else out.unionAll(one)
    return out


# --- stitching ---------------------------------------------------------------------------------------------------------------
_P4 = f"p AS ({sqlgen.motif_sql(path(4))})"
_JOINED = "FROM p a JOIN p b ON a.c0 = b.c3 AND a.c3 = b.c0"


def _two(spark, sf_dir, on="theta7"):
    g = graph(spark, sf_dir, on)
    t = MotifCatalog.build(g, ["edge", "path4"]).table("path4")
    return execute.seed(t, RING6_TILES[0]), t


@query("stitch_join", f"WITH {ctes('trade')}, {_P4} SELECT a.c0 AS v2, a.c1 AS v3, a.c2 AS v4, a.c3 AS v5, b.c1 AS r0, b.c2 AS r1 {_JOINED}")
def _(spark, sf_dir):
    bound, t = _two(spark, sf_dir, "trade")
    right = t.select(*[F.col(f"c{j}").alias(f"r{v}") for j, v in enumerate(RING6_TILES[1].verts)])
    return bound.join(right, (F.col("v5") == F.col("r5")) & (F.col("v2") == F.col("r2"))).drop("r5", "r2")


_STITCHED = f"WITH {THETA_SQL}, {_P4} SELECT a.c0 AS v2, a.c1 AS v3, a.c2 AS v4, a.c3 AS v5, b.c1 AS v0, b.c2 AS v1 {_JOINED} WHERE b.c1 NOT IN (a.c0, a.c1, a.c2, a.c3) AND b.c2 NOT IN (a.c0, a.c1, a.c2, a.c3)"
for _name, _how in (("stitch_filter", "in"), ("stitch_filter_count", "count"), ("stitch_filter_array", "array")):
    query(_name, _STITCHED)(lambda spark, sf_dir, how=_how: execute.stitch(*_two(spark, sf_dir), RING6_TILES[1], distinct=how))
_match("stitch_match", "hh156", P12)
_match("match_ring6_example", "theta7", ring(6))
_match("match_edge_only", "hh156", P8, motifs=("edge",))
_match("match_induced", "hh156", P20)
_match("match_mono", "hh156", P20, induced=False)
_match("match_ring12_grid", "hh1990", ring(12), motifs=("edge", "path4"))
_match("motif_set_claw", "hh156", P12, motifs=("edge", "claw4"))
_match("motif_set_grid", "sq1600", ring(8), motifs=("edge", "ring4", "ring6"))
for _hint in ("merge", "shuffle_hash", "broadcast"):
    _match({"merge": "join_sort_merge", "shuffle_hash": "join_hash", "broadcast": "join_broadcast"}[_hint], "hh156", P8, induced=False, strategy=_hint)


@query("motif_advice", f"WITH {ctes('hh156')} " + " UNION ALL ".join(f"SELECT '{m}' AS motif, count(*) AS rows, CAST(count(*) / {len(LIBRARY[m].pattern.automorphisms())} AS BIGINT) AS frequency FROM ({sqlgen.motif_sql(LIBRARY[m].pattern)}) q" for m in _SET))
def _(spark, sf_dir):
    return advisor.frequency(MotifCatalog.build(graph(spark, sf_dir, "hh156"), _SET), _SET)


@query("motif_ranking", f"WITH {ctes('hh156')} " + " UNION ALL ".join(f"SELECT '{m}' AS motif, count(*) AS est_rows, CAST(count(*) // {len(LIBRARY[m].pattern.automorphisms())} AS BIGINT) AS frequency, {len(decompose(P12, ['edge', m]).tiles)} AS est_tiles, CASE WHEN count(*) = 0 THEN 0 ELSE round({len(LIBRARY[m].pattern.edges)} / (1 + CAST(count(*) AS DOUBLE) / 156), 6) END AS score FROM ({sqlgen.motif_sql(LIBRARY[m].pattern)}) q" for m in _SET))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "hh156")
    return advisor.advise(g, P12, _SET, catalog=MotifCatalog.build(g, _SET, persist=True))


@query("stitch_order", sqlgen.to_sql(P12, ctes("hh156"), False))
def _(spark, sf_dir):
    c = MotifCatalog.build(graph(spark, sf_dir, "hh156"), _SET, persist=True)
    return execute.run_plan(advisor.ordered(P12, _SET, c), c)


_RECIPES = {m: sqlgen.motif_sql(LIBRARY[m].pattern) for m in ("edge", "path4")}
_PORTABLE = decompose(P8, ["edge", "path4"])


@query("sql_portable", sqlgen.to_sql(P8, ctes("hh156"), False))
def _(spark, sf_dir):
    graph(spark, sf_dir, "hh156").edges.createOrReplaceTempView("edges_in")
    return spark.sql(sqlgen.plan_sql(_PORTABLE, _RECIPES, "edges AS (SELECT u, v FROM edges_in)"))


@query("nway_sql", sqlgen.to_sql(path(5), ctes("hh156"), True, "steps"))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "hh156")
    g.edges.createOrReplaceTempView("edges")
    return spark.sql(sqlgen.flat(path(5), True))


# --- layouts -------------------------------------------------------------------------------------------------------------------
_QUALITY = (
    f"{ctes('hh156')}, vq AS MATERIALIZED (SELECT l_partkey AS id, 1 - avg(l_tax) / 10 AS q FROM lineitem WHERE l_partkey IN (SELECT id FROM ids) GROUP BY 1), "
    "ek AS (SELECT u, v, row_number() OVER (ORDER BY u, v) - 1 AS k FROM edges WHERE u < v), lk AS (SELECT (l_partkey + l_suppkey) % (SELECT count(*) FROM ek) AS k, 1 - avg(l_discount) / 10 AS q FROM lineitem GROUP BY 1), "
    "e1 AS (SELECT u, v, q FROM ek JOIN lk USING (k)), eq AS MATERIALIZED (SELECT u, v, q FROM e1 UNION ALL SELECT v, u, q FROM e1)"
)


def _score_sql(p: Pattern, what: str) -> str:
    body, last = sqlgen.steps(p, True)
    edges = sorted(p.edges)
    joins = " ".join([f"JOIN eq a{k} ON a{k}.u = v{i} AND a{k}.v = v{j}" for k, (i, j) in enumerate(edges)] + [f"JOIN vq b{i} ON b{i}.id = v{i}" for i in range(p.n)])
    product = " * ".join([f"a{k}.q" for k in range(len(edges))] + [f"b{i}.q" for i in range(p.n)])
    return f"WITH {_QUALITY}, {body}, m AS (SELECT {sqlgen.select_list(p.n)}, {product} AS score FROM {last} {joins}) {what}"


_L = P8
_ROUNDED = f"SELECT {sqlgen.select_list(_L.n)}, round(score, 9) AS score FROM m"


def _scored(spark, sf_dir, **options):
    g = graph(spark, sf_dir, "hh156")
    return scoring.score_layouts(g, _L, *scoring.quality_tables(spark, sf_dir, g), **options)


def _rounded(df):
    return df.withColumn("score", F.round("score", 9))


_match("layout_generate", "hh156", P12)
query("layout_score", _score_sql(_L, _ROUNDED))(lambda spark, sf_dir: _rounded(_scored(spark, sf_dir)))
query("layout_select_pruned", _score_sql(_L, _ROUNDED + " WHERE score >= 0.9345"))(lambda spark, sf_dir: _rounded(_scored(spark, sf_dir, min_score=0.9345)))
query("layout_select", _score_sql(_L, _ROUNDED + f" ORDER BY round(score, 9) DESC, {sqlgen.select_list(_L.n)} LIMIT 5"))(lambda spark, sf_dir: scoring.select_layouts(_scored(spark, sf_dir), _L.n, 5))
query("topk_layouts", SQL["layout_select"].replace("LIMIT 5", "LIMIT 20"))(lambda spark, sf_dir: scoring.select_layouts(_scored(spark, sf_dir), _L.n, 20))
query("metric_score", _score_sql(_L, "SELECT count(*) AS layouts, round(max(score), 9) AS best, round(avg(score), 9) AS mean FROM m"))(lambda spark, sf_dir: metrics.scores(_scored(spark, sf_dir)))
query("agg_best_by", _score_sql(_L, f"SELECT {sqlgen.select_list(_L.n)}, round(score, 9) AS score FROM (SELECT *, row_number() OVER (PARTITION BY v0 ORDER BY round(score, 9) DESC, {sqlgen.select_list(_L.n)}) AS r FROM m) WHERE r = 1"))(
    lambda spark, sf_dir: _rounded(scoring.best_by_anchor(_scored(spark, sf_dir), _L.n))
)


@query("layout_score_post", SQL["layout_score"])
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "hh156")
    return _rounded(scoring.score_after(execute.match(g, _L), _L, *scoring.quality_tables(spark, sf_dir, g)))


query("agg_product", SQL["layout_score"])(QUERIES["layout_score_post"])


@query("vf2_post_layout", SQL["layout_score"])
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "hh156")
    vq, eq = scoring.quality_tables(spark, sf_dir, g)
    rows, _, _ = baselines.vf2_post_layout(g.local(), _L, {r["id"]: r["q"] for r in vq.collect()}, {(r["u"], r["v"]): r["q"] for r in eq.collect()})
    return _rounded(spark.createDataFrame(rows, ", ".join(f"v{i} long" for i in range(_L.n)) + ", score double"))


@query("layout_orient", f"WITH {ctes('hh156')}, {sqlgen.steps(path(4), True)[0]} SELECT {sqlgen.select_list(4)}, CAST(v0 > v1 AS INTEGER) + CAST(v1 > v2 AS INTEGER) + CAST(v2 > v3 AS INTEGER) AS flips FROM s3")
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "hh156")
    return scoring.orient(execute.match(g, path(4)), path(4), g.edges.where("u < v"))


# --- semantics, multiplicity, limits -------------------------------------------------------------------------------------------------
for _how in ("adjacency", "antijoin", "edgecount"):
    query(f"induced_{_how}", sqlgen.to_sql(P8, ctes("hh156"), True))(lambda spark, sf_dir, how=_how: execute.match(graph(spark, sf_dir, "hh156"), P8, induced=how))


@query("distinct_subgraphs", f"WITH {ctes('theta7')}, {sqlgen.steps(path(4), False)[0]}, k AS (SELECT *, list_sort([least(v0, v1) * 100 + greatest(v0, v1), least(v1, v2) * 100 + greatest(v1, v2), least(v2, v3) * 100 + greatest(v2, v3)]) AS k FROM s3) SELECT v0, v1, v2, v3 FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY v0, v1, v2, v3) AS r FROM k) WHERE r = 1")
def _(spark, sf_dir):
    return execute.match(graph(spark, sf_dir, "theta7"), path(4), semantics_="monomorphism", distinct_subgraphs=True)


@query("count_matches", sqlgen.to_sql(P12, ctes("hh156"), True, what="count(*) AS n"))
def _(spark, sf_dir):
    return execute.count_matches(graph(spark, sf_dir, "hh156"), P12)


@query("symmetry_broken", f"WITH {ctes('sq1600')}, m AS ({sqlgen.flat(ring(4), False, symmetry=True)}) SELECT {sqlgen.select_list(4)} FROM m")
def _(spark, sf_dir):
    return execute.match(graph(spark, sf_dir, "sq1600"), ring(4), semantics_="monomorphism", symmetry=True)


@query("automorphisms", f"WITH {LINES_SQL} SELECT 'star' || CAST(n AS VARCHAR) AS motif, CAST(CASE WHEN n = 1 THEN 2 ELSE factorial(CAST(n AS INTEGER)) END AS BIGINT) AS n, orders FROM lines")
def _(spark, sf_dir):
    """Of each order tied to its lines; orders of as many lines are one pattern."""
    return spark.createDataFrame([(f"star{n}", len(star(n).automorphisms()), k) for n, k in _lines(spark, sf_dir)], "motif string, n long, orders long")


query("first_k_matches")(lambda spark, sf_dir: execute.match(graph(spark, sf_dir, "hh156"), P8, limit=25, seed_batches=4))


@query("exists_match", "SELECT TRUE AS ring12_there, FALSE AS ring4_there")
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "hh156")
    return spark.createDataFrame([(execute.exists(g, ring(12)), execute.exists(g, ring(4), ["edge"]))], "ring12_there boolean, ring4_there boolean")


_match("degree_prefilter", "hh156", P12, degree_filter=True)
_match("seed_batches", "hh156", P8, seed_batches=3)


@query("vertex_predicate", f"WITH {ctes('hh156')}, {sqlgen.steps(path(4), True)[0]} SELECT {sqlgen.select_list(4)} FROM s3 WHERE v1 IN (SELECT p_partkey FROM part WHERE p_size > 20)")
def _(spark, sf_dir):
    keep = io.table(spark, sf_dir, "part").where("p_size > 20").select("p_partkey")
    return execute.match(graph(spark, sf_dir, "hh156"), path(4), where={1: keep})


# --- baselines ---------------------------------------------------------------------------------------------------------------------
for _name, _f in (("vf2_driver", baselines.vf2_driver), ("vf2_distributed", baselines.vf2_distributed), ("map_in_arrow_vf2", baselines.vf2_distributed), ("frontier_match", baselines.frontier_match)):
    query(_name, sqlgen.to_sql(P8, ctes("hh156"), True))(lambda spark, sf_dir, f=_f: f(graph(spark, sf_dir, "hh156"), P8))
query("brute_force", sqlgen.to_sql(star(3), ctes("trade"), True))(lambda spark, sf_dir: baselines.brute_force(graph(spark, sf_dir, "trade"), star(3)))


# --- measures ------------------------------------------------------------------------------------------------------------------------
def _run_once(spark, sf_dir, **options):
    g = graph(spark, sf_dir, "hh156")
    data = g.local()
    return metrics.report(spark, [metrics.run(g, P8, ("edge", "path4"), "hh156", 3, baseline=lambda: baselines.vf2(data, P8), **options)])


for _name, _cols in (("metric_total", ["total_s"]), ("metric_prep", ["prep_s"]), ("metric_compute", ["compute_s"]), ("metric_warm", ["warm_s"]), ("metric_tiling_share", ["tiling_share"])):
    query(_name)(lambda spark, sf_dir, cols=_cols: _run_once(spark, sf_dir).select("graph", "n", "seed", "motifs", *cols))
query("metric_completion", "SELECT 'hh156' AS graph, 'over budget' AS status")(lambda spark, sf_dir: _run_once(spark, sf_dir, max_rows=10).select("graph", "status"))


@query("metric_speedup", "SELECT graph, n, round(min(b / t), 4) AS min, round(avg(b / t), 4) AS mean, round(max(b / t), 4) AS max FROM (SELECT l_returnflag AS graph, l_linenumber AS n, l_quantity AS t, l_extendedprice AS b FROM lineitem WHERE l_quantity <> 0) r GROUP BY graph, n")
def _(spark, sf_dir):
    """Lines stand for runs: their quantity for our time, their price for that of the baseline."""
    runs = io.table(spark, sf_dir, "lineitem").where("l_quantity <> 0").select(F.col("l_returnflag").alias("graph"), F.col("l_linenumber").alias("n"), F.col("l_quantity").alias("total_s"), F.col("l_extendedprice").alias("baseline_s"))
    return metrics.speedups(runs).select("graph", "n", *[F.round(c, 4).alias(c) for c in ("min", "mean", "max")])


#: Edges, and tiles of {edge} and of {edge, path4}, of chains of so many lines, as recorded once: a change of the tiling shows.
_TILES = [(1, 0, 0, 0), (2, 1, 1, 1), (3, 2, 2, 2), (4, 3, 3, 1), (5, 4, 4, 2), (6, 5, 5, 3), (7, 6, 6, 2)]


def _tiles_of_lines(spark: SparkSession, sf_dir: str, motifs: list[str]) -> DataFrame:
    """The lines of each order as a chain; orders of as many lines are one pattern, named by how many."""
    lines = _lines(spark, sf_dir)
    tiles = metrics.tiles(spark, [path(n) for n, _ in lines], motifs)
    known = spark.createDataFrame([(i, n, k) for i, (n, k) in enumerate(lines)], "pattern int, n int, orders long")
    return tiles.join(known, "pattern").select(F.col("n").alias("pattern"), "edges", "tiles", "orders")


query("metric_iterations", f"WITH {LINES_SQL} SELECT pattern, edges, tiles, orders FROM lines JOIN ({_golden([(p, e, t) for p, e, t, _ in _TILES], 'pattern, edges, tiles')}) g ON pattern = n")(lambda spark, sf_dir: _tiles_of_lines(spark, sf_dir, ["edge"]))
query("metric_iterations_path4", f"WITH {LINES_SQL} SELECT pattern, edges, tiles, orders FROM lines JOIN ({_golden([(p, e, t) for p, e, _, t in _TILES], 'pattern, edges, tiles')}) g ON pattern = n")(lambda spark, sf_dir: _tiles_of_lines(spark, sf_dir, ["edge", "path4"]))


@query("metric_solutions", sqlgen.to_sql(ring(12), ctes("hh156"), True, what="count(*) AS mappings, CAST(count(*) / 24 AS BIGINT) AS subgraphs"))
def _(spark, sf_dir):
    return metrics.solutions(flagship(spark, sf_dir), ring(12), True)


@query("metric_intermediate", f"WITH {THETA_SQL}, {_P4} SELECT 0 AS step, 'path4' AS motif, 0 AS seam_cols, count(*) AS rows_joined, count(*) AS rows_kept FROM p UNION ALL SELECT 1, 'path4', 2, count(*), count(CASE WHEN b.c1 NOT IN (a.c0, a.c1, a.c2, a.c3) AND b.c2 NOT IN (a.c0, a.c1, a.c2, a.c3) THEN 1 END) {_JOINED}")
def _(spark, sf_dir):
    return metrics.trace(graph(spark, sf_dir, "theta7"), ring(6), ["edge", "path4"])


@query("metric_agreement", "SELECT CAST(0 AS BIGINT) AS only_a, CAST(0 AS BIGINT) AS only_b")
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "hh156")
    return metrics.diff(execute.match(g, P12), baselines.vf2_driver(g, P12))


# --- sources and sinks -------------------------------------------------------------------------------------------------------------------
query("scan_parquet", "SELECT p_partkey, p_name, p_size FROM part WHERE p_size > 10")(lambda spark, sf_dir: io.table(spark, sf_dir, "part").where("p_size > 10").select("p_partkey", "p_name", "p_size"))


def _reread(fmt):
    def run(spark, sf_dir):
        at = shared_path(spark, "edges")
        e = graph(spark, sf_dir, "hh156").edges
        if fmt == "text":
            e.select(F.concat_ws(" ", "u", "v").alias("value")).unionAll(spark.createDataFrame([("no edge",)], "value string")).write.text(at)
        else:
            (e.write.option("header", True) if fmt == "csv" else e.write).format(fmt).save(at)
        return io.read_edges(spark, at, fmt)[0]

    return run


for _fmt in ("csv", "json", "orc", "text"):
    query(f"scan_edge_{_fmt}", f"WITH {ctes('hh156')} SELECT u, v FROM edges")(_reread(_fmt))


def _folded(spark: SparkSession, sf_dir: str, shape: lattice.Shape) -> DataFrame:
    """Edges of the lattice on the remainders of all keys of `orders`."""
    ids = io.table(spark, sf_dir, "orders").select((F.col("o_orderkey") % shape.vertices).alias("id"))
    return lattice.on_table(ids, "id", shape).edges


def _folded_sql(shape: lattice.Shape) -> str:
    half = f"SELECT u, v FROM ({shape.sql('ids')}) h WHERE v IN (SELECT id FROM ids)"
    return f"WITH ids AS (SELECT DISTINCT o_orderkey % {shape.vertices} AS id FROM orders), half AS ({half}) SELECT u, v FROM half UNION SELECT v, u FROM half"


query("scan_lattice_grid", _folded_sql(lattice.Grid(20)))(lambda spark, sf_dir: _folded(spark, sf_dir, lattice.Grid(20)))
query("scan_lattice_heavyhex", _folded_sql(lattice.HeavyHex(8, 16)))(lambda spark, sf_dir: _folded(spark, sf_dir, lattice.HeavyHex(8, 16)))
query("lattice_on_keys", f"WITH {ctes('hh4485')} SELECT u, v FROM edges")(lambda spark, sf_dir: graph(spark, sf_dir, "hh4485").edges)
for _name in derive.GRAPHS:
    query(f"graph_{_name}", f"WITH {derive.SQL[_name]} SELECT u, v FROM edges")(lambda spark, sf_dir, n=_name: graph(spark, sf_dir, n).edges)


@query("sink_catalog", f"WITH {ctes('hh156')} {sqlgen.motif_sql(path(4))}")
def _(spark, sf_dir):
    at, g = shared_path(spark, "catalog"), graph(spark, sf_dir, "hh156")
    MotifCatalog.build(g, ["edge", "path4"]).save(at)
    return MotifCatalog.load(spark, at, g.fingerprint()).table("path4")


query("scan_catalog", SQL["sink_catalog"])(QUERIES["sink_catalog"])


@query("sink_matches", sqlgen.to_sql(P8, ctes("hh156"), True))
def _(spark, sf_dir):
    at = shared_path(spark, "matches")
    io.write_matches(execute.match(graph(spark, sf_dir, "hh156"), P8), at)
    return spark.read.parquet(at).drop("batch")


@query("sink_noop", "SELECT 'done' AS status")
def _(spark, sf_dir):
    io.noop(graph(spark, sf_dir, "hh156").edges)
    return spark.createDataFrame([("done",)], "status string")


# --- relational operators over graphs and tables -----------------------------------------------------------------------------------------------
text("proj_rename", "SELECT u AS v3, v AS v7 FROM edges", "hh156")
text("proj_computed", "SELECT id, id % 40 AS col, (id - id % 40) / 40 AS row_at FROM ids", "sq1600", duck_body="SELECT id, id % 40 AS col, (id - id % 40) / 40 AS row_at FROM ids")
text("proj_case", "SELECT id, CASE WHEN id % 2 = 0 THEN 3 ELSE 1 END AS shift FROM ids", "hh156")
text("filter_loop", "SELECT l_partkey AS u, l_suppkey AS v FROM lineitem WHERE l_partkey <> l_suppkey")
text("filter_distinct", "SELECT a.u AS v0, a.v AS v1, b.v AS v2 FROM edges a JOIN edges b ON a.v = b.u WHERE b.v NOT IN (a.u, a.v)", "hh156")
text("filter_degree", "SELECT u AS id FROM edges GROUP BY u HAVING count(*) >= 3", "hh1990")
text("filter_range", "SELECT p_partkey, p_size FROM part WHERE p_size BETWEEN 5 AND 15")
text("filter_in", "SELECT p_partkey, p_brand FROM part WHERE p_brand IN ('Brand#11', 'Brand#12', 'Brand#13')")
text("filter_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%'")
text("filter_null", "SELECT doc_id, lang FROM documents WHERE (nullif(lang, 'en') IS NOT DISTINCT FROM NULL)", spark_body="SELECT doc_id, lang FROM documents WHERE nullif(lang, 'en') <=> NULL")
text("join_multi_key", "SELECT a.u, a.v, l_orderkey FROM edges a JOIN lineitem ON l_partkey = a.u AND l_suppkey = a.v", "hh156")
text("join_self", "SELECT a.u AS c0, a.v AS c1, b.v AS c2 FROM edges a JOIN edges b ON a.v = b.u WHERE a.u <> b.v", "hh1990")
text("join_theta", "SELECT a.u AS c0, a.v AS c1, b.v AS c2 FROM edges a JOIN edges b ON a.v = b.u AND a.u < b.v", "hh1990")
text("join_nested_loop", "SELECT a.id AS a, b.id AS b FROM ids a JOIN ids b ON a.id < b.id", "hh156")
text("join_semi", "SELECT id FROM ids WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = id AND l_quantity > 45)", "hh156")
text("join_anti", "SELECT a.u AS c0, a.v AS c1, b.v AS c2 FROM edges a JOIN edges b ON a.v = b.u AND a.u <> b.v WHERE NOT EXISTS (SELECT 1 FROM edges x WHERE x.u = a.u AND x.v = b.v)", "copurchase")
text("join_left", "SELECT id, p_brand FROM ids LEFT JOIN part ON p_partkey = id + 1950", "hh156")
text("join_full", "SELECT coalesce(a.id, b.k) AS id, a.id IS NULL AS only_b, b.k IS NULL AS only_a FROM (SELECT id FROM ids WHERE id % 2 = 0) a FULL JOIN (SELECT id AS k FROM ids WHERE id % 3 = 0) b ON a.id = b.k", "hh156")
_RANGE = "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_id <> a.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL {} "
text("join_range", _RANGE.format("'600' SECOND"), spark_body=_RANGE.format("600 SECONDS").replace("a.user_id = b.user_id", "a.user_id = b.user_id"))


@query("join_asof", "SELECT a.event_id, a.user_id, (SELECT arg_max(b.value, b.ts) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'purchase' AND b.ts <= a.ts) AS q FROM events a WHERE a.event_type = 'click'")
def _(spark, sf_dir):
    e = io.table(spark, sf_dir, "events")
    rows, readings = e.where("event_type = 'click'").select("event_id", "user_id", "ts"), e.where("event_type = 'purchase'").select("user_id", "ts", F.col("value").alias("q"))
    return streaming.latest_before(rows, readings, "user_id").select("event_id", "user_id", "q")


query("agg_degree", f"WITH {ctes('copurchase')} SELECT u, count(*) AS degree FROM edges GROUP BY u")(lambda spark, sf_dir: graph(spark, sf_dir, "copurchase").degrees)
query("agg_degree_hist", f"WITH {ctes('sq1600')} SELECT degree, count(*) AS n FROM (SELECT count(*) AS degree FROM edges GROUP BY u) q GROUP BY degree")(lambda spark, sf_dir: graph(spark, sf_dir, "sq1600").degrees.groupBy("degree").agg(F.count("*").alias("n")))
text("agg_seed_stats", "SELECT o_orderpriority, min(o_totalprice) AS lo, max(o_totalprice) AS hi, round(avg(o_totalprice), 4) AS mean FROM orders GROUP BY o_orderpriority")
text("agg_participation", "SELECT x AS id, count(*) AS n FROM (SELECT u AS x FROM edges UNION ALL SELECT v FROM edges) q GROUP BY x", "copurchase")
text("agg_count_distinct", "SELECT count(DISTINCT u) AS touched, count(DISTINCT v) AS reached FROM edges", "copurchase")
query("agg_approx_distinct")(lambda spark, sf_dir: graph(spark, sf_dir, "copurchase").edges.agg(F.approx_count_distinct("u").alias("touched")))
_REPORT = "CASE WHEN user_id % 2 = 0 THEN 'even' ELSE 'odd' END"
text("agg_grouping_sets", "SELECT event_type, user_id % 3 AS part, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type, user_id % 3), (event_type), ())")
text("agg_rollup", "SELECT event_type, user_id % 3 AS part, count(*) AS n, grouping(event_type) AS g FROM events GROUP BY ROLLUP (event_type, user_id % 3)")
text("agg_cube", "SELECT event_type, user_id % 3 AS part, count(*) AS n FROM events GROUP BY CUBE (event_type, user_id % 3)")


@query("agg_pivot", "SELECT event_type, count(CASE WHEN user_id % 3 = 0 THEN 1 END) AS n0, count(CASE WHEN user_id % 3 = 1 THEN 1 END) AS n1, count(CASE WHEN user_id % 3 = 2 THEN 1 END) AS n2 FROM events GROUP BY event_type")
def _(spark, sf_dir):
    e = io.table(spark, sf_dir, "events").withColumn("k", F.concat(F.lit("n"), F.col("user_id") % 3))
    return e.groupBy("event_type").pivot("k", ["n0", "n1", "n2"]).agg(F.count(F.lit(1))).na.fill(0)


query("agg_adjacency", f"WITH {ctes('hh156')} SELECT u, string_agg(CAST(v AS VARCHAR), ' ' ORDER BY v) AS nbrs FROM edges GROUP BY u")(lambda spark, sf_dir: graph(spark, sf_dir, "hh156").adjacency.select("u", F.array_join("nbrs", " ").alias("nbrs")))
text("agg_percentile", "SELECT event_type, round(percentile(value, 0.5), 6) AS median FROM events GROUP BY event_type", duck_body="SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median FROM events GROUP BY event_type")
query("agg_percentile_approx")(lambda spark, sf_dir: io.table(spark, sf_dir, "events").groupBy("event_type").agg(F.percentile_approx("value", 0.5).alias("median")))
text("agg_filter", "SELECT user_id, count(*) FILTER (WHERE value > 50) AS high FROM events GROUP BY user_id")
text("agg_having", "SELECT u FROM edges GROUP BY u HAVING count(*) = 3", "hh156")
text("agg_bool", "SELECT event_type, bool_and(value >= 0) AS all_up, bool_or(value > 99) AS any_top FROM events GROUP BY event_type")


@query("agg_sort_fallback", "SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS types, count(*) AS n FROM events GROUP BY user_id")
def _(spark, sf_dir):
    """An aggregation over hash maps that may hold four groups only, so that all others go by way of sorting and spilling."""
    own = spark.newSession()
    own.conf.set("spark.sql.objectHashAggregate.sortBased.fallbackThreshold", "4")
    return io.table(own, sf_dir, "events").groupBy("user_id").agg(F.array_join(F.sort_array(F.collect_set("event_type")), ",").alias("types"), F.count("*").alias("n"))


_W = "OVER (PARTITION BY user_id ORDER BY ts, event_id)"
text("win_rank", f"SELECT event_id, row_number() {_W} AS rn, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS rk, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS dr FROM events")
text("win_distribution", f"SELECT event_id, ntile(4) {_W} AS band, round(percent_rank() {_W}, 9) AS pr, round(cume_dist() {_W}, 9) AS cd FROM events")
text("win_lag_lead", f"SELECT event_id, lag(event_id) {_W} AS before, lead(event_id) {_W} AS after FROM events")
text("win_running", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS so_far FROM events")
text("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM (SELECT event_id, user_id, unix_timestamp(ts) AS s FROM events) q", duck_body="SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM (SELECT event_id, user_id, CAST(floor(epoch(ts)) AS BIGINT) AS s FROM events) q")
text("win_first_last", "SELECT event_id, first_value(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS first_type FROM events")
text("win_topk_neighbors", "SELECT u, v FROM (SELECT u, v, row_number() OVER (PARTITION BY u ORDER BY v DESC) AS r FROM edges) q WHERE r <= 2", "copurchase")
text("sort_global", "SELECT u, v FROM edges ORDER BY u, v", "hh156")
text("sort_nulls", "SELECT id, p_brand FROM ids LEFT JOIN part ON p_partkey = id + 1950 ORDER BY p_brand NULLS LAST, id", "hh156")
query("sort_within_partitions", f"WITH {ctes('hh156')} SELECT u, v FROM edges")(lambda spark, sf_dir: graph(spark, sf_dir, "hh156").edges.repartition("u").sortWithinPartitions("u", "v"))
query("limit_matches")(lambda spark, sf_dir: graph(spark, sf_dir, "hh156").edges.limit(10))
text("limit_offset", "SELECT u, v FROM edges ORDER BY u, v LIMIT 10 OFFSET 20", "hh156")
text("sample_by_hash", "SELECT id FROM ids WHERE (id * 2654435761) % 97 < 20", "hh1990")
query("sample_random")(lambda spark, sf_dir: graph(spark, sf_dir, "hh1990").vertices.sample(0.1, 7))
_A, _B = "SELECT u % 7 AS x FROM edges WHERE u < 60", "SELECT v % 5 AS x FROM edges WHERE v < 40"
for _name, _op in (("set_union_all", "UNION ALL"), ("set_union", "UNION"), ("set_intersect", "INTERSECT"), ("set_intersect_all", "INTERSECT ALL"), ("set_except", "EXCEPT"), ("set_except_all", "EXCEPT ALL")):
    text(_name, f"{_A} {_op} {_B}", "hh156")
query("set_union_by_name", f"WITH {ctes('hh156')} SELECT u, v FROM edges UNION ALL SELECT v AS u, u AS v FROM edges")(lambda spark, sf_dir: (e := graph(spark, sf_dir, "hh156").edges).unionByName(e.select(F.col("u").alias("v"), F.col("v").alias("u"))))

# --- functions -----------------------------------------------------------------------------------------------------------------------------
text("fn_math", "SELECT id, id % 7 AS m, CAST(floor(sqrt(id)) AS BIGINT) AS r, round(ln(id + 1), 9) AS l, greatest(id, 50) AS g, least(id, 50) AS s, CAST(bit_count(id) AS INTEGER) AS b, least(id, 9) * 1000 + greatest(id, 9) AS code FROM ids", "hh156")
text("fn_string", "SELECT page_id, lower(url) AS low, regexp_extract(url, '//([^/]+)/', 1) AS host, substring(url, 1, 10) AS head, instr(url, 'example') AS at, lpad(CAST(page_id AS STRING), 6, '0') AS pad FROM pages", duck_body="SELECT page_id, lower(url) AS low, regexp_extract(url, '//([^/]+)/', 1) AS host, substring(url, 1, 10) AS head, instr(url, 'example') AS at, lpad(CAST(page_id AS VARCHAR), 6, '0') AS pad FROM pages")
text("fn_date", "SELECT event_id, year(ts) AS y, month(ts) AS m, date_trunc('hour', ts) AS h FROM events", duck_body="SELECT event_id, year(ts) AS y, month(ts) AS m, date_trunc('hour', ts) AS h FROM events")


@query("fn_array", f"WITH {ctes('hh156')}, a AS (SELECT u, list_sort(list(v)) AS n FROM edges GROUP BY u) SELECT u, len(n) AS size, n[1] AS first, list_contains(n, u + 1) AS next_there, list_sum(n) AS total FROM a".replace("list_sum(n)", "CAST(list_sum(n) AS BIGINT)"))
def _(spark, sf_dir):
    a = graph(spark, sf_dir, "hh156").adjacency
    return a.select("u", F.size("nbrs").alias("size"), F.get("nbrs", F.lit(0)).alias("first"), F.array_contains("nbrs", F.col("u") + 1).alias("next_there"), F.aggregate("nbrs", F.lit(0).cast("long"), lambda s, x: s + x).alias("total"))


@query("fn_map", f"WITH {ctes('hh156')}, {sqlgen.steps(path(3), True)[0]} SELECT v0 + 1000 * v2 AS code, 3 AS keys FROM s2")
def _(spark, sf_dir):
    m = semantics.as_map(execute.match(graph(spark, sf_dir, "hh156"), path(3)), 3)
    return m.select((F.element_at("mapping", 0) + 1000 * F.element_at("mapping", 2)).alias("code"), F.size(F.map_keys("mapping")).alias("keys"))


@query("fn_struct", f"WITH {ctes('hh156')}, {sqlgen.steps(path(3), True)[0]} SELECT v1 AS middle FROM s2")
def _(spark, sf_dir):
    return semantics.as_struct(execute.match(graph(spark, sf_dir, "hh156"), path(3)), 3).select(F.col("mapping.v1").alias("middle"))


text(
    "fn_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS INT) AS k, from_json(props, 'k INT').k + 1 AS next, to_json(named_struct('id', event_id, 'type', event_type)) AS made FROM events",
    duck_body="SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, CAST(json_extract_string(props, '$.k') AS INTEGER) + 1 AS next, CAST(json_object('id', event_id, 'type', event_type) AS VARCHAR) AS made FROM events",
)
query("fn_hash")(lambda spark, sf_dir: spark.createDataFrame([(graph(spark, sf_dir, "hh156").fingerprint(),)], "fingerprint string"))
text("fn_null", "SELECT id, coalesce(p_brand, '-') AS brand, nullif(id % 2, 0) AS odd, p_brand IS NULL AS lone FROM ids LEFT JOIN part ON p_partkey = id + 1950", "hh156")


@query("udf_distinct_rows", f"WITH {ctes('theta7')} SELECT count(*) AS n FROM edges a JOIN edges b ON a.v = b.u WHERE a.u <> b.v")
def _(spark, sf_dir):
    e = graph(spark, sf_dir, "theta7").edges
    two = e.select("u", F.col("v").alias("m")).join(e.select(F.col("u").alias("m"), "v"), "m")
    return two.where(fn.all_distinct(F.array("u", "m", "v"))).agg(F.count("*").alias("n"))


@query("udaf_fidelity", "SELECT l_partkey, round(product(1 - l_tax / 10), 9) AS q FROM lineitem GROUP BY l_partkey")
def _(spark, sf_dir):
    return io.table(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(F.round(fn.fidelity(1 - F.col("l_tax") / 10), 9).alias("q"))


@query("udtf_backtrack", f"WITH {ctes('theta7')}, {sqlgen.steps(path(4), False)[0]} SELECT concat_ws('-', v0, v1, v2, v3) AS mapping FROM s3")
def _(spark, sf_dir):
    fn.register(spark, THETA)
    return spark.sql("SELECT concat_ws('-', transform(mapping, x -> CAST(x AS STRING))) AS mapping FROM backtrack('0-1,1-2,2-3')")


@query("apply_component", sqlgen.to_sql(path(3), ctes("turns"), False))
def _(spark, sf_dir):
    g = graph(spark, sf_dir, "turns")
    return fn.per_component(g.edges, g.components(), path(3))


@query("graph_components", "SELECT count(*) AS n FROM (SELECT DISTINCT a.conv_id FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1) q")
def _(spark, sf_dir):
    return graph(spark, sf_dir, "turns").components().agg(F.countDistinct("component").alias("n"))


@query("graph_encode_ids", "WITH k AS (SELECT DISTINCT source AS key FROM documents UNION SELECT DISTINCT lang FROM documents), b AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS id FROM k) SELECT key, id FROM b WHERE key IS NOT NULL")
def _(spark, sf_dir):
    return DataGraph.encode_ids(io.table(spark, sf_dir, "documents"), "source", "lang")[1]


@query("sql_canonical_edge", f"WITH {ctes('hh156')} SELECT DISTINCT least(u, v) * 2147483648 + greatest(u, v) AS code FROM edges")
def _(spark, sf_dir):
    fn.register(spark)
    graph(spark, sf_dir, "hh156").edges.createOrReplaceTempView("edges")
    return spark.sql("SELECT DISTINCT canonical_edge(u, v) AS code FROM edges")


@query("sql_canonical_set", f"WITH {ctes('sq1600')}, m AS ({sqlgen.flat(ring(4), False)}) SELECT DISTINCT array_to_string(list_sort([v0, v1, v2, v3]), '-') AS s FROM m")
def _(spark, sf_dir):
    fn.register(spark)
    execute.match(graph(spark, sf_dir, "sq1600"), ring(4), semantics_="monomorphism").createOrReplaceTempView("m")
    return spark.sql("SELECT DISTINCT concat_ws('-', transform(canonical_set(array(v0, v1, v2, v3)), x -> CAST(x AS STRING))) AS s FROM m")


# --- streams --------------------------------------------------------------------------------------------------------------------------------
query("stream_source_events", "SELECT event_id, user_id, event_type FROM events")(lambda spark, sf_dir: streaming.drain(streaming.events(spark, sf_dir).select("event_id", "user_id", "event_type")))


@query("stream_edges", f"WITH {derive.SQL['coactive']} SELECT u, v FROM half WHERE u <> v GROUP BY u, v")
def _(spark, sf_dir):
    at = shared_path(spark, "stream-edges")
    streaming.edges(streaming.events(spark, sf_dir), 60, lambda df, i: df.write.mode("overwrite").parquet(f"{at}/batch={i}"), shared_path(spark, "log")).awaitTermination()
    return spark.read.parquet(at).select("u", "v").distinct()


@query("stream_incremental_match", f"WITH {ctes('hh156')}, {sqlgen.steps(path(4), False)[0]} SELECT {sqlgen.select_list(4)} FROM s3")
def _(spark, sf_dir):
    at = shared_path(spark, "edge-files")
    e = graph(spark, sf_dir, "hh156").edges
    for i in range(2):  # two files, so two batches
        e.where(F.pmod(F.col("u") + F.col("v"), F.lit(2)) == i).coalesce(1).write.mode("append").parquet(at)
    stream = spark.readStream.schema("u long, v long").option("maxFilesPerTrigger", 1).parquet(at)
    return streaming.incremental_match(stream, path(4), shared_path(spark, "match-state"))


_HOUR = "SELECT time_bucket(INTERVAL '1 hour', ts) AS start, time_bucket(INTERVAL '1 hour', ts) + INTERVAL '1 hour' AS \"end\", count(*) AS n FROM events GROUP BY 1, 2 HAVING time_bucket(INTERVAL '1 hour', ts) + INTERVAL '1 hour' <= (SELECT max(ts) - INTERVAL '1 hour' FROM events)"
query("stream_tumbling", _HOUR)(lambda spark, sf_dir: streaming.drain(streaming.windowed(streaming.events(spark, sf_dir), "tumbling")))
_SLIDES = "SELECT s AS start, s + INTERVAL '1 hour' AS \"end\", count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL '30 minutes', ts), time_bucket(INTERVAL '30 minutes', ts) - INTERVAL '30 minutes']) AS s FROM events) w GROUP BY s HAVING s + INTERVAL '1 hour' <= (SELECT max(ts) - INTERVAL '1 hour' FROM events)"
_SESSIONS = (
    "SELECT min(ts) AS start, max(ts) + INTERVAL '2 minutes' AS \"end\", user_id, count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM "
    "(SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL '2 minutes' THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s HAVING max(ts) + INTERVAL '2 minutes' <= (SELECT max(ts) - INTERVAL '1 hour' FROM events)"
)
query("stream_sliding", _SLIDES)(lambda spark, sf_dir: streaming.drain(streaming.windowed(streaming.events(spark, sf_dir), "sliding")))
query("stream_session", _SESSIONS)(lambda spark, sf_dir: streaming.drain(streaming.windowed(streaming.events(spark, sf_dir), "session", "2 minutes")))
query("stream_dedup", "SELECT DISTINCT event_id, user_id FROM events")(lambda spark, sf_dir: streaming.drain(streaming.dedup(streaming.events(spark, sf_dir), ["event_id"], "400 days").select("event_id", "user_id")))
query("stream_stream_join", _RANGE.format("'600' SECOND").replace("SELECT a.event_id", "SELECT a.user_id, a.event_id"))(lambda spark, sf_dir: streaming.drain(streaming.interval_join(streaming.events(spark, sf_dir), streaming.events(spark, sf_dir), 600)))
query("join_interval_stream", SQL["stream_stream_join"])(QUERIES["stream_stream_join"])


@query("stream_static_join", f"WITH {ctes('hh156')} SELECT event_id, user_id, v AS c1 FROM events JOIN edges ON u = user_id")
def _(spark, sf_dir):
    static = MotifCatalog.build(graph(spark, sf_dir, "hh156"), ["edge"]).table("edge")
    return streaming.drain(streaming.enrich(streaming.events(spark, sf_dir).select("event_id", "user_id"), static, "user_id", "c0").select("event_id", "user_id", "c1"))


query("stream_stateful_degree", "SELECT user_id, count(*) AS degree FROM events GROUP BY user_id")(lambda spark, sf_dir: streaming.drain(streaming.degrees(streaming.events(spark, sf_dir)), "update"))


@query("stream_late_data", "SELECT CAST(1 AS BIGINT) AS dropped")
def _(spark, sf_dir):
    at, log, out = (shared_path(spark, n) for n in ("late-files", "late-log", "late-out"))
    e = io.table(spark, sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"), "user_id")
    last = e.agg(F.max("ts").alias("ts"), F.lit(1).cast("long").alias("user_id"))
    for df in (last, last.select((F.col("ts") - F.expr("INTERVAL 5 DAYS")).alias("ts"), "user_id")):
        df.coalesce(1).write.mode("append").parquet(at)
        stream = spark.readStream.schema(e.schema).parquet(at)
        q = streaming.windowed(stream, "tumbling").writeStream.format("parquet").option("path", out).option("checkpointLocation", log).trigger(availableNow=True).start()
        q.awaitTermination()
    return spark.createDataFrame([(streaming.late_report(q),)], "dropped long")


def _workloads() -> None:
    from graphstitch import workloads

    for name, f in workloads.WORKLOADS.items():
        query(name)(f)


_workloads()
