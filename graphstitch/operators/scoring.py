"""Layout quality: the product of the qualities of all used vertices and edges, carried along the stitches."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphstitch.operators.catalog import MotifCatalog
from graphstitch.operators.execute import run_plan
from graphstitch.operators.semantics import names
from graphstitch.plans.decompose import Tile, decompose
from graphstitch.plans.pattern import Pattern
from graphstitch.sources.graph import DataGraph


def tile_factor(tile: Tile, motif: Pattern, gates: dict[tuple[int, int], int] | None = None) -> Column:
    """A tile's factor from the quality columns of its motif table: every edge of the tile, and only the vertices that this
    tile binds first, so nothing is charged twice. gates: how often a pattern's edge is used."""
    factor = F.lit(1.0)
    for k, (a, b) in enumerate(sorted(motif.edges)):
        i, j = sorted((tile.verts[a], tile.verts[b]))
        times = (gates or {}).get((i, j), 1)
        factor = factor * (F.col(f"e{k}") if times == 1 else F.pow(F.col(f"e{k}"), F.lit(times)))
    for j, v in enumerate(tile.verts):
        if v in tile.fresh:
            factor = factor * F.col(f"p{j}")
    return factor


def score_layouts(g: DataGraph, pattern: Pattern, vertex_q: DataFrame, edge_q: DataFrame, motifs: Sequence = ("edge", "path4"), catalog: MotifCatalog | None = None, gates=None, min_score: float | None = None, induced: str | None = "adjacency") -> DataFrame:
    """All layouts with their score, multiplied at every stitch from qualities that the motif tables hold. Factors are at most
    1, so rows below `min_score` go at the stitch where they fall below it."""
    catalog = catalog or MotifCatalog.build(g, motifs)
    plan = decompose(pattern, motifs)
    keep = (lambda df: df.where(F.col("score") >= min_score)) if min_score is not None else None
    if not plan.tiles:
        out = g.vertices.join(vertex_q, "id").select(F.col("id").alias("v0"), F.col("q").alias("score"))
        return keep(out) if keep else out
    return run_plan(plan, catalog, induced, factor=lambda t: tile_factor(t, catalog.motifs[t.motif].pattern, gates), quality=(vertex_q, edge_q), keep=keep)


def score_after(layouts: DataFrame, pattern: Pattern, vertex_q: DataFrame, edge_q: DataFrame) -> DataFrame:
    """The same score, looked up after the enumeration: the way that the running score avoids."""
    cols = names(range(pattern.n))
    rows = layouts.select(*cols)
    pairs = F.array(*[F.struct(F.col(f"v{i}").alias("u"), F.col(f"v{j}").alias("v")) for i, j in sorted(pattern.edges)])
    by_edge = rows.select(*cols, F.explode(pairs).alias("e")).select(*cols, F.col("e.u").alias("u"), F.col("e.v").alias("v")).join(edge_q, ["u", "v"]).select(*cols, "q")
    by_vertex = rows.select(*cols, F.explode(F.array(*cols)).alias("id")).join(vertex_q, "id").select(*cols, "q")
    return by_edge.unionAll(by_vertex).groupBy(*cols).agg(F.product("q").alias("score"))


def select_layouts(scored: DataFrame, n: int, k: int = 1) -> DataFrame:
    """The best k; ties go to the least mapping."""
    return scored.withColumn("score", F.round("score", 9)).orderBy(F.desc("score"), *names(range(n))).limit(k)


def best_by_anchor(scored: DataFrame, n: int) -> DataFrame:
    """The best layout for each place of vertex 0, by rank."""
    w = Window.partitionBy("v0").orderBy(F.desc(F.round("score", 9)), *names(range(n)))
    return scored.withColumn("rank", F.row_number().over(w)).where("rank = 1").drop("rank")


def orient(layouts: DataFrame, pattern: Pattern, directed: DataFrame) -> DataFrame:
    """How many pattern edges, in their written direction, lie on couplers that exist only the other way: to be flipped."""
    out, flips = layouts, F.lit(0)
    for k, (i, j) in enumerate(sorted(pattern.edges)):
        d = directed.select(F.col("u").alias(f"_u{k}"), F.col("v").alias(f"_w{k}")).distinct()
        out = out.join(d, (F.col(f"v{i}") == F.col(f"_u{k}")) & (F.col(f"v{j}") == F.col(f"_w{k}")), "left")
        flips = flips + F.col(f"_u{k}").isNull().cast("int")
    return out.select(*names(range(pattern.n)), flips.alias("flips"))


def quality_tables(spark, sf_dir: str, g: DataGraph) -> tuple[DataFrame, DataFrame]:
    """Per vertex 1 - avg(l_tax) / 10 over its part's lines; per edge 1 - avg(l_discount) / 10 over the lines whose
    (part + supplier) falls on the edge's number."""
    line = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_partkey", "l_suppkey", "l_discount", "l_tax")
    vertex = line.groupBy(F.col("l_partkey").alias("id")).agg((1 - F.avg("l_tax") / 10).alias("q")).join(g.vertices, "id", "left_semi")
    numbered = g.numbered_edges()
    m = numbered.count()
    by = line.groupBy(F.pmod(F.col("l_partkey") + F.col("l_suppkey"), F.lit(m)).alias("k")).agg((1 - F.avg("l_discount") / 10).alias("q"))
    one = numbered.join(by, "k").select("u", "v", "q")
    return vertex, one.unionAll(one.select(F.col("v").alias("u"), F.col("u").alias("v"), "q"))
