"""Which motifs to use, and in which order to stitch: estimates from degrees, sampled counts and catalog sizes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphstitch.plans.decompose import StitchPlan, decompose
from graphstitch.plans.motifs import Motif, motif, motif_set
from graphstitch.plans.pattern import Pattern


def frequency(catalog, motifs: Sequence[Motif | str]) -> DataFrame:
    """motif, rows, frequency (placements up to symmetry)."""
    out = None
    for m in motif_set(motifs):
        same = len(m.pattern.automorphisms())
        one = catalog.table(m.name).agg(F.count("*").alias("rows")).select(F.lit(m.name).alias("motif"), "rows", (F.col("rows") / same).cast("long").alias("frequency"))
        out = one if out is None else out.unionAll(one)
    return out


def sampled_rows(g, m: Motif, share: int = 8) -> int:
    """Placements estimated from those whose first vertex falls into one of `share` hash classes."""
    from graphstitch.operators.execute import match

    first = {0: g.vertices.where(F.pmod(F.xxhash64("id"), F.lit(share)) == 0)}
    return share * match(g, m.pattern, ["edge"], semantics_="monomorphism", where=first).count()


def advise(g, pattern: Pattern | None = None, motifs: Sequence[Motif | str] = ("edge", "path3", "path4", "claw4", "ring4", "ring6"), budget_rows: int = 50_000_000, catalog=None) -> DataFrame:
    """motif, est_rows, frequency, est_tiles, score. A motif pays by the edges it covers at once and costs by its rows per
    vertex; those over the budget, or absent from the graph, score 0. Edge-sparse graphs thus favour large motifs, and dense
    ones, where rows explode, moderate motifs."""
    spark, n = g.vertices.sparkSession, max(1, g.vertices.count())
    rows = []
    for m in motif_set(motifs):
        est = catalog.count(m.name) if catalog is not None and m.name in catalog.motifs else sampled_rows(g, m)
        tiles = len(decompose(pattern, ["edge", m]).tiles) if pattern else -1
        score = 0.0 if not est or est > budget_rows else len(m.pattern.edges) / (1 + est / n)
        rows.append((m.name, est, est // len(m.pattern.automorphisms()), tiles, round(score, 6)))
    return spark.createDataFrame(rows, "motif string, est_rows long, frequency long, est_tiles int, score double").orderBy(F.desc("score"), "motif")


def ordered(pattern: Pattern, motifs: Sequence[Motif | str], catalog, vertices: int | None = None) -> StitchPlan:
    """A tiling that always takes the occurrence expected to leave the fewest rows per edge it covers: a motif's rows, divided
    once by the number of vertices for every seam column."""
    n = vertices or max(1, catalog.graph.vertices.count())

    def choose(hits, covered):
        def rows(hit):
            m, at = hit
            seam = sum(v in covered for v in at.values())
            return (max(1e-9, catalog.count(motif(m).name) / n**seam) ** (1 / len(m.pattern.edges)), -len(m.pattern.edges), m.name)

        return min(hits, key=rows)

    return decompose(pattern, motifs, choose=choose)
