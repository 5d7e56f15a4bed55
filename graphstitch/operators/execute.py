"""Stitching: tilings become chains of equi-joins over motif tables."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from typing import TYPE_CHECKING

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphstitch.operators import semantics
from graphstitch.operators.semantics import names
from graphstitch.plans.decompose import StitchPlan, Tile, decompose
from graphstitch.plans.motifs import HEAVY_HEX_DEFAULT, Motif
from graphstitch.plans.pattern import Pattern
from graphstitch.session import cut
from graphstitch.sources.graph import DataGraph

if TYPE_CHECKING:
    from graphstitch.operators.catalog import MotifCatalog

CUT_EVERY = 8
#: Rows of an adjacency list table that may be broadcast.
BROADCAST_VERTICES = 200_000


class BudgetExceeded(RuntimeError):
    """A binding table grew beyond the row budget; `trace` holds (step, rows) so far."""

    def __init__(self, trace: list[tuple[int, int]]):
        super().__init__(f"binding table over budget: {trace[-1]}")
        self.trace = trace


def seed(table: DataFrame, tile: Tile) -> DataFrame:
    """The first tile's motif table under pattern vertex names: the identity of the chain of joins."""
    return table.select(*[F.col(f"c{j}").alias(f"v{v}") for j, v in enumerate(tile.verts)], *_near(table, tile), *[c for c in ("score",) if c in table.columns])


def _near(table: DataFrame, tile: Tile) -> list[Column]:
    """The neighbours of the vertices that the tile binds first, if the table has them: _n and the pattern's vertex."""
    return [F.col(f"n{j}").alias(f"_n{v}") for j, v in enumerate(tile.verts) if v in tile.fresh and f"n{j}" in table.columns]


def stitch(bound: DataFrame, table: DataFrame, tile: Tile, strategy: str | None = None, distinct: str = "in") -> DataFrame:
    """One equi-join on all seam columns; rows that reuse a vertex are refused inside the join. A tile without fresh vertices
    only closes edges, so it is a semi-join."""
    right = table.select(*[F.col(f"c{j}").alias(f"r{v}") for j, v in enumerate(tile.verts)], *_near(table, tile), *([F.col("score").alias("_s")] if "score" in table.columns else []))
    right = right.hint(strategy) if strategy else right
    on = [bound[f"v{v}"] == right[f"r{v}"] for v in tile.seam]
    if not on:
        raise ValueError("a tile without a seam would be a cross product")
    scored = "_s" in right.columns
    if not tile.fresh and not scored:
        return bound.join(right, _all(on), "left_semi")
    old = [c for c in bound.columns if c != "score"]
    if tile.fresh:
        on.append(semantics.fresh_condition(old, [f"r{v}" for v in tile.fresh], distinct))
    out = bound.join(right, _all(on))
    cols = [*old, *[F.col(f"r{v}").alias(f"v{v}") for v in tile.fresh], *[c for c in right.columns if c.startswith("_n")]]
    return out.select(*cols, *([(F.col("score") * F.col("_s")).alias("score")] if scored else []))


def _all(conditions: Sequence[Column]) -> Column:
    out = conditions[0]
    for c in conditions[1:]:
        out = out & c
    return out


def run_plan(
    plan: StitchPlan, catalog: MotifCatalog, induced: str | None = None, strategy: str | None = None, distinct: str = "in", symmetry: bool = False,
    cut_every: int = CUT_EVERY, first: Callable[[DataFrame], DataFrame] | None = None, factor: Callable[[DataFrame, Tile], DataFrame] | None = None,
    max_rows: int | None = None, allowed: dict[int, DataFrame] | None = None, quality: tuple[DataFrame, DataFrame] | None = None,
    keep: Callable[[DataFrame], DataFrame] | None = None,
) -> DataFrame:
    """The chain of stitches. induced: None, "adjacency", "antijoin" or "edgecount". first: applied to the seed (batches).
    factor: makes a score column of a tile's motif table with qualities. keep: applied after every stitch. allowed: per pattern vertex, the ids it may take."""
    pattern, g = plan.pattern, catalog.graph
    if not plan.tiles:
        out = g.vertices.select(F.col("id").alias("v0"))
        return first(out) if first else out
    # small graphs: neighbours and qualities are columns of the motif tables, and a stitch is one join whatever it checks
    held = induced == "adjacency" and g.pinned
    near = g.adjacency if induced == "adjacency" and not held else None
    if near is not None and catalog.count("edge") <= BROADCAST_VERTICES:
        near = F.broadcast(near)
    bound, covered, trace = None, [], []
    for i, tile in enumerate(plan.tiles):
        table = catalog.wide(tile.motif, held, quality) if held or quality else catalog.table(tile.motif)
        for v, ids in (allowed or {}).items():
            if v in tile.fresh:
                table = table.join(ids.select(F.col(ids.columns[0]).alias(f"c{tile.verts.index(v)}")), f"c{tile.verts.index(v)}", "left_semi")
        score = [factor(tile).alias("score")] if factor else []
        table = table.select(*[f"c{j}" for j in range(len(tile.verts))], *[c for c in table.columns if held and c[0] == "n"], *score)
        if bound is None:
            bound = seed(table, tile)
            bound = first(bound) if first else bound
        else:
            bound = stitch(bound, table, tile, strategy, distinct)
        covered += [v for v in tile.fresh if v not in covered]
        if symmetry and (c := semantics.symmetry_condition(pattern, set(covered), set(tile.fresh))) is not None:
            bound = bound.where(c)
        if held and tile.fresh:
            bound = semantics.induced_rows(bound, pattern, sorted(covered), tile.fresh)
        elif induced == "adjacency" and tile.fresh:
            bound = semantics.induced_step(bound, near, pattern, sorted(covered), tile.fresh)
        bound = keep(bound) if keep else bound
        if max_rows is not None:
            bound = cut(bound)
            trace.append((i, bound.count()))
            if trace[-1][1] > max_rows:
                raise BudgetExceeded(trace)
        elif cut_every and i % cut_every == cut_every - 1 and i + 1 < len(plan.tiles):
            bound = cut(bound)
    bound = bound.select(*names(range(pattern.n)), *[c for c in ("score",) if c in bound.columns])
    if induced == "antijoin":
        return semantics.induced_antijoin(bound, g.edges, pattern)
    if induced == "edgecount":
        return semantics.induced_edgecount(bound, g.edges, pattern)
    return bound


def match(
    g: DataGraph, pattern: Pattern, motifs: Sequence[Motif | str] = HEAVY_HEX_DEFAULT, semantics_: str = "induced", catalog: MotifCatalog | None = None,
    induced: str = "adjacency", order: str = "size_desc", rotate: int = 0, distinct_subgraphs: bool = False, symmetry: bool = False, degree_filter: bool = False,
    limit: int | None = None, seed_batches: int = 1, where: dict[int, DataFrame] | None = None, **run,
) -> DataFrame:
    """All mappings of the pattern into the graph, columns v0..v{n-1}. semantics_: "induced" or "monomorphism"."""
    from graphstitch.operators.catalog import MotifCatalog

    catalog = catalog or MotifCatalog.build(g, motifs)
    plan = decompose(pattern, motifs, order=order, rotate=rotate)
    how = induced if semantics_ == "induced" else None
    allowed = dict(where or {})
    if degree_filter:
        for v in range(pattern.n):
            if (d := len(pattern.adj[v])) > 1:
                ids = g.where_degree(d)
                allowed[v] = ids.join(allowed[v].select(F.col(allowed[v].columns[0]).alias("id")), "id", "left_semi") if v in allowed else ids
    parts = []
    for b in range(seed_batches):
        first = (lambda df, b=b: df.where(F.pmod(F.xxhash64(df.columns[0]), F.lit(seed_batches)) == b)) if seed_batches > 1 else None
        part = run_plan(plan, catalog, how, symmetry=symmetry, first=first, allowed=allowed, **run)
        if limit is not None and seed_batches > 1:
            part = cut(part.limit(limit))
        parts.append(part)
        if limit is not None and seed_batches > 1 and sum(p.count() for p in parts) >= limit:
            break
    out = parts[0]
    for p in parts[1:]:
        out = out.unionAll(p)
    if distinct_subgraphs:
        out = semantics.distinct_subgraphs(out, pattern, semantics_ == "induced")
    return out if limit is None else out.limit(limit)


def match_many(g: DataGraph, patterns: Sequence[Pattern], catalog: MotifCatalog, motifs: Sequence[Motif | str], **options) -> DataFrame:
    """Counts of several patterns over one catalog: pattern number and mappings."""
    out = None
    for i, p in enumerate(patterns):
        one = match(g, p, motifs, catalog=catalog, **options).agg(F.count("*").alias("mappings")).select(F.lit(i).alias("pattern"), "mappings")
        out = one if out is None else out.unionAll(one)
    return out


def count_matches(*args, **options) -> DataFrame:
    return match(*args, **options).agg(F.count("*").alias("n"))


def exists(*args, **options) -> bool:
    return not match(*args, limit=1, **options).isEmpty()
