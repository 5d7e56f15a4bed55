"""What makes a row an answer: distinct vertices, kept non-edges, one row per subgraph, one per symmetry class."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphstitch.plans.pattern import Pattern

#: Columns beyond which distinctness is tested on an array (long IN lists make code too large to compile).
ARRAY_FROM = 64


def names(vertices: Sequence[int]) -> list[str]:
    return [f"v{i}" for i in vertices]


def fresh_condition(old: Sequence[str], fresh: Sequence[str], mode: str = "in") -> Column:
    """No fresh column repeats an old one; fresh ones differ among themselves inside their motif row. "count" states the same
    as a number of distinct values."""
    if mode == "count":
        every = [*old, *fresh]
        return F.size(F.array_distinct(F.array(*every))) == len(every)
    if mode == "array" or len(old) > ARRAY_FROM:
        return ~F.arrays_overlap(F.array(*old), F.array(*fresh))
    out = F.lit(True)
    for f in fresh:
        out = out & ~F.col(f).isin(*[F.col(o) for o in old])
    return out


def induced_step(bound: DataFrame, adjacency: DataFrame, pattern: Pattern, covered: Sequence[int], fresh: Sequence[int]) -> DataFrame:
    """Each fresh vertex must have exactly as many data neighbours among the covered ones as the pattern says. All pattern
    edges among covered vertices count, tiled yet or not, so rows go as early as they can."""
    inside = set(covered)
    every = F.array(*names(covered))
    for v in fresh:
        want = len(pattern.adj[v] & inside)
        near = adjacency.select(F.col("u").alias("_u"), F.col("nbrs").alias("_n"))
        bound = bound.join(near, bound[f"v{v}"] == F.col("_u")).where(F.size(F.array_intersect("_n", every)) == want).drop("_u", "_n")
    return bound


def induced_rows(bound: DataFrame, pattern: Pattern, covered: Sequence[int], fresh: Sequence[int]) -> DataFrame:
    """The same check for all fresh vertices of a tile together, on rows that carry their neighbours: no join."""
    inside, every = set(covered), F.array(*names(covered))
    ok = F.lit(True)
    for v in fresh:
        ok = ok & (F.size(F.array_intersect(F.coalesce(f"_n{v}", F.array().cast("array<bigint>")), every)) == len(pattern.adj[v] & inside))
    return bound.where(ok).drop(*[f"_n{v}" for v in fresh])


def induced_antijoin(matches: DataFrame, edges: DataFrame, pattern: Pattern) -> DataFrame:
    """One anti-join for each non-edge of the pattern."""
    for i in range(pattern.n):
        for j in range(i + 1, pattern.n):
            if j not in pattern.adj[i]:
                e = edges.select(F.col("u").alias("_u"), F.col("v").alias("_v"))
                matches = matches.join(e, (matches[f"v{i}"] == e["_u"]) & (matches[f"v{j}"] == e["_v"]), "left_anti")
    return matches


def induced_edgecount(matches: DataFrame, edges: DataFrame, pattern: Pattern) -> DataFrame:
    """As many data edges among the mapped vertices as the pattern has. The row is its own key."""
    cols = names(range(pattern.n))
    pairs = F.array(*[F.struct(F.col(cols[i]).alias("u"), F.col(cols[j]).alias("v")) for i in range(pattern.n) for j in range(i + 1, pattern.n)])
    each = matches.select(*cols, F.explode(pairs).alias("p")).select(*cols, F.col("p.u").alias("u"), F.col("p.v").alias("v"))
    return each.join(edges, ["u", "v"], "left_semi").groupBy(*cols).agg(F.count("*").alias("_e")).where(F.col("_e") == len(pattern.edges)).drop("_e")


def distinct_subgraphs(matches: DataFrame, pattern: Pattern, induced: bool) -> DataFrame:
    """One row for each vertex set (induced) or edge set: the smallest of its mappings."""
    cols = names(range(pattern.n))
    if induced:
        key = F.sort_array(F.array(*cols))
    else:
        key = F.sort_array(F.array(*[F.struct(F.least(f"v{i}", f"v{j}").alias("a"), F.greatest(f"v{i}", f"v{j}").alias("b")) for i, j in sorted(pattern.edges)]))
    return matches.groupBy(key.alias("_k")).agg(F.min(F.struct(*cols)).alias("_m")).select("_m.*")


def symmetry_condition(pattern: Pattern, available: set[int] | None = None, fresh: set[int] | None = None) -> Column | None:
    """Order conditions among the available vertices that touch a fresh one."""
    pairs = [(i, j) for i, j in pattern.symmetry_conditions() if (available is None or {i, j} <= available) and (fresh is None or {i, j} & fresh)]
    out = None
    for i, j in pairs:
        c = F.col(f"v{i}") < F.col(f"v{j}")
        out = c if out is None else out & c
    return out


def as_array(matches: DataFrame, n: int) -> DataFrame:
    return matches.select(F.array(*names(range(n))).alias("mapping"))


def as_map(matches: DataFrame, n: int) -> DataFrame:
    return matches.select(F.map_from_arrays(F.array(*[F.lit(i) for i in range(n)]), F.array(*names(range(n)))).alias("mapping"))


def as_struct(matches: DataFrame, n: int) -> DataFrame:
    return matches.select(F.struct(*names(range(n))).alias("mapping"))
