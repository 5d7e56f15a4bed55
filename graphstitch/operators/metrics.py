"""Cost measures of runs, and agreement of answers."""

from __future__ import annotations

import time
from collections.abc import Iterable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphstitch.operators.catalog import MotifCatalog
from graphstitch.operators.execute import BudgetExceeded, run_plan, seed
from graphstitch.operators.semantics import fresh_condition
from graphstitch.plans.decompose import decompose
from graphstitch.plans.pattern import Pattern
from graphstitch.session import cut
from graphstitch.sources.graph import DataGraph

RUN = "graph string, n int, seed int, motifs string, tiles int, solutions long, prep_s double, compute_s double, total_s double, warm_s double, baseline_s double, tiling_share double, status string"


def run(g: DataGraph, pattern: Pattern, motifs: Sequence[str], graph: str = "", seed_: int = 0, semantics: str = "induced", catalog: MotifCatalog | None = None, baseline=None, max_rows: int | None = None) -> tuple:
    """One execution: a row of RUN. prep: motif tables built and stored; compute: tiling and stitches; warm: without prep. baseline: what is timed beside it,
    or its seconds."""
    began = time.perf_counter()
    mine = catalog or MotifCatalog.build(g, motifs, persist=True)
    prep = 0.0 if catalog else time.perf_counter() - began
    began = time.perf_counter()
    plan = decompose(pattern, motifs)
    tiling = time.perf_counter() - began
    status, solutions = "finished", -1
    try:
        solutions = run_plan(plan, mine, "adjacency" if semantics == "induced" else None, max_rows=max_rows).count()
    except BudgetExceeded:
        status = "over budget"
    compute = time.perf_counter() - began
    if catalog is None:
        mine.unpersist()
    began = time.perf_counter()
    if callable(baseline):
        baseline()
        base = time.perf_counter() - began
    else:
        base = -1.0 if baseline is None else baseline
    return graph, pattern.n, seed_, "+".join(motifs), len(plan.tiles), solutions, prep, compute, prep + compute, compute, base, tiling / max(prep + compute, 1e-9), status


def report(spark: SparkSession, rows: Iterable[tuple]) -> DataFrame:
    return spark.createDataFrame(list(rows), RUN)


def speedups(runs: DataFrame, ours: str = "total_s", baseline: str = "baseline_s") -> DataFrame:
    """Of baseline over ours: min, mean and max over the seeds of each graph and size."""
    ratio = F.col(baseline) / F.col(ours)
    return runs.groupBy("graph", "n").agg(F.min(ratio).alias("min"), F.avg(ratio).alias("mean"), F.max(ratio).alias("max"))


def tiles(spark: SparkSession, patterns: Sequence[Pattern], motifs: Sequence[str]) -> DataFrame:
    """pattern, edges, tiles."""
    return spark.createDataFrame([(i, len(p.edges), len(decompose(p, motifs).tiles)) for i, p in enumerate(patterns)], "pattern int, edges int, tiles int")


def trace(g: DataGraph, pattern: Pattern, motifs: Sequence[str], catalog: MotifCatalog | None = None) -> DataFrame:
    """Rows of every stitch before and after vertex reuse is refused (monomorphisms): step, motif, seam_cols, rows_joined,
    rows_kept. Each step is materialised."""
    catalog = catalog or MotifCatalog.build(g, motifs)
    bound, rows = None, []
    for i, t in enumerate(decompose(pattern, motifs).tiles):
        table = catalog.table(t.motif)
        if bound is None:
            bound = cut(seed(table, t))
            n = bound.count()
            rows.append((i, t.motif, 0, n, n))
            continue
        old = bound.columns
        right = table.select(*[F.col(f"c{j}").alias(f"r{v}") for j, v in enumerate(t.verts)])
        on = [bound[f"v{v}"] == right[f"r{v}"] for v in t.seam]
        joined = bound.join(right, on)
        before = joined.count()
        if t.fresh:
            joined = joined.where(fresh_condition(old, [f"r{v}" for v in t.fresh]))
        bound = cut(joined.select(*old, *[F.col(f"r{v}").alias(f"v{v}") for v in t.fresh]))
        rows.append((i, t.motif, len(t.seam), before, bound.count()))
    return bound.sparkSession.createDataFrame(rows, "step int, motif string, seam_cols int, rows_joined long, rows_kept long")


def solutions(matches: DataFrame, pattern: Pattern, induced: bool) -> DataFrame:
    """mappings, and subgraphs: mappings over the number of automorphisms."""
    same = len(pattern.automorphisms())
    return matches.agg(F.count("*").alias("mappings")).select("mappings", (F.col("mappings") / same).cast("long").alias("subgraphs"))


def scores(scored: DataFrame) -> DataFrame:
    return scored.agg(F.count("*").alias("layouts"), F.round(F.max("score"), 9).alias("best"), F.round(F.avg("score"), 9).alias("mean"))


def diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of one answer that the other lacks, with multiplicity."""
    return a.exceptAll(b).agg(F.count("*").alias("only_a")).crossJoin(b.select(*a.columns).exceptAll(a).agg(F.count("*").alias("only_b")))
