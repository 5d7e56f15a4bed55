"""The experiments, re-expressed: lattices, sampled patterns, motif sets, warm runs, layouts. Each gives one row per run.

Lattices, sizes and seeds are parameters. The registered queries run on the published lattices with the smallest published
`max_solutions` mappings; one that has more is reported with the status "too many solutions" and is not run.
"""

from __future__ import annotations

import time
from itertools import islice

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphstitch.operators import baselines, execute, metrics, scoring
from graphstitch.operators.catalog import MotifCatalog
from graphstitch.plans.backtrack import adjacency, embeddings
from graphstitch.plans.decompose import decompose
from graphstitch.plans.motifs import GRID_DEFAULT, GRID_SMALL, HEAVY_HEX_CLAW, HEAVY_HEX_DEFAULT
from graphstitch.plans.pattern import Pattern, routed_star, sample_pattern
from graphstitch.session import cut, forget, lean, shared_path
from graphstitch.sources import derive
from graphstitch.sources.graph import DataGraph, two_way
from graphstitch.sources.lattice import LATTICES, lattice

MAX_SOLUTIONS = 100_000
HEX_SETS = (("edge",), ("edge", "path4"), ("edge", "claw4"), ("edge", "ring12"), ("edge", "ring12", "sunhex18"))
IRREGULAR, IRREGULAR_SHAPES = ("copurchase", "supply", "knn", "pagelinks"), ("triangle", "ring4", "path4", "claw4")
GRID_SETS = (("edge",), ("edge", "path4"), ("edge", "ring4"), ("edge", "ring4", "ring6"), ("edge", "ladder6"))


def screened(name: str, n: int, seeds, max_solutions: int = MAX_SOLUTIONS, compact: float = 0.0) -> list[tuple[int, Pattern, int]]:
    """(seed, pattern, solutions) of the sampled patterns that are feasible."""
    return [(seed, p, found) for seed, p, found, _ in sampled(name, n, seeds, max_solutions, compact) if found <= max_solutions]


def sampled(name: str, n: int, seeds, max_solutions: int = MAX_SOLUTIONS, compact: float = 0.0):
    """(seed, pattern, solutions, seconds of the sequential search), counted up to one more than `max_solutions`."""
    data = adjacency(LATTICES[name][0].pairs())
    for seed in seeds:
        p = sample_pattern(data, n, seed, compact)
        began = time.perf_counter()
        found = sum(1 for _ in islice(embeddings(p.adj, data, induced=True), max_solutions + 1))
        yield seed, p, found, time.perf_counter() - began


def scaling(spark: SparkSession, sf_dir: str, names=("hh1990", "hh4485", "sq1600", "sq3600"), sizes=(20,), seeds=range(1), max_solutions: int = MAX_SOLUTIONS) -> DataFrame:
    """The catalog of a lattice is built and timed for each run, as the published figures have it; warm_s leaves it out."""
    rows = []
    for name in names:
        g = lattice(spark, sf_dir, name).pin()
        motifs = HEAVY_HEX_DEFAULT if name.startswith("hh") else GRID_DEFAULT
        for n in sizes:
            for seed, p, found, seconds in sampled(name, n, seeds, max_solutions):
                if found > max_solutions:
                    rows.append((name, n, seed, "+".join(motifs), len(decompose(p, motifs).tiles), -1, *[-1.0] * 6, "too many solutions"))
                else:
                    rows.append(metrics.run(g, p, motifs, name, seed, baseline=seconds))
        g.unpin()
    return metrics.report(spark, rows)


def motif_sets(spark: SparkSession, sf_dir: str, names=("hh4485", "sq3600"), n: int = 20, seeds=range(1), sets=None) -> DataFrame:
    rows = []
    for name in names:
        g = lattice(spark, sf_dir, name).pin()
        for seed, p, _ in screened(name, n, seeds):
            rows += [metrics.run(g, p, motifs, name, seed) for motifs in sets or (HEX_SETS if name.startswith("hh") else GRID_SETS)]
        g.unpin()
    return metrics.report(spark, rows)


def solutions(spark: SparkSession, sf_dir: str, names=("hh1990", "sq1600"), n: int = 20, seeds=range(1)) -> DataFrame:
    """Cold, warm and baseline seconds beside the number of solutions."""
    rows = []
    for name in names:
        g, data = lattice(spark, sf_dir, name).pin(), adjacency(LATTICES[name][0].pairs())
        motifs = HEAVY_HEX_CLAW if name.startswith("hh") else GRID_SMALL
        rows += [metrics.run(g, p, motifs, name, seed, baseline=lambda p=p, data=data: baselines.vf2(data, p)) for seed, p, _ in screened(name, n, seeds)]
        g.unpin()
    return metrics.report(spark, rows)


def layouts(spark: SparkSession, sf_dir: str, sizes=(30, 50, 70), seeds=range(0), family: bool = True) -> DataFrame:
    """Generation and scoring of layouts on the 156-vertex device, for routed star circuits and sampled patterns: ours, with the
    running score, and the sequential pass. split_share: the part of our time that scoring takes beyond generation."""
    g, data = lattice(spark, sf_dir, "hh156").pin(), adjacency(LATTICES["hh156"][0].pairs())
    vq, eq = scoring.quality_tables(spark, sf_dir, g)
    v, e = {r["id"]: r["q"] for r in vq.collect()}, {(r["u"], r["v"]): r["q"] for r in eq.collect()}
    rows = []
    circuits = [(f"sample{s}", p) for n in sizes for s, p, _ in screened("hh156", n, seeds)]
    circuits += [(f"star{n}", routed_star(data, LATTICES["hh156"][0].snake(), n)) for n in sizes if family]
    for tag, p in circuits:
        began = time.perf_counter()
        catalog = MotifCatalog.build(g, HEAVY_HEX_DEFAULT)
        found = execute.match(g, p, HEAVY_HEX_DEFAULT, catalog=catalog).count()
        middle = time.perf_counter()
        best = scoring.select_layouts(scoring.score_layouts(g, p, vq, eq, catalog=catalog), p.n).collect()
        end = time.perf_counter()
        base, generate, score = baselines.vf2_post_layout(data, p, v, e)
        rows.append((tag, p.n, found, round(best[0]["score"], 9) if best else None, middle - began, end - middle, generate, score, len(base) == found))
    g.unpin()
    return spark.createDataFrame(rows, "circuit string, n int, layouts long, best double, generate_s double, select_s double, baseline_generate_s double, baseline_score_s double, agree boolean")


def layout_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How the time of a layout run divides: ours into generation and scored selection, the baseline's into generation and
    sequential scoring."""
    share = lambda a, b: (F.col(b) / (F.col(a) + F.col(b))).alias(f"{b}hare")
    return layouts(spark, sf_dir, sizes=(30,)).select("circuit", "n", "layouts", "generate_s", "select_s", "baseline_generate_s", "baseline_score_s", share("generate_s", "select_s"), share("baseline_generate_s", "baseline_score_s"))


def frontier(spark: SparkSession, sf_dir: str, names=("sq1600",), n: int = 20, seeds=range(1)) -> DataFrame:
    rows = []
    for name in names:
        g = lattice(spark, sf_dir, name).pin()
        rows += [metrics.run(g, p, HEAVY_HEX_DEFAULT if name.startswith("hh") else GRID_DEFAULT, name, seed, baseline=lambda p=p, g=g: baselines.frontier_match(g, p).count()) for seed, p, _ in screened(name, n, seeds)]
        g.unpin()
    return metrics.report(spark, rows)


def warm(spark: SparkSession, sf_dir: str, name: str = "hh1990", n: int = 12, seeds=range(2)) -> DataFrame:
    """The same patterns cold and over a catalog that was saved before and is read again."""
    g = lattice(spark, sf_dir, name).pin()
    at = shared_path(spark, "catalog")
    MotifCatalog.build(g, HEAVY_HEX_DEFAULT).save(at)
    catalog = MotifCatalog.load(spark, at, g.fingerprint(), graph=g)
    rows = []
    for seed, p, _ in screened(name, n, seeds):
        rows += [metrics.run(g, p, HEAVY_HEX_DEFAULT, f"{name} cold", seed), metrics.run(g, p, HEAVY_HEX_DEFAULT, f"{name} warm", seed, catalog=catalog)]
    catalog.unpersist()
    g.unpin()
    return metrics.report(spark, rows)


def tiling_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scaling(spark, sf_dir, ("hh1990",), seeds=range(1)).select("graph", "n", "seed", "tiles", "tiling_share")


def irregular(spark: SparkSession, sf_dir: str, shapes=IRREGULAR_SHAPES) -> DataFrame:
    """Small motifs on graphs that are no lattices: rows and seconds, and the seconds of the graph's own derivation."""
    rows = []
    for name, derived in derive.GRAPHS.items():
        if name not in IRREGULAR:
            continue
        # the graph is derived once, and one direction of it stored; counts name its edges several times
        began = time.perf_counter()
        half = cut(derived(lean(spark), sf_dir).edges.where("u < v"))
        took = time.perf_counter() - began
        edges = two_way(half)
        g = DataGraph(edges.select(F.col("u").alias("id")).distinct(), edges)
        for shape in shapes:
            began = time.perf_counter()
            n = MotifCatalog.build(g, ["edge", "path3", shape]).count(shape)
            rows.append((name, shape, n, time.perf_counter() - began, took))
        forget(half)
    return spark.createDataFrame(rows, "graph string, motif string, rows long, seconds double, derive_s double")


def tile_counts(names=("hh4485", "sq3600"), n: int = 60, seeds=range(5)) -> list[tuple]:
    """(graph, motif set, mean tiles, mean edges) at the published size; needs no Spark."""
    out = []
    for name in names:
        data = adjacency(LATTICES[name][0].pairs())
        patterns = [sample_pattern(data, n, s) for s in seeds]
        for motifs in HEX_SETS if name.startswith("hh") else GRID_SETS:
            tiles = [len(decompose(p, motifs).tiles) for p in patterns]
            out.append((name, "+".join(motifs), sum(tiles) / len(tiles), sum(len(p.edges) for p in patterns) / len(patterns)))
    return out


WORKLOADS = {
    "bench_scaling": scaling, "bench_motifs": motif_sets, "bench_solutions": solutions, "bench_layout": layouts, "bench_frontier": frontier,
    "bench_warm": warm, "bench_tiling_share": tiling_share, "bench_irregular": irregular, "metric_layout_split": layout_split,
}
