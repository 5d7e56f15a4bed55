"""What stitching is compared with: sequential and distributed backtracking, and vertex-at-a-time frontiers."""

from __future__ import annotations

import time
from itertools import islice

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphstitch.operators.semantics import fresh_condition, names
from graphstitch.plans.backtrack import Adjacency, brute, embeddings, visit_order
from graphstitch.plans.pattern import Pattern
from graphstitch.sources.graph import DataGraph


def _schema(n: int) -> str:
    return ", ".join(f"v{i} long" for i in range(n))


def vf2(data: Adjacency, pattern: Pattern, semantics: str = "induced", limit: int | None = None) -> list[tuple[int, ...]]:
    """One thread on the driver; for graphs that fit there."""
    found = embeddings(pattern.adj, data, induced=semantics == "induced")
    return [tuple(m[i] for i in range(pattern.n)) for m in islice(found, limit)]


def vf2_driver(g: DataGraph, pattern: Pattern, semantics: str = "induced", limit: int | None = None) -> DataFrame:
    return g.edges.sparkSession.createDataFrame(vf2(g.local(), pattern, semantics, limit), _schema(pattern.n))


def vf2_distributed(g: DataGraph, pattern: Pattern, semantics: str = "induced") -> DataFrame:
    """Starts are dealt over tasks, each task searches depth first on a broadcast copy of the graph (size-checked)."""
    spark = g.edges.sparkSession
    held = spark.sparkContext.broadcast(g.local())
    start = max(range(pattern.n), key=lambda v: (len(pattern.adj[v]), -v))
    cols, induced, adj = names(range(pattern.n)), semantics == "induced", pattern.adj

    def run(batches):
        for batch in batches:
            found = embeddings(adj, held.value, induced=induced, start=start, roots=batch.column(0).to_pylist())
            while rows := [tuple(m[i] for i in range(len(cols))) for m in islice(found, 10_000)]:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], cols)

    tasks = spark.sparkContext.defaultParallelism * 4
    return g.vertices.repartition(tasks, "id").select("id").mapInArrow(run, _schema(pattern.n))


def frontier_match(g: DataGraph, pattern: Pattern, semantics: str = "induced") -> DataFrame:
    """Breadth first, one vertex a step: extended along one edge, its other edges verified by semi-joins."""
    start = max(range(pattern.n), key=lambda v: (len(pattern.adj[v]), -v))
    order = visit_order(pattern.adj, start)
    bound, seen = g.vertices.select(F.col("id").alias(f"v{start}")), [start]
    edges = g.edges
    for v in order[1:]:
        back = [w for w in seen if w in pattern.adj[v]]
        e = edges.select(F.col("u").alias("_u"), F.col("v").alias(f"v{v}"))
        bound = bound.join(e, (bound[f"v{back[0]}"] == e["_u"]) & fresh_condition(names(seen), [f"v{v}"])).drop("_u")
        for w in back[1:]:
            e = edges.select(F.col("u").alias("_u"), F.col("v").alias("_w"))
            bound = bound.join(e, (bound[f"v{w}"] == e["_u"]) & (bound[f"v{v}"] == e["_w"]), "left_semi")
        if semantics == "induced":
            for w in seen:
                if w not in pattern.adj[v]:
                    e = edges.select(F.col("u").alias("_u"), F.col("v").alias("_w"))
                    bound = bound.join(e, (bound[f"v{w}"] == e["_u"]) & (bound[f"v{v}"] == e["_w"]), "left_anti")
        seen.append(v)
    return bound.select(*names(range(pattern.n)))


def vf2_post_layout(data: Adjacency, pattern: Pattern, vertex_q: dict[int, float], edge_q: dict[tuple[int, int], float]) -> tuple[list[tuple], float, float]:
    """Layouts by backtracking, then a sequential scoring loop: rows with score, seconds of either part."""
    began = time.perf_counter()
    layouts = vf2(data, pattern)
    middle = time.perf_counter()
    rows = []
    for m in layouts:
        score = 1.0
        for i, j in sorted(pattern.edges):
            score *= edge_q[m[i], m[j]]
        for v in m:
            score *= vertex_q[v]
        rows.append((*m, score))
    return rows, middle - began, time.perf_counter() - middle


def brute_force(g: DataGraph, pattern: Pattern, semantics: str = "induced") -> DataFrame:
    rows = sorted(brute(pattern.n, pattern.edges, g.local(200), semantics == "induced"))
    return g.edges.sparkSession.createDataFrame(rows, _schema(pattern.n))
