"""Motif catalogs: tables of all ordered placements of small motifs, each built from those already there."""

from __future__ import annotations

import json
from collections.abc import Sequence
from concurrent.futures import ThreadPoolExecutor

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphstitch.operators.execute import run_plan
from graphstitch.plans.decompose import StitchPlan, decompose
from graphstitch.plans.motifs import Motif, motif_set
from graphstitch.sources.graph import DataGraph


class MotifCatalog:
    def __init__(self, graph: DataGraph):
        self.graph = graph
        self.motifs: dict[str, Motif] = {}
        self.recipes: dict[str, StitchPlan | None] = {}
        self._tables: dict[str, DataFrame] = {}
        self._rows: dict[str, int] = {}
        self._wide: dict[tuple, DataFrame] = {}

    @classmethod
    def build(cls, graph: DataGraph, motifs: Sequence[Motif | str], reuse: bool = True, parallel: int = 1, persist: bool = False) -> MotifCatalog:
        """reuse=False builds every motif straight from the edges. parallel: motifs whose parts are all there are
        materialised from so many driver threads. A pinned graph keeps the catalogs made for it, one for each set of motifs;
        with persist the caller gets one of its own, to time it and to unpersist it."""
        key = tuple((m.name, m.pattern.text()) for m in motif_set(motifs))
        if graph.pinned and reuse and not persist:
            if key not in graph.catalogs:
                graph.catalogs[key] = cls._build(graph, motifs, reuse, parallel, persist)
            return graph.catalogs[key]
        return cls._build(graph, motifs, reuse, parallel, persist)

    @classmethod
    def _build(cls, graph: DataGraph, motifs: Sequence[Motif | str], reuse: bool, parallel: int, persist: bool) -> MotifCatalog:
        out = cls(graph)
        for m in motif_set(motifs):
            out.add(m, reuse=reuse)
            if graph.pinned and m.name != "edge":
                out._rows[m.name] = out._tables[m.name].persist(StorageLevel.MEMORY_AND_DISK).count()
        if persist and not graph.pinned:
            for t in out._tables.values():
                t.persist(StorageLevel.MEMORY_AND_DISK)
            with ThreadPoolExecutor(max(1, parallel)) as pool:
                out._rows = dict(zip(out._tables, pool.map(lambda t: t.count(), out._tables.values())))
        return out

    def add(self, m: Motif, reuse: bool = True, using: Sequence[str] | None = None) -> MotifCatalog:
        """using: the names of the motifs to build from; by default all smaller ones that are there."""
        self.motifs[m.name] = m
        if m.name == "edge":
            self._tables["edge"] = self.graph.edges.select(F.col("u").alias("c0"), F.col("v").alias("c1"))
            self.recipes["edge"] = None
            return self
        parts = [self.motifs[u] for u in using] if using else [x for x in self.motifs.values() if x.size < m.size] if reuse else ["edge"]
        plan = decompose(m.pattern, parts)
        self.recipes[m.name] = plan
        table = run_plan(plan, self, cut_every=0)
        self._tables[m.name] = table.select(*[F.col(f"v{i}").alias(f"c{i}") for i in range(m.n)])
        return self

    def table(self, name: str) -> DataFrame:
        return self._tables[name]

    def wide(self, name: str, neighbours: bool = False, quality: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
        """The motif table with n{j}, the neighbours of the vertex in column j, and with the qualities p{j} of that vertex and e{k}
        of the motif's k-th edge. Made once for the catalog and held, so that a stitch looks nothing up any more."""
        key = (name, neighbours, quality and tuple(map(id, quality)))
        if key in self._wide:
            return self._wide[key]
        out, k = self._tables[name], self.motifs[name].n
        if neighbours:
            for j in range(k):
                near = self.graph.adjacency.select(F.col("u").alias(f"c{j}"), F.col("nbrs").alias(f"n{j}"))
                out = out.join(F.broadcast(near) if self.graph.pinned else near, f"c{j}", "left")
        if quality:
            vertex_q, edge_q = quality
            for j in range(k):
                out = out.join(vertex_q.select(F.col("id").alias(f"c{j}"), F.col("q").alias(f"p{j}")), f"c{j}")
            for i, (a, b) in enumerate(sorted(self.motifs[name].pattern.edges)):
                out = out.join(edge_q.select(F.col("u").alias(f"c{a}"), F.col("v").alias(f"c{b}"), F.col("q").alias(f"e{i}")), [f"c{a}", f"c{b}"])
        self._wide[key] = out.persist(StorageLevel.MEMORY_AND_DISK)
        self._wide[key].count()  # so that its size is known when stitches are planned
        return self._wide[key]

    def count(self, name: str) -> int:
        """Rows of a motif table. Where the motif's shape allows, they are counted below the stitches and not made; tables that
        are stored, and other shapes, are counted as they are."""
        if name not in self._rows:
            free = self.recipes[name] is not None and self.graph.symmetric
            n = self.graph.counts.of(self.motifs[name].pattern) if free else None
            self._rows[name] = self._tables[name].count() if n is None else n
        return self._rows[name]

    def stats(self) -> DataFrame:
        """motif, arity, rows, bytes (eight for each id)."""
        out = None
        for name, t in self._tables.items():
            k = self.motifs[name].n
            one = t.agg(F.count("*").alias("rows")).select(F.lit(name).alias("motif"), F.lit(k).alias("arity"), "rows", (F.col("rows") * 8 * k).alias("bytes"))
            out = one if out is None else out.unionAll(one)
        return out

    def unpersist(self) -> None:
        for t in [*self._tables.values(), *self._wide.values()]:
            t.unpersist()
        self._wide.clear()

    def save(self, path: str) -> None:
        """A Parquet table per motif, clustered by c0, and a manifest with the graph's fingerprint."""
        spark = self.graph.edges.sparkSession
        for name, t in self._tables.items():
            t.repartition("c0").sortWithinPartitions("c0").write.mode("overwrite").parquet(f"{path}/{name}")
        self.graph.vertices.write.mode("overwrite").parquet(f"{path}/_vertices_of_graph".replace("/_", "/"))
        about = {"fingerprint": self.graph.fingerprint(), "motifs": {m.name: m.pattern.text() for m in self.motifs.values()}}
        spark.createDataFrame([(json.dumps(about),)], "manifest string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")

    @classmethod
    def load(cls, spark: SparkSession, path: str, fingerprint: str | None = None, graph: DataGraph | None = None) -> MotifCatalog:
        """graph: the graph itself where it is at hand; else it is read from the catalog."""
        from graphstitch.plans.pattern import Pattern

        about = json.loads(spark.read.text(f"{path}/manifest").first()["value"])
        if fingerprint is not None and about["fingerprint"] != fingerprint:
            raise ValueError("the saved catalog belongs to another graph")
        edges = spark.read.parquet(f"{path}/edge")
        out = cls(graph or DataGraph(spark.read.parquet(f"{path}/vertices_of_graph"), edges.select(F.col("c0").alias("u"), F.col("c1").alias("v"))))
        for name, text in about["motifs"].items():
            out.motifs[name], out.recipes[name] = Motif(name, Pattern.from_text(text)), None
            out._tables[name] = spark.read.parquet(f"{path}/{name}")
        return out
