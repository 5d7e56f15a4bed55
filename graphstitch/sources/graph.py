"""DataGraph: two DataFrames, vertices(id) and edges(u, v); edges hold both directions, no loops, no repeats."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphstitch.plans.backtrack import Adjacency, adjacency
from graphstitch.session import cut, forget

#: Edge rows up to which a graph may be collected for a driver-side baseline.
LOCAL_EDGES = 2_000_000


def numbered(df: DataFrame, by: list[str], name: str) -> DataFrame:
    """Rows with their places 0, 1, ... in the order of `by`: positions inside range partitions, plus the rows of the partitions
    before. Nothing is sorted into one task; the window over all holds a row per partition."""
    ranged = cut(df.repartitionByRange(*by).select(*df.columns, F.spark_partition_id().alias("_p")))
    inside = F.row_number().over(Window.partitionBy("_p").orderBy(*by)) - 1
    sizes = ranged.groupBy("_p").count()
    starts = sizes.select("_p", (F.sum("count").over(Window.orderBy("_p")) - F.col("count")).alias("_start"))
    return ranged.withColumn("_i", inside).join(F.broadcast(starts), "_p").select(*df.columns, (F.col("_i") + F.col("_start")).cast("long").alias(name))


def two_way(half: DataFrame) -> DataFrame:
    """Both directions of edges of which one is given."""
    pair = lambda a, b: F.struct(F.col(a).alias("u"), F.col(b).alias("v"))
    return half.select(F.explode(F.array(pair("u", "v"), pair("v", "u"))).alias("_e")).select("_e.u", "_e.v")


@dataclass(frozen=True)
class DataGraph:
    vertices: DataFrame
    edges: DataFrame
    pinned: bool = False
    #: Motif catalogs of a pinned graph.
    catalogs: dict = field(default_factory=dict, compare=False, repr=False)
    #: Whether edges hold both directions; only a directed table that stays so does not.
    symmetric: bool = True

    @classmethod
    def from_edges(cls, df: DataFrame, u: str = "u", v: str = "v", directed: bool = False, symmetrize: bool = True, vertices: DataFrame | None = None) -> DataGraph:
        """Rows with a null end or a loop go; both directions are added unless the table is directed and stays so."""
        both = not directed or symmetrize
        e = df.select(F.col(u).cast("long").alias("u"), F.col(v).cast("long").alias("v")).where("u <> v")
        if both:
            # repeats go while an edge is one row
            e = e.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()
            e = two_way(e)
        else:
            e = e.distinct()
        ids = e.select(F.col("u").alias("id")).union(e.select(F.col("v").alias("id"))).distinct() if vertices is None else vertices.select(F.col(vertices.columns[0]).cast("long").alias("id")).distinct()
        return cls(ids, e, symmetric=both)

    @staticmethod
    def encode_ids(df: DataFrame, u: str, v: str) -> tuple[DataFrame, DataFrame]:
        """Any ids to dense longs: (edges u, v; dictionary key, id). Numbers follow the sorted keys."""
        keys = df.select(F.col(u).cast("string").alias("key")).union(df.select(F.col(v).cast("string").alias("key"))).where("key is not null").distinct()
        book = numbered(keys, ["key"], "id")
        a, b = book.select(F.col("key").alias("ka"), F.col("id").alias("u")), book.select(F.col("key").alias("kb"), F.col("id").alias("v"))
        e = df.select(F.col(u).cast("string").alias("ka"), F.col(v).cast("string").alias("kb"))
        return e.join(a, "ka").join(b, "kb").select("u", "v"), book

    def numbered_edges(self) -> DataFrame:
        """u < v, and k: the place of the edge in sorted order."""
        return numbered(self.edges.where("u < v").select("u", "v"), ["u", "v"], "k")

    @cached_property
    def counts(self):
        """Rows of motif tables, counted from the edges."""
        from graphstitch.operators.counting import Counts

        return Counts(self.edges)

    @cached_property
    def degrees(self) -> DataFrame:
        return self.edges.groupBy("u").agg(F.count("*").alias("degree"))

    @cached_property
    def adjacency(self) -> DataFrame:
        near = self.edges.groupBy("u").agg(F.sort_array(F.collect_list("v")).alias("nbrs"))
        if self.pinned:
            near.persist().count()
        return near

    def pin(self) -> DataGraph:
        """Holds a small graph in the executors. Its true size is then known when joins are planned, so they broadcast it, and
        motif tables built on it are held too."""
        out = DataGraph(self.vertices.persist(), self.edges.persist(), True, symmetric=self.symmetric)
        out.vertices.count(), out.edges.count()
        return out

    def unpin(self) -> None:
        """Lets go of what pin() and the catalogs hold."""
        for c in self.catalogs.values():
            c.unpersist()
        self.catalogs.clear()
        for t in (self.vertices, self.edges, self.adjacency):
            t.unpersist()

    def where_degree(self, least: int) -> DataFrame:
        return self.degrees.where(F.col("degree") >= least).select(F.col("u").alias("id"))

    def restrict(self, ids: DataFrame) -> DataGraph:
        """The subgraph on the given ids."""
        a, b = ids.select(F.col(ids.columns[0]).alias("u")), ids.select(F.col(ids.columns[0]).alias("v"))
        return DataGraph(self.vertices.join(ids.select(F.col(ids.columns[0]).alias("id")), "id", "left_semi"), self.edges.join(a, "u", "left_semi").join(b, "v", "left_semi"), symmetric=self.symmetric)

    def components(self) -> DataFrame:
        """id, component (its least id): least labels spread along edges and through the labels' own labels."""
        labels = cut(self.vertices.select("id", F.col("id").alias("component")))
        while True:
            near = self.edges.join(labels.withColumnRenamed("id", "v"), "v").select(F.col("u").alias("id"), "component").union(labels)
            near = near.groupBy("id").agg(F.min("component").alias("component"))
            own = labels.select(F.col("id").alias("_i"), F.col("component").alias("_c"))
            new = cut(near.join(own, near["component"] == own["_i"]).select("id", F.least("component", "_c").alias("component")))
            done = new.join(own, (new["id"] == own["_i"]) & (new["component"] != own["_c"])).isEmpty()
            forget(labels)
            if done:
                return new
            labels = new

    def largest_component(self) -> DataGraph:
        c = self.components()
        top = c.groupBy("component").count().orderBy(F.desc("count"), "component").limit(1)
        return self.restrict(c.join(top, "component", "left_semi").select("id"))

    def local(self, most: int = LOCAL_EDGES) -> Adjacency:
        """The graph on the driver, refused beyond `most` edge rows."""
        rows = self.edges.limit(most + 1).collect()
        if len(rows) > most:
            raise ValueError(f"more than {most} edge rows: too large for the driver")
        return adjacency(((r["u"], r["v"]) for r in rows), (r["id"] for r in self.vertices.collect()))

    def fingerprint(self) -> str:
        r = self.edges.agg(F.count("*").alias("n"), F.expr("bit_xor(xxhash64(u, v))").alias("x")).first()
        return f"{r['n']}-{r['x'] & 0xFFFFFFFFFFFFFFFF:016x}" if r["n"] else "0"
