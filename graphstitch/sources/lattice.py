"""Square grids and heavy-hex lattices, from ranges or laid over the keys of a table; and their SQL."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphstitch.sources.graph import DataGraph


@dataclass(frozen=True)
class Grid:
    """n x n vertices r * n + c, joined to the right and below."""

    n: int

    @property
    def vertices(self) -> int:
        return self.n * self.n

    def pairs(self) -> list[tuple[int, int]]:
        n = self.n
        return [(r * n + c, r * n + c + s) for r in range(n) for c in range(n) for s, ok in ((1, c < n - 1), (n, r < n - 1)) if ok]

    def half_edges(self, ids: DataFrame) -> DataFrame:
        n, i = self.n, F.col("id")
        to = F.array(F.when(i % n < n - 1, i + 1), F.when(i < n * (n - 1), i + n))
        return ids.select(i.alias("u"), F.explode(to).alias("v")).where("v is not null")

    def sql(self, ids: str) -> str:
        n = self.n
        return f"SELECT id AS u, id + 1 AS v FROM {ids} WHERE id % {n} < {n - 1} UNION ALL SELECT id, id + {n} FROM {ids} WHERE id < {n * (n - 1)}"


@dataclass(frozen=True)
class HeavyHex:
    """`rows` chains of `length` vertices; between two chains, a bridge at every fourth column, shifted on odd rows."""

    rows: int
    length: int

    @property
    def vertices(self) -> int:
        return self.rows * self.length + (self.rows - 1) * self.length // 4

    def pairs(self) -> list[tuple[int, int]]:
        out = [(r * self.length + c, r * self.length + c + 1) for r in range(self.rows) for c in range(self.length - 1)]
        for r in range(self.rows - 1):
            for j in range(self.length // 4):
                bridge, top = self.rows * self.length + r * (self.length // 4) + j, r * self.length + 4 * j + (1 if r % 2 else 3)
                out += [(top, bridge), (top + self.length, bridge)]
        return out

    def snake(self) -> list[int]:
        """Along the first chain, over its last bridge, back along the second, and so on."""
        per, out = self.length // 4, []
        for r in range(self.rows):
            columns = range(1 if r else 0, self.length) if r % 2 == 0 else range(self.length - 1, 0, -1)
            out += [r * self.length + c for c in columns]
            out.append(self.rows * self.length + r * per + (per - 1 if r % 2 == 0 else 0))
        return out[:-1]

    def half_edges(self, ids: DataFrame) -> DataFrame:
        base, length, per = self.rows * self.length, self.length, self.length // 4
        i = F.col("id")
        row = F.floor((i - base) / per)
        column = 4 * ((i - base) % per) + F.when(row % 2 == 0, 3).otherwise(1)
        upper = row * length + column
        to = F.when(i < base, F.array(F.when(i % length < length - 1, i + 1))).otherwise(F.array(upper, upper + length))
        return ids.select(i.alias("u"), F.explode(to.cast("array<bigint>")).alias("v")).where("v is not null")

    def sql(self, ids: str) -> str:
        base, length, per = self.rows * self.length, self.length, self.length // 4
        row = f"((id - {base}) // {per})"
        upper = f"({row} * {length} + 4 * ((id - {base}) % {per}) + CASE WHEN {row} % 2 = 0 THEN 3 ELSE 1 END)"
        return (
            f"SELECT id AS u, id + 1 AS v FROM {ids} WHERE id < {base} AND id % {length} < {length - 1} "
            f"UNION ALL SELECT id, {upper} FROM {ids} WHERE id >= {base} UNION ALL SELECT id, {upper} + {length} FROM {ids} WHERE id >= {base}"
        )


Shape = Grid | HeavyHex
#: The lattices of the experiments by name: shape, and the table and key that carry the vertices.
LATTICES: dict[str, tuple[Shape, str, str]] = {
    "hh156": (HeavyHex(8, 16), "part", "p_partkey"), "hh1990": (HeavyHex(40, 40), "part", "p_partkey"), "hh4485": (HeavyHex(60, 60), "orders", "o_orderkey"),
    "sq1600": (Grid(40), "part", "p_partkey"), "sq3600": (Grid(60), "orders", "o_orderkey"),
}


def of_range(spark: SparkSession, shape: Shape) -> DataGraph:
    ids = spark.range(shape.vertices)
    return DataGraph.from_edges(shape.half_edges(ids), vertices=ids)


def on_table(df: DataFrame, key: str, shape: Shape) -> DataGraph:
    """The lattice on the keys below its size; an edge needs both ends among the keys."""
    ids = df.select(F.col(key).cast("long").alias("id")).where(F.col("id").between(0, shape.vertices - 1)).distinct()
    half = shape.half_edges(ids).join(ids.withColumnRenamed("id", "v"), "v", "left_semi")
    return DataGraph.from_edges(half, vertices=ids)


def lattice(spark: SparkSession, sf_dir: str, name: str) -> DataGraph:
    shape, table, key = LATTICES[name]
    return on_table(spark.read.parquet(f"{sf_dir}/{table}.parquet"), key, shape)


def lattice_sql(name: str) -> str:
    """CTEs ids and edges of a lattice over its table."""
    shape, table, key = LATTICES[name]
    return (
        f"ids AS MATERIALIZED (SELECT {key} AS id FROM {table} WHERE {key} BETWEEN 0 AND {shape.vertices - 1}), half AS ({shape.sql('ids')}), "
        "edges AS MATERIALIZED (SELECT u, v FROM half UNION SELECT v, u FROM half)"
    )
