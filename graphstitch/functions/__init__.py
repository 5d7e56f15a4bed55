"""Scalar, aggregate and table functions over mappings."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import BooleanType, DoubleType

from graphstitch.plans.backtrack import adjacency, embeddings
from graphstitch.plans.pattern import Pattern


def edge_code(u, v, n: int = 1 << 31) -> Column:
    """One number for an undirected edge."""
    return F.least(u, v) * F.lit(n) + F.greatest(u, v)


def vertex_set(*cols) -> Column:
    return F.sort_array(F.array(*cols))


@pandas_udf(BooleanType())
def all_distinct(values: pd.Series) -> pd.Series:
    """Are all values of an array different? A cross-check of the built-in form."""
    return values.map(lambda x: len(set(x)) == len(x))


@pandas_udf(DoubleType())
def fidelity(q: pd.Series) -> float:
    """Product of factors, as a grouped aggregate."""
    return float(q.prod())


def register(spark: SparkSession, edges: list[tuple[int, int]] | None = None) -> None:
    """SQL names: canonical_edge, canonical_set, all_distinct, fidelity; with edges of a small graph, also the table function
    backtrack(pattern text)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION canonical_edge(u BIGINT, v BIGINT) RETURNS BIGINT RETURN least(u, v) * 2147483648 + greatest(u, v)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION canonical_set(vs ARRAY<BIGINT>) RETURNS ARRAY<BIGINT> RETURN sort_array(vs)")
    spark.udf.register("all_distinct", all_distinct)
    spark.udf.register("fidelity", fidelity)
    if edges is not None:
        data = adjacency(edges)

        @udtf(returnType="mapping array<bigint>")
        class Backtrack:
            def eval(self, text: str):
                p = Pattern.from_text(text)
                for m in embeddings(p.adj, data):
                    yield ([m[i] for i in range(p.n)],)

        spark.udtf.register("backtrack", Backtrack)


def per_component(edges, components, pattern: Pattern):
    """Matches component by component (grouped map); a component must fit one task."""
    cols = [f"v{i}" for i in range(pattern.n)]

    def run(part: pd.DataFrame) -> pd.DataFrame:
        found = [[m[i] for i in range(pattern.n)] for m in embeddings(pattern.adj, adjacency(zip(part["u"], part["v"])))]
        return pd.DataFrame(found, columns=cols, dtype="int64")

    joined = edges.join(components.withColumnRenamed("id", "u"), "u")
    return joined.groupBy("component").applyInPandas(run, ", ".join(f"{c} long" for c in cols))
