"""Data graphs derived from the given tables; each comes with the SQL of its edges."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphstitch.sources.graph import DataGraph

SUPPLIER_BASE, LINK_BASE, SOURCE_BASE = 10_000_000, 1_000_000, 2_000_000_000
#: Vectors of a block of the exact nearest-neighbour graph, and of a slice of those that ask.
KNN_BLOCK, KNN_SLICE = 16_384, 512


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def copurchase(spark: SparkSession, sf_dir: str, k: int = 2) -> DataGraph:
    """Parts that share at least k orders. The self-join is per order, whose lines are few; lines are dealt by order once, for
    the repeats and for both sides of the join."""
    a = _t(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("u")).repartition("l_orderkey").distinct()
    pairs = a.join(a.withColumnRenamed("u", "v"), "l_orderkey").where("u < v").groupBy("u", "v").count().where(F.col("count") >= k)
    return DataGraph.from_edges(pairs.select("u", "v"))


def supply(spark: SparkSession, sf_dir: str) -> DataGraph:
    """Parts and the suppliers that ship them; supplier ids are offset."""
    return DataGraph.from_edges(_t(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("u"), (F.col("l_suppkey") + SUPPLIER_BASE).alias("v")))


def trade(spark: SparkSession, sf_dir: str, top: int = 3) -> DataGraph:
    """Each customer nation with the `top` supplier nations that ship it most lines."""
    line = _t(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    o = _t(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    c = _t(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").alias("u"))
    s = _t(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").alias("v"))
    n = line.join(o, "l_orderkey").join(c, "o_custkey").join(s, "l_suppkey").groupBy("u", "v").count()
    w = Window.partitionBy("u").orderBy(F.desc("count"), "v")
    return DataGraph.from_edges(n.withColumn("r", F.row_number().over(w)).where(F.col("r") <= top))


def pagelinks(spark: SparkSession, sf_dir: str) -> DataGraph:
    """Pages and the targets of their links; targets are numbered in sorted order."""
    links = _t(spark, sf_dir, "pages").select(F.col("page_id").alias("u"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), 1)).alias("link")).distinct()
    _, book = DataGraph.encode_ids(links.select("link"), "link", "link")
    return DataGraph.from_edges(links.join(book, links["link"] == book["key"]).select("u", (F.col("id") + LINK_BASE).alias("v")))


def knn(spark: SparkSession, sf_dir: str, k: int = 3, block: int = KNN_BLOCK) -> DataGraph:
    """Each vector with its k nearest by cosine, symmetrised; exact. Vectors are dealt to blocks; a task holds two of them, and
    gives the k nearest in the one for each vector of the other, so nothing grows with the table but the number of tasks. Each
    vector goes to twice as many tasks as there are blocks, as it is stored; a block is large, its cosines come in slices."""
    e = _t(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").alias("x"))
    blocks = max(1, -(-e.count() // block))
    e = e.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks))).withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    # the first of a pair asks, the second answers
    each = e.select("vec_id", "x", F.col("b").alias("i"), F.col("o").alias("j"), F.lit(True).alias("asks")).unionAll(e.select("vec_id", "x", F.col("o").alias("i"), F.col("b").alias("j"), F.lit(False).alias("asks")))

    def nearest(table: pa.Table) -> pa.Table:
        asks = table.column("asks").to_numpy().astype(bool)
        ids = table.column("vec_id").to_numpy()
        x = table.column("x").combine_chunks().flatten().to_numpy().astype(float).reshape(len(ids), -1)
        x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)
        order = np.argsort(ids[~asks], kind="stable")
        v, m = ids[~asks][order], x[~asks][order]
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        for at in range(0, int(asks.sum()) if len(v) else 0, KNN_SLICE):
            u = ids[asks][at : at + KNN_SLICE]
            cos = np.round(x[asks][at : at + KNN_SLICE] @ m.T, 9)
            cos[u[:, None] == v] = -2
            n = min(k, len(v))
            # all that reach the n-th largest, then the n first of them by cosine and id
            r, c = np.nonzero(cos >= np.partition(cos, len(v) - n, axis=1)[:, len(v) - n, None])
            best = np.lexsort((c, -cos[r, c], r))
            r, c = r[best], c[best]
            first = np.arange(len(r)) - np.searchsorted(r, r) < n
            out.append((u[r[first]], v[c[first]], cos[r[first], c[first]]))
        return pa.table(dict(zip(("u", "v", "cos"), map(np.concatenate, zip(*out)))))

    found = each.groupBy("i", "j").applyInArrow(nearest, "u long, v long, cos double").where("cos > -2")
    w = Window.partitionBy("u").orderBy(F.desc("cos"), "v")
    return DataGraph.from_edges(found.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).select("u", "v"))


def coactive(spark: SparkSession, sf_dir: str, seconds: int = 60) -> DataGraph:
    """Users of consecutive events at most `seconds` apart. The event before is in the same span of time or is the last one of
    the span before, so no window runs over all rows."""
    return DataGraph.from_edges(consecutive(_t(spark, sf_dir, "events"), seconds))


def consecutive(events: DataFrame, seconds: int) -> DataFrame:
    e = events.select("event_id", F.col("user_id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t")).withColumn("b", F.floor(F.col("t") / (seconds * 1_000_000)).cast("long"))
    w = Window.partitionBy("b").orderBy("t", "event_id")
    e = e.withColumns({"pu": F.lag("user_id").over(w), "pt": F.lag("t").over(w)})
    last = e.groupBy((F.col("b") + 1).alias("b")).agg(F.max(F.struct("t", "event_id", "user_id")).alias("last"))
    e = e.join(last, "b", "left").select("user_id", "t", F.coalesce("pu", "last.user_id").alias("pu"), F.coalesce("pt", "last.t").alias("pt"))
    return e.where((F.col("t") - F.col("pt")) <= seconds * 1_000_000).select(F.col("pu").alias("u"), F.col("user_id").alias("v"))


def nations(spark: SparkSession, sf_dir: str) -> DataGraph:
    """The tree customer - nation - region; ids of the three levels are offset."""
    c = _t(spark, sf_dir, "customer").select((F.col("c_custkey") + 10_000).alias("u"), (F.col("c_nationkey") + 100).alias("v"))
    n = _t(spark, sf_dir, "nation").select((F.col("n_nationkey") + 100).alias("u"), F.col("n_regionkey").alias("v"))
    return DataGraph.from_edges(c.unionAll(n))


def doc_sources(spark: SparkSession, sf_dir: str) -> DataGraph:
    """Documents and their sources (numbered by their digits): a bipartite graph with one hub."""
    d = _t(spark, sf_dir, "documents").select(F.col("doc_id").alias("u"), (F.regexp_extract("source", r"(\d+)", 1).cast("long") + SOURCE_BASE).alias("v"))
    return DataGraph.from_edges(d)


def turns(spark: SparkSession, sf_dir: str) -> DataGraph:
    """Chains of the turns of each conversation: conv_id * 1000 + turn."""
    t = _t(spark, sf_dir, "conversations").select("conv_id", "turn")
    nxt = t.select("conv_id", (F.col("turn") - 1).alias("turn"), F.lit(1).alias("_x")).distinct()
    return DataGraph.from_edges(t.join(nxt, ["conv_id", "turn"], "left_semi").select((F.col("conv_id") * 1000 + F.col("turn")).alias("u"), (F.col("conv_id") * 1000 + F.col("turn") + 1).alias("v")))


def _both(half: str) -> str:
    return f"half AS MATERIALIZED ({half}), edges AS MATERIALIZED (SELECT u, v FROM half WHERE u <> v UNION SELECT v, u FROM half WHERE u <> v), ids AS (SELECT DISTINCT u AS id FROM edges)"


SQL = {
    "copurchase": _both("SELECT a.l_partkey AS u, b.l_partkey AS v FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(*) >= 2"),
    "supply": _both(f"SELECT DISTINCT l_partkey AS u, l_suppkey + {SUPPLIER_BASE} AS v FROM lineitem"),
    "trade": _both("SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v FROM (SELECT u, v, row_number() OVER (PARTITION BY u ORDER BY n DESC, v) AS r FROM (SELECT c_nationkey AS u, s_nationkey AS v, count(*) AS n FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey GROUP BY 1, 2)) WHERE r <= 3"),
    "pagelinks": "l AS MATERIALIZED (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS link FROM pages), "
    + _both(f"SELECT page_id AS u, {LINK_BASE} + dense_rank() OVER (ORDER BY link) - 1 AS v FROM l"),
    "knn": _both("SELECT u, v FROM (SELECT a.vec_id AS u, b.vec_id AS v, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) DESC, b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 3"),
    "coactive": _both("SELECT pu AS u, user_id AS v FROM (SELECT user_id, epoch_us(ts) AS t, lag(user_id) OVER w AS pu, lag(epoch_us(ts)) OVER w AS pt FROM events WINDOW w AS (ORDER BY ts, event_id)) WHERE t - pt <= 60000000"),
    "nations": _both("SELECT c_custkey + 10000 AS u, CAST(c_nationkey + 100 AS BIGINT) AS v FROM customer UNION ALL SELECT n_nationkey + 100, n_regionkey FROM nation"),
    "doc_sources": _both(f"SELECT doc_id AS u, CAST(regexp_extract(source, '(\\d+)', 1) AS BIGINT) + {SOURCE_BASE} AS v FROM documents"),
    "turns": _both("SELECT a.conv_id * 1000 + a.turn AS u, b.conv_id * 1000 + b.turn AS v FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1"),
}
GRAPHS = {f.__name__: f for f in (copurchase, supply, trade, pagelinks, knn, coactive, nations, doc_sources, turns)}
