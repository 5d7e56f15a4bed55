"""Streams of events as streams of edges: windows, dedup, joins, running degrees, and matches that use a new edge.

Each helper takes and returns streaming DataFrames; `drain` runs one to the end of what is there and returns its rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphstitch.plans.pattern import Pattern
from graphstitch.session import shared_path

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """A file stream over the table `events`."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs to the end of the input; rows go to Parquet in the shared folder."""
    spark = stream.sparkSession
    path, state = shared_path(spark, "stream"), shared_path(spark, "stream-state")
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start()
    else:
        query = stream.writeStream.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(path)).option("checkpointLocation", state).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)


def edges(stream: DataFrame, seconds: int, sink: Callable[[DataFrame, int], None], state: str):
    """Edges between consecutive users of each micro-batch; row-based windows run on the batch, not on the stream."""
    from graphstitch.sources.derive import consecutive

    return stream.writeStream.foreachBatch(lambda df, i: sink(consecutive(df, seconds).where("u <> v").distinct(), i)).option("checkpointLocation", state).trigger(availableNow=True).start()


def windowed(stream: DataFrame, kind: str, size: str = "1 hour", slide: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """Events per tumbling or sliding window, or per user's session (gap = size); closed windows are given out."""
    s = stream.withWatermark("ts", delay)
    w = {"tumbling": lambda: F.window("ts", size), "sliding": lambda: F.window("ts", size, slide), "session": lambda: F.session_window("ts", size)}[kind]()
    key = ["user_id"] if kind == "session" else []
    return s.groupBy(w.alias("w"), *key).agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), F.col("w.end").cast("timestamp_ntz").alias("end"), *key, "n")


def dedup(stream: DataFrame, keys: list[str], delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys)


def interval_join(a: DataFrame, b: DataFrame, seconds: int, delay: str = "1 hour") -> DataFrame:
    """Pairs of events of one user, the second later by at most `seconds`: two-edge paths in time."""
    left = a.select(F.col("user_id"), F.col("event_id").alias("a"), F.col("ts").alias("ta")).withWatermark("ta", delay)
    right = b.select(F.col("user_id").alias("ub"), F.col("event_id").alias("b"), F.col("ts").alias("tb")).withWatermark("tb", delay)
    near = (F.col("user_id") == F.col("ub")) & (F.col("a") != F.col("b")) & (F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr(f"INTERVAL {seconds} SECONDS"))
    return left.join(right, near).select("user_id", "a", "b")


def enrich(stream: DataFrame, static: DataFrame, stream_key: str, static_key: str) -> DataFrame:
    """Stream rows with the rows of a static table."""
    return stream.join(static, stream[stream_key] == static[static_key])


def degrees(stream: DataFrame, key: str = "user_id", timeout: str = "NoTimeout") -> DataFrame:
    """Running number of rows per key."""

    def update(who: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(p) for p in parts)
        state.update((n,))
        yield pd.DataFrame({key: [who[0]], "degree": [n]})

    return stream.groupBy(key).applyInPandasWithState(update, f"{key} long, degree long", "n long", "update", timeout)


def delta_matches(new: DataFrame, old: DataFrame, pattern: Pattern) -> DataFrame:
    """Monomorphisms that use at least one new edge, each once: the first pattern edge on new edges is edge i, edges before it
    lie on old ones and edges after it on either. `old` and `new` are symmetric and disjoint."""
    from graphstitch.operators.semantics import names

    order = sorted(pattern.edges)
    both, out = old.unionAll(new), None
    for i in range(len(order)):
        todo, bound, seen = [(e, new if k == i else old if k < i else both) for k, e in enumerate(order)], None, []
        todo.insert(0, todo.pop(i))  # the new edge first: it is the smallest table
        while todo:
            k = next(k for k, ((a, b), _) in enumerate(todo) if bound is None or a in seen or b in seen)
            (a, b), table = todo.pop(k)
            if bound is None:
                bound, seen = table.select(F.col("u").alias(f"v{a}"), F.col("v").alias(f"v{b}")), [a, b]
                continue
            e = table.select(F.col("u").alias("_u"), F.col("v").alias("_v"))
            if a in seen and b in seen:
                bound = bound.join(e, (bound[f"v{a}"] == e["_u"]) & (bound[f"v{b}"] == e["_v"]), "left_semi")
                continue
            at, to = (a, b) if a in seen else (b, a)
            apart = ~F.col("_v").isin(*[F.col(c) for c in names(seen)])
            bound = bound.join(e, (bound[f"v{at}"] == e["_u"]) & apart).select(*names(seen), F.col("_v").alias(f"v{to}"))
            seen.append(to)
        bound = bound.select(*names(range(pattern.n)))
        out = bound if out is None else out.unionAll(bound)
    return out


def incremental_match(stream: DataFrame, pattern: Pattern, state_dir: str):
    """stream: edges u, v. Every batch adds the matches that use one of its edges; state is Parquet by batch, and a batch that
    runs again overwrites its own part."""
    spark = stream.sparkSession
    edge_dir, match_dir = f"{state_dir}/edges", f"{state_dir}/matches"

    def step(df: DataFrame, batch: int) -> None:
        session = df.sparkSession
        e = df.select("u", "v").where("u <> v")
        e = e.union(e.select("v", "u")).distinct()
        session.createDataFrame([], "u long, v long, batch long").write.mode("append").partitionBy("batch").parquet(edge_dir)
        old = session.read.schema("u long, v long, batch long").parquet(edge_dir).where(F.col("batch") < batch).select("u", "v")
        new = e.join(old, ["u", "v"], "left_anti")
        new.write.mode("overwrite").parquet(f"{edge_dir}/batch={batch}")
        new = session.read.schema("u long, v long").parquet(f"{edge_dir}/batch={batch}")
        delta_matches(new, old, pattern).write.mode("overwrite").parquet(f"{match_dir}/batch={batch}")

    query = stream.writeStream.foreachBatch(step).option("checkpointLocation", f"{state_dir}/log").trigger(availableNow=True).start()
    query.awaitTermination()
    cols = ", ".join(f"v{i} long" for i in range(pattern.n))
    return spark.read.schema(cols).option("recursiveFileLookup", True).parquet(match_dir)


def late_report(query) -> int:
    """Rows that came behind the watermark and were dropped, over all batches of a query."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])


def latest_before(rows: DataFrame, readings: DataFrame, key: str, time: str = "ts") -> DataFrame:
    """As-of join: each row with the last reading (column q) of its key at or before its time; one shuffle and a sort."""
    both = rows.select(*rows.columns, F.lit(None).cast("double").alias("q"), F.lit(1).alias("_o")).unionByName(readings.select(key, time, "q", F.lit(0).alias("_o")), allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(time, "_o").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("q", F.last("q", ignorenulls=True).over(w)).where("_o = 1").drop("_o")
