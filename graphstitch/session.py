"""Sessions and lineage cuts."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Defaults for sessions that we start ourselves; a session as given is never changed.
DEFAULTS = {
    "spark.sql.adaptive.enabled": "true", "spark.sql.adaptive.skewJoin.enabled": "true", "spark.sql.session.timeZone": "UTC",
    "spark.sql.codegen.maxFields": "250", "spark.sql.execution.arrow.pyspark.enabled": "true", "spark.ui.enabled": "false",
}


def get_spark(master: str = "local[*]", **conf: str) -> SparkSession:
    """A session with our defaults; keyword names use __ for the dots."""
    builder = SparkSession.builder.master(master).appName("graphstitch")
    for k, v in (DEFAULTS | {k.replace("__", "."): v for k, v in conf.items()}).items():
        builder = builder.config(k, v)
    return builder.getOrCreate()


def lean(spark: SparkSession) -> SparkSession:
    """A session of the same application and settings whose queries delete their shuffle files when they end, not when the
    driver happens to collect its garbage. The given session is not changed."""
    own = spark.newSession()
    for k, v in spark.conf.getAll.items():
        if k.startswith("spark.sql.") and spark.conf.isModifiable(k):
            own.conf.set(k, v)
    own.conf.set("spark.sql.classic.shuffleDependency.fileCleanup.enabled", "true")
    return own


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share, as the session names it. Only where none is named and Spark runs on this
    machine alone, one of our own; several machines would not see each other's files there."""
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if not path and not held.isEmpty():
        path = held.get()
    if not path:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        path = "file://" + os.path.join(tempfile.gettempdir(), "graphstitch-checkpoints")
    return path.rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder."""
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Materialised as a table in the shared folder, which survives lost executors. Unlike a checkpoint it brings along no
    constraints of the plan before, which double with each round of a loop, and its size is known to the planner."""
    path = shared_path(df.sparkSession, "cut")
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._cut_path = path
    return out


def forget(*tables: DataFrame) -> None:
    """Deletes tables that cut() made and that nothing will read again."""
    for t in tables:
        jvm, session = t.sparkSession._jvm, t.sparkSession._jsparkSession
        path = jvm.org.apache.hadoop.fs.Path(t._cut_path)
        path.getFileSystem(session.sessionState().newHadoopConf()).delete(path, True)
