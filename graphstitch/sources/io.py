"""Reading edge lists in several formats, and writing answers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str, u: str = "u", v: str = "v") -> tuple[DataFrame, DataFrame]:
    """(edges u, v; bad rows as text). fmt: csv with a header, json, orc, parquet, or text with two numbers a line."""
    if fmt in ("orc", "parquet"):
        df = spark.read.format(fmt).load(path).select(F.col(u).alias("u"), F.col(v).alias("v"))
        good, raw = df, F.concat_ws(",", "u", "v")
    elif fmt == "text":
        two = F.split(F.trim("value"), r"[\s,]+")
        df = spark.read.text(path).select(F.try_element_at(two, F.lit(1)).try_cast("long").alias("u"), F.try_element_at(two, F.lit(2)).try_cast("long").alias("v"), "value")
        good, raw = df, F.col("value")
    else:
        schema = f"{u} long, {v} long, _bad string"
        reader = spark.read.schema(schema).option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_bad")
        df = (reader.option("header", True).csv(path) if fmt == "csv" else reader.json(path)).select(F.col(u).alias("u"), F.col(v).alias("v"), "_bad")
        good, raw = df.where("_bad is null"), F.coalesce("_bad", F.lit(""))
    return good.where("u is not null and v is not null").select("u", "v"), df.where("u is null or v is null" + (" or _bad is not null" if "_bad" in df.columns else "")).select(raw.alias("row"))


def write_matches(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite", batches: int = 8) -> None:
    """Answers dealt into folders by the hash of their first column, so that batches can be redone on their own."""
    df.withColumn("batch", F.pmod(F.xxhash64(df.columns[0]), F.lit(batches))).write.mode(mode).format(fmt).partitionBy("batch").save(path)


def noop(df: DataFrame) -> None:
    """Runs a plan to the end without keeping its rows."""
    df.write.format("noop").mode("overwrite").save()
