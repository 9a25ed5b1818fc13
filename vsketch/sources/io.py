"""Readers and writers of edges: Parquet, ORC, CSV, JSON and text lists ``u v`` with # comments."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "u long, v long"


def read_edges(spark: SparkSession, path: str, form: str = "parquet", u: str = "u", v: str = "v") -> DataFrame:
    if form == "text":
        lines = spark.read.text(path).filter(~F.trim("value").startswith("#") & (F.trim("value") != ""))
        parts = F.split(F.trim("value"), r"[\s,]+")
        return lines.select(parts[0].cast("long").alias("u"), parts[1].cast("long").alias("v"))
    if form in ("csv", "json"):
        reader = spark.read.schema(f"{u} long, {v} long")
        rows = reader.csv(path, header=True) if form == "csv" else reader.json(path)
    else:
        rows = spark.read.format(form).load(path)
    return rows.select(F.col(u).cast("long").alias("u"), F.col(v).cast("long").alias("v"))


def write_edges(edges: DataFrame, path: str, form: str = "parquet") -> None:
    if form == "text":
        edges.select(F.concat_ws(" ", "u", "v")).write.mode("overwrite").text(path)
    elif form == "csv":
        edges.write.mode("overwrite").csv(path, header=True)
    else:
        edges.write.mode("overwrite").format(form).save(path)


def save_bucketed(regs: DataFrame, name: str, buckets: int = 16) -> None:
    """A registered table bucketed by x: later joins on x with an equally bucketed side need no shuffle."""
    regs.write.mode("overwrite").bucketBy(buckets, "x").sortBy("x", "j").saveAsTable(name)
