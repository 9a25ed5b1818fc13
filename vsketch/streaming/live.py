"""Live forms: accumulation into a sketch table, windowed degrees, late and repeated edges, stream joins.

State and table are maxima, so order, repeats and replayed batches do no harm."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import hash_word, index_of, rank_of
from ..functions.spec import SketchSpec
from ..operators.balls import shared_table
from ..operators.vst import Vst, merge
from ..sources.build import arcs


def _root(spark: SparkSession) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")
    return f"{root.rstrip('/')}/vsketch/stream-{uuid.uuid4().hex}"


def run_now(stream: DataFrame, mode: str = "append", last_only: bool = False) -> DataFrame:
    """Run a streaming plan over what is there, once; all rows it emitted (complete mode: those of the last batch)."""
    spark, root = stream.sparkSession, _root(stream.sparkSession)

    def write(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(f"{root}/out/batch={batch}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).foreachBatch(write).start()
    query.awaitTermination()
    rows = spark.read.schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.IntegerType())])).parquet(f"{root}/out")
    if last_only:
        last = rows.agg(F.max("batch").alias("batch"))
        rows = rows.join(F.broadcast(last), "batch")
    return rows.drop("batch")


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream; timestamps without a zone are cast, as watermarks need."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    rows = spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parquet*")
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def edge_stream(edges: DataFrame, files: int = 4) -> DataFrame:
    """Edges written as files and read back as a stream of several batches."""
    spark, path = edges.sparkSession, f"{_root(edges.sparkSession)}/edges"
    edges.select("u", "v").repartition(files).write.parquet(path)
    return spark.readStream.schema("u long, v long").option("maxFilesPerTrigger", 1).parquet(path)


def register_updates(edges: DataFrame, spec: SketchSpec) -> DataFrame:
    """x, j, rho: grouped maxima, as a streaming aggregate whose update mode emits registers that grew."""
    word = hash_word(F.col("y"), spec)
    return merge(arcs(edges).select("x", index_of(word, spec).alias("j"), rank_of(word, spec).alias("rho")), ["x"])


def accumulate_stream(edges: DataFrame, spec: SketchSpec) -> Vst:
    """The sketch table after all batches: a log of updates, merged by maximum."""
    log = run_now(register_updates(edges, spec), "update")
    return Vst(merge(log, ["x"]), spec)


def windowed_degrees(events: DataFrame, window, late: str = "10 minutes") -> DataFrame:
    """start, end, user_id, n, top: rows of each user in a window and their largest value; window is a window column."""
    marked = events.withWatermark("ts", late)
    got = marked.groupBy(window.alias("w"), "user_id").agg(F.count("*").alias("n"), F.max("value").alias("top"))
    return got.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n", "top")


def without_repeats(events: DataFrame, key: list[str], late: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(key)


def live_proximity(events: DataFrame, seconds: int, late: str = "10 minutes") -> DataFrame:
    """u, v: pairs of users whose events lie under ``seconds`` apart, from a stream-stream interval join."""
    a = events.select(F.col("ts").alias("ta"), F.col("user_id").alias("ua")).withWatermark("ta", late)
    b = events.select(F.col("ts").alias("tb"), F.col("user_id").alias("ub")).withWatermark("tb", late)
    cell = lambda c, k: (F.floor(F.unix_micros(c) / F.lit(seconds * 1_000_000)) - k).cast("long")
    one = a.withColumn("cell_a", cell("ta", 0))
    two = b.withColumn("cell_b", F.explode(F.array(cell("tb", 0), cell("tb", 1))))  # own cell and the one before
    near = F.expr(f"cell_a = cell_b and ua <> ub and tb >= ta and tb < ta + interval {seconds} seconds")
    return one.join(two, near).select(F.least("ua", "ub").alias("u"), F.greatest("ua", "ub").alias("v"))


def edge_triangles_live(edges: DataFrame, vst: Vst) -> DataFrame:
    """Triangle estimates of fresh edges against a written snapshot of the table (a batch at a time)."""
    from ..operators.triangles import edge_triangles

    return edge_triangles(edges, Vst(shared_table(vst.regs, "snapshot"), vst.spec), "ie_packed")
