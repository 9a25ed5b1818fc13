"""Shared plumbing: shared-folder tables, Arrow mapping, unique row keys."""

from __future__ import annotations

import ctypes
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: dict[str, str] = {}


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.
    Only where that is unset: the warehouse on a cluster, a temporary folder in local mode."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _OWN:
        if spark.sparkContext.master.startswith("local["):
            _OWN[app] = tempfile.mkdtemp(prefix="vsketch-")
        else:
            _OWN[app] = f"{spark.conf.get('spark.sql.warehouse.dir')}/_vsketch"
    return _OWN[app]


def table(frame: DataFrame, tag: str) -> DataFrame:
    """Write ``frame`` to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = frame.sparkSession
    path = f"{shared_dir(spark)}/vsketch/{tag}-{uuid.uuid4().hex}"
    frame.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(frame.schema).parquet(path)


def tidy(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """The same function, which returns freed memory to the system at its end: a Python worker outlives its
    task and would keep it beside the next stage's own."""

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
            if trim is not None:
                trim(0)

    return wrapped


def arrow_map(frame: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], dict | None]], schema: str, slice_by: str | None = None) -> DataFrame:
    """``make()`` runs once a task and returns a function from a batch to columns by name.

    slice_by: a text column; the function gets slices of bounded bytes of it instead of whole batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = make()
        for whole in batches:
            for batch in [whole] if slice_by is None else slices(whole, whole.schema.get_field_index(slice_by)):
                if batch.num_rows and (out := step(batch)) is not None:
                    yield pa.RecordBatch.from_arrays(list(out.values()), names=list(out))

    return frame.mapInArrow(tidy(run), schema)


def texts(batch: pa.RecordBatch, name: str = "text") -> list[bytes]:
    """UTF-8 of each text; null counts as empty."""
    return [x or b"" for x in batch.column(batch.schema.get_field_index(name)).cast(pa.binary()).to_pylist()]


def slices(batch: pa.RecordBatch, at: int, most: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The batch in order, in slices of at most ``most`` bytes in column ``at`` (a longer text is one alone), so
    that what a task holds beside the batch doesn't grow with the rows of a batch."""
    ends = np.cumsum(np.asarray(pc.binary_length(batch.column(at)).fill_null(0)), dtype=np.int64)
    lo = 0
    while lo < len(ends):
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + most, "right")))
        yield batch.slice(lo, hi - lo)
        lo = hi


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def unique_ids(docs: DataFrame) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """(doc_id, text) with a unique, non-null doc_id, and a function that brings results back.

    Usual tables pass through.  Where doc_id is null or repeats, equal rows become one row with a
    surrogate that ascends by (doc_id, nulls first, then text); results are then copied to all of them."""
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if not base.groupBy("doc_id").count().filter("count > 1 or doc_id is null").limit(1).take(1):
        return base, lambda out: out
    rows = base.groupBy("doc_id", "text").count().orderBy(F.col("doc_id").asc_nulls_first(), F.col("text").asc_nulls_first())
    rows = table(rows.select(F.monotonically_increasing_id().alias("uid"), "doc_id", "text", "count"), "ids")
    keys = rows.select("uid", F.col("doc_id").alias("own_id"), "count")

    def back(out: DataFrame) -> DataFrame:
        rest = [c for c in out.columns if c != "doc_id"]
        if "component_id" in rest:
            named = keys.select(F.col("uid").alias("component_id"), F.col("own_id").alias("component_own"))
            out = out.join(named, "component_id").drop("component_id").withColumnRenamed("component_own", "component_id")
        out = out.withColumnRenamed("doc_id", "uid").join(keys, "uid")
        return out.withColumn("copy", F.explode(F.expr("sequence(1, int(count))"))).select(F.col("own_id").alias("doc_id"), *rest)

    return rows.select(F.col("uid").alias("doc_id"), "text"), back


def without(docs: DataFrame, gone: DataFrame, key: str = "doc_id", most: int = 4_000_000) -> DataFrame:
    """Rows of docs whose key is not in gone (one long column): by a broadcast array of up to ``most`` keys
    (32 MB), by an anti join beyond that."""
    gone = table(gone.select(key).distinct(), "gone")
    if gone.count() > most:
        return docs.join(gone, key, "left_anti").select(*docs.columns)
    shared = docs.sparkSession.sparkContext.broadcast(np.sort(np.asarray(gone.toArrow().column(0))))
    at = docs.columns.index(key)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = shared.value
        for batch in batches:
            own = np.asarray(batch.column(at).cast(pa.int64()))
            found = keys[np.minimum(np.searchsorted(keys, own), len(keys) - 1)] == own if len(keys) else np.zeros(len(own), bool)
            yield batch.filter(pa.array(~found))

    return docs.mapInArrow(tidy(run), docs.schema)
