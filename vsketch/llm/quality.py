"""Quality: an ordinal model of graded ratings selects documents by expected grade and tail probability."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import ordinal
from .common import slices, tidy

LEAST_TAIL = 0.1  # rows are rejected only where the model is sure: grades weigh alike in the fit


def quality_model(docs: DataFrame, labels: DataFrame, bound: int = 1500) -> ordinal.Ordinal:
    """Hashed words, word shapes and statistics; the screening leaves words out that don't depend on the grade."""
    return ordinal.train(docs, labels, "quality", bound)


def quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, expected_grade, tail_probability (of more than the lowest grade), kept for every row of docs.

    Null and empty texts are graded like any text, by their statistics.  Equal texts get equal results.
    Without labels, or with one grade, every row has that grade (0 without labels) and is kept."""
    model = quality_model(docs, labels)
    out = ordinal.grade(docs, model)
    kept = F.col("tail") >= LEAST_TAIL if len(model.grades) > 1 else F.lit(True)
    return out.select("doc_id", F.col("expected").alias("expected_grade"), F.col("tail").alias("tail_probability"), kept.alias("kept"))


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows of docs, all columns, that the model does not reject: null and empty texts are judged by their
    statistics, equal texts alike; without labels, or with one grade, all rows stay; see quality."""
    model = quality_model(docs, labels)
    if len(model.grades) < 2:
        return docs
    shared, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index("text")

    def run(batches):
        import numpy as np

        own = shared.value
        for batch in (part for whole in batches for part in slices(whole, at)):
            latent = np.array([own.latent(x or b"") for x in batch.column(at).cast(pa.binary()).to_pylist()])
            yield batch.filter(pa.array(own.tails(latent)[:, 0] >= LEAST_TAIL))

    return docs.mapInArrow(tidy(run), docs.schema)


def toxicity(docs: DataFrame, labels: DataFrame, bound: int = 4000) -> DataFrame:
    """doc_id, expected_severity, tail_probability (of more than the lowest grade), toxic for every row of docs.

    Null and empty texts have no words and so the severity of plain text.  Without labels, or with one
    grade, no row is toxic."""
    model = ordinal.train(docs, labels, "toxic", bound, least=20.0)
    out = ordinal.grade(docs, model)
    toxic = F.col("tail") >= 0.5 if len(model.grades) > 1 else F.lit(False)
    return out.select("doc_id", F.col("expected").alias("expected_severity"), F.col("tail").alias("tail_probability"), toxic.alias("toxic"))
