"""The learned block classifier: byte statistics of a block, a multinomial logistic model, scores that order and never exclude.

Defined results: an empty or null block has all-zero features; a type without training blocks gets no score; with no
training rows fitting is an error.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.ml.classification import LogisticRegression, LogisticRegressionModel
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, StructField, StructType


def statistics(block: bytes | None) -> np.ndarray:
    """Shares of 32 byte ranges, then entropy, share of high bits, of printable bytes and of repeats of the byte before."""
    data = np.frombuffer(block or b"", np.uint8)
    if not len(data):
        return np.zeros(36)
    counts = np.bincount(data, minlength=256) / len(data)
    some = counts[counts > 0]
    return np.concatenate([counts.reshape(32, 8).sum(axis=1), [-(some * np.log2(some)).sum() / 8, counts[128:].sum(), counts[32:127].sum(), (data[1:] == data[:-1]).mean() if len(data) > 1 else 0.0]])


def with_features(blocks: DataFrame) -> DataFrame:
    """blocks (payload binary, and others) with ``features``."""
    schema = StructType([*blocks.schema.fields, StructField("features", ArrayType(DoubleType()))])

    def run(batches):
        for b in batches:
            made = [statistics(x) for x in b.column("payload").to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([list(x) for x in made], pa.list_(pa.float64()))], names=[*b.schema.names, "features"])

    return blocks.mapInArrow(run, schema)


def train(labelled: DataFrame, types: list[str], *, iterations: int = 40) -> LogisticRegressionModel:
    """A model over labelled blocks (type, payload); classes are numbered as in ``types``. The fit runs over all rows given."""
    number = F.array_position(F.array(*[F.lit(t) for t in types]), F.col("type")) - 1
    rows = with_features(labelled.select("type", "payload")).select(number.cast("double").alias("label"), array_to_vector("features").alias("features")).where("label >= 0")
    return LogisticRegression(maxIter=iterations, regParam=1e-4, family="multinomial").fit(rows)


def score(blocks: DataFrame, model: LogisticRegressionModel, types: list[str]) -> DataFrame:
    """blocks with ``confidence`` (map of type to 1..100) and ``guess``, the likeliest type. Without a model all types
    score 100."""
    if model is None:
        return blocks.withColumn("confidence", F.create_map(*[x for t in types for x in (F.lit(t), F.lit(100))])).withColumn("guess", F.lit(None).cast("string"))
    names = F.array(*[F.lit(t) for t in types])
    rows = model.transform(with_features(blocks).withColumn("features", array_to_vector("features")))
    marks = F.transform(vector_to_array("probability"), lambda p: F.greatest(F.lit(1), F.round(p * 100).cast("int")))
    return rows.withColumn("confidence", F.map_from_arrays(F.slice(names, F.lit(1), F.size(marks)), marks)).withColumn("guess", F.get(names, F.col("prediction").cast("int"))).select(*blocks.columns, "confidence", "guess")


def confusion(scored: DataFrame) -> DataFrame:
    """truth, guess, n over scored blocks with a column ``type``."""
    return scored.groupBy(F.col("type").alias("truth"), "guess").agg(F.count(F.lit(1)).alias("n"))
