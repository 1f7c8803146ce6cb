"""Cost and accuracy measures of an update against retraining."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from delprop.functions.vector import array_of, dot
from delprop.operators.train import sample_factor
from delprop.scratch import stored
from delprop.spec import ModelSpec


def timed(call: Callable[[], object]) -> tuple[object, float]:
    """Result and wall seconds; a DataFrame result is materialised."""
    began = time.perf_counter()
    out = call()
    if isinstance(out, DataFrame):
        out = stored(out, "timed")
    return out, time.perf_counter() - began


def speed_up(retrain_seconds: float, method_seconds: float) -> float:
    return retrain_seconds / method_seconds if method_seconds else float("inf")


def score(w: np.ndarray, spec: ModelSpec) -> Column:
    """Prediction: value (linear), -1 or 1 (binary), class (softmax)."""
    x = F.col("features")
    if spec.kind == "softmax":
        logits = F.array(*[dot(x, array_of(row)) for row in w.reshape(spec.q, spec.m)])
        return (F.array_position(logits, F.array_max(logits)) - 1).cast("double")
    z = dot(x, array_of(w))
    return z if spec.kind == "linear" else F.when(z >= 0, 1.0).otherwise(-1.0)


def predict(rows: DataFrame, w: np.ndarray, spec: ModelSpec) -> DataFrame:
    return rows.withColumn("prediction", score(w, spec))


def mse(rows: DataFrame, w: np.ndarray, spec: ModelSpec) -> DataFrame:
    return predict(rows, w, spec).agg(F.avg(F.pow(F.col("label") - F.col("prediction"), F.lit(2.0))).alias("mse"))


def accuracy(rows: DataFrame, w: np.ndarray, spec: ModelSpec) -> DataFrame:
    return predict(rows, w, spec).agg(F.avg((F.col("prediction") == F.col("label")).cast("double")).alias("accuracy"))


def compare(models: DataFrame, truth: DataFrame) -> DataFrame:
    """(model_id, distance, cosine, sign_flips, largest_change) of long-form ``models`` against long-form ``truth`` (pos, value)."""
    both = models.join(truth.select("pos", F.col("value").alias("want")), "pos")
    dots = both.groupBy("model_id").agg(
        F.sqrt(F.sum(F.pow(F.col("value") - F.col("want"), F.lit(2.0)))).alias("distance"),
        F.sum(F.col("value") * F.col("want")).alias("xy"),
        F.sqrt(F.sum(F.col("value") * F.col("value")) * F.sum(F.col("want") * F.col("want"))).alias("norms"),
        F.sum((F.signum("value") != F.signum("want")).cast("long")).alias("sign_flips"),
        F.max(F.abs(F.col("value") - F.col("want"))).alias("largest_change"),
    )
    cosine = F.when(F.col("norms") != 0, F.try_divide("xy", "norms"))
    return dots.select("model_id", "distance", cosine.alias("cosine"), "sign_flips", "largest_change")


def distance(w: np.ndarray, truth: np.ndarray) -> float:
    return float(np.linalg.norm(w - truth))


def cosine(w: np.ndarray, truth: np.ndarray) -> float | None:
    size = np.linalg.norm(w) * np.linalg.norm(truth)
    return float(w @ truth / size) if size else None


def capture_bytes(frame: DataFrame) -> DataFrame:
    """Bytes of captured arrays: one row with the total and the number of blocks."""
    arrays = [f.name for f in frame.schema.fields if f.dataType.typeName() == "array"]
    each = sum((F.size(c) for c in arrays), F.lit(0)) * 8
    return frame.agg(F.sum(each.cast("long")).alias("bytes"), F.count("*").alias("blocks"))


def convergence(trajectory: DataFrame) -> DataFrame:
    """(t, step): length of each parameter step of ``trajectory`` (t, w); at most as many rows as iterations."""
    before = F.lag("w").over(Window.orderBy("t"))
    rows = trajectory.withColumn("before", before).where("before is not null")
    return rows.select("t", F.sqrt(F.aggregate(F.zip_with("w", "before", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)).alias("step"))


def deletion_rate(samples: DataFrame, removals: DataFrame) -> DataFrame:
    gone = removals.select("sample_id").distinct().withColumn("gone", F.lit(1))
    return samples.join(gone, "sample_id", "left").agg(F.count("*").alias("n"), F.count("gone").alias("removed"), (F.count("gone") / F.count("*")).alias("rate"))


def rank_summary(factors: DataFrame) -> DataFrame:
    return factors.agg(F.min("r").alias("least"), F.percentile_approx("r", 0.5).alias("median"), F.max("r").alias("most"), F.avg("r").alias("mean"))


def passes(spec: ModelSpec, n: int) -> float:
    return spec.tau * (spec.batch_size or n) / n


def sample_influence(samples: DataFrame, w: np.ndarray, spec: ModelSpec, k: int) -> DataFrame:
    """The ``k`` samples with the longest gradients."""
    factor, x = sample_factor(spec, w), F.col("features")
    square = F.pow(factor, F.lit(2.0)) if spec.kind != "softmax" else dot(factor, factor)
    return samples.select("sample_id", F.sqrt(square * dot(x, x)).alias("gradient_norm")).orderBy(F.desc("gradient_norm"), "sample_id").limit(k)
