"""Batch schedules: pure functions of (sample_id, seed), so deletions never move a row to another batch."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from delprop.functions.hashing import uniform
from delprop.spec import ModelSpec


def batch_id(key: Column, spec: ModelSpec, n: int) -> Column:
    """The batch of a row in one pass."""
    return F.floor(uniform(key, spec.seed) * spec.batches(n)).cast("int")


def assign(samples: DataFrame, spec: ModelSpec, n: int) -> DataFrame:
    """``samples`` with ``block_id``; iteration ``t`` uses the rows of block ``t`` modulo ``spec.blocks(n)``.

    ``n`` is the size of the undeleted training set.  Only blocks that some
    iteration uses are produced.
    """
    key, k = F.col("sample_id"), spec.batches(n)
    if spec.schedule == "full":
        return samples.withColumn("block_id", F.lit(0))
    if spec.schedule == "cyclic":
        return samples.withColumn("block_id", batch_id(key, spec, n)).where(F.col("block_id") < spec.tau)
    if spec.schedule == "reshuffle":
        passes = -(-spec.tau // k)
        places = F.transform(F.sequence(F.lit(0), F.lit(passes - 1)), lambda p: (p * k + F.floor(uniform(key, F.concat(F.lit(spec.seed), p.cast("string"))) * k)).cast("int"))
        return samples.withColumn("block_id", F.explode(F.filter(places, lambda b: b < spec.tau)))
    if spec.schedule == "sampled":
        # the hits of a row are found before it is repeated
        hits = F.filter(F.sequence(F.lit(0), F.lit(spec.tau - 1)), lambda t: uniform(key, F.concat(F.lit(spec.seed), t.cast("string"))) < F.lit(spec.batch_size / n))
        return samples.withColumn("block_id", F.explode(hits))
    # one sample an iteration: the first rows by hash; their number is bounded by the iterations
    first = order_of_singles(samples, spec, n)
    return samples.join(F.broadcast(first), "sample_id")


def order_of_singles(samples: DataFrame, spec: ModelSpec, n: int) -> DataFrame:
    """(sample_id, block_id) of the at most ``tau`` rows that a one-sample schedule touches."""
    luck = uniform(F.col("sample_id"), spec.seed)
    picked = samples.select("sample_id", luck.alias("u")).orderBy("u", "sample_id").limit(spec.blocks(n)).collect()
    rows = [(r.sample_id, i) for i, r in enumerate(sorted(picked, key=lambda r: (r.u, r.sample_id)))]
    return samples.sparkSession.createDataFrame(rows, "sample_id bigint, block_id int")


def steps(spec: ModelSpec, n: int, spark) -> DataFrame:
    """(t, block_id) for every iteration."""
    return spark.range(spec.tau).select(F.col("id").cast("int").alias("t"), (F.col("id") % spec.blocks(n)).cast("int").alias("block_id"))


def survivor_counts(blocked: DataFrame, removals: DataFrame) -> DataFrame:
    """(block_id, total, removed, left): how many rows each block keeps; unknown ids do nothing, duplicates count once."""
    gone = removals.select("sample_id").distinct().withColumn("gone", F.lit(1))
    return (
        blocked.select("sample_id", "block_id")
        .join(gone, "sample_id", "left")
        .groupBy("block_id")
        .agg(F.count("*").alias("total"), F.count("gone").alias("removed"))
        .withColumn("left", F.col("total") - F.col("removed"))
    )
