"""Readers for the given tables and for user sets, and sinks for captures and models."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Rows up to which a dimension table of the star is offered for broadcast; Spark's own size check still decides.
STAR = ("orders", "part", "supplier", "customer")
#: Parts or suppliers up to this number are sent to every task by :func:`lean_star`; more are joined by a shuffle.
BROADCAST_ROWS = 2_000_000


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def star(spark: SparkSession, folder: str) -> DataFrame:
    """lineitem with its order, part, supplier and customer; every key is an equi-join, so the optimizer picks the strategy."""
    t = {name: table(spark, folder, name) for name in ("lineitem", *STAR)}
    return (
        t["lineitem"]
        .join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey"))
        .join(t["part"], F.col("l_partkey") == F.col("p_partkey"))
        .join(t["supplier"], F.col("l_suppkey") == F.col("s_suppkey"))
        .join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
    )


def lean_star(spark: SparkSession, folder: str, codes: dict[str, Column] | None = None) -> DataFrame:
    """The rows of :func:`star` with the lines dealt out once, by order: orders meet their customers first, parts and suppliers come to the lines.

    ``codes`` are columns added to the parts before they are sent: of what is sent, only used columns take memory.
    """
    t = {name: table(spark, folder, name) for name in ("lineitem", *STAR)}
    t["part"] = t["part"].withColumns(codes or {})
    orders = t["orders"].join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
    rows = t["lineitem"].join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    for name, key in (("part", "partkey"), ("supplier", "suppkey")):
        side = F.broadcast(t[name]) if t[name].count() <= BROADCAST_ROWS else t[name]
        rows = rows.join(side, F.col(f"l_{key}") == F.col(f"{name[0]}_{key}"))
    return rows


def read_samples(spark: SparkSession, path: str, format: str = "parquet", features: list[str] | None = None, label: str = "label", key: str = "sample_id", **options) -> DataFrame:
    """User samples from parquet, csv, json, orc or libsvm, as (sample_id, features, label)."""
    if format == "libsvm":
        from pyspark.ml.functions import vector_to_array

        rows = spark.read.format("libsvm").options(**options).load(path)
        return rows.select(F.monotonically_increasing_id().alias("sample_id"), vector_to_array("features").alias("features"), "label")
    if format in ("csv", "json") and "schema" not in options:
        fields = [T.StructField(key, T.LongType()), *(T.StructField(c, T.DoubleType()) for c in features or []), T.StructField(label, T.DoubleType())]
        options["schema"] = T.StructType(fields)
    schema = options.pop("schema", None)
    reader = spark.read.format(format).options(**({"header": True} if format == "csv" else {}) | options)
    rows = (reader.schema(schema) if schema is not None else reader).load(path)
    x = F.array(*[F.col(c).cast("double") for c in features]) if features else F.col("features")
    return rows.select(F.col(key).alias("sample_id"), x.alias("features"), F.col(label).cast("double").alias("label"))


def write_capture(capture, path: str, blocks_per_group: int = 4096) -> None:
    """Blocks or factors, trajectory and manifest as Parquet under ``path``; blocks are laid out by ranges of their id."""
    from delprop.operators.capture import trajectory_frame

    frame = capture.factors if capture.factors is not None else capture.blocks
    kind = "factors" if capture.factors is not None else "blocks"
    spark = frame.sparkSession
    frame.withColumn("grp", F.floor(F.col("block_id") / blocks_per_group).cast("int")).write.mode("overwrite").partitionBy("grp").parquet(f"{path}/{kind}")
    if len(capture.trajectory):
        trajectory_frame(capture.trajectory, spark).write.mode("overwrite").parquet(f"{path}/trajectory")
    s = capture.spec
    eta = [float(s.eta)] if not hasattr(s.eta, "__len__") else [float(e) for e in s.eta]
    row = (kind, s.kind, s.m, s.q, s.lam, eta, s.tau, s.batch_size, s.schedule, s.seed, list(s.w0) if s.w0 else None, capture.n, capture.upto)
    schema = "holds string, kind string, m int, q int, lam double, eta array<double>, tau int, batch_size int, schedule string, seed string, w0 array<double>, n bigint, upto int"
    spark.createDataFrame([row], schema).write.mode("overwrite").parquet(f"{path}/manifest")


def read_capture(spark: SparkSession, path: str):
    import numpy as np

    from delprop.operators.capture import Capture
    from delprop.spec import ModelSpec

    r = spark.read.parquet(f"{path}/manifest").first()
    spec = ModelSpec(r.kind, r.m, r.q, r.lam, r.eta[0] if len(r.eta) == 1 else tuple(r.eta), r.tau, r.batch_size, r.schedule, r.seed, tuple(r.w0) if r.w0 else None)
    frame = spark.read.parquet(f"{path}/{r.holds}").drop("grp")
    path_of = np.zeros((0, 0))
    if spec.kind != "linear":
        path_of = np.array([x.w for x in spark.read.parquet(f"{path}/trajectory").orderBy("t").collect()])
    return Capture(spec, r.n, frame if r.holds == "blocks" else None, frame if r.holds == "factors" else None, path_of, {}, r.upto)


def write_models(models: DataFrame, path: str, mode: str = "append") -> None:
    models.write.mode(mode).parquet(path)
