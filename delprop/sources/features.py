"""Features of the given tables, planted labels, dirty rows, splits, copies and removal sets.

Statistics and vocabularies are arguments or fixed values, so a deletion never
changes the features.  Every random choice is the portable hash of the id.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from delprop.functions.hashing import identity, uniform, uniform_of
from delprop.functions.vector import dot
from delprop.sources.tables import star, table

BRANDS = [f"Brand#{k}" for k in range(1, 26)]
TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
STATUSES = ["F", "O", "P"]


def line_id() -> Column:
    """A line's id from its key columns and values: no sort, no counter, the same in any engine."""
    price = F.round(F.col("l_extendedprice") * 100).cast("bigint")
    return identity(F.col("l_orderkey"), F.col("l_linenumber"), F.col("l_partkey"), F.col("l_suppkey"), F.col("l_quantity").cast("bigint"), price, F.unix_timestamp("l_shipdate"))


def is_valid(key: Column) -> Column:
    """The validation tenth."""
    return uniform(key, "split") < 0.1


def teacher(m: int, cls: int = 0) -> list[float]:
    return [2 * uniform_of(j, f"teacher{cls}") - 1 for j in range(m)]


def planted_linear(x: Column, key: Column, m: int, noise: float = 0.1) -> Column:
    gauss = sum((uniform(key, f"n{k}") for k in range(12)), F.lit(0.0)) - 6.0
    return dot(x, F.array(*[F.lit(v) for v in teacher(m)])) + noise * gauss


def _clipped(key: Column, salt: str) -> Column:
    return F.least(F.greatest(uniform(key, salt), F.lit(1e-9)), F.lit(1 - 1e-9))


def planted_binary(x: Column, key: Column, m: int) -> Column:
    u = _clipped(key, "logit")
    z = dot(x, F.array(*[F.lit(v) for v in teacher(m)])) + F.ln(u / (1.0 - u))
    return F.when(z >= 0, 1.0).otherwise(-1.0)


def planted_class(x: Column, key: Column, m: int, q: int) -> Column:
    scores = F.array(*[dot(x, F.array(*[F.lit(v) for v in teacher(m, c)])) - F.ln(-F.ln(_clipped(key, f"gumbel{c}"))) for c in range(q)])
    return (F.array_position(scores, F.array_max(scores)) - 1).cast("double")


def with_label(rows: DataFrame, m: int, kind: str, q: int = 1) -> DataFrame:
    key, x = F.col("sample_id"), F.col("features")
    planted = {"linear": lambda: planted_linear(x, key, m), "binary": lambda: planted_binary(x, key, m), "softmax": lambda: planted_class(x, key, m, q)}[kind]()
    return rows.select("sample_id", "features", planted.alias("label"), is_valid(key).alias("is_valid"))


def _scaled(name: str, centre: float, spread: float) -> Column:
    return (F.col(name).cast("double") - F.lit(centre)) / F.lit(spread)


def small(spark: SparkSession, folder: str, columns: int = 3, kind: str = "linear", q: int = 1) -> DataFrame:
    """Two or three scaled columns of lineitem and an intercept; constants are fixed, so SQL needs no statistics."""
    rows = table(spark, folder, "lineitem")
    parts = [_scaled("l_quantity", 25.0, 15.0), _scaled("l_discount", 0.05, 0.03), _scaled("l_tax", 0.04, 0.03)][:columns]
    rows = rows.select(line_id().alias("sample_id"), F.array(*parts, F.lit(1.0)).alias("features"))
    return with_label(rows, columns + 1, kind, q)


def whole_numbers(spark: SparkSession, folder: str) -> DataFrame:
    """Integer features and label, so that sums are exact: quantity, discount and tax in hundredths, line number; label is the rounded price."""
    parts = [F.col("l_quantity"), F.round(F.col("l_discount") * 100), F.round(F.col("l_tax") * 100), F.col("l_linenumber")]
    x = F.array(*[p.cast("bigint") for p in parts])
    return table(spark, folder, "lineitem").select(line_id().alias("sample_id"), "l_suppkey", x.alias("features"), F.round("l_extendedprice").cast("bigint").alias("label"))


#: Centre and spread of the eighteen columns, near those of the given tables and frozen here.
FIXED = {
    "l_quantity": (25.5, 14.4), "l_extendedprice": (50000.0, 29000.0), "l_discount": (0.05, 0.03), "l_tax": (0.04, 0.026), "l_linenumber": (4.0, 2.0), "p_size": (25.5, 14.4),
    "p_retailprice": (1500.0, 290.0), "s_acctbal": (4500.0, 3200.0), "o_totalprice": (250000.0, 145000.0), "c_acctbal": (4500.0, 3200.0), "ship_year": (1995.5, 2.0), "ship_month": (6.5, 3.5), "ship_day": (15.5, 8.8),
}


def _flag(name: str, value: str) -> Column:
    return F.when(F.col(name) == value, 1.0).otherwise(0.0)


def eighteen_columns() -> list[Column]:
    dates = {"ship_year": F.year("l_shipdate"), "ship_month": F.month("l_shipdate"), "ship_day": F.dayofmonth("l_shipdate")}

    def z(name: str) -> Column:
        centre, spread = FIXED[name]
        return (dates.get(name, F.col(name)).cast("double") - F.lit(centre)) / F.lit(spread)

    return [
        z("l_quantity"), z("l_extendedprice"), z("l_discount"), z("l_tax"), z("l_linenumber"), _flag("l_returnflag", "A"), _flag("l_returnflag", "R"), _flag("l_linestatus", "O"),
        z("ship_year"), z("ship_month"), z("ship_day"), z("p_size"), z("p_retailprice"), z("s_acctbal"), z("o_totalprice"), z("c_acctbal"), _flag("o_orderstatus", "P"), _flag("o_orderstatus", "F"),
    ]


def star18(spark: SparkSession, folder: str, extra: int = 0, kind: str = "linear") -> DataFrame:
    """Eighteen columns of the star, and ``extra`` hash-random ones."""
    rows = star(spark, folder).select(line_id().alias("sample_id"), F.array(*eighteen_columns()).alias("features"))
    if extra:
        noise = F.transform(F.sequence(F.lit(0), F.lit(extra - 1)), lambda j: 2.0 * uniform(F.col("sample_id"), F.concat(F.lit("x"), j.cast("string"))) - 1.0)
        rows = rows.withColumn("features", F.concat("features", noise))
    return with_label(rows, 18 + extra, kind)


def twenty_eight_columns() -> list[Column]:
    x = eighteen_columns()
    return x + [x[i] * x[j] for i in range(5) for j in range(i + 1, 5)]


def star28(spark: SparkSession, folder: str, native: bool = False) -> DataFrame:
    """The eighteen columns and the ten products of the first five; two classes."""
    status = F.when(F.col("l_linestatus") == "O", 1.0).otherwise(-1.0)
    rows = star(spark, folder).select(line_id().alias("sample_id"), F.array(*twenty_eight_columns()).alias("features"), status.alias("label"))
    return rows.withColumn("is_valid", is_valid(F.col("sample_id"))) if native else with_label(rows.drop("label"), 28, "binary")


def part_codes() -> dict[str, Column]:
    """The places of a part's brand and type among those of :func:`fifty_four_columns`, in place of their strings."""

    def place(values: list[str], key: Column) -> Column:
        return F.array_position(F.array(*[F.lit(v) for v in values]), key).cast("byte")

    return {"brand_no": place(BRANDS, F.col("p_brand")), "type_no": place(TYPES, F.split("p_type", " ")[0])}


def fifty_four_columns(coded: bool = False) -> list[Column]:
    """``coded``: from rows with :func:`part_codes`."""
    ship = F.datediff("l_shipdate", "o_orderdate").cast("double") / 60.0 - 1.0
    first = F.split("p_type", " ")[0]

    def z(name: str) -> Column:
        return _scaled(name, *FIXED[name])

    numeric = [z(c) for c in ("l_quantity", "l_discount", "l_tax", "o_totalprice", "p_retailprice", "p_size", "s_acctbal", "c_acctbal", "l_extendedprice")] + [ship]
    if coded:
        hot = [F.when(F.col(name) == k, 1.0).otherwise(0.0) for name, values in (("brand_no", BRANDS), ("type_no", TYPES)) for k in range(1, len(values) + 1)]
    else:
        hot = [_flag("p_brand", b) for b in BRANDS] + [F.when(first == t, 1.0).otherwise(0.0) for t in TYPES]
    hot += [_flag("c_mktsegment", s) for s in SEGMENTS]
    hot += [F.when(F.substring("o_orderpriority", 1, 1) == str(k), 1.0).otherwise(0.0) for k in range(1, 6)] + [_flag("o_orderstatus", s) for s in STATUSES]
    return numeric + hot


def star54(spark: SparkSession, folder: str, native: bool = False) -> DataFrame:
    """Ten numeric columns and one-hot brand, type, segment, priority and status; seven classes."""
    label = (F.col("l_linenumber") - 1).cast("double")
    rows = star(spark, folder).select(line_id().alias("sample_id"), F.array(*fifty_four_columns()).alias("features"), label.alias("label"))
    return rows.withColumn("is_valid", is_valid(F.col("sample_id"))) if native else with_label(rows.drop("label"), 54, "softmax", 7)


def frames(events: DataFrame, width: int = 188, chunk: int = 8192) -> DataFrame:
    """(sample_id, features): ``width`` successive scaled event values of one day, by (ts, event_id); incomplete frames go.

    A day does not meet in one task: events are numbered within a second, the
    seconds' counts are summed up per day, and windows run over chunks of
    ``chunk`` numbers, each with the first ``width - 1`` events of the next one.
    """
    within = Window.partitionBy("day", "chunk").orderBy("at").rowsBetween(0, width - 1)
    framed = _dealt(events, width, chunk).withColumn("features", F.collect_list((F.col("value") - 50.0) / 30.0).over(within))
    return framed.where((F.size("features") == width) & (F.col("chunk") == F.col("own"))).select(F.col("event_id").alias("sample_id"), "features")


def _dealt(events: DataFrame, width: int, chunk: int) -> DataFrame:
    """Events with their number ``at`` within the day, dealt to chunks: the ``own`` one, and the one before if it needs them."""
    rows = events.select("event_id", "ts", "value", F.to_date("ts").alias("day"), F.unix_timestamp("ts").alias("second"))
    counts = rows.groupBy("day", "second").agg(F.count("*").alias("n"))
    before = counts.select("day", "second", (F.sum("n").over(Window.partitionBy("day").orderBy("second")) - F.col("n")).alias("before"))
    place = F.row_number().over(Window.partitionBy("day", "second").orderBy("ts", "event_id")) - 1
    numbered = rows.withColumn("place", place).join(before, ["day", "second"]).withColumn("at", F.col("before") + F.col("place"))
    own = F.floor(F.col("at") / chunk).cast("long")
    again = (F.col("at") % chunk < width - 1) & (own > 0)
    return numbered.withColumn("own", own).withColumn("chunk", F.explode(F.when(again, F.array(own, own - 1)).otherwise(F.array(own))))


def stretches(events: DataFrame, width: int, chunk: int) -> DataFrame:
    """(ids, vals): the same frames, ``chunk`` of a day in a row: frame ``i`` has the values ``i`` to ``i + width - 1``."""
    if chunk < width - 1:
        raise ValueError("a stretch must not be shorter than a frame")
    each = F.struct("at", "event_id", ((F.col("value") - 50.0) / 30.0).alias("v"), (F.col("chunk") == F.col("own")).alias("mine"))
    rows = _dealt(events, width, chunk).groupBy("day", "chunk").agg(F.sort_array(F.collect_list(each)).alias("s"))
    vals = F.transform("s", lambda e: e["v"])
    mine = F.transform(F.filter("s", lambda e: e["mine"]), lambda e: e["event_id"])
    rows = rows.select(vals.alias("vals"), mine.alias("mine")).where(F.size("vals") >= width)
    return rows.select(F.slice("mine", 1, F.size("vals") - (width - 1)).alias("ids"), "vals")


def series(spark: SparkSession, folder: str, width: int = 188, q: int = 7) -> DataFrame:
    """Windows of ``width`` successive event values of one day, with planted classes."""
    return with_label(frames(table(spark, folder, "events"), width), width, "softmax", q)


def embedded(spark: SparkSession, folder: str, maps: int = 0, q: int = 10, native: bool = False) -> DataFrame:
    """Embeddings as doubles; with ``maps``, that many rectified hash-random rotations of each (64 columns a map)."""
    rows = table(spark, folder, "embeddings").select(F.col("vec_id").alias("sample_id"), F.col("embedding").cast("array<double>").alias("features"), F.col("label").cast("double").alias("label"))
    if maps:
        weights = np.array([[2 * uniform_of(i, f"map{j}") - 1 for i in range(64)] for j in range(64 * maps)])

        @F.pandas_udf("array<double>")
        def mapped(v: pd.Series) -> pd.Series:
            return pd.Series(list(np.maximum(np.array(v.tolist()) @ weights.T, 0)))

        rows = rows.withColumn("features", mapped("features"))
    if native:
        return rows.withColumn("is_valid", is_valid(F.col("sample_id")))
    return with_label(rows.drop("label"), 64 * max(1, maps), "softmax", q)


def hashed_words(spark: SparkSession, folder: str, buckets: int = 47236, target: str = "quality") -> DataFrame:
    """Sparse samples: hashed, length-normalised word counts of labelled documents; label 1 or -1."""
    docs = table(spark, folder, "documents").join(table(spark, folder, "labels"), "doc_id")
    word = F.explode(F.split(F.lower("text"), r"[^\p{L}]+"))
    counts = docs.select("doc_id", F.when(F.col(target) == 1, 1.0).otherwise(-1.0).alias("label"), word.alias("word")).where("word <> ''")
    slot = F.conv(F.substring(F.md5(F.col("word").cast("binary")), 1, 8), 16, 10).cast("bigint") % buckets
    cells = counts.groupBy("doc_id", "label", slot.cast("int").alias("index")).agg(F.count("*").cast("double").alias("v"))
    rows = cells.groupBy("doc_id", "label").agg(F.sort_array(F.collect_list(F.struct("index", "v"))).alias("c"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("length"))
    return rows.select(
        F.col("doc_id").alias("sample_id"), F.transform("c", lambda x: x["index"]).alias("indices"), F.transform("c", lambda x: x["v"] / F.col("length")).alias("values"), "label", is_valid(F.col("doc_id")).alias("is_valid")
    )


def removals_at(samples: DataFrame, rate: float, salt: str = "rm", subset_id: int = 0) -> DataFrame:
    """A hash-chosen share of the ids."""
    return samples.where(uniform(F.col("sample_id"), salt) < rate).select(F.lit(subset_id).alias("subset_id"), "sample_id")


def ten_removals(samples: DataFrame, rate: float = 0.001, subsets: int = 10) -> DataFrame:
    sets = samples.select("sample_id", F.explode(F.sequence(F.lit(0), F.lit(subsets - 1))).alias("subset_id"))
    return sets.where(uniform(F.col("sample_id"), F.concat(F.lit("rm"), F.col("subset_id").cast("string"))) < rate).select("subset_id", "sample_id")


def removals_where(samples: DataFrame, condition: Column, subset_id: int = 0) -> DataFrame:
    """The ids of the rows that a predicate picks."""
    return samples.where(condition).select(F.lit(subset_id).alias("subset_id"), "sample_id")


def dirty(samples: DataFrame, rate: float, mode: str = "rescale", factor: float = 10.0, intercept: bool = False, q: int = 1) -> DataFrame:
    """``samples`` with a ``dirty`` mark and its error on the hash-chosen rows: rescaled features, flipped labels, or appended wrong rows."""
    hit = uniform(F.col("sample_id"), "rm") < rate
    if mode == "rescale":
        last = F.size("features") - 1 if intercept else F.lit(1 << 30)
        changed = F.transform("features", lambda v, i: F.when(i == last, v).otherwise(v * factor))
        return samples.withColumn("features", F.when(hit, changed).otherwise(F.col("features"))).withColumn("dirty", hit)
    if mode == "flip":
        flipped = -F.col("label") if q == 1 else (F.col("label") + 1) % q
        return samples.withColumn("label", F.when(hit, flipped).otherwise(F.col("label"))).withColumn("dirty", hit)
    if mode == "append":
        wrong = samples.where(hit).withColumn("sample_id", -F.col("sample_id") - 1).withColumn("features", F.transform("features", lambda v: v * factor))
        return samples.withColumn("dirty", F.lit(False)).unionByName(wrong.withColumn("dirty", F.lit(True)))
    raise ValueError("mode must be 'rescale', 'flip' or 'append'")


def copies(samples: DataFrame, k: int) -> DataFrame:
    """Each row ``k`` times under new ids."""
    return samples.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(k - 1)))).withColumn("sample_id", F.col("sample_id") * k + F.col("copy")).drop("copy")


def standardised(rows: DataFrame, columns: list[str], statistics: dict[str, tuple[float, float]] | None = None) -> tuple[Column, dict[str, tuple[float, float]]]:
    """Scaled columns as one array, and the statistics, which later sets must reuse."""
    if statistics is None:
        r = rows.agg(*[f(c).alias(f"{f.__name__}_{c}") for c in columns for f in (F.avg, F.stddev)]).first()
        statistics = {c: (r[f"avg_{c}"], r[f"stddev_{c}"] or 1.0) for c in columns}
    return F.array(*[_scaled(c, *statistics[c]) for c in columns]), statistics
