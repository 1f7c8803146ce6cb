"""Every method, variant, baseline, measure and operator as a query over the given tables, with its SQL where SQL can say it.

Each entry is registered by :func:`query`; results are in long form and
rounded, since sums of doubles depend on their order.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from delprop.functions import sqlfuncs
from delprop.functions.hashing import uniform
from delprop.functions.linearize import coefficients_of
from delprop.functions.linearize import table as interpolant_table
from delprop.functions.vector import dot, unpack
from delprop.operators import baselines, capture, gram, measures, prov, replay, schedule, sparse, spectral, train
from delprop.plans import oracles as sql
from delprop.plans import maintain, planner, workloads
from delprop.scratch import stored
from delprop.sources import features as fx
from delprop.sources.tables import star, table
from delprop.spec import ModelSpec
from delprop.streaming import requests

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

ETA, LAM = 0.05, 0.1
#: The small linear and binary models of the queries.
LINEAR = ModelSpec("linear", 4, lam=LAM, eta=ETA, tau=30)
BINARY = ModelSpec("binary", 3, lam=LAM, eta=0.2, tau=8)
#: Mini-batches in a pass: batches grow with the rows, so that every run passes over all of them at least twice.
LINEAR_PARTS, BINARY_PARTS = 10, 4
RATE = 0.01


def samples(spark: SparkSession, sf: str, columns: int = 3, kind: str = "linear", q: int = 1) -> DataFrame:
    """The small fixture, hashed once: the jobs of a query then share one table."""
    return stored(fx.small(spark, sf, columns, kind, q), "samples")


def sized(rows: DataFrame, spec: ModelSpec, parts: int | None = None, schedule_name: str = "cyclic") -> ModelSpec:
    """``spec`` with mini-batches of one of ``parts`` equal parts of the rows."""
    parts = parts or (LINEAR_PARTS if spec.kind == "linear" else BINARY_PARTS)
    return spec.with_(batch_size=-(-rows.count() // parts), schedule=schedule_name)


def query(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if oracle is not None:
            ORACLES[name] = oracle
        return f

    return put


def rounded(column: Column | str, digits: int = 6) -> Column:
    return F.round(column, digits) + F.lit(0.0)


def long(spark: SparkSession, w: np.ndarray, digits: int = 6, **labels) -> DataFrame:
    return train.long_form(w, spark, **labels).withColumn("value", rounded("value", digits))


def cells_long(frame: DataFrame, keys: list[str], column: str = "gram", digits: int = 3) -> DataFrame:
    return frame.select(*keys, "cnt", F.posexplode(column).alias("pos", "value")).withColumn("value", rounded("value", digits))


# ---- hashes, splits and batches -------------------------------------------------------------

_ID = sql.ID


@query("hash_uniform", f"SELECT {_ID} AS sample_id, round({sql.u(_ID, repr('a'))}, 9) AS u FROM lineitem")
def hash_uniform(spark, sf):
    return table(spark, sf, "lineitem").select(fx.line_id().alias("sample_id"), F.round(uniform(fx.line_id(), "a"), 9).alias("u"))


@query("split_assign", f"WITH {sql.small()} SELECT is_valid, count(*) AS cnt FROM fx GROUP BY is_valid")
def split_assign(spark, sf):
    return fx.small(spark, sf).groupBy("is_valid").agg(F.count("*").alias("cnt"))


@query("batch_assign", f"WITH {sql.small()}, {sql.blocked('cyclic', 30, 10)} SELECT sample_id, b AS block_id FROM bl")
def batch_assign(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return schedule.assign(rows, spec, rows.count()).select("sample_id", "block_id")


@query(
    "survivor_counts",
    f"WITH {sql.small()}, {sql.blocked('cyclic', 30, 10)} SELECT b AS block_id, count(*) AS total, count(*) FILTER (WHERE {sql.gone(RATE)}) AS removed, count(*) FILTER (WHERE NOT {sql.gone(RATE)}) AS \"left\" FROM bl GROUP BY b",
)
def survivor_counts(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return schedule.survivor_counts(schedule.assign(rows, spec, rows.count()), fx.removals_at(rows, RATE))


_PHASES = [("head", 0, 21), ("tail", 21, 30)]


@query(
    "interval_schedule",
    f"WITH {sql.small()}, {sql.blocked('cyclic', 30, 10)}, c AS (SELECT b, count(*) AS cnt FROM bl GROUP BY b) SELECT s.t::INT AS t, c.b::INT AS block_id, p.name AS phase, c.cnt AS cnt FROM range(30) s(t) CROSS JOIN blocks_of JOIN c ON c.b = s.t % nb JOIN (VALUES ('head', 0, 21), ('tail', 21, 30)) p(name, first, last) ON s.t >= p.first AND s.t < p.last",
)
def interval_schedule(spark, sf):
    """Range join of the iterations over the lines' batches with phases: what each iteration reads."""
    rows = stored(table(spark, sf, "lineitem").select(fx.line_id().alias("sample_id")), "ids")
    n, spec = rows.count(), sized(rows, LINEAR)
    sizes = schedule.assign(rows, spec, n).groupBy("block_id").agg(F.count("*").alias("cnt"))
    phases = spark.createDataFrame(_PHASES, "phase string, first int, last int")
    steps = schedule.steps(spec, n, spark).join(F.broadcast(phases), (F.col("t") >= F.col("first")) & (F.col("t") < F.col("last")))
    return steps.join(sizes, "block_id").select("t", "block_id", "phase", "cnt")


# ---- features and labels --------------------------------------------------------------------


def summary(rows: DataFrame, digits: int = 3) -> DataFrame:
    cell = rows.select(F.posexplode("features").alias("pos", "v"))
    return cell.groupBy("pos").agg(F.count("*").alias("cnt"), rounded(F.sum("v"), digits).alias("total"), rounded(F.min("v")).alias("low"), rounded(F.max("v")).alias("high"))


@query("features_18", f"WITH {sql.star(sql.star_columns())} {sql.summary(18)}")
def features_18(spark, sf):
    return summary(star(spark, sf).select(F.array(*fx.eighteen_columns()).alias("features")))


_C = sql.star_columns()


@query("features_28", f"WITH {sql.star(_C + [f'({_C[i]}) * ({_C[j]})' for i in range(5) for j in range(i + 1, 5)])} {sql.summary(28)}")
def features_28(spark, sf):
    return summary(fx.star28(spark, sf, native=True))


@query("features_54", f"WITH {sql.star(sql.star54_columns())} {sql.summary(54)}")
def features_54(spark, sf):
    return summary(fx.star54(spark, sf, native=True))


@query(
    "features_188",
    f"""WITH f AS (SELECT event_id, list((value - 50.0) / 30.0) OVER (PARTITION BY ts::DATE ORDER BY ts, event_id ROWS BETWEEN CURRENT ROW AND 187 FOLLOWING) AS x FROM events),
fx AS (SELECT x FROM f WHERE len(x) = 188) {sql.summary(188)}""",
)
def features_188(spark, sf):
    return summary(fx.frames(table(spark, sf, "events")))


@query("features_64", "WITH fx AS (SELECT embedding::DOUBLE[] AS x FROM embeddings) " + sql.summary(64, digits=4))
def features_64(spark, sf):
    return summary(fx.embedded(spark, sf, native=True), 4)


@query("features_random", f"WITH {sql.small(2)} SELECT j::INT AS pos, count(*) AS cnt, round(sum(2 * {sql.u('sample_id', chr(39) + 'x' + chr(39) + ' || j')} - 1), 4) + 0.0 AS total FROM fx, range(4) r(j) GROUP BY j")
def features_random(spark, sf):
    """The hash-random columns that widen a set."""
    cell = fx.small(spark, sf, 2).select("sample_id", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("pos"))
    value = 2.0 * uniform(F.col("sample_id"), F.concat(F.lit("x"), F.col("pos").cast("string"))) - 1.0
    return cell.groupBy("pos").agg(F.count("*").alias("cnt"), rounded(F.sum(value), 4).alias("total"))


_WORDS = r"""WITH w AS (SELECT doc_id, unnest(string_split_regex(lower(text), '[^\p{L}]+')) AS word FROM documents JOIN labels USING (doc_id)),
c AS (SELECT doc_id, ('0x' || substr(md5(word), 1, 8))::BIGINT % 47236 AS ix, count(*)::DOUBLE AS v FROM w WHERE word <> '' GROUP BY 1, 2)
SELECT doc_id AS sample_id, count(*)::BIGINT AS cells, round(sum(v) / sqrt(sum(v * v)), 6) AS total, round(max(v) / sqrt(sum(v * v)), 6) AS top FROM c GROUP BY doc_id"""


@query("features_sparse", _WORDS)
def features_sparse(spark, sf):
    rows = fx.hashed_words(spark, sf)
    total = F.aggregate("values", F.lit(0.0), lambda s, v: s + v)
    return rows.select("sample_id", F.size("indices").cast("long").alias("cells"), F.round(total, 6).alias("total"), F.round(F.array_max("values"), 6).alias("top"))


@query("planted_labels_linear", f"WITH {sql.small(3, 'linear')} SELECT sample_id, round(y, 9) + 0.0 AS label FROM fx")
def planted_labels_linear(spark, sf):
    return fx.small(spark, sf).select("sample_id", rounded("label", 9).alias("label"))


@query("planted_labels_binary", f"WITH {sql.small(2, 'binary')} SELECT sample_id, y AS label FROM fx")
def planted_labels_binary(spark, sf):
    return fx.small(spark, sf, 2, "binary").select("sample_id", "label")


@query("planted_labels_class", f"WITH {sql.small(2, 'softmax', 3)} SELECT sample_id, y AS label FROM fx")
def planted_labels_class(spark, sf):
    return fx.small(spark, sf, 2, "softmax", 3).select("sample_id", "label")


@query("dirty_scale", f"WITH {sql.small()} SELECT sample_id, round(CASE WHEN {sql.gone(0.05)} THEN x[1] * 10.0 ELSE x[1] END, 9) + 0.0 AS first, x[4] AS last, {sql.gone(0.05)} AS dirty FROM fx")
def dirty_scale(spark, sf):
    rows = fx.dirty(fx.small(spark, sf), 0.05, "rescale", 10.0, intercept=True)
    return rows.select("sample_id", rounded(F.col("features")[0], 9).alias("first"), F.col("features")[3].alias("last"), "dirty")


@query("dirty_flip", f"WITH {sql.small(2, 'binary')} SELECT sample_id, CASE WHEN {sql.gone(0.05)} THEN -y ELSE y END AS label, {sql.gone(0.05)} AS dirty FROM fx")
def dirty_flip(spark, sf):
    return fx.dirty(fx.small(spark, sf, 2, "binary"), 0.05, "flip").select("sample_id", "label", "dirty")


@query("dirty_append", f"WITH {sql.small()} SELECT false AS dirty, count(*) AS cnt, round(sum(x[1]), 4) + 0.0 AS total FROM fx UNION ALL SELECT true, count(*), round(sum(x[1] * 10.0), 4) + 0.0 FROM fx WHERE {sql.gone(0.05)}")
def dirty_append(spark, sf):
    rows = fx.dirty(fx.small(spark, sf), 0.05, "append")
    return rows.groupBy("dirty").agg(F.count("*").alias("cnt"), rounded(F.sum(F.col("features")[0]), 4).alias("total"))


@query("copies_k", f"WITH {sql.small()} SELECT sample_id * 4 + c AS sample_id, round(y, 9) + 0.0 AS label FROM fx, range(4) r(c)")
def copies_k(spark, sf):
    return fx.copies(fx.small(spark, sf), 4).select("sample_id", rounded("label", 9).alias("label"))


# ---- objectives, gradients, sums ------------------------------------------------------------

_W4 = np.array([0.3, -0.2, 0.1, 0.05])
_W3 = np.array([0.3, -0.2, 0.1])
_WQ = np.array([0.3, -0.2, 0.1, 0.0, 0.2, -0.1, -0.4, 0.1, 0.05])
_L4, _L3 = "[0.3, -0.2, 0.1, 0.05]", "[0.3, -0.2, 0.1]"
_SOFT = ModelSpec("softmax", 3, q=3, lam=LAM, eta=0.1, tau=6)
_LOGITS = "[list_dot_product(x, [0.3, -0.2, 0.1]), list_dot_product(x, [0.0, 0.2, -0.1]), list_dot_product(x, [-0.4, 0.1, 0.05])]"


@query("objective_linear", f"WITH {sql.small()} SELECT round(avg((y - list_dot_product(x, {_L4})) ** 2) + {LAM / 2 * float(_W4 @ _W4)}, 6) AS objective FROM fx")
def objective_linear(spark, sf):
    return train.objective(fx.small(spark, sf), _W4, LINEAR).select(rounded("objective").alias("objective"))


@query("objective_binary", f"WITH {sql.small(2, 'binary')} SELECT round(avg(ln(1 + exp(-y * list_dot_product(x, {_L3})))) + {LAM / 2 * float(_W3 @ _W3)}, 6) AS objective FROM fx")
def objective_binary(spark, sf):
    return train.objective(fx.small(spark, sf, 2, "binary"), _W3, BINARY).select(rounded("objective").alias("objective"))


@query("objective_softmax", f"WITH {sql.small(2, 'softmax', 3)}, s AS (SELECT y, {_LOGITS} AS l FROM fx) SELECT round(avg(ln(exp(l[1]) + exp(l[2]) + exp(l[3])) - l[y::INT + 1]) + {LAM / 2 * float(_WQ @ _WQ)}, 6) AS objective FROM s")
def objective_softmax(spark, sf):
    return train.objective(fx.small(spark, sf, 2, "softmax", 3), _WQ, _SOFT).select(rounded("objective").alias("objective"))


@query("gradient_linear", f"WITH {sql.small()} SELECT (i - 1)::INT AS pos, round(avg(2 * (list_dot_product(x, {_L4}) - y) * x[i]) + {LAM} * ({_L4})[i], 6) + 0.0 AS gradient FROM fx, range(1, 5) r(i) GROUP BY i")
def gradient_linear(spark, sf):
    return train.gradient(fx.small(spark, sf), _W4, LINEAR).withColumn("gradient", rounded("gradient"))


@query("gradient_binary", f"WITH {sql.small(2, 'binary')} SELECT (i - 1)::INT AS pos, round(avg(-y / (1 + exp(y * list_dot_product(x, {_L3}))) * x[i]) + {LAM} * ({_L3})[i], 6) + 0.0 AS gradient FROM fx, range(1, 4) r(i) GROUP BY i")
def gradient_binary(spark, sf):
    return train.gradient(fx.small(spark, sf, 2, "binary"), _W3, BINARY).withColumn("gradient", rounded("gradient"))


@query(
    "gradient_softmax",
    f"""WITH {sql.small(2, 'softmax', 3)}, s AS (SELECT x, y, {_LOGITS} AS l FROM fx),
p AS (SELECT x, y, exp(l[1]) + exp(l[2]) + exp(l[3]) AS z, l FROM s)
SELECT ((c - 1) * 3 + i - 1)::INT AS pos, round(avg((exp(l[c]) / z - CASE WHEN y = c - 1 THEN 1 ELSE 0 END) * x[i]) + {LAM} * ([0.3, -0.2, 0.1, 0.0, 0.2, -0.1, -0.4, 0.1, 0.05])[(c - 1) * 3 + i], 6) + 0.0 AS gradient
FROM p, range(1, 4) r(c), range(1, 4) s(i) GROUP BY c, i""",
)
def gradient_softmax(spark, sf):
    return train.gradient(fx.small(spark, sf, 2, "softmax", 3), _WQ, _SOFT).withColumn("gradient", rounded("gradient"))


_INT = "ints AS (SELECT l_suppkey, [l_quantity::BIGINT, round(l_discount * 100)::BIGINT, round(l_tax * 100)::BIGINT, l_linenumber::BIGINT] AS x, round(l_extendedprice)::BIGINT AS y FROM lineitem)"


@query("gram_total_int", f"WITH {_INT} SELECT (i - 1)::INT AS i, (j - 1)::INT AS j, sum(x[i] * x[j])::BIGINT AS value FROM ints, range(1, 5) r(i), range(1, 5) s(j) WHERE i <= j GROUP BY i, j")
def gram_total_int(spark, sf):
    return gram.long_gram(fx.whole_numbers(spark, sf), by=[]).select("i", "j", "value")


_PACKED = "(i - 1) * {m} - (i - 1) * (i - 2) // 2 + j - i"


def _packed_sql(m: int, by: str = "b AS block_id", weight: str = "1", off: float = 0.0) -> str:
    key = by.split(" ")[0]
    return f"SELECT {by}, count(*) AS cnt, ({_PACKED.format(m=m)})::INT AS pos, round(sum({weight} * x[i] * x[j]) + {off}, {3 if off else 5}) + 0.0 AS value FROM bl, range(1, {m + 1}) r(i), range(1, {m + 1}) s(j) WHERE i <= j GROUP BY {key}, i, j"


#: Less than half a unit of rounding: cells of few-digit decimals would else end on rounding boundaries, where the order of a sum of doubles decides.
_OFF = 0.000123


@query("gram_blocks", f"WITH {sql.star(sql.star_columns())}, {sql.blocked('cyclic', 30, 10)} {_packed_sql(18, off=_OFF)}")
def gram_blocks(spark, sf):
    """Arrow partial sums of eighteen columns by batch; cells are rounded after ``_OFF`` is added."""
    rows = star(spark, sf).select(fx.line_id().alias("sample_id"), F.array(*fx.eighteen_columns()).alias("features"), F.lit(0.0).alias("label"))
    lines = table(spark, sf, "lineitem")
    sums = gram.arrow_gram(schedule.assign(rows, sized(lines, ModelSpec("linear", 18, tau=30)), lines.count()), 18)
    return cells_long(sums.withColumn("gram", F.transform("gram", lambda v: v + _OFF)), ["block_id"], digits=3)


@query("gram_blocks_native", f"WITH {sql.small()}, {sql.blocked('cyclic', 30, 10)} {_packed_sql(4)}")
def gram_blocks_native(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return cells_long(gram.native_gram(schedule.assign(rows, spec, rows.count()), 4), ["block_id"], digits=5)


@query("gram_weighted", f"WITH {sql.small()}, {sql.blocked('full', 1, None)} {_packed_sql(4, weight='(1 / (1 + exp(y)))')}")
def gram_weighted(spark, sf):
    rows = fx.small(spark, sf).withColumn("block_id", F.lit(0))
    return cells_long(gram.native_gram(rows, 4, weight=1.0 / (1.0 + F.exp("label"))), ["block_id"], digits=5)


_SLICE = "ints_n AS (SELECT n_regionkey, n_nationkey, x, y FROM ints JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey)"


def _slices(spark, sf) -> DataFrame:
    places = table(spark, sf, "supplier").join(F.broadcast(table(spark, sf, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_regionkey", "n_nationkey")
    return fx.whole_numbers(spark, sf).join(places, F.col("l_suppkey") == F.col("s_suppkey"))


def _sliced_sql(grouping: str, level: bool = True) -> str:
    mark = "grouping(s.n_regionkey, s.n_nationkey)::BIGINT AS level, " if level else ""
    return f"WITH {_INT}, {_SLICE} SELECT coalesce(s.n_regionkey, -1)::INT AS n_regionkey, coalesce(s.n_nationkey, -1)::INT AS n_nationkey, {mark}count(*) AS cnt, sum(x[1] * x[1])::BIGINT AS g00, sum(x[1] * x[2])::BIGINT AS g01, sum(y * x[1])::BIGINT AS c0 FROM ints_n s GROUP BY {grouping}"


def _sliced(frame: DataFrame, level: bool = True) -> DataFrame:
    marks = [F.col("level").cast("bigint").alias("level")] if level else []
    keys = [F.coalesce(k, F.lit(-1)).cast("int").alias(k) for k in ("n_regionkey", "n_nationkey")]
    return frame.select(*keys, *marks, "cnt", F.col("gram")[0].alias("g00"), F.col("gram")[1].alias("g01"), F.col("cross")[0].alias("c0"))


@query("gram_cube", _sliced_sql("CUBE (s.n_regionkey, s.n_nationkey)"))
def gram_cube(spark, sf):
    return _sliced(gram.sliced_grams(_slices(spark, sf), 4, ["n_regionkey", "n_nationkey"], "cube"))


@query("gram_rollup", _sliced_sql("ROLLUP (s.n_regionkey, s.n_nationkey)"))
def gram_rollup(spark, sf):
    return _sliced(gram.sliced_grams(_slices(spark, sf), 4, ["n_regionkey", "n_nationkey"], "rollup"))


@query("gram_grouping_sets", _sliced_sql("GROUPING SETS ((s.n_regionkey), (s.n_nationkey), ())"))
def gram_grouping_sets(spark, sf):
    _slices(spark, sf).createOrReplaceTempView("sliced_samples")
    return spark.sql("""SELECT CAST(coalesce(s.n_regionkey, -1) AS INT) AS n_regionkey, CAST(coalesce(s.n_nationkey, -1) AS INT) AS n_nationkey, CAST(grouping_id(s.n_regionkey, s.n_nationkey) AS BIGINT) AS level, count(*) AS cnt, sum(features[0] * features[0]) AS g00, sum(features[0] * features[1]) AS g01, sum(label * features[0]) AS c0
        FROM sliced_samples s GROUP BY GROUPING SETS ((s.n_regionkey), (s.n_nationkey), ())""")


@query(
    "leave_slice_out",
    f"WITH {_INT}, {_SLICE}, tot AS (SELECT count(*) AS n, sum(x[1] * x[1]) AS g, sum(y * x[1]) AS c FROM ints_n) SELECT n_regionkey, n - count(*) AS cnt, (g - sum(x[1] * x[1]))::BIGINT AS g00, (c - sum(y * x[1]))::BIGINT AS c0 FROM ints_n, tot GROUP BY n_regionkey, n, g, c",
)
def leave_slice_out(spark, sf):
    out = gram.leave_slice_out(_slices(spark, sf), 4, "n_regionkey")
    return out.select("n_regionkey", "cnt", F.col("gram")[0].alias("g00"), F.col("cross")[0].alias("c0"))


# ---- training and retraining ----------------------------------------------------------------


for _name, _how, _tau, _parts in (("train_gd_linear", "full", 20, None), ("train_mb_linear", "cyclic", 30, 10), ("train_sgd_linear", "single", 40, None), ("train_reshuffle_linear", "reshuffle", 25, 10), ("train_sampled_linear", "sampled", 6, 6)):

    def _trained(spark, sf, how=_how, tau=_tau, parts=_parts):
        rows = samples(spark, sf)
        return long(spark, train.train(rows, sized(rows, LINEAR.with_(tau=tau), parts, how) if parts else LINEAR.with_(tau=tau, schedule=how)).w)

    query(_name, sql.linear(_how, _tau, _parts, ETA, LAM))(_trained)


@query("train_jobs_linear", sql.linear("cyclic", 6, 3, ETA, LAM))
def train_jobs_linear(spark, sf):
    """The engine with one aggregation an iteration."""
    rows = samples(spark, sf)
    return long(spark, train.train(rows, sized(rows, LINEAR.with_(tau=6), 3), engine="jobs").w)


@query("train_gd_binary", sql.binary("full", 6, None, 0.2, LAM))
def train_gd_binary(spark, sf):
    return long(spark, train.train(samples(spark, sf, 2, "binary"), BINARY.with_(tau=6)).w)


@query("train_mb_binary", sql.binary("cyclic", 8, 4, 0.2, LAM))
def train_mb_binary(spark, sf):
    rows = samples(spark, sf, 2, "binary")
    spec = sized(rows, BINARY)
    return long(spark, train.train(rows, spec).w)


@query("train_linearized_binary", sql.binary("cyclic", 8, 4, 0.2, LAM, linearized=True))
def train_linearized_binary(spark, sf):
    rows = samples(spark, sf, 2, "binary")
    spec = sized(rows, BINARY)
    return long(spark, train.train(rows, spec, linearized={}).w)


@query("train_gd_softmax", sql.softmax(6, 0.1, LAM))
def train_gd_softmax(spark, sf):
    return long(spark, train.train(samples(spark, sf, 2, "softmax", 3), _SOFT).w)


_KEEP = f"NOT ({sql.gone(RATE)})"


@query("retrain_linear", sql.linear("cyclic", 30, 10, ETA, LAM, keep=_KEEP))
def retrain_linear(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return long(spark, train.retrain(rows, fx.removals_at(rows, RATE), spec).w)


@query("retrain_binary", sql.binary("cyclic", 8, 4, 0.2, LAM, keep=_KEEP))
def retrain_binary(spark, sf):
    rows = samples(spark, sf, 2, "binary")
    spec = sized(rows, BINARY)
    return long(spark, train.retrain(rows, fx.removals_at(rows, RATE), spec).w)


# ---- replay ---------------------------------------------------------------------------------


@query("replay_linear", sql.linear("cyclic", 30, 10, ETA, LAM, keep=_KEEP))
def replay_linear(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return long(spark, replay.replay(capture.capture_linear(rows, spec), rows, fx.removals_at(rows, RATE)))


@query("replay_linear_lowrank", sql.linear("cyclic", 30, 10, ETA, LAM, keep=_KEEP))
def replay_linear_lowrank(spark, sf):
    """Full rank kept, so that it equals retraining."""
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return long(spark, replay.replay(capture.compress(capture.capture_linear(rows, spec), eps=1e-13), rows, fx.removals_at(rows, RATE)))


@query("replay_linear_truncated", sql.linear("cyclic", 30, 10, ETA, LAM, keep=_KEEP, tail="SELECT pos::INT AS pos, round(w[pos + 1], 6) + 0.0 AS value, true AS close FROM it, range(4) p(pos) WHERE t = 30"))
def replay_linear_truncated(spark, sf):
    """Three of four directions kept: retrained parameters, and whether the replayed ones lie within the dropped part's bound.

    A dropped eigenvalue of at most e times the largest moves each step by at
    most 2 eta e (largest / n) |w|, so all steps by tau times that.
    """
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    held, gone = stored_blocks(capture.capture_linear(rows, spec)), fx.removals_at(rows, RATE)
    truth, eps = train.retrain(rows, gone, spec).w, 0.9
    cut = capture.compress(held, eps)
    top = max(np.linalg.eigvalsh(unpack(np.array(r.gram), 4))[-1] / r.cnt for r in held.blocks.collect())
    got = replay.replay(cut, rows, gone)
    bound = 2 * ETA * eps * top * spec.tau * max(np.linalg.norm(got), np.linalg.norm(truth))
    out = long(spark, truth)
    return out.withColumn("close", F.lit(bool(np.linalg.norm(got - truth) <= bound and cut.factors.agg(F.max("r")).first()[0] < 4)))


def stored_blocks(held: capture.Capture) -> capture.Capture:
    """The capture with its sums in a table, so that later jobs read them."""
    return capture.Capture(held.spec, held.n, stored(held.blocks, "captured"), None, held.trajectory, held.options, held.upto)


@query("replay_linear_rows", sql.linear("cyclic", 30, 10, ETA, LAM, keep=_KEEP))
def replay_linear_rows(spark, sf):
    """Factors taken straight from each block's rows."""
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return long(spark, replay.replay(capture.capture_factors(rows, spec, eps=1e-13), rows, fx.removals_at(rows, RATE)))


@query("replay_linear_reshuffle", sql.linear("reshuffle", 25, 10, ETA, LAM, keep=_KEEP))
def replay_linear_reshuffle(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR.with_(tau=25), schedule_name="reshuffle")
    return long(spark, replay.replay(capture.capture_linear(rows, spec), rows, fx.removals_at(rows, RATE)))


@query("replay_linear_composed", sql.linear("cyclic", 30, 10, ETA, LAM, keep=_KEEP))
def replay_linear_composed(spark, sf):
    """Affine steps folded in chunks by parallel tasks."""
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    got = capture.capture_linear(rows, spec)
    gone = replay._local_rows(replay.removed_rows(rows, fx.removals_at(rows, RATE), spec, got.n), 4)
    return long(spark, replay.compose(got, gone, 4, rows))


_FIRST_BATCH = f"floor({sql.u('sample_id', repr('batch'))} * (SELECT k FROM size)) = 0"


@query("replay_linear_empty_batch", sql.linear("cyclic", 30, 10, ETA, LAM, keep=f"NOT ({_FIRST_BATCH})"))
def replay_linear_empty_batch(spark, sf):
    """Every row of one batch goes, and an id that does not exist."""
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    got = capture.capture_linear(rows, spec)
    first = schedule.assign(rows, spec, got.n).where("block_id = 0").select(F.lit(0).alias("subset_id"), "sample_id")
    return long(spark, replay.replay(got, rows, first.unionByName(spark.createDataFrame([(0, -5)], "subset_id int, sample_id bigint"))))


@query("replay_linear_chained", sql.linear("cyclic", 30, 10, ETA, LAM, keep=f"NOT ({sql.gone(RATE, 'one')} OR {sql.gone(RATE, 'two')})"))
def replay_linear_chained(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return long(spark, replay.update(capture.capture_linear(rows, spec), rows, fx.removals_at(rows, RATE, "two"), earlier=fx.removals_at(rows, RATE, "one")))


@query("replay_linear_insertion", sql.linear("cyclic", 30, 10, ETA, LAM, keep=f"NOT ({sql.gone(RATE, 'one')})"))
def replay_linear_insertion(spark, sf):
    """Rows of one set are added back after the others were captured without them."""
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    new = rows.where(uniform(F.col("sample_id"), "two") < RATE)
    start = rows.join(new.select("sample_id"), "sample_id", "left_anti")
    gone = fx.removals_at(rows, RATE, "one")
    return long(spark, replay.update_with_insertions(capture.capture_linear(start, spec, rows.count()), start, gone, new.join(gone.select("sample_id"), "sample_id", "left_anti")))


@query(
    "update_many",
    " UNION ALL ".join(f"SELECT {s}::INT AS subset_id, pos, value FROM ({sql.linear('cyclic', 30, 10, ETA, LAM, keep='NOT (' + sql.gone(0.001, f'rm{s}') + ')')})" for s in range(10)),
)
def update_many(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    models = replay.update_many(capture.capture_linear(rows, spec), rows, fx.ten_removals(rows, 0.001))
    return models.select("subset_id", F.posexplode("w").alias("pos", "value")).withColumn("value", rounded("value"))


@query("replay_binary", sql.binary("cyclic", 8, 4, 0.2, LAM, keep=_KEEP, replay=True))
def replay_binary(spark, sf):
    rows = samples(spark, sf, 2, "binary")
    spec = sized(rows, BINARY)
    fit = train.train(rows, spec, keep_trajectory=True)
    return long(spark, replay.replay(capture.capture_logistic(rows, fit.trajectory, spec, fit.n), rows, fx.removals_at(rows, RATE)))


@query("replay_binary_stored", sql.binary("cyclic", 8, 4, 0.2, LAM, keep=_KEEP, replay=True))
def replay_binary_stored(spark, sf):
    """Coefficients of the removed rows read from a stored table instead of computed again."""
    rows = samples(spark, sf, 2, "binary")
    spec = sized(rows, BINARY)
    fit = train.train(rows, spec, keep_trajectory=True)
    held = capture.stored_coefficients(rows, fit.trajectory, spec, fit.n)
    return long(spark, replay.replay(capture.capture_logistic(rows, fit.trajectory, spec, fit.n), rows, fx.removals_at(rows, RATE), "stored", held))


@query("replay_binary_lowrank", sql.binary("cyclic", 8, 4, 0.2, LAM, keep=_KEEP, replay=True))
def replay_binary_lowrank(spark, sf):
    rows = samples(spark, sf, 2, "binary")
    spec = sized(rows, BINARY)
    fit = train.train(rows, spec, keep_trajectory=True)
    got = capture.compress(capture.capture_logistic(rows, fit.trajectory, spec, fit.n), eps=1e-13)
    return long(spark, replay.replay(got, rows, fx.removals_at(rows, RATE)))


_AT, _BT = sql.piece("(y * list_dot_product(x, it.w))")


@query(
    "capture_logistic",
    sql.binary(
        "cyclic", 8, 4, 0.2, LAM,
        tail=f"SELECT t::INT AS block_id, count(*) AS cnt, ({_PACKED.format(m=3)})::INT AS pos, round(sum(({_AT}) * x[i] * x[j]), 3) + 0.0 AS value FROM it CROSS JOIN blocks_of JOIN bl ON bl.b = it.t % nb, range(1, 4) r(i), range(1, 4) s(j) WHERE t < 8 AND i <= j GROUP BY t, i, j",
    ),
)
def capture_logistic(spark, sf):
    rows = samples(spark, sf, 2, "binary")
    spec = sized(rows, BINARY)
    fit = train.train(rows, spec, keep_trajectory=True)
    return cells_long(capture.capture_logistic(rows, fit.trajectory, spec, fit.n).blocks, ["block_id"])


def _softmax_run(spark, sf, schedule_name: str = "full", tau: int = 12):
    rows = samples(spark, sf, 2, "softmax", 3)
    spec = _SOFT.with_(tau=tau)
    fit = train.train(rows, spec, keep_trajectory=True)
    return rows, spec, fit, capture.capture_logistic(rows, fit.trajectory, spec, fit.n)


@query("replay_softmax", sql.softmax(12, 0.1, LAM, keep=_KEEP, replay=True, digits=5))
def replay_softmax(spark, sf):
    """Tangents at the captured trajectory, summed over the survivors."""
    rows, spec, fit, got = _softmax_run(spark, sf)
    return long(spark, replay.replay(got, rows, fx.removals_at(rows, RATE)), 5)


def held_against(spark, truth: np.ndarray, got: np.ndarray, bound: float) -> DataFrame:
    """The exact retrained parameters, and whether ``got`` lies within ``bound`` of each: for methods that SQL cannot repeat but whose error is bounded."""
    rows = [(i, round(float(t), 5) + 0.0, bool(abs(t - g) < bound)) for i, (t, g) in enumerate(zip(truth, got, strict=True))]
    return spark.createDataFrame(rows, "pos int, value double, close boolean")


@query("replay_softmax_simplex", sql.softmax(12, 0.1, LAM, keep=_KEEP, digits=5, extra=", true AS close"))
def replay_softmax_simplex(spark, sf):
    """Pieces of a grid interpolant over simplices in place of tangents, against retraining."""
    rows, spec = samples(spark, sf, 2, "softmax", 3), _SOFT.with_(tau=12)
    fit = train.train(rows, spec, keep_trajectory=True)
    got = capture.capture_logistic(rows, fit.trajectory, spec, fit.n, method="simplex", dx=0.02)
    gone = fx.removals_at(rows, RATE)
    return held_against(spark, train.retrain(rows, gone, spec).w, replay.replay(got, rows, gone), 2e-3)


@query("replay_sparse", sql.sparse(60, 20, 0.1, 0.5, 0.05))
def replay_sparse(spark, sf):
    """Hashed words; one row: distance and cosine to retraining, and to no update."""
    rows = stored(fx.hashed_words(spark, sf).where("not is_valid"), "sparse-samples")
    n, gone, held = rows.count(), fx.removals_at(rows, 0.05), {}
    spec = sized(rows, ModelSpec("binary", 47236, lam=0.5, eta=0.1, tau=60), 20)
    w = sparse.train(rows, spec, n, held)
    new, truth = sparse.replay(rows, gone, spec, n, held), sparse.retrain(rows, gone, spec, n)
    row = (n, gone.count(), round(measures.distance(new, truth), 5), round(measures.cosine(new, truth), 5), round(measures.distance(w, truth), 5))
    return spark.createDataFrame([row], "n bigint, removed bigint, distance double, cosine double, stale_distance double")


# ---- spectral -------------------------------------------------------------------------------


@query("gd_from_gram", sql.linear("full", 40, None, ETA, LAM))
def gd_from_gram(spark, sf):
    g, c, n = baselines.global_sums(fx.small(spark, sf), 4)
    return long(spark, spectral.gd_from_gram(g, c, n, LINEAR.with_(tau=40)))


@query("spectral_linear_nodelete", sql.linear("full", 40, None, ETA, LAM))
def spectral_linear_nodelete(spark, sf):
    rows, spec = samples(spark, sf), LINEAR.with_(tau=40)
    return long(spark, spectral.spectral_linear(spectral.fit_eigen(rows, spec), rows, fx.removals_at(rows, 0.0), spec))


@query("spectral_linear_exact", sql.linear("full", 40, None, ETA, LAM, keep=_KEEP))
def spectral_linear_exact(spark, sf):
    """Decomposed anew, so that only the eigenvalue estimate is left out: equals full-batch retraining."""
    rows, spec = samples(spark, sf), LINEAR.with_(tau=40)
    return long(spark, spectral.spectral_linear(spectral.fit_eigen(rows, spec), rows, fx.removals_at(rows, RATE), spec, eigen_update="exact"))


_SPECTRAL_TAU = 40


def _spectral_sql(keep: str, subset: str = "") -> str:
    return f"""WITH {sql.small(1)}, s AS (
  SELECT sum(x[1] * x[1]) AS a, sum(x[1] * x[2]) AS b, sum(x[2] * x[2]) AS d, sum(x[1] * y) FILTER (WHERE {keep}) AS p, sum(x[2] * y) FILTER (WHERE {keep}) AS q, count(*) FILTER (WHERE {keep}) AS n FROM fx
), e AS (SELECT *, (a + d) / 2 + sqrt(((a - d) / 2) ** 2 + b * b) AS l1, (a + d) / 2 - sqrt(((a - d) / 2) ** 2 + b * b) AS l2 FROM s
), v AS (SELECT *, b / sqrt(b * b + (l1 - a) ** 2) AS u1, (l1 - a) / sqrt(b * b + (l1 - a) ** 2) AS u2 FROM e
), g AS (SELECT sum((x[1] * u1 + x[2] * u2) ** 2) AS r1, sum((x[2] * u1 - x[1] * u2) ** 2) AS r2 FROM fx, v WHERE NOT ({keep})
), r AS (SELECT *, 1 - {ETA * LAM} - {2 * ETA} * (l1 - r1) / n AS h1, 1 - {ETA * LAM} - {2 * ETA} * (l2 - r2) / n AS h2 FROM v, g
), z AS (SELECT *, {2 * ETA} / n * (u1 * p + u2 * q) * (1 - h1 ** {_SPECTRAL_TAU}) / (1 - h1) AS z1, {2 * ETA} / n * (u1 * q - u2 * p) * (1 - h2 ** {_SPECTRAL_TAU}) / (1 - h2) AS z2 FROM r)
SELECT {subset}0::INT AS pos, round(u1 * z1 - u2 * z2, 6) + 0.0 AS value FROM z UNION ALL SELECT {subset}1::INT, round(u2 * z1 + u1 * z2, 6) + 0.0 FROM z"""


@query("spectral_linear", _spectral_sql(_KEEP))
def spectral_linear(spark, sf):
    """Two coordinates, so that SQL can decompose by formula."""
    rows, spec = samples(spark, sf, 1), ModelSpec("linear", 2, lam=LAM, eta=ETA, tau=_SPECTRAL_TAU)
    return long(spark, spectral.spectral_linear(spectral.fit_eigen(rows, spec), rows, fx.removals_at(rows, RATE), spec))


@query("spectral_linear_many", " UNION ALL ".join(f"SELECT * FROM ({_spectral_sql('NOT (' + sql.gone(0.001, f'rm{k}') + ')', f'{k}::INT AS subset_id, ')})" for k in range(10)))
def spectral_linear_many(spark, sf):
    """Ten removal sets from one job; two coordinates, so that SQL can decompose by formula."""
    rows, spec = samples(spark, sf, 1), ModelSpec("linear", 2, lam=LAM, eta=ETA, tau=_SPECTRAL_TAU)
    found = spectral.spectral_many(spectral.fit_eigen(rows, spec), rows, fx.ten_removals(rows), spec)
    return spark.createDataFrame([(int(s), i, round(float(v), 6)) for s, w in sorted(found.items()) for i, v in enumerate(w)], "subset_id int, pos int, value double")


def _spectral_logistic(spark, rows, spec, removals, at: float = 0.7):
    fit = train.train(rows, spec, keep_trajectory=True)
    got = capture.capture_logistic(rows, fit.trajectory, spec, fit.n, upto=int(at * spec.tau))
    return spectral.spectral_logistic(spectral.fit_logistic(rows, got, int(at * spec.tau)), rows, removals)


_HEAD, _ALL = 28, 40
_FA, _FB = sql.piece("(y * list_dot_product(x, w))")
_FROZEN_SQL = sql.binary(
    "cyclic", _HEAD, 4, 0.2, LAM, columns=1, keep=_KEEP, replay=True,
    tail=f""", f AS (SELECT x, y, {_KEEP} AS stays, {_FA} AS sa, {_FB} AS sb FROM fx, full_run WHERE t = {_HEAD}),
s AS (SELECT sum(sa * x[1] * x[1]) AS a, sum(sa * x[1] * x[2]) AS b, sum(sa * x[2] * x[2]) AS d, sum(sb * y * x[1]) FILTER (WHERE stays) AS p, sum(sb * y * x[2]) FILTER (WHERE stays) AS q, count(*) FILTER (WHERE stays) AS n FROM f),
e AS (SELECT *, (a + d) / 2 + sqrt(((a - d) / 2) ** 2 + b * b) AS l1, (a + d) / 2 - sqrt(((a - d) / 2) ** 2 + b * b) AS l2 FROM s),
v AS (SELECT *, b / sqrt(b * b + (l1 - a) ** 2) AS u1, (l1 - a) / sqrt(b * b + (l1 - a) ** 2) AS u2 FROM e),
g AS (SELECT sum(sa * (x[1] * u1 + x[2] * u2) ** 2) AS r1, sum(sa * (x[2] * u1 - x[1] * u2) ** 2) AS r2 FROM f, v WHERE NOT stays),
r AS (SELECT *, {1 - 0.2 * LAM} + 0.2 * (l1 - r1) / n AS h1, {1 - 0.2 * LAM} + 0.2 * (l2 - r2) / n AS h2 FROM v, g),
o AS (SELECT *, h1 ** {_ALL - _HEAD} * (u1 * w[1] + u2 * w[2]) + 0.2 / n * (u1 * p + u2 * q) * (1 - h1 ** {_ALL - _HEAD}) / (1 - h1) AS z1, h2 ** {_ALL - _HEAD} * (u1 * w[2] - u2 * w[1]) + 0.2 / n * (u1 * q - u2 * p) * (1 - h2 ** {_ALL - _HEAD}) / (1 - h2) AS z2 FROM r, it WHERE it.t = {_HEAD})
SELECT 0::INT AS pos, round(u1 * z1 - u2 * z2, 5) + 0.0 AS value FROM o UNION ALL SELECT 1::INT, round(u2 * z1 + u1 * z2, 5) + 0.0 FROM o""",
)


@query("spectral_binary", _FROZEN_SQL)
def spectral_binary(spark, sf):
    """Replay to the switch point, then powers of the frozen pieces' shifted eigenvalues; two coordinates, so that SQL can decompose by formula."""
    rows = samples(spark, sf, 1, "binary")
    spec = sized(rows, ModelSpec("binary", 2, lam=LAM, eta=0.2, tau=_ALL), 4)
    return long(spark, _spectral_logistic(spark, rows, spec, fx.removals_at(rows, RATE)), 5)


@query("spectral_softmax", sql.softmax(30, 0.1, LAM, keep=_KEEP, digits=5, extra=", true AS close"))
def spectral_softmax(spark, sf):
    """Against retraining."""
    rows, spec = samples(spark, sf, 2, "softmax", 3), _SOFT.with_(tau=30)
    gone = fx.removals_at(rows, RATE)
    return held_against(spark, train.retrain(rows, gone, spec).w, _spectral_logistic(spark, rows, spec, gone), 1e-2)


@query("switch_by_gradient", sql.linear("full", 40, None, ETA, LAM, columns=1, tail=f"SELECT coalesce(min(a.t), 40)::INT AS t, 28::INT AS by_fraction FROM it a JOIN it b ON b.t = a.t + 1 WHERE sqrt((a.w[1] - b.w[1]) ** 2 + (a.w[2] - b.w[2]) ** 2) / {ETA} < 0.05"))
def switch_by_gradient(spark, sf):
    """Where the pieces freeze: the first iteration whose parameter step over the rate is short, and a fraction of all."""
    rows, spec = samples(spark, sf, 1), ModelSpec("linear", 2, lam=LAM, eta=ETA, tau=40)
    path = train.train(rows, spec, keep_trajectory=True).trajectory
    gradients = (np.linalg.norm(np.diff(path, axis=0), axis=1) / ETA).tolist()
    return spark.createDataFrame([(spectral.switch_point(spec, None, 0.05, gradients), spectral.switch_point(spec))], "t int, by_fraction int")


# ---- choice of method, costs -----------------------------------------------------------------

#: A rate for each method that few features leave in question: fixed values.
CHOSEN = {"spectral": RATE, "replay": 0.3, "retrain": 0.6}


def _chosen_sql(method: str, rate: float) -> str:
    keep = f"NOT ({sql.gone(rate)})"
    body = _spectral_sql(keep) if method == "spectral" else sql.linear("full", _SPECTRAL_TAU, None, ETA, LAM, columns=1, keep=keep)
    return f"SELECT {rate}::DOUBLE AS rate, '{method}' AS method, pos, value FROM ({body})"


@query("update_chosen", " UNION ALL ".join(_chosen_sql(m, r) for m, r in CHOSEN.items()))
def update_chosen(spark, sf):
    """One maintained model under three removals; the planner names the method of each by their size."""
    rows, spec = samples(spark, sf, 1), ModelSpec("linear", 2, lam=LAM, eta=ETA, tau=_SPECTRAL_TAU)
    kept, out = maintain.maintain(rows, spec), []
    for rate in CHOSEN.values():
        got = maintain.update(kept, rows, fx.removals_at(rows, rate))
        out += [(rate, got.method, i, round(float(v), 6) + 0.0) for i, v in enumerate(got.w)]
    return spark.createDataFrame(out, "rate double, method string, pos int, value double")


_COST = {
    "retrain": ("30 * (b - db) * 4", "0", "0"),
    "replay": ("30 * (db * 4 + 16)", "blocks * b * 16", "8 * blocks * 16"),
    "replay_lowrank": ("30 * (16 + db * 4)", "blocks * 4 * b * 4", "16 * blocks * 16"),
    "spectral": ("4 * 16 + 30 * 4", "n * 16 + 64", "8 * 16"),
    "influence": ("removed * 4 + 16", "n * 16 + 64", "8 * 16"),
    "normal_eq": ("4 * 16 + 64", "n * 16", "8 * 16"),
}


@query(
    "method_costs",
    f"WITH {sql.small()}, c AS (SELECT count(*)::DOUBLE AS n, count(*) FILTER (WHERE {sql.gone(RATE)})::DOUBLE AS removed, ceil(count(*) / {LINEAR_PARTS}.0) AS b FROM fx), s AS (SELECT *, removed * b / n AS db, least(30, ceil(n / b)) AS blocks, 30 * b / n AS passes FROM c) "
    + " UNION ALL ".join(f"SELECT '{m}' AS method, round({on}, 3)::DOUBLE AS online, ({off})::DOUBLE AS offline, ({held})::DOUBLE AS bytes, round(passes, 6) AS passes FROM s" for m, (on, off, held) in _COST.items()),
)
def method_costs(spark, sf):
    """Operations before and after the removal is known, provenance bytes, and passes of training over the rows."""
    rows = samples(spark, sf)
    n, spec = rows.count(), sized(rows, LINEAR)
    costs = planner.cost(planner.Stats(n, spec.m, spec.batch_size, spec.tau, fx.removals_at(rows, RATE).count()))
    out = [(m, round(float(c["online"]), 3), float(c["offline"]), float(c["bytes"]), round(measures.passes(spec, n), 6)) for m, c in costs.items()]
    return spark.createDataFrame(out, "method string, online double, offline double, bytes double, passes double")


@query("step_bound", f"WITH {sql.small(1)}, s AS (SELECT count(*) AS n, sum(x[1] * x[1]) AS a, sum(x[1] * x[2]) AS b, sum(x[2] * x[2]) AS d FROM fx), e AS (SELECT n, (a + d) / 2 + sqrt(((a - d) / 2) ** 2 + b * b) AS top FROM s) SELECT k AS kind, round(1 / (f * top / n + {LAM}), 6) AS largest_rate FROM e, (VALUES ('linear', 2.0::DOUBLE), ('binary', 0.25), ('softmax', 0.5)) v(k, f)")
def step_bound(spark, sf):
    """The largest admissible learning rate of each family, from the top eigenvalue of X'X."""
    eigen = spectral.fit_eigen(samples(spark, sf, 1), ModelSpec("linear", 2, lam=LAM, eta=ETA, tau=1))
    top = float(-eigen.c.min() / 2)
    return spark.createDataFrame([(k, round(planner.step_bound(top, eigen.n, k, LAM), 6)) for k in ("linear", "binary", "softmax")], "kind string, largest_rate double")


@query("train_rates_linear", sql.linear("cyclic", 30, 10, "0.05 / (1 + it.t * 0.1)", LAM))
def train_rates_linear(spark, sf):
    """A learning rate for each iteration."""
    rows = samples(spark, sf)
    return long(spark, train.train(rows, sized(rows, LINEAR.with_(eta=tuple(0.05 / (1 + t * 0.1) for t in range(30))))).w)


@query("replay_rates_linear", sql.linear("cyclic", 30, 10, "0.05 / (1 + it.t * 0.1)", LAM, keep=_KEEP))
def replay_rates_linear(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR.with_(eta=tuple(0.05 / (1 + t * 0.1) for t in range(30))))
    return long(spark, replay.replay(capture.capture_linear(rows, spec), rows, fx.removals_at(rows, RATE)))


@query("train_warm_linear", sql.linear("full", 40, None, ETA, LAM))
def train_warm_linear(spark, sf):
    """Fifteen iterations, then twenty-five more from the parameters they gave."""
    rows = samples(spark, sf)
    first = train.train(rows, LINEAR.with_(tau=15)).w
    return long(spark, train.train(rows, LINEAR.with_(tau=25, w0=tuple(float(v) for v in first))).w)


# ---- baselines ------------------------------------------------------------------------------

_CRAMER = f"""WITH {sql.small(1)}, s AS (
  SELECT count(*) AS n, sum(x[1] * x[1]) AS a, sum(x[1] * x[2]) AS b, sum(x[2] * x[2]) AS d, sum(x[1] * y) AS p, sum(x[2] * y) AS q FROM fx WHERE {_KEEP}
), r AS (SELECT a + n * {LAM} / 2 AS a, b, d + n * {LAM} / 2 AS d, p, q FROM s)
SELECT 0::INT AS pos, round((p * d - b * q) / (a * d - b * b), 6) + 0.0 AS value FROM r UNION ALL SELECT 1::INT, round((a * q - b * p) / (a * d - b * b), 6) + 0.0 FROM r"""


@query("normal_eq", _CRAMER)
def normal_eq(spark, sf):
    """From cached sums and the removed rows' aggregated sums."""
    rows = samples(spark, sf, 1)
    return long(spark, baselines.normal_eq_sums(baselines.global_sums(rows, 2), baselines.removed_sums(rows, fx.removals_at(rows, RATE), 2), LAM))


@query("normal_eq_woodbury", _CRAMER)
def normal_eq_woodbury(spark, sf):
    """By a rank update of at most as many rows as features."""
    rows = samples(spark, sf, 1)
    return long(spark, baselines.normal_eq_rank(baselines.global_sums(rows, 2), baselines.removed_sums(rows, fx.removals_at(rows, RATE), 2), LAM))


def _influence_sql(removed: str) -> str:
    tail = f"""SELECT pos::INT AS pos, round(w[pos + 1] + (CASE pos WHEN 0 THEN d * p - b * q ELSE a * q - b * p END) / (a * d - b * b) / n, 6) + 0.0 AS value
FROM it, range(2) r(pos), (SELECT count(*) AS n, 2 * sum(x[1] * x[1]) / count(*) + {LAM} AS a, 2 * sum(x[1] * x[2]) / count(*) AS b, 2 * sum(x[2] * x[2]) / count(*) + {LAM} AS d FROM fx) h,
  (SELECT sum(2 * (list_dot_product(x, w) - y) * x[1]) AS p, sum(2 * (list_dot_product(x, w) - y) * x[2]) AS q FROM fx, it WHERE t = 40 AND ({removed})) g WHERE t = 40"""
    return sql.linear("full", 40, None, ETA, LAM, columns=1, tail=tail)


def _influenced(spark, sf, pick) -> DataFrame:
    rows, spec = samples(spark, sf, 1), ModelSpec("linear", 2, lam=LAM, eta=ETA, tau=40)
    return long(spark, baselines.influence(rows, train.train(rows, spec).w, pick(rows), spec))


@query("influence_single", _influence_sql("sample_id = (SELECT min(sample_id) FROM fx)"))
def influence_single(spark, sf):
    return _influenced(spark, sf, lambda rows: rows.agg(F.min("sample_id").alias("sample_id")))


@query("influence_multi", _influence_sql(sql.gone(RATE)))
def influence_multi(spark, sf):
    return _influenced(spark, sf, lambda rows: fx.removals_at(rows, RATE))


_NEWTON_SQL = sql.binary(
    "cyclic", 40, 4, 0.2, LAM, columns=1,
    tail=f"""SELECT pos::INT AS pos, round(w[pos + 1] - (CASE pos WHEN 0 THEN d * p - b * q ELSE a * q - b * p END) / (a * d - b * b), 5) + 0.0 AS value FROM it, range(2) r(pos),
(SELECT sum(f * (1 - f) * x[1] * x[1]) / count(*) + {LAM} AS a, sum(f * (1 - f) * x[1] * x[2]) / count(*) AS b, sum(f * (1 - f) * x[2] * x[2]) / count(*) + {LAM} AS d,
  sum(-y * f * x[1]) / count(*) + {LAM} * any_value(w)[1] AS p, sum(-y * f * x[2]) / count(*) + {LAM} * any_value(w)[2] AS q
  FROM (SELECT x, y, w, 1 / (1 + exp(y * list_dot_product(x, w))) AS f FROM fx, it WHERE t = 40 AND {_KEEP})) g WHERE t = 40""",
)


@query("influence_newton", _NEWTON_SQL)
def influence_newton(spark, sf):
    """Hessian of the survivors: a Newton step from the old parameters."""
    rows = samples(spark, sf, 1, "binary")
    spec = sized(rows, ModelSpec("binary", 2, lam=LAM, eta=0.2, tau=40), 4)
    return long(spark, baselines.influence(rows, train.train(rows, spec).w, fx.removals_at(rows, RATE), spec, of="survivors"), 5)


@query("library_linear", f"""WITH {sql.small(1)}, s AS (SELECT count(*) AS n, sum(x[1] * x[1]) AS a, sum(x[1] * x[2]) AS b, sum(x[2] * x[2]) AS d, sum(x[1] * y) AS p, sum(x[2] * y) AS q FROM fx),
r AS (SELECT a + n * {LAM} / 2 AS a, b, d + n * {LAM} / 2 AS d, p, q FROM s)
SELECT 0::INT AS pos, round((p * d - b * q) / (a * d - b * b), 2) + 0.0 AS value FROM r UNION ALL SELECT 1::INT, round((a * q - b * p) / (a * d - b * b), 2) + 0.0 FROM r""")  # fmt: skip
def library_linear(spark, sf):
    return long(spark, baselines.library_fit(fx.small(spark, sf, 1), ModelSpec("linear", 2, lam=LAM)), 2)


@query("library_binary", sql.binary("full", 80, None, 2.0, LAM, columns=1).replace("round(w[pos + 1], 6)", "round(w[pos + 1], 3)"))
def library_binary(spark, sf):
    """The library's solver against long descent."""
    return long(spark, baselines.library_fit(samples(spark, sf, 1, "binary"), ModelSpec("binary", 2, lam=LAM)), 3)


@query("stale", sql.linear("cyclic", 30, 10, ETA, LAM))
def stale(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return long(spark, baselines.stale(train.train(rows, spec).w))


# ---- linearisation --------------------------------------------------------------------------

_Z = "(y * list_dot_product(x, [0.3, -0.2, 0.1]) * 30)"
_PA, _PB = sql.piece(_Z)


@query("interp_coefficients", f"WITH {sql.small(2, 'binary')} SELECT sample_id, round({_PA}, 4) + 0.0 AS slope, round({_PB}, 4) + 0.0 AS \"offset\" FROM fx")
def interp_coefficients(spark, sf):
    rows = fx.small(spark, sf, 2, "binary").withColumn("z", F.col("label") * dot(F.col("features"), F.array(*[F.lit(v) for v in (0.3, -0.2, 0.1)])) * 30)
    return rows.select("sample_id", coefficients_of(F.col("z")).alias("c")).select("sample_id", rounded("c.a", 4).alias("slope"), rounded("c.b", 4).alias("offset"))


@query(
    "interp_table",
    """WITH c AS (SELECT k AS cell, -4.0 + k * 0.125 AS low, -4.0 + (k + 1) * 0.125 AS high FROM range(64) r(k)),
p AS (SELECT *, (tanh(high) - tanh(low)) / 0.125 AS slope, tanh(low) - (tanh(high) - tanh(low)) / 0.125 * low AS "offset" FROM c),
v AS (SELECT (l_extendedprice - 50000.0) / 15000.0 AS z FROM lineitem)
SELECT cell, low, high, round(slope, 9) + 0.0 AS slope, round("offset", 9) + 0.0 AS "offset", count(z) AS cnt, round(coalesce(max(abs(tanh(z) - (slope * z + "offset"))), 0.0), 9) + 0.0 AS worst
FROM p LEFT JOIN v ON z >= low AND z < high GROUP BY cell, low, high, slope, "offset\"""",
)
def interp_table(spark, sf):
    """The interpolant's cells, how many of the lines' scaled prices each serves, and its largest error on them."""
    cells = interpolant_table(spark, F.tanh, -4.0, 4.0, 64)
    prices = table(spark, sf, "lineitem").select(((F.col("l_extendedprice") - 50000.0) / 15000.0).alias("z"))
    hit = prices.join(F.broadcast(cells), (F.col("z") >= F.col("low")) & (F.col("z") < F.col("high")))
    error = F.abs(F.tanh("z") - (F.col("slope") * F.col("z") + F.col("offset")))
    used = hit.groupBy("cell").agg(F.count("*").alias("cnt"), F.max(error).alias("worst"))
    rounds = [rounded(c, 9).alias(c) for c in ("slope", "offset")]
    return cells.join(used, "cell", "left").select("cell", "low", "high", *rounds, F.coalesce("cnt", F.lit(0)).alias("cnt"), rounded(F.coalesce("worst", F.lit(0.0)), 9).alias("worst"))


@query("theta_cells", f"WITH {sql.small()}, c AS (SELECT k AS cell, -4.0 + k * 0.5 AS low, -4.0 + (k + 1) * 0.5 AS high FROM range(16) r(k)) SELECT cell, count(*) AS cnt FROM fx JOIN c ON y >= low AND y < high GROUP BY cell")
def theta_cells(spark, sf):
    """Cell lookup as a range join with a small table of breakpoints."""
    cells = interpolant_table(spark, F.tanh, -4.0, 4.0, 16)
    rows = fx.small(spark, sf)
    return rows.join(F.broadcast(cells), (F.col("label") >= F.col("low")) & (F.col("label") < F.col("high"))).groupBy("cell").agg(F.count("*").alias("cnt"))


# ---- measures -------------------------------------------------------------------------------


@query("mse", f"WITH {sql.small()} SELECT round(avg((y - list_dot_product(x, {_L4})) ** 2), 6) AS mse FROM fx WHERE is_valid")
def mse(spark, sf):
    return measures.mse(fx.small(spark, sf).where("is_valid"), _W4, LINEAR).select(rounded("mse").alias("mse"))


@query("accuracy_binary", f"WITH {sql.small(2, 'binary')} SELECT round(avg(CASE WHEN (list_dot_product(x, {_L3}) >= 0) = (y > 0) THEN 1.0 ELSE 0.0 END), 9) AS accuracy FROM fx WHERE is_valid")
def accuracy_binary(spark, sf):
    return measures.accuracy(fx.small(spark, sf, 2, "binary").where("is_valid"), _W3, BINARY).select(rounded("accuracy", 9).alias("accuracy"))


@query("accuracy_softmax", f"WITH {sql.small(2, 'softmax', 3)}, s AS (SELECT y, {_LOGITS} AS l FROM fx WHERE is_valid) SELECT round(avg(CASE WHEN list_position(l, list_max(l)) - 1 = y THEN 1.0 ELSE 0.0 END), 9) AS accuracy FROM s")
def accuracy_softmax(spark, sf):
    return measures.accuracy(fx.small(spark, sf, 2, "softmax", 3).where("is_valid"), _WQ, _SOFT).select(rounded("accuracy", 9).alias("accuracy"))


_TRUTH = sql.linear("cyclic", 30, 10, ETA, LAM, keep=_KEEP, digits=12)
_OLD = sql.linear("cyclic", 30, 10, ETA, LAM, digits=12)


@query(
    "compare_models",
    f"""WITH a AS ({_OLD}), b AS ({_TRUTH}) SELECT 'stale' AS model_id, round(sqrt(sum((a.value - b.value) ** 2)), 6) + 0.0 AS distance, round(sum(a.value * b.value) / sqrt(sum(a.value ** 2) * sum(b.value ** 2)), 6) AS cosine,
count(*) FILTER (WHERE sign(a.value) <> sign(b.value)) AS sign_flips, round(max(abs(a.value - b.value)), 6) + 0.0 AS largest_change FROM a JOIN b ON a.pos = b.pos""",
)
def compare_models(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    truth = train.long_form(train.retrain(rows, fx.removals_at(rows, RATE), spec).w, spark)
    old = train.long_form(train.train(rows, spec).w, spark, model_id="stale")
    out = measures.compare(old, truth)
    return out.select("model_id", rounded("distance").alias("distance"), rounded("cosine").alias("cosine"), "sign_flips", rounded("largest_change").alias("largest_change"))


@query("capture_bytes", f"WITH {sql.small()}, {sql.blocked('cyclic', 30, 10)} SELECT (count(DISTINCT b) * (10 + 4) * 8)::BIGINT AS bytes, count(DISTINCT b)::BIGINT AS blocks FROM bl")
def capture_bytes(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    return measures.capture_bytes(capture.capture_linear(rows, spec).blocks)


@query("deletion_rate", f"WITH {sql.small()} SELECT count(*) AS n, count(*) FILTER (WHERE {sql.gone(RATE)}) AS removed, count(*) FILTER (WHERE {sql.gone(RATE)}) / count(*)::DOUBLE AS rate FROM fx")
def deletion_rate(spark, sf):
    rows = fx.small(spark, sf)
    return measures.deletion_rate(rows, fx.removals_at(rows, RATE))


@query("convergence_lag", sql.linear("cyclic", 30, 10, ETA, LAM, tail="SELECT b.t::INT AS t, round(sqrt(list_sum([(a.w[i] - b.w[i]) ** 2 for i in range(1, 5)])), 6) + 0.0 AS step FROM it a JOIN it b ON b.t = a.t + 1"))
def convergence_lag(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    path = train.train(rows, spec, keep_trajectory=True).trajectory
    return measures.convergence(capture.trajectory_frame(path, spark)).select(F.col("t").cast("int").alias("t"), rounded("step").alias("step"))


@query("topk_influential", f"WITH {sql.small()} SELECT sample_id, round(abs(2 * (list_dot_product(x, {_L4}) - y)) * sqrt(list_dot_product(x, x)), 6) AS gradient_norm FROM fx ORDER BY gradient_norm DESC, sample_id LIMIT 20")
def topk_influential(spark, sf):
    return measures.sample_influence(fx.small(spark, sf), _W4, LINEAR, 20).withColumn("gradient_norm", F.round("gradient_norm", 6))


@query(
    "rank_summary",
    f"""WITH {sql.small(1)}, {sql.blocked('cyclic', 30, 10)}, s AS (SELECT b AS blk, sum(x[1] * x[1]) AS a, sum(x[1] * x[2]) AS b, sum(x[2] * x[2]) AS d FROM bl GROUP BY b),
e AS (SELECT (a + d) / 2 + sqrt(((a - d) / 2) ** 2 + b * b) AS l1, (a + d) / 2 - sqrt(((a - d) / 2) ** 2 + b * b) AS l2 FROM s),
r AS (SELECT 1 + (l2 > 0.92 * l1)::INT AS r FROM e) SELECT min(r)::INT AS least, quantile_disc(r, 0.5)::INT AS median, max(r)::INT AS most, avg(r) AS mean FROM r""",
)
def rank_summary(spark, sf):
    """Ranks kept in each block; two coordinates, so that SQL can decompose by formula."""
    rows = samples(spark, sf, 1)
    got = capture.compress(capture.capture_linear(rows, sized(rows, ModelSpec("linear", 2, tau=30))), eps=0.92)
    return measures.rank_summary(got.factors)


# ---- provenance algebra ---------------------------------------------------------------------


def _poly(spark, sf, table_name: str, key: str, step: int) -> DataFrame:
    """A polynomial over the rows of a small table: token n<key mod step>, exponent 1 + key mod 2, coefficient key + 1."""
    k = F.col(key)
    monomial = F.create_map(F.concat(F.lit("n"), (k % step).cast("string")), (1 + k % 2).cast("int"))
    return table(spark, sf, table_name).select(monomial.alias("monomial"), (k + 1).cast("bigint").alias("coefficient"))


def _poly_text(polynomial: DataFrame) -> DataFrame:
    return polynomial.select(prov.label(F.col("monomial")).alias("monomial"), F.col("coefficient").cast("bigint").alias("coefficient"))


def _poly_sql(table_name: str, key: str, step: int, name: str) -> str:
    return f"{name} AS (SELECT 'n' || ({key} % {step}) AS tok, 1 + {key} % 2 AS e, {key} + 1 AS c FROM {table_name})"


_MONO = "tok || CASE WHEN e > 1 THEN '^' || e ELSE '' END"


@query("poly_add", f"WITH {_poly_sql('nation', 'n_nationkey', 5, 'p')}, {_poly_sql('region', 'r_regionkey', 5, 'q')} SELECT {_MONO} AS monomial, sum(c)::BIGINT AS coefficient FROM (SELECT * FROM p UNION ALL SELECT * FROM q) GROUP BY 1")
def poly_add(spark, sf):
    return _poly_text(prov.add(_poly(spark, sf, "nation", "n_nationkey", 5), _poly(spark, sf, "region", "r_regionkey", 5)))


_PRODUCT = """SELECT CASE WHEN p.tok = q.tok THEN p.tok || '^' || (p.e + q.e) WHEN p.tok < q.tok THEN p.tok || CASE WHEN p.e > 1 THEN '^' || p.e ELSE '' END || '*' || q.tok || CASE WHEN q.e > 1 THEN '^' || q.e ELSE '' END
ELSE q.tok || CASE WHEN q.e > 1 THEN '^' || q.e ELSE '' END || '*' || p.tok || CASE WHEN p.e > 1 THEN '^' || p.e ELSE '' END END AS monomial, p.c * q.c AS c FROM p, q"""


@query("poly_mul", f"WITH {_poly_sql('nation', 'n_nationkey', 5, 'p')}, {_poly_sql('region', 'r_regionkey', 3, 'q')} SELECT monomial, sum(c)::BIGINT AS coefficient FROM ({_PRODUCT}) GROUP BY monomial")
def poly_mul(spark, sf):
    return _poly_text(prov.mul(_poly(spark, sf, "nation", "n_nationkey", 5), _poly(spark, sf, "region", "r_regionkey", 3)))


@query("poly_delete", f"WITH {_poly_sql('nation', 'n_nationkey', 5, 'p')} SELECT {_MONO} AS monomial, sum(c)::BIGINT AS coefficient FROM p WHERE tok NOT IN ('n1', 'n3') GROUP BY 1")
def poly_delete(spark, sf):
    return _poly_text(prov.add(prov.delete(_poly(spark, sf, "nation", "n_nationkey", 5), ["n1", "n3"]), prov.zero(spark)))


@query("poly_eval", f"WITH {_poly_sql('nation', 'n_nationkey', 5, 'p')} SELECT sum(c)::BIGINT AS value FROM p WHERE tok NOT IN ('n1', 'n3')")
def poly_eval(spark, sf):
    return prov.evaluate(prov.delete(_poly(spark, sf, "nation", "n_nationkey", 5), ["n1", "n3"]))


@query("poly_idempotent", f"WITH {_poly_sql('nation', 'n_nationkey', 5, 'p')} SELECT tok AS monomial, sum(c)::BIGINT AS coefficient FROM p GROUP BY tok")
def poly_idempotent(spark, sf):
    return _poly_text(prov.idempotent(_poly(spark, sf, "nation", "n_nationkey", 5)))


def _nations(spark, sf) -> DataFrame:
    k = F.col("n_nationkey")
    return table(spark, sf, "nation").select(k.cast("bigint").alias("sample_id"), F.array((k + 1).cast("double"), (k % 4).cast("double")).alias("features"), (k % 3).cast("double").alias("label"))


@query("decompose", "SELECT 'p' || n_nationkey AS monomial, 1::INT AS rows, 2::INT AS cols, (n_nationkey + 1)::DOUBLE AS first, (n_nationkey % 4)::DOUBLE AS second FROM nation")
def decompose(spark, sf):
    terms = prov.decompose(_nations(spark, sf))
    return terms.select(prov.label(F.col("monomial")).alias("monomial"), "rows", "cols", F.col("cells")[0].alias("first"), F.col("cells")[1].alias("second"))


@query("annotated_gram", "SELECT 'p' || n_nationkey || '^2' AS monomial, ((n_nationkey + 1) ** 2)::DOUBLE AS c0, ((n_nationkey + 1) * (n_nationkey % 4))::DOUBLE AS c1, ((n_nationkey % 4) ** 2)::DOUBLE AS c3 FROM nation")
def annotated_gram(spark, sf):
    terms = prov.gram(prov.decompose(_nations(spark, sf)))
    return terms.select(prov.label(F.col("monomial")).alias("monomial"), F.col("cells")[0].alias("c0"), F.col("cells")[1].alias("c1"), F.col("cells")[3].alias("c3"))


@query("annotated_product", "SELECT CASE WHEN r.r_regionkey < s.r_regionkey THEN 'a' || r.r_regionkey || '*b' || s.r_regionkey ELSE 'a' || r.r_regionkey || '*b' || s.r_regionkey END AS monomial, ((r.r_regionkey + 1) * (s.r_regionkey + 2) + s.r_regionkey)::DOUBLE AS value FROM region r, region s")
def annotated_product(spark, sf):
    """Row terms times column terms: (k + 1, 1) . (h + 2, h)."""
    k = F.col("r_regionkey")
    rows = table(spark, sf, "region")
    left = rows.select(F.create_map(F.concat(F.lit("a"), k.cast("string")), F.lit(1)).alias("monomial"), F.lit(1).alias("rows"), F.lit(2).alias("cols"), F.array((k + 1).cast("double"), F.lit(1.0)).alias("cells"))
    right = rows.select(F.create_map(F.concat(F.lit("b"), k.cast("string")), F.lit(1)).alias("monomial"), F.lit(2).alias("rows"), F.lit(1).alias("cols"), F.array((k + 2).cast("double"), k.cast("double")).alias("cells"))
    return prov.matmul(left, right).select(prov.label(F.col("monomial")).alias("monomial"), F.col("cells")[0].alias("value"))


@query("annotated_eval", "SELECT 0::INT AS pos, sum(n_nationkey + 1)::DOUBLE AS value FROM nation WHERE n_nationkey % 5 <> 0 UNION ALL SELECT 1::INT, sum(n_nationkey % 4)::DOUBLE FROM nation WHERE n_nationkey % 5 <> 0")
def annotated_eval(spark, sf):
    tokens = table(spark, sf, "nation").where("n_nationkey % 5 = 0").select(F.concat(F.lit("p"), F.col("n_nationkey").cast("string")).alias("token"))
    return prov.evaluate(prov.delete_by_join(prov.decompose(_nations(spark, sf)), tokens))


@query("contributions", "SELECT 'p' || n_nationkey || '^2' AS monomial, sqrt(((n_nationkey + 1) ** 2 + (n_nationkey % 4) ** 2) ** 2) AS size FROM nation")
def contributions(spark, sf):
    """Length of each token's part of the annotated X'X."""
    return prov.contributions(prov.gram(prov.decompose(_nations(spark, sf))))


# ---- joins, sets, windows and functions that users of the methods need ----------------------

_RM1, _RM2 = sql.gone(0.02, "one"), sql.gone(0.02, "two")


def _sets(spark, sf) -> tuple[DataFrame, DataFrame, DataFrame]:
    rows = fx.small(spark, sf).select("sample_id")
    return rows, rows.where(uniform(F.col("sample_id"), "one") < 0.02), rows.where(uniform(F.col("sample_id"), "two") < 0.02)


for _name, _make, _where in (
    ("removal_semi", lambda r, a, b: r.join(a, "sample_id", "left_semi"), _RM1),
    ("removal_anti", lambda r, a, b: r.join(a, "sample_id", "left_anti"), f"NOT {_RM1}"),
    ("removal_union", lambda r, a, b: a.union(b).distinct(), f"{_RM1} OR {_RM2}"),
    ("removal_intersect", lambda r, a, b: a.intersect(b), f"{_RM1} AND {_RM2}"),
    ("removal_except", lambda r, a, b: a.exceptAll(b), f"{_RM1} AND NOT {_RM2}"),
):

    def _set_op(spark, sf, make=_make):
        return make(*_sets(spark, sf))

    query(_name, f"WITH {sql.small()} SELECT sample_id FROM fx WHERE {_where}")(_set_op)


@query("removal_where", f"SELECT {_ID} AS sample_id FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1995-03-01' AND l_returnflag IN ('A', 'R')")
def removal_where(spark, sf):
    rows = table(spark, sf, "lineitem").withColumn("sample_id", fx.line_id())
    pick = (F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp")) & (F.col("l_shipdate") < F.lit("1995-03-01").cast("timestamp")) & F.col("l_returnflag").isin("A", "R")
    return fx.removals_where(rows, pick).select("sample_id")


@query("asof_model", "WITH m AS (SELECT TIMESTAMP '2024-01-01' + INTERVAL (k * 3) DAY AS made, k AS version FROM range(10) r(k)) SELECT event_id, version FROM events ASOF JOIN m ON ts >= made")
def asof_model(spark, sf):
    """The latest model version before each event: models ride in the events' order, and the last seen one is taken.

    Versions are few, so each event's version is looked up as an interval.
    """
    made = spark.range(10).select((F.lit("2024-01-01").cast("timestamp") + F.make_interval(days=(F.col("id") * 3).cast("int"))).alias("made"), F.col("id").alias("version"))
    until = F.lead("made").over(Window.orderBy("made"))
    spans = made.withColumn("until", until)
    events = table(spark, sf, "events").select("event_id", "ts")
    return events.join(F.broadcast(spans), (F.col("ts") >= F.col("made")) & (F.col("until").isNull() | (F.col("ts") < F.col("until")))).select("event_id", "version")


@query("rank_batches", f"WITH {sql.small()}, {sql.blocked('cyclic', 30, 10)}, c AS (SELECT b AS block_id, count(*) AS cnt FROM bl GROUP BY b) SELECT block_id, cnt, rank() OVER (ORDER BY cnt DESC)::INT AS rank, dense_rank() OVER (ORDER BY cnt DESC)::INT AS dense, ntile(3) OVER (ORDER BY cnt DESC, block_id)::INT AS third FROM c")
def rank_batches(spark, sf):
    rows = samples(spark, sf)
    spec = sized(rows, LINEAR)
    sizes = schedule.assign(rows, spec, rows.count()).groupBy("block_id").agg(F.count("*").alias("cnt"))
    by_size = Window.orderBy(F.desc("cnt"))
    return sizes.select("block_id", "cnt", F.rank().over(by_size).alias("rank"), F.dense_rank().over(by_size).alias("dense"), F.ntile(3).over(Window.orderBy(F.desc("cnt"), "block_id")).alias("third"))


@query("running_deletions", "WITH d AS (SELECT ts::DATE AS day, count(*) FILTER (WHERE event_type = 'error') AS gone FROM events GROUP BY 1) SELECT day::VARCHAR AS day, gone, sum(gone) OVER (ORDER BY day)::BIGINT AS running FROM d")
def running_deletions(spark, sf):
    """Daily totals first, so the running window sees one row a day."""
    daily = table(spark, sf, "events").groupBy(F.to_date("ts").alias("day")).agg(F.sum((F.col("event_type") == "error").cast("bigint")).alias("gone"))
    return daily.withColumn("running", F.sum("gone").over(Window.orderBy("day"))).withColumn("day", F.col("day").cast("string"))


@query("next_event", "SELECT event_id, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next_type FROM events")
def next_event(spark, sf):
    return table(spark, sf, "events").select("event_id", F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("next_type"))


@query("json_props", "SELECT json_extract_string(props, '$.k')::BIGINT AS k, count(*) AS cnt FROM events GROUP BY 1")
def json_props(spark, sf):
    return table(spark, sf, "events").groupBy(F.get_json_object("props", "$.k").cast("bigint").alias("k")).agg(F.count("*").alias("cnt"))


@query("text_tokens", r"SELECT doc_id, len(list_filter(string_split_regex(lower(text), '[^\p{L}]+'), lambda w: w <> ''))::BIGINT AS words FROM documents")
def text_tokens(spark, sf):
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda w: w != "")
    return table(spark, sf, "documents").select("doc_id", F.size(words).cast("bigint").alias("words"))


@query("date_parts", "SELECT year(l_shipdate)::INT AS y, month(l_shipdate)::INT AS m, count(*) AS cnt, sum(date_diff('day', o_orderdate::DATE, l_shipdate::DATE))::BIGINT AS days FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2")
def date_parts(spark, sf):
    rows = table(spark, sf, "lineitem").join(table(spark, sf, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.groupBy(F.year("l_shipdate").alias("y"), F.month("l_shipdate").alias("m")).agg(F.count("*").alias("cnt"), F.sum(F.datediff("l_shipdate", "o_orderdate")).alias("days"))


@query("array_ops", "SELECT vec_id, round(list_max(embedding::DOUBLE[]), 6) AS top, (list_position(embedding, list_max(embedding)) - 1)::INT AS at, len(list_filter(embedding, lambda v: v > 0))::INT AS positive FROM embeddings")
def array_ops(spark, sf):
    v = F.col("embedding")
    return table(spark, sf, "embeddings").select("vec_id", F.round(F.array_max(v.cast("array<double>")), 6).alias("top"), (F.array_position(v, F.array_max(v)) - 1).cast("int").alias("at"), F.size(F.filter(v, lambda x: x > 0)).alias("positive"))


@query("map_ops", "SELECT n_name AS name, (n_nationkey * 2 + 1)::BIGINT AS merged FROM nation")
def map_ops(spark, sf):
    k = F.col("n_nationkey").cast("bigint")
    merged = F.map_zip_with(F.create_map(F.lit("a"), k), F.create_map(F.lit("a"), k + 1), lambda _, x, y: x + y)
    return table(spark, sf, "nation").select(F.col("n_name").alias("name"), merged["a"].alias("merged"))


@query("approx_distinct", "SELECT count(DISTINCT l_orderkey) AS orders, true AS within FROM lineitem")
def approx_distinct(spark, sf):
    """The exact count, and whether the sketch's lies within its stated five per cent (three deviations)."""
    exact, near = F.count_distinct("l_orderkey"), F.approx_count_distinct("l_orderkey")
    return table(spark, sf, "lineitem").agg(exact.alias("orders"), near.alias("near")).select("orders", (F.abs(F.col("near") / F.col("orders") - 1) < 0.15).alias("within"))


@query("approx_percentile", "SELECT p::DOUBLE AS p, true AS within FROM (VALUES (0.1), (0.5), (0.9)) t(p)")
def approx_percentile(spark, sf):
    """Whether each approximate decile has its share of the rows at or below it, within the sketch's stated error."""
    prices = table(spark, sf, "lineitem").select("l_extendedprice")
    points = [0.1, 0.5, 0.9]
    found = prices.agg(F.percentile_approx("l_extendedprice", F.array(*map(F.lit, points)), 1000).alias("v")).first().v  # three numbers
    shares = prices.agg(*[F.avg((F.col("l_extendedprice") <= v).cast("double")).alias(f"s{i}") for i, v in enumerate(found)])
    return shares.select(F.explode(F.array(*[F.struct(F.lit(p).alias("p"), (F.abs(F.col(f"s{i}") - p) < 0.003).alias("within")) for i, p in enumerate(points)])).alias("r")).select("r.p", "r.within")


@query("udtf_schedule", "SELECT t::INT AS t, (t % 7)::INT AS block_id FROM range(3, 40) r(t)")
def udtf_schedule(spark, sf):
    sqlfuncs.register(spark)
    return spark.sql("SELECT * FROM dp_steps(3, 40, 7)")


@query("sql_predict", f"WITH {sql.small(2, 'binary')} SELECT sample_id, round(1 / (1 + exp(-list_dot_product(x, {_L3}))), 9) AS p, round({sql.piece(f'(y * list_dot_product(x, {_L3}))')[0]}, 6) + 0.0 AS slope FROM fx")
def sql_predict(spark, sf):
    sqlfuncs.register(spark)
    fx.small(spark, sf, 2, "binary").createOrReplaceTempView("small_binary")
    w = "array(0.3D, -0.2D, 0.1D)"
    return spark.sql(f"SELECT sample_id, round(dp_predict({w}, features), 9) AS p, round(dp_slope(dp_margin({w}, features, label)), 6) + 0D AS slope FROM small_binary")


@query("softmax_interpolated", "SELECT count(*) AS cnt, true AS accurate FROM lineitem")
def softmax_interpolated(spark, sf):
    """Interpolated class probabilities by an Arrow UDF: whether the worst is within the square of the grid's step."""
    from delprop.functions.linearize import softmax_column

    x = F.col("features")
    logits = F.array(*[dot(x, F.array(*[F.lit(float(v)) for v in row])) for row in _WQ.reshape(3, 3)])
    rows = fx.small(spark, sf, 2, "softmax", 3).select(logits.alias("u")).withColumn("p", softmax_column("simplex", 0.05)("u"))
    total = F.aggregate(F.transform("u", lambda v: F.exp(v)), F.lit(0.0), lambda s, v: s + v)
    worst = F.array_max(F.zip_with("p", F.transform("u", lambda v: F.exp(v) / total), lambda a, b: F.abs(a - b)))
    return rows.agg(F.count("*").alias("cnt"), (F.max(worst) < 0.05**2).alias("accurate"))


# ---- experiment workloads (seconds vary from run to run, so they have no SQL) ---------------

#: Iterations, copies, columns and batch sizes as far as a query may take; the published ones are in ``workloads.WORKLOADS``.
SCALES = {
    "sgemm_original": {}, "sgemm_extended": {}, "covtype_small": {}, "covtype_large_1": {}, "covtype_large_2": {},
    "covtype_extended": {}, "higgs": {"tau_scale": 0.01}, "higgs_extended": {"tau_scale": 0.001, "copies": 2}, "heartbeat": {}, "heartbeat_extended": {},
    "rcv1": {"tau_scale": 0.1, "batch": 50}, "cifar10": {"tau_scale": 0.01, "width": 64, "batch": 50},
}

for _name, _scale in SCALES.items():

    def _workload(spark, sf, name=_name, scale=_scale):
        return workloads.run(spark, sf, name, rates=(0.01,), repeat=3, workload=workloads.scaled(name, **scale))

    query(f"workload_{_name}")(_workload)


for _name in ("sgemm_original", "higgs_extended"):

    def _repeated(spark, sf, name=_name):
        return workloads.repeated(spark, sf, name, workload=workloads.scaled(name, **SCALES[name]))

    query(f"repeated_{_name}")(_repeated)


@query("rate_sweep")
def rate_sweep(spark, sf):
    """Speed-ups over retraining at all six rates."""
    return workloads.speed_ups(workloads.run(spark, sf, "sgemm_original", repeat=3))


@query("parameter_effects")
def parameter_effects(spark, sf):
    """Speed-ups under a larger batch, more iterations and more features, each pair from runs with all else equal."""
    return workloads.effects(spark, sf, workloads.SMALL_EFFECTS, workloads.SMALL_SETS, repeat=3)


# ---- streams --------------------------------------------------------------------------------


@query("stream_removals", "SELECT event_id AS request_id FROM events WHERE event_type = 'error'")
def stream_removals(spark, sf):
    return requests.drain(requests.requests(spark, sf, delay="40 days").select("request_id"))


@query("stream_windows", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY AS \"end\", count(*) AS requests FROM events WHERE event_type = 'error' GROUP BY 1")
def stream_windows(spark, sf):
    batches = requests.drain(requests.window_counts(requests.requests(spark, sf, delay="40 days")), "complete")
    return batches.where(F.col("batch") == batches.agg(F.max("batch")).first()[0]).select("start", "end", "requests")


@query("stream_states", "SELECT (event_id % 4)::INT AS model, count(*) AS removed, floor(max(epoch(ts)))::BIGINT AS last_ts FROM events WHERE event_type = 'error' GROUP BY 1")
def stream_states(spark, sf):
    batches = requests.drain(requests.running_sets(requests.requests(spark, sf, delay="40 days")), "update")
    return batches.groupBy("model").agg(F.max("removed").alias("removed"), F.max("last_ts").alias("last_ts"))


@query(
    "stream_sessions",
    """WITH e AS (SELECT ts, (event_id % 4)::INT AS model FROM events WHERE event_type = 'error'),
g AS (SELECT ts, model, CASE WHEN ts - lag(ts) OVER (PARTITION BY model ORDER BY ts) < INTERVAL 1 HOUR THEN 0 ELSE 1 END AS fresh FROM e),
s AS (SELECT ts, model, sum(fresh) OVER (PARTITION BY model ORDER BY ts) AS k FROM g) SELECT model, min(ts) AS start, max(ts) + INTERVAL 1 HOUR AS "end", count(*) AS requests FROM s GROUP BY model, k""",
)
def stream_sessions(spark, sf):
    batches = requests.drain(requests.session_counts(requests.requests(spark, sf, delay="40 days")), "complete")
    return batches.where(F.col("batch") == batches.agg(F.max("batch")).first()[0]).select("model", "start", "end", "requests")
