"""The symbolic layer: provenance polynomials and annotated matrices as DataFrames.

A polynomial is a set of rows (monomial map<string,int>, coefficient bigint);
an annotated matrix has rows (monomial, rows, cols, cells array<double>), the
sum of monomial * matrix over the rows.  Monomials map tokens to exponents;
the empty map is one.  Rows group by the sorted entry list, since maps do not.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from delprop.functions.linearize import pieces
from delprop.scratch import stored
from delprop.spec import ModelSpec

POLYNOMIAL = "monomial map<string,int>, coefficient bigint"
TERMS = "monomial map<string,int>, rows int, cols int, cells array<double>"
#: Above this many sample-iterations the symbolic iteration is refused: its size is exponential.
MAX_STEPS = 64


def canonical(monomial: Column) -> Column:
    return F.array_sort(F.map_entries(F.map_filter(monomial, lambda _, e: e != 0)))


def label(monomial: Column) -> Column:
    """Readable form, tokens in order: ``p^2*q``; one is ``1``."""
    entry = F.transform(canonical(monomial), lambda e: F.when(e["value"] == 1, e["key"]).otherwise(F.concat(e["key"], F.lit("^"), e["value"].cast("string"))))
    return F.when(F.size(entry) == 0, F.lit("1")).otherwise(F.array_join(entry, "*"))


def merge(a: Column, b: Column) -> Column:
    """Product of monomials: exponents add."""
    return F.map_zip_with(a, b, lambda _, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))


def _regroup(terms: DataFrame) -> DataFrame:
    if "coefficient" in terms.columns:
        summed = terms.groupBy(canonical(F.col("monomial")).alias("entries")).agg(F.sum("coefficient").alias("coefficient")).where("coefficient <> 0")
        return summed.select(F.map_from_entries("entries").alias("monomial"), "coefficient")
    cell = terms.select(canonical(F.col("monomial")).alias("entries"), "rows", "cols", F.posexplode("cells").alias("pos", "v"))
    return _gathered(cell)


def _gathered(cell: DataFrame) -> DataFrame:
    """Terms from their cells (entries, rows, cols, pos, v)."""
    totals = cell.groupBy("entries", "rows", "cols", "pos").agg(F.sum("v").alias("v"))
    whole = totals.groupBy("entries", "rows", "cols").agg(F.sort_array(F.collect_list(F.struct("pos", "v"))).alias("s"))
    return whole.select(F.map_from_entries("entries").alias("monomial"), "rows", "cols", F.transform("s", lambda x: x["v"]).alias("cells"))


def zero(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], POLYNOMIAL)


def one(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([({}, 1)], POLYNOMIAL)


def add(left: DataFrame, right: DataFrame) -> DataFrame:
    return _regroup(left.unionByName(right))


def mul(left: DataFrame, right: DataFrame) -> DataFrame:
    """Every pair of terms is what a product of sums is; symbolic operands are small."""
    pairs = left.crossJoin(right.select(F.col("monomial").alias("m2"), F.col("coefficient").alias("c2")))
    return _regroup(pairs.select(merge(F.col("monomial"), F.col("m2")).alias("monomial"), (F.col("coefficient") * F.col("c2")).alias("coefficient")))


def annotate(matrix: np.ndarray, monomial: dict[str, int], spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(monomial, *matrix.shape, [float(v) for v in matrix.ravel()])], TERMS)


def scale(polynomial: DataFrame, terms: DataFrame) -> DataFrame:
    """p * A for a polynomial p: monomials multiply, coefficients scale the cells."""
    pairs = terms.crossJoin(polynomial.select(F.col("monomial").alias("m2"), "coefficient"))
    cells = F.transform("cells", lambda v: v * F.col("coefficient"))
    return _regroup(pairs.select(merge(F.col("monomial"), F.col("m2")).alias("monomial"), "rows", "cols", cells.alias("cells")))


def times(number: float, terms: DataFrame) -> DataFrame:
    return terms.withColumn("cells", F.transform("cells", lambda v: v * F.lit(float(number))))


def matmul(left: DataFrame, right: DataFrame) -> DataFrame:
    """(p1 * A1)(p2 * A2) = (p1 p2) * (A1 A2), summed over all terms: a join on the inner dimension."""
    a = left.select(F.col("monomial").alias("m1"), F.col("rows").alias("r1"), F.col("cols").alias("c1"), F.posexplode("cells").alias("pos1", "x"))
    a = a.select("m1", "r1", F.floor(F.col("pos1") / F.col("c1")).cast("int").alias("i"), (F.col("pos1") % F.col("c1")).alias("inner"), "x")
    b = right.select(F.col("monomial").alias("m2"), F.col("cols").alias("c2"), F.posexplode("cells").alias("pos2", "y"))
    b = b.select("m2", "c2", F.floor(F.col("pos2") / F.col("c2")).cast("int").alias("inner"), (F.col("pos2") % F.col("c2")).alias("j"), "y")
    cell = a.join(b, "inner").select(
        canonical(merge(F.col("m1"), F.col("m2"))).alias("entries"), F.col("r1").alias("rows"), F.col("c2").alias("cols"), (F.col("i") * F.col("c2") + F.col("j")).alias("pos"), (F.col("x") * F.col("y")).alias("v")
    )
    return _gathered(cell)


def decompose(samples: DataFrame, token: str = "p") -> DataFrame:
    """Each sample's row, annotated with its token: X as a sum of single-row terms."""
    monomial = F.create_map(F.concat(F.lit(token), F.col("sample_id").cast("string")), F.lit(1))
    return samples.select(monomial.alias("monomial"), F.lit(1).alias("rows"), F.size("features").alias("cols"), F.col("features").alias("cells"))


def gram(terms: DataFrame, alpha: Column | float = 1.0) -> DataFrame:
    """Sum of alpha_i x_i x_i' of single-row terms: tokens come out squared."""
    alpha = F.lit(float(alpha)) if isinstance(alpha, (int, float)) else alpha
    x = F.col("cells")
    outer = F.flatten(F.transform(x, lambda a: F.transform(x, lambda b: alpha * a * b)))
    return _regroup(terms.select(merge(F.col("monomial"), F.col("monomial")).alias("monomial"), F.col("cols").alias("rows"), "cols", outer.alias("cells")))


def delete(terms: DataFrame, tokens: list[str]) -> DataFrame:
    """Set tokens to zero: their terms vanish."""
    if not tokens:
        return terms
    return terms.where(~F.arrays_overlap(F.map_keys("monomial"), F.array(*[F.lit(t) for t in tokens])))


def delete_by_join(terms: DataFrame, tokens: DataFrame) -> DataFrame:
    """The same for a table of tokens (token string) of any size."""
    marked = terms.withColumn("key", F.array_join(F.transform(canonical(F.col("monomial")), lambda e: e["key"]), "\x00"))
    hit = marked.select("key", F.explode(F.map_keys("monomial")).alias("token")).join(tokens, "token", "left_semi").select("key").distinct()
    return marked.join(hit, "key", "left_anti").drop("key")


def evaluate(terms: DataFrame) -> DataFrame:
    """Set the remaining tokens to one: (pos, value) of the summed matrix, or (value) of a polynomial."""
    if "coefficient" in terms.columns:
        return terms.agg(F.coalesce(F.sum("coefficient"), F.lit(0)).alias("value"))
    return terms.select(F.posexplode("cells").alias("pos", "v")).groupBy("pos").agg(F.sum("v").alias("value"))


def idempotent(terms: DataFrame) -> DataFrame:
    """Products of a token with itself collapse: exponents become one."""
    return _regroup(terms.withColumn("monomial", F.transform_values("monomial", lambda _, e: F.least(e, F.lit(1)))))


def _plus(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return _regroup(out)


def _iterate(samples: DataFrame, spec: ModelSpec, n_rows: int, row_terms, collapse: bool) -> DataFrame:
    if n_rows * spec.tau > MAX_STEPS:
        raise ValueError(f"symbolic iteration over {n_rows} samples and {spec.tau} steps is exponential; the limit is {MAX_STEPS} sample-steps")
    spark = samples.sparkSession
    w = annotate(spec.start()[:, None], {}, spark)
    for t in range(spec.tau):
        matrix, rest = row_terms(t)
        w = _plus([times(1 - spec.rate(t) * spec.lam, w), matmul(matrix, w), rest])
        w = stored(idempotent(w) if collapse else w, "terms")
    return w


def iterate_linear(samples: DataFrame, spec: ModelSpec, collapse: bool = True, divisor: int | None = None) -> DataFrame:
    """Annotated full-batch linear iterations: the parameters as terms over the samples' tokens.

    Deleting tokens and evaluating gives the survivors' run with ``divisor``
    (their number, the whole set's by default) in every step.
    """
    rows = samples.select("sample_id", "features", "label").collect()
    spark, n = samples.sparkSession, divisor or len(rows)

    def terms(matrix_of) -> DataFrame:
        return spark.createDataFrame([({f"p{r.sample_id}": 2}, *(m := matrix_of(r)).shape, [float(v) for v in m.ravel()]) for r in rows], TERMS)

    def at(t: int) -> tuple[DataFrame, DataFrame]:
        k = 2 * spec.rate(t) / n
        return terms(lambda r: -k * np.outer(r.features, r.features)), terms(lambda r: k * r.label * np.array(r.features)[:, None])

    return _iterate(samples, spec, len(rows), at, collapse)


def iterate_logistic(samples: DataFrame, spec: ModelSpec, trajectory: np.ndarray, collapse: bool = True, divisor: int | None = None) -> DataFrame:
    """Annotated full-batch iterations of the linearised binary rule, with pieces at the captured ``trajectory``."""
    rows = samples.select("sample_id", "features", "label").collect()
    spark, n = samples.sparkSession, divisor or len(rows)

    def at(t: int) -> tuple[DataFrame, DataFrame]:
        k = spec.rate(t) / n
        quadratic, linear = [], []
        for r in rows:
            x = np.array(r.features)
            a, b = (float(v) for v in pieces(r.label * (x @ trajectory[t])))
            token = {f"p{r.sample_id}": 2}
            quadratic.append((token, len(x), len(x), [float(v) for v in (k * a * np.outer(x, x)).ravel()]))
            linear.append((token, len(x), 1, [float(v) for v in k * b * r.label * x]))
        return spark.createDataFrame(quadratic, TERMS), spark.createDataFrame(linear, TERMS)

    return _iterate(samples, spec, len(rows), at, collapse)


def contributions(terms: DataFrame) -> DataFrame:
    """(monomial text, size): Euclidean length of each monomial's cells."""
    square = F.aggregate("cells", F.lit(0.0), lambda s, v: s + v * v)
    return _regroup(terms).select(label(F.col("monomial")).alias("monomial"), F.sqrt(square).alias("size"))
