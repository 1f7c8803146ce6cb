"""Functions for SQL users: vector and linearisation expressions as SQL functions, and a schedule table function."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

# Bodies of the SQL functions; they inline into plans, so they stay in generated code.
_BODIES = {
    "dp_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "dp_margin": "(w ARRAY<DOUBLE>, x ARRAY<DOUBLE>, y DOUBLE) RETURNS DOUBLE RETURN y * aggregate(zip_with(w, x, (a, b) -> a * b), 0D, (s, v) -> s + v)",
    "dp_slope": "(z DOUBLE) RETURNS DOUBLE RETURN CASE WHEN abs(z) < 20 THEN (1 / (1 + exp(floor((z + 20) / 4e-5) * 4e-5 - 20 + 4e-5)) - 1 / (1 + exp(floor((z + 20) / 4e-5) * 4e-5 - 20))) / 4e-5 ELSE 0D END",
    "dp_offset": "(z DOUBLE) RETURNS DOUBLE RETURN CASE WHEN abs(z) < 20 THEN 1 / (1 + exp(floor((z + 20) / 4e-5) * 4e-5 - 20)) - (1 / (1 + exp(floor((z + 20) / 4e-5) * 4e-5 - 20 + 4e-5)) - 1 / (1 + exp(floor((z + 20) / 4e-5) * 4e-5 - 20))) / 4e-5 * (floor((z + 20) / 4e-5) * 4e-5 - 20) ELSE 1 / (1 + exp(greatest(least(z, 20D), -20D))) END",
    "dp_predict": "(w ARRAY<DOUBLE>, x ARRAY<DOUBLE>) RETURNS DOUBLE RETURN 1 / (1 + exp(-aggregate(zip_with(w, x, (a, b) -> a * b), 0D, (s, v) -> s + v)))",
}


@udtf(returnType="t int, block_id int")
class Steps:
    """(t, block) for the iterations first..last-1 over ``blocks`` blocks."""

    def eval(self, first: int, last: int, blocks: int) -> Iterator[tuple[int, int]]:
        for t in range(first, last):
            yield t, t % blocks


def register(spark: SparkSession) -> None:
    for name, body in _BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name} {body}")
    spark.udtf.register("dp_steps", Steps)
