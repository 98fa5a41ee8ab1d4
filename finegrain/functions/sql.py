"""SQL functions: the model's value, the rank bound, and table functions for cosine bases and periods."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


@udtf(returnType="m long, k long, value double")
class DctBasis:
    """dct_basis(n): the orthonormal cosine basis, a row for each entry."""

    def eval(self, n: int):
        import numpy as np

        for m in range(n):
            scale = np.sqrt((1 if m == 0 else 2) / n)
            for k in range(n):
                yield m, k, float(scale * np.cos(np.pi * m * (2 * k + 1) / (2 * n)))


@udtf(returnType="tick long")
class ExpandPeriod:
    """expand_period(low, high): the ticks low <= tick < high."""

    def eval(self, low: int, high: int):
        for t in range(low or 0, high or 0):
            yield (t,)


def gram_agg(factor: Column, rank: int) -> Column:
    """An aggregate: the Gram matrix of a column of arrays as an array of rows; rank * (rank + 1) / 2 sums, partial on every task."""
    sums = {(r, s): F.sum(factor[r] * factor[s]) for r in range(rank) for s in range(r, rank)}
    return F.array(*(F.array(*(sums[min(r, s), max(r, s)] for s in range(rank))) for r in range(rank)))


#: Native functions: no Python runs.
SQL_FUNCTIONS = {
    "cp_value": "CREATE OR REPLACE TEMPORARY FUNCTION cp_value(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>, c ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(zip_with(a, b, (x, y) -> x * y), c, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "rank_bound": "CREATE OR REPLACE TEMPORARY FUNCTION rank_bound(n_i BIGINT, n_j BIGINT, iu BIGINT, jv BIGINT, kw BIGINT) RETURNS BIGINT RETURN CAST(floor(least(n_i * n_j, n_i * kw, n_j * kw, 16 * iu * jv) / 16) AS BIGINT)",
    "tick_of": "CREATE OR REPLACE TEMPORARY FUNCTION tick_of(at TIMESTAMP_NTZ, origin DATE, days INT) RETURNS BIGINT RETURN CAST(floor(datediff(CAST(at AS DATE), origin) / days) AS BIGINT)",
}


def register(spark: SparkSession) -> None:
    for text in SQL_FUNCTIONS.values():
        spark.sql(text)
    spark.udtf.register("dct_basis", DctBasis)
    spark.udtf.register("expand_period", ExpandPeriod)


def register_model(spark: SparkSession, name: str, factors: dict) -> None:
    """A table function ``name(i, j, k)`` with the model's value for one key, for lateral joins."""
    import numpy as np

    rows = {m: np.asarray(factors[m]).tolist() for m in "ijk"}

    class Reconstruct:
        def eval(self, i: int, j: int, k: int):
            a, b, c = rows["i"][i], rows["j"][j], rows["k"][k]
            yield (float(sum(x * y * z for x, y, z in zip(a, b, c))),)

    spark.udtf.register(name, udtf(Reconstruct, returnType="v double"))
