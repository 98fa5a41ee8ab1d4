"""Fine cells of a fitted model, only those asked for."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from finegrain.sources.tables import factor_frame


def cp_value(*rows: Column) -> Column:
    """The model's value from the factor rows (arrays) of a cell, without Python."""
    product = reduce(lambda a, b: F.zip_with(a, b, lambda x, y: x * y), rows)
    return F.aggregate(product, F.lit(0.0), lambda s, x: s + x)


def reconstruct(keys: DataFrame, factors: dict[str, np.ndarray], name: str = "v", modes: str = "ijk") -> DataFrame:
    """keys (i, j, k or the letters of ``modes``, and more) with the model's value.

    Factors are broadcast (their size is checked in ``cell_pass``'s way); keys stay where they are, and filters on them reach their scan.
    """
    from finegrain.operators.kernels import check_size

    factors = {m: factors[m] for m in modes}
    check_size(factors)
    spark = keys.sparkSession
    shared = spark.sparkContext.broadcast(factors)
    schema = T.StructType([*keys.schema.fields, T.StructField(name, T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = shared.value
        for batch in batches:
            value = reduce(np.multiply, [f[m][batch.column(m).to_numpy()] for m in modes]).sum(1)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(value)], names=[*batch.schema.names, name])

    return keys.mapInArrow(run, schema)


def reconstruct_sql(keys: DataFrame, factors: dict[str, np.ndarray], name: str = "v") -> DataFrame:
    """As reconstruct, as broadcast joins and array functions: one plan for Catalyst, for small ranks."""
    out = keys
    for m in "ijk":
        out = out.join(F.broadcast(factor_frame(keys.sparkSession, factors[m]).toDF(m, f"_f{m}")), m)
    return out.withColumn(name, cp_value(*(F.col(f"_f{m}") for m in "ijk"))).drop("_fi", "_fj", "_fk").select(*keys.columns, name)


def top_cells(spark: SparkSession, factors: dict[str, np.ndarray], n: int, modes: str = "ijk") -> DataFrame:
    """The n largest cells of a model, of any number of modes.

    No cell that begins with indexes (i, j, ...) exceeds |a_i * b_j * ...| times the largest row norms of the other modes. Beginnings are taken in
    the order of these bounds, and none is gone on with whose bound is below the n-th value found so far.
    """
    rows = [factors[m] for m in modes]
    most = np.cumprod([1.0, *(np.linalg.norm(f, axis=1).max() for f in rows[:0:-1])])[::-1]  # of the modes after each
    best: list[tuple[float, tuple[int, ...]]] = []
    least = lambda: best[-1][0] if len(best) == n else -np.inf

    def go_on(begin: tuple[int, ...], product: np.ndarray) -> None:
        nonlocal best
        at = len(begin)
        each = product * rows[at]
        bound = np.linalg.norm(each, axis=1) * most[at]
        order = np.argsort(-bound)
        if at < len(rows) - 2:
            for x in order:
                if bound[x] < least():
                    return
                go_on((*begin, int(x)), each[x])
            return
        for first in range(0, len(order), 1024):  # the last two modes together
            own = order[first : first + 1024]
            own = own[bound[own] >= least()]
            if not len(own):
                return
            values = each[own] @ rows[-1].T
            top = np.argpartition(-values.ravel(), min(n, values.size) - 1)[:n]
            found = [(float(values[x, y]), (*begin, int(own[x]), int(y))) for x, y in zip(*np.unravel_index(top, values.shape))]
            best = sorted(best + found, key=lambda t: (-t[0], t[1]))[:n]

    go_on((), np.ones(rows[0].shape[1]))
    return spark.createDataFrame([(*index, v) for v, index in best], ", ".join([*(f"{m} long" for m in modes), "v double"]))
