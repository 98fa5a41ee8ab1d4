"""What tests share."""

import numpy as np

SF = "/root/testdata/sf0.001"


def cells(spark, x, keep_zero=True):
    """A dense array as cells; NaN is missing."""
    at = np.argwhere(~np.isnan(x))
    rows = [(int(i), int(j), int(k), float(x[i, j, k])) for i, j, k in at if keep_zero or x[i, j, k] != 0]
    return spark.createDataFrame(rows, "i long, j long, k long, v double")


def dense(df, shape):
    out = np.full(shape, np.nan)
    for r in df.collect():
        out[r.i, r.j, r.k] = np.nan if r.v is None else r.v
    return out
