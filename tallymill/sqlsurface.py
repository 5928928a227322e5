"""Names for SQL users: functions for hashing and reading, a table function for packed sketches."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallymill.functions.hashing import hash_np
from tallymill.params import SketchParams


def register(spark: SparkSession, p: SketchParams, cells: DataFrame | None = None) -> None:
    """cm_col(key, row), counter_read(state) and sketch_cells(payload) for one set of parameters, and
    a view `cells`."""
    base = p.base or 2.0

    @F.pandas_udf("int")
    def cm_col(key: pd.Series, row: pd.Series) -> pd.Series:
        out = np.zeros(len(key), np.int32)
        for i in range(p.l):
            out = np.where(row == i, hash_np(key.to_numpy(), i, p), out)
        return pd.Series(out.astype(np.int32))

    @F.pandas_udf("double")
    def counter_read(state: pd.Series) -> pd.Series:
        return (base ** state.astype(float) - 1) / (base - 1)

    @F.udtf(returnType="i int, col int, value long")
    class SketchCells:
        def eval(self, payload: bytes):
            m = np.frombuffer(payload, {8: "<u1", 16: "<u2", 32: "<u4", 64: "<u8"}[p.bits])
            for at in np.flatnonzero(m).tolist():
                yield at // p.w, at % p.w, int(m[at])

    spark.udf.register("cm_col", cm_col)
    spark.udf.register("counter_read", counter_read)
    spark.udtf.register("sketch_cells", SketchCells)
    if cells is not None:
        cells.createOrReplaceTempView("cells")
