"""Functions for SQL users: registered column functions, aggregates, a table function over curve ranges, and views."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from meshcut.operators.relational import curve_ranges


def _harmonic(x: pd.Series) -> float:
    s = sum(0.0 if v == float("inf") else 1 / v for v in x)
    return float("inf") if s == 0 else len(x) / s


def _geometric(x: pd.Series) -> float:
    import numpy as np

    return float(np.exp(np.log(x).mean()))


class TileRanges:
    """tile_ranges(x0, x1, y0, y1, bits): the Hilbert key ranges that cover a box of cells."""

    def eval(self, x0: int, x1: int, y0: int, y1: int, bits: int):
        yield from curve_ranges((x0, x1), (y0, y1), bits)


def register(spark: SparkSession) -> None:
    """hilbert2d(gx, gy), harmonic_mean, geometric_mean and tile_ranges for spark.sql."""
    import numpy as np

    def hilbert(gx: pd.Series, gy: pd.Series) -> pd.Series:
        x, y, key = gx.to_numpy(np.int64), gy.to_numpy(np.int64), np.zeros(len(gx), np.int64)
        top = (1 << 16) - 1
        for b in range(15, -1, -1):
            rx, ry = x >> b & 1, y >> b & 1
            key = key * 4 + ((3 * rx) ^ ry)
            x, y = np.where(ry == 1, x, np.where(rx == 1, top - y, y)), np.where(ry == 1, y, np.where(rx == 1, top - x, x))
        return pd.Series(key)

    spark.udf.register("hilbert2d", F.pandas_udf(hilbert, T.LongType()))
    spark.udf.register("harmonic_mean", F.pandas_udf(_harmonic, T.DoubleType(), F.PandasUDFType.GROUPED_AGG))
    spark.udf.register("geometric_mean", F.pandas_udf(_geometric, T.DoubleType(), F.PandasUDFType.GROUPED_AGG))
    spark.udtf.register("tile_ranges", F.udtf(TileRanges, returnType="lo: bigint, hi: bigint"))


def views(points: DataFrame, edges: DataFrame | None = None, assignment: DataFrame | None = None, centres: DataFrame | None = None) -> None:
    """Temp views points, edges, assignment and centres, so the methods can be written in SQL."""
    for name, df in (("points", points), ("edges", edges), ("assignment", assignment), ("centres", centres)):
        if df is not None:
            df.createOrReplaceTempView(name)
