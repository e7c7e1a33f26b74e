"""Python twins of built-in expressions: Arrow-batched scalar, grouped aggregate and table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .geo import EARTH_M


def great_circle(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    """Haversine metres, for callers that need a Python function; `geo.great_circle_m` is the fast form."""

    @F.pandas_udf("double")
    def run(a: pd.Series, o: pd.Series, b: pd.Series, p: pd.Series) -> pd.Series:
        a, o, b, p = (np.radians(x) for x in (a, o, b, p))
        h = np.sin((b - a) / 2) ** 2 + np.cos(a) * np.cos(b) * np.sin((p - o) / 2) ** 2
        return 2 * EARTH_M * np.arcsin(np.minimum(1.0, np.sqrt(h)))

    return run(lat1, lon1, lat2, lon2)


def mean_micro(c: Column) -> Column:
    @F.pandas_udf("double")
    def run(x: pd.Series) -> float:
        return float(x.mean())

    return run(c)


def parent_cells(spark: SparkSession, places: DataFrame) -> DataFrame:
    """(poi_id, n_grid, r, c): the cells of a place at several resolutions, by a table function in a lateral join."""

    @F.udtf(returnType="n_grid int, r int, c int")
    class Cells:
        def eval(self, y: int, x: int, height: int, width: int):
            for n in (20, 50, 150):
                yield n, min(n - 1, y * n // height), min(n - 1, x * n // width)

    spark.udtf.register("parent_cells", Cells)
    return spark.sql("SELECT poi_id, g.n_grid, g.r, g.c FROM {p} p, LATERAL parent_cells(p.lat_u - p.lat_min_u, p.lon_u - p.lon_min_u, p.lat_max_u - p.lat_min_u, p.lon_max_u - p.lon_min_u) g", p=places)
