"""What users call from SQL and Python: SQL functions, table functions, user regions, grouped aggregates."""

from __future__ import annotations

import sys

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StructField, StructType

from . import geometry as G

cloudpickle.register_pickle_by_value(sys.modules[__name__])

SQL_FUNCTIONS = {
    "nf_dist": "(x1 DOUBLE, y1 DOUBLE, x2 DOUBLE, y2 DOUBLE) RETURNS DOUBLE RETURN sqrt((x1 - x2) * (x1 - x2) + (y1 - y2) * (y1 - y2))",
    "nf_clover_radius": "(t DOUBLE) RETURNS DOUBLE RETURN 1.5 - power(cos(3 * t - pi() / 2), 3)",
    "nf_clover_spacing": "(x DOUBLE, y DOUBLE, h DOUBLE) RETURNS DOUBLE RETURN h * (1 + 4 * power(cos(3 * atan2(y, x)), 2) * tanh(sqrt(x * x + y * y)))",
}


def register(spark: SparkSession) -> None:
    """SQL functions are inlined by the optimizer, so they cost what their text costs."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name} {body}")


def region_from_python(name: str, dim: int, low, high, test):
    """A region whose membership is a Python function of an [n, dim] array: Arrow batches, after the box filter."""

    @F.pandas_udf("boolean")
    def member(x: pd.Series, y: pd.Series, z: pd.Series) -> pd.Series:
        import numpy as np

        return pd.Series(test(np.stack([x, y, z], 1)[:, :dim]))

    class PythonRegion(G.Region):
        def contains(self) -> Column:
            box = " AND ".join(f"{c} >= {lo!r} AND {c} <= {hi!r}" for c, lo, hi in zip("xyz", self.low, self.high, strict=False))
            return F.expr(box) & member("x", "y", "z")

    return PythonRegion(name, dim, tuple(map(float, low)), tuple(map(float, high)), "TRUE", test)


@F.udtf(returnType=StructType([StructField("cand", IntegerType()), StructField("cx", DoubleType()), StructField("cy", DoubleType())]))
class ExpandPoint:
    """Table function: the n directions around a point at distance h."""

    def eval(self, x: float, y: float, h: float, n: int):
        for j, (u, v) in enumerate(G.sphere(2, n).tolist()):
            yield j, x + h * u, y + h * v


@F.pandas_udf(DoubleType())
def spread(v: pd.Series) -> float:
    """Grouped aggregate: largest minus least."""
    return float(v.max() - v.min())
