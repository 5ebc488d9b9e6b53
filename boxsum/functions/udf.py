"""User-defined functions: packed running sums, a compensated sum, and pieces of boxes as a table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from boxsum.plans.box import pieces


@F.pandas_udf(T.ArrayType(T.LongType()))
def packed_cumsum(values: pd.Series) -> pd.Series:
    """Running sums of each array."""
    return values.map(np.cumsum)


@F.pandas_udf(T.DoubleType())
def compensated_sum(values: pd.Series) -> float:
    """A group's sum with the rounding errors carried along."""
    total = rest = 0.0
    for v in values.dropna().to_numpy(float):
        new = total + v
        rest += (total - new) + v if abs(total) >= abs(v) else (v - new) + total
        total = new
    return total + rest


class BoxPieces:
    """(kind, lo, hi, sign) of the pieces of one averaged range."""

    def eval(self, lo: int, hi: int, step: int, n: int) -> Iterator[tuple[str, int, int, int]]:
        found = pieces(lo, hi, step, n)
        for q, sign in found.anchors:
            yield "anchor", q, q, sign
        for a, b, sign in found.gaps:
            yield "gap", a, b, sign


def register(spark: SparkSession) -> None:
    """Make box_pieces(lo, hi, step, n) a table function of the session's SQL."""
    spark.udtf.register("box_pieces", F.udtf(BoxPieces, returnType="kind string, lo int, hi int, sign int"))
