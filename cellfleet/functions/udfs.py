"""Functions that Spark lacks, for DataFrames and SQL: a grouped flatness and the code ranges of a box."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from cellfleet.functions import zorder


@pandas_udf(DoubleType())
def flatness(order: pd.Series, value: pd.Series) -> float:
    """Sum of absolute steps of the values in the order of the first column."""
    v = value.to_numpy()[np.argsort(order.to_numpy(), kind="stable")]
    return float(np.abs(np.diff(v)).sum())


@udtf(returnType=StructType([StructField("lo", LongType()), StructField("hi", LongType())]))
class ZorderRanges:
    def eval(self, x0: int, y0: int, x1: int, y1: int) -> Iterator[tuple[int, int]]:
        yield from zorder.ranges(x0, y0, x1, y1)


def register(spark: SparkSession) -> None:
    """Names for SQL: ``flatness`` and ``zorder_ranges``."""
    spark.udf.register("flatness", flatness)
    spark.udtf.register("zorder_ranges", ZorderRanges)
