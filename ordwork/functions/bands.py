"""Functions of the methods for SQL and user code: band keys, statistics of classes, neighbours."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, LongType, StructField, StructType


def band_udf(delta: float):
    """Band of a distance as a vectorised UDF, for band rules that expressions can't write; integers have `div`."""

    @F.pandas_udf(LongType())
    def band(dist: pd.Series) -> pd.Series:
        return (dist // delta).astype("int64")

    return band


@F.pandas_udf(DoubleType())
def mean_distance(dist: pd.Series) -> float:
    """Mean as a grouped aggregate UDF."""
    return float(dist.mean())


@F.udtf(returnType=StructType([StructField("dst", LongType()), StructField("w", LongType())]))
class Unpack:
    """Rows of an adjacency array."""

    def eval(self, nbrs):
        for e in nbrs or []:
            yield e["dst"], e["w"]


def register(spark: SparkSession) -> None:
    spark.udf.register("mean_distance", mean_distance)
    spark.udtf.register("unpack_edges", Unpack)


