"""Functions for users: column expressions, Arrow functions, a table function, and their registration for SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from boundspark.operators import entropy as E
from boundspark.plans.lattice import multilevel_plan


def quantize(x: Column, p: Column, step: Column) -> Column:
    return F.when(step == 0, F.lit(0)).otherwise(F.floor((x - p) / step + 0.5)).cast("long")


def dequantize(k: Column, p: Column, step: Column) -> Column:
    return p + k * step


def zigzag(k: Column) -> Column:
    return F.when(k >= 0, 2 * k).otherwise(-2 * k - 1)


def bits_per_value(n_bytes: Column, n: Column) -> Column:
    return 8.0 * n_bytes / n


def gain_pct(bytes_model: Column, bytes_bar: Column) -> Column:
    return 100.0 * (1 - bytes_model / bytes_bar)


def flip_probability(drift: Column, step: Column, n: Column) -> Column:
    return 1 - F.exp(-n * drift / step)


@F.pandas_udf(T.BinaryType())
def encode_indices(k: pd.Series) -> pd.Series:
    """Range-coded bytes of arrays of indices; the lanes of a batch are coded in lockstep."""
    import numpy as np

    return pd.Series(E.encode_lanes([np.asarray(v if v is not None else [], np.int64) for v in k]))


@F.pandas_udf(T.ArrayType(T.LongType()))
def decode_indices(data: pd.Series, n: pd.Series) -> pd.Series:
    return pd.Series([E.decode_lane(d, int(m)).tolist() for d, m in zip(data, n, strict=True)])


@F.pandas_udf(T.LongType())
def coded_bytes(k: pd.Series) -> int:
    """Aggregate: real bytes of a group's indices in the order given."""
    import numpy as np

    return len(E.encode_lanes([k.to_numpy(np.int64)])[0])


@F.udtf(returnType="level int, idx int, stride int")
class MultilevelSchedule:
    """Targets of a block in emission order."""

    def eval(self, size: int):
        for k, (i, stride, _) in enumerate(multilevel_plan("linear", size)):
            yield k, i, stride


def register_all(spark: SparkSession) -> None:
    spark.udf.register("encode_indices", encode_indices)
    spark.udf.register("decode_indices", decode_indices)
    spark.udf.register("coded_bytes", coded_bytes)
    spark.udtf.register("multilevel_schedule", MultilevelSchedule)
