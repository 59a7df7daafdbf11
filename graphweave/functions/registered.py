"""User-defined forms of the kernels: scalar, pandas and Arrow functions, a grouped reducer, a table function."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


@F.udf("double")
def norm_row(x):
    return float(sum(v * v for v in x)) if x is not None else None


@F.pandas_udf("double")
def norm_pandas(x: pd.Series) -> pd.Series:
    return x.map(lambda v: float(np.dot(np.asarray(v, float), np.asarray(v, float))))


@F.arrow_udf("double")
def norm_arrow(x: pa.Array) -> pa.Array:
    values = x.flatten().to_numpy(zero_copy_only=False).astype(float)
    ends = np.concatenate([[0], np.cumsum(pa.compute.list_value_length(x).fill_null(0).to_numpy(zero_copy_only=False))]).astype(int)
    sums = np.concatenate([[0.0], np.cumsum(values * values)])
    return pa.array(sums[ends[1:]] - sums[ends[:-1]])


@F.pandas_udf("array<double>")
def vector_sum(x: pd.Series) -> list:
    """A user-defined reducer over a group's vectors."""
    return np.sum(np.stack([np.asarray(v, float) for v in x]), axis=0).tolist()


@F.udtf(returnType="vid bigint, part int")
class EdgeClones:
    """An edge's two clones."""

    def eval(self, src: int, dst: int, part: int):
        yield src, part
        yield dst, part


def register(spark: SparkSession) -> None:
    """vec_norm, part_of and edge_clones for SQL text."""
    spark.udf.register("vec_norm2", norm_pandas)
    spark.udtf.register("edge_clones", EdgeClones)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION part_of(a BIGINT, b BIGINT, p INT) RETURNS INT RETURN CAST((least(a, b) * 7919 + greatest(a, b) * 104729) % p AS INT)")
