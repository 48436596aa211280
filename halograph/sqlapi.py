"""User-defined functions for SQL: an Arrow scalar, an aggregate over vectors, and a table function that samples adjacency lists."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StructField, StructType

#: as objects, since a type's text is parsed by a session and modules must load without one
VECTOR = ArrayType(DoubleType())


@arrow_udf(VECTOR)
def relu_vec(x: pa.Array) -> pa.Array:
    """ReLU of every element, on Arrow buffers."""
    flat = np.maximum(x.flatten().to_numpy(zero_copy_only=False), 0.0)
    return pa.ListArray.from_arrays(x.offsets.slice(0), pa.array(flat)) if x.offset == 0 and x.null_count == 0 else pa.array([None if v is None else [max(0.0, e) for e in v] for v in x.to_pylist()], pa.list_(pa.float64()))


@pandas_udf(VECTOR)
def vec_mean(x: pd.Series) -> list:
    """Mean vector of a group."""
    return np.mean(np.array(x.tolist(), np.float64), axis=0).tolist()


@udtf(returnType=StructType([StructField("src", LongType()), StructField("n", IntegerType())]))
class SampleNeighbors:
    """Up to f entries of an adjacency list, in the order of their hashes."""

    def eval(self, dst: int, adj: list, f: int, seed: int) -> Iterator[tuple[int, int]]:
        import hashlib

        order = sorted(adj, key=lambda s: (hashlib.md5(f"{seed}|{dst}|{s}".encode()).hexdigest(), s))
        yield from ((int(s), k) for k, s in enumerate(order[:f]))


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL as relu_vec, vec_mean and sample_neighbors."""
    spark.udf.register("relu_vec", relu_vec)
    spark.udf.register("vec_mean", vec_mean)
    spark.udtf.register("sample_neighbors", SampleNeighbors)


