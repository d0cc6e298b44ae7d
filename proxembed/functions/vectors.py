"""Vector arithmetic as column expressions over ARRAY<DOUBLE>, the gradient scalar, and packing to float32 bytes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_axpy(k: Column, a: Column, b: Column) -> Column:
    """k * a + b."""
    return F.zip_with(a, b, lambda x, y: k * x + y)


def vec_norm(a: Column) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_cosine(a: Column, b: Column) -> Column:
    return vec_dot(a, b) / (vec_norm(a) * vec_norm(b))


def sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))


def grad_scalar(dot: Column, sign: Column, lr: float, neg_weight: float = 1.0) -> Column:
    """Signed step of a pair: towards each other if sign is 1, apart if it is -1."""
    return F.when(sign > 0, lr * (1 - sigmoid(dot))).otherwise(-lr * neg_weight * sigmoid(dot))


def vec_sum(rows: DataFrame, keys: list[str], vector: str) -> DataFrame:
    """Element-wise sums by key: one row per element, partial sums before the shuffle, packed again in order."""
    parts = rows.select(*keys, F.posexplode(vector).alias("_i", "_x")).groupBy(*keys, "_i").agg(F.sum("_x").alias("_x"))
    return parts.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("_i", "_x"))), lambda s: s["_x"]).alias(vector))


def pack(rows: np.ndarray) -> bytes:
    return np.ascontiguousarray(rows, dtype="<f4").tobytes()


def unpack(data: bytes, dim: int) -> np.ndarray:
    return np.frombuffer(data, dtype="<f4").reshape(-1, dim).copy()


def register_sql(spark: SparkSession) -> None:
    """SQL names for use in spark.sql: vec_dot, vec_cosine, proximity."""
    for name, body in {
        "vec_dot": "aggregate(zip_with(a, b, (x, y) -> cast(x as double) * cast(y as double)), cast(0 as double), (s, x) -> s + x)",
        "vec_cosine": "aggregate(zip_with(a, b, (x, y) -> cast(x as double) * y), cast(0 as double), (s, x) -> s + x) / sqrt(aggregate(a, cast(0 as double), (s, x) -> s + cast(x as double) * x) * aggregate(b, cast(0 as double), (s, x) -> s + cast(x as double) * x))",
        "proximity": "1 / (1 + exp(-aggregate(zip_with(a, b, (x, y) -> cast(x as double) * y), cast(0 as double), (s, x) -> s + x)))",
    }.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")
