"""Objectives with a target: least squares and logistic loss, by full passes; one block of weights."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gossamer.functions.arrays import dot


def residual(kind: str):
    """Derivative of the loss by the prediction; labels of logistic loss are 0 and 1."""
    score = dot("x", F.col("w"))
    return score - F.col("y") if kind == "squares" else F.lit(1.0) / (F.lit(1.0) + F.exp(-score)) - F.col("y")


def linear_batch(points: DataFrame, kind: str, eps: float, steps: int) -> list[float]:
    """Weights after ``steps`` full passes over ``(x, y)``."""
    spark = points.sparkSession
    w = [0.0] * points.select(F.size("x")).first()[0]
    for _ in range(steps):
        state = spark.createDataFrame([(w,)], "w array<double>")
        each = points.crossJoin(F.broadcast(state)).select("x", residual(kind).alias("r"))
        g = each.agg(*[F.avg(F.col("r") * F.col("x")[j]).alias(f"g{j}") for j in range(len(w))]).first()
        w = [a - eps * b for a, b in zip(w, g, strict=True)]
    if any(math.isnan(v) for v in w):
        raise ValueError("the weights diverged: use a smaller step")
    return w
