"""Vector quantisation: prototypes as a codebook, objects as histograms of their samples' nearest entries."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gossamer.operators.descent import assigned


def histogram(points: DataFrame, w: list, groups: DataFrame) -> DataFrame:
    """``object, cluster, n`` for ``groups (sample_id, object)``."""
    return assigned(points, w).join(groups, "sample_id").groupBy("object", "cluster").agg(F.count("*").alias("n"))
