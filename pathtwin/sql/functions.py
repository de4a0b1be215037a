"""SQL names for the engine's functions."""

from __future__ import annotations

from pyspark.sql import SparkSession

from pathtwin.metrics import distance_udf
from pathtwin.metrics.kernels import REGISTRY


def register(spark: SparkSession) -> list[str]:
    """Registers ``path_distance_<metric>(array<bigint>, array<bigint>)`` for every metric."""
    names = []
    for metric in REGISTRY:
        names.append(f"path_distance_{metric}")
        spark.udf.register(names[-1], distance_udf(metric))
    return names
