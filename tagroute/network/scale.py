from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fit_scale(edges: DataFrame, pois: DataFrame, ratio: float = 10) -> DataFrame:
    """One row: the factors that bring lengths to (0, 1] and ratings to (0, ratio]."""
    return edges.agg(F.max("w").alias("w_max")).crossJoin(pois.agg(F.max("rating").alias("r_max"))).select("w_max", "r_max", (1.0 / F.col("w_max")).alias("w_factor"), (ratio / F.col("r_max")).alias("r_factor"))
