"""Column functions that methods share."""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .arrow import geometric_mean, register_orders, score_udf  # noqa: F401

#: Scaling of the lattices: longest edge, best rating, and the ratio of their ranges.
W_MAX, R_MAX, RATIO = 19, 90, 10


def route_score(dist: Column, rating: Column, alpha: Column | float, w_max: float = W_MAX, r_max: float = R_MAX) -> Column:
    """-alpha * scaled distance + (1 - alpha) * scaled ratings, rounded for output."""
    a = alpha if isinstance(alpha, Column) else F.lit(float(alpha))
    return F.round(-a * dist / w_max + (1 - a) * RATIO * rating / r_max, 6)


def reach_radius(alpha: Column, tau: Column, floor: Column, w_max: float = W_MAX, r_max: float = R_MAX) -> Column:
    """Distance beyond which no route with ratings up to tau beats the floor; null (no bound) for alpha 0 or without a floor."""
    return F.when((alpha > 0) & floor.isNotNull(), w_max * ((1 - alpha) * RATIO * tau / r_max - floor) / alpha)


def orders_table(spark: SparkSession, m: int) -> DataFrame:
    """All visiting orders of m tags: (o1, ..., om). m is small and fixed, m! rows."""
    return spark.createDataFrame([tuple(p) for p in permutations(range(m))], ", ".join(f"o{i + 1} int" for i in range(m)))


def line_length(xs: list[Column], ys: list[Column]) -> Column:
    """Straight-line length of a chain of points."""
    legs = [F.hypot((xs[i + 1] - xs[i]).cast("double"), (ys[i + 1] - ys[i]).cast("double")) for i in range(len(xs) - 1)]
    out = legs[0]
    for leg in legs[1:]:
        out = out + leg
    return out
