"""Functions that go through Arrow batches: a scalar one, an aggregate, and a table function."""

from itertools import permutations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


def score_udf(alpha: float, w_max: float = 19, r_max: float = 90, ratio: float = 10):
    """The score of a route as an Arrow-batched function of distance and ratings; `route_score` is the same within code generation."""

    @pandas_udf("double")
    def score(dist: pd.Series, rating: pd.Series) -> pd.Series:
        return (-alpha * dist / w_max + (1 - alpha) * ratio * rating / r_max).round(6)

    return score


def geometric_mean():
    """An aggregate over Arrow batches of a group; groups must fit a task, so prefer built-in ones for large groups."""

    @pandas_udf("double")
    def mean(x: pd.Series) -> float:
        return float(np.exp(np.log(x).mean()))

    return mean


def register_orders(spark: SparkSession, name: str = "tcr_orders") -> None:
    """A SQL table function: every order of visiting m tags, as text."""

    @udtf(returnType="visits string")
    class Orders:
        def eval(self, m: int):
            for p in permutations(range(m)):
                yield (",".join(map(str, p)),)

    spark.udtf.register(name, Orders)
