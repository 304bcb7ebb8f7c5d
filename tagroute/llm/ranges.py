"""Rows dealt out by order, so that a hot key spreads over as many tasks as it fills."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .textblocks import materialize, shuffle_parts


def dealt_by_order(df: DataFrame, *order: Column, name: str = "ranges") -> DataFrame:
    """The rows with `pid`: every range of the order is one pid, in order; written, so that a retry deals alike."""
    return materialize(df.repartitionByRange(shuffle_parts(df.sparkSession), *order).withColumn("pid", F.spark_partition_id()), name)
