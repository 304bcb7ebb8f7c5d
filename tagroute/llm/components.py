"""Connected components of a graph of links, by alternating large-star and small-star rounds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textblocks import discard, materialize


def _toward_least(edges: DataFrame, larger_only: bool) -> DataFrame:
    """Each node tells its neighbours (the larger ones, or the smaller ones and itself) of the least node it sees."""
    if larger_only:
        both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        told = both.join(least, "a").filter(F.col("b") > F.col("a")).select(F.col("b").alias("x"), "m")
    else:
        down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        least = down.groupBy("a").agg(F.min("b").alias("m"))
        told = down.join(least, "a").select(F.col("b").alias("x"), "m").unionByName(least.select(F.col("a").alias("x"), "m"))
    return told.filter("x <> m").select(F.col("x").alias("a"), F.col("m").alias("b")).distinct()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(a, b) links of any comparable type -> (node, root): the least node that each linked node reaches.

    Loops and repeated links do no harm; nodes without links are not returned. The links are
    rewritten round by round until they are stars; each round is written to the shared folder.
    """
    now = materialize(edges.select("a", "b").filter("a <> b").distinct(), "links")
    seen = None
    for _ in range(max_rounds):
        last, now = now, materialize(_toward_least(_toward_least(now, True), False), "links")
        discard(last)
        n, total, spread = now.agg(F.count("*"), F.sum(F.hash("a", "b").cast("decimal(38,0)")), F.max(F.hash("b", "a"))).first()
        if (n, total, spread) == seen:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
        seen = (n, total, spread)
    raise RuntimeError("components did not settle")
