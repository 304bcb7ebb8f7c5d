"""Relational operators around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, on: str, time: str, value: str) -> DataFrame:
    """Each row of left with right's latest value not after it: one pass over both sides, sorted by key and time."""
    both = left.select(on, time, *(c for c in left.columns if c not in (on, time)), F.lit(None).cast(right.schema[value].dataType).alias(f"_{value}"), F.lit(1).alias("_side")).unionByName(
        right.select(on, time, F.col(value).alias(f"_{value}"), F.lit(0).alias("_side")), allowMissingColumns=True
    )
    w = W.partitionBy(on).orderBy(time, "_side").rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn(value, F.last(f"_{value}", ignorenulls=True).over(w)).filter("_side = 1").drop(f"_{value}", "_side")


def interval_join(left: DataFrame, right: DataFrame, on: str, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of a key with right's time within so many seconds after left's: an equi-join on time buckets, then the exact bound."""
    bucket = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / seconds)
    a = left.withColumn("_b", F.explode(F.array(bucket(left_time), bucket(left_time) + 1)))
    b = right.withColumn("_b", bucket(right_time))
    gap = F.unix_micros(F.col(right_time).cast("timestamp")) - F.unix_micros(F.col(left_time).cast("timestamp"))
    return a.join(b, [on, "_b"]).filter((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_b")


def connected(edges: DataFrame, max_rounds: int = 200) -> DataFrame:
    """(v, root): the least vertex of each vertex' component, by stars.

    A round hangs each vertex' greater neighbours, then its lesser ones, on the least vertex near it. Ways shrink by halves and not by
    steps, so rounds grow with the logarithm of the network's width.
    """
    from ..plans.rounds import discard, materialize

    least = lambda df, key, of: df.join(df.groupBy(key).agg(F.min(of).alias("m")), key)
    # (a, b) with a > b hangs a on b; alone: every vertex, for those that have loops alone
    every = materialize(edges.select(F.col("u").alias("v")).unionByName(edges.select("v")).distinct(), "vertices")
    now = materialize(edges.filter("u <> v").select(F.greatest("u", "v").alias("a"), F.least("u", "v").alias("b")).distinct(), "stars")
    for _ in range(max_rounds):
        both = now.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(now.select(F.col("b").alias("u"), F.col("a").alias("v")))
        large = least(both, "u", "v").filter("v > u").select(F.col("v").alias("a"), F.least("u", "m").alias("b")).distinct()
        near = least(large, "a", "b")
        nxt = near.filter("b > m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(near.select("a", F.col("m").alias("b"))).distinct()
        nxt = materialize(nxt, "stars")
        # settled: every vertex hangs once, and on one that hangs on none
        settled = nxt.groupBy("a").count().filter("count > 1").isEmpty() and nxt.join(nxt.select(F.col("a").alias("b")), "b", "left_semi").isEmpty()
        discard(now)
        now = nxt
        if settled:
            return every.join(now.select(F.col("a").alias("v"), F.col("b").alias("root")), "v", "left").select("v", F.coalesce("root", "v").alias("root"))
    raise RuntimeError("components did not settle")


def set_counts(a: DataFrame, b: DataFrame) -> DataFrame:
    """(kind, n): distinct rows of both, of the first alone, and of any."""
    kinds = (("both", a.intersect(b)), ("supplier only", a.exceptAll(b).distinct().join(b, a.columns, "left_anti")), ("any", a.union(b).distinct()))
    counted = [df.agg(F.count("*").alias("n")).select(F.lit(k).alias("kind"), "n") for k, df in kinds]
    return counted[0].unionByName(counted[1]).unionByName(counted[2])


def hash_sample(rows: DataFrame, key: str, share: float) -> DataFrame:
    """Rows of about a share of the keys: the same ones on every run, and all rows of a key or none."""
    return rows.filter(F.substring(F.md5(F.col(key).cast("string")), 1, 2) < f"{int(share * 256):02x}")


def approximate(pois: DataFrame) -> DataFrame:
    """(tag, places, close, median_close): distinct vertices, and whether a sketch of them and one of the median rating come near."""
    exact, sketch = F.count_distinct("v"), F.approx_count_distinct("v", 0.02)
    median = F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY rating)")
    return pois.groupBy("tag").agg(exact.alias("places"), (F.abs(sketch - exact) <= 0.1 * exact).alias("close"), (F.abs(F.percentile_approx("rating", 0.5, 10_000) - median) <= 1).alias("median_close"))


def k_hop(arcs: DataFrame, start: DataFrame, k: int) -> DataFrame:
    """(v, hop): vertices within k arcs of the start, by rounds."""
    from ..plans.rounds import materialize

    seen = front = materialize(start.select(F.col("v").cast("long").alias("v"), F.lit(0).cast("long").alias("hop")), "hops")
    for _ in range(k):
        told = arcs.select("u", F.col("v").alias("to")).join(front.select(F.col("v").alias("u"), "hop"), "u").select(F.col("to").alias("v"), (F.col("hop") + 1).alias("hop")).distinct()
        front = materialize(told.join(seen.select("v"), "v", "left_anti"), "hops")
        seen = seen.unionByName(front)
    return seen


def rollup_pois(pois: DataFrame, nations: DataFrame, regions: DataFrame) -> DataFrame:
    """POIs and mean ratings by region and nation, with subtotals."""
    named = pois.join(F.broadcast(nations.join(regions, nations.n_regionkey == regions.r_regionkey)), F.col("tag") == F.col("n_name"))
    return named.rollup("r_name", "n_name").agg(F.count("*").alias("n"), F.round(F.avg("rating"), 6).alias("rating"))
