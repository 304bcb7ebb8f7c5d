"""Partitions of the vertices into cells: (v, cell)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.rounds import discard, materialize


def tiles(vertices: DataFrame, side: int = 70) -> DataFrame:
    """Square tiles of the plane, by arithmetic alone."""
    return vertices.select("v", (F.floor(F.col("x") / side) * 1000 + F.floor(F.col("y") / side)).alias("cell"))


def kd(vertices: DataFrame, n_s: int = 64) -> DataFrame:
    """Balanced bisection, by turns across x and y, until no cell has more than n_s vertices.

    Cells are numbered by the path of halves; vertices that share the median's coordinate are told apart by
    the other one and by their number. A level deals the vertices out by ranges of (cell, key): a vertex' rank in its
    cell is that within its range, plus what the cell has in earlier ranges (one row a cell and range).
    """
    n = vertices.count()
    now = vertices.select("v", "x", "y", F.lit(1).cast("long").alias("cell"))
    level = 0
    while n > n_s:
        key = ("x", "y", "v") if level % 2 == 0 else ("y", "x", "v")
        dealt = materialize(now.repartitionByRange("cell", *key).withColumn("pid", F.spark_partition_id()), "dealt")
        counts = dealt.groupBy("cell", "pid").agg(F.count("*").alias("c"))
        of_cell = W.partitionBy("cell")
        before = counts.select("cell", "pid", (F.sum("c").over(of_cell.orderBy("pid")) - F.col("c")).alias("before"), F.sum("c").over(of_cell).alias("size"))
        within = dealt.withColumn("r", F.row_number().over(W.partitionBy("cell", "pid").orderBy(*key)))
        upper = (F.col("before") + F.col("r") > F.ceil(F.col("size") / 2)).cast("long")
        last, now = now, materialize(within.join(before, ["cell", "pid"]).select("v", "x", "y", (F.col("cell") * 2 + upper).alias("cell")), "kd")
        discard(dealt, last)
        n, level = -(-n // 2), level + 1
    return now.select("v", "cell")


def propagate(edges: DataFrame, n_s: int = 64, rounds: int = 6) -> DataFrame:
    """For graphs without coordinates: labels spread to neighbours by weight of short edges, cut to n_s by rank within a label."""
    e = edges.select("u", "v", "w").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "w"))
    now = e.select(F.col("u").alias("v")).distinct().withColumn("cell", F.col("v"))
    for _ in range(rounds):
        told = e.join(now.select(F.col("v").alias("u"), "cell"), "u").select("v", "cell", (1.0 / F.col("w")).alias("s"))
        held = now.join(e.groupBy("v").agg(F.avg(1.0 / F.col("w")).alias("s")), "v").select("v", "cell", "s")  # its own label counts as a neighbour's
        votes = told.unionByName(held).groupBy("v", "cell").agg(F.sum("s").alias("s"))
        best = votes.groupBy("v").agg(F.max_by("cell", F.struct("s", -F.col("cell"))).alias("cell"))
        size = best.groupBy("cell").agg(F.count("*").alias("n"))
        keep = best.join(size, "cell").filter(F.col("n") <= n_s).select("v", "cell")
        rank = F.row_number().over(W.partitionBy("cell").orderBy("v"))
        parts = best.join(size, "cell").filter(F.col("n") > n_s).withColumn("part", F.floor((rank - 1) / n_s))
        cut = parts.withColumn("least", F.min("v").over(W.partitionBy("cell", "part"))).select("v", F.col("least").alias("cell"))
        now = materialize(keep.unionByName(cut), "labels")
    return now


def multilevel(edges: DataFrame, n_s: int = 64, rounds: int = 12) -> DataFrame:
    """Heavy-edge matching: cells that choose each other over their strongest cut merge while they fit n_s."""
    nodes = edges.select(F.col("u").alias("v")).unionByName(edges.select("v")).distinct()
    now = materialize(nodes.withColumn("cell", F.col("v")), "cells")
    for _ in range(rounds):
        size = now.groupBy("cell").agg(F.count("*").alias("n"))
        cu, cv = now.select(F.col("v").alias("u"), F.col("cell").alias("a")), now.select("v", F.col("cell").alias("b"))
        cut = edges.join(cu, "u").join(cv, "v").filter("a <> b").groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.sum(1.0 / F.col("w")).alias("s"))
        fits = cut.join(size.select(F.col("cell").alias("a"), F.col("n").alias("na")), "a").join(size.select(F.col("cell").alias("b"), F.col("n").alias("nb")), "b").filter(F.col("na") + F.col("nb") <= n_s)
        # light cells first, so that sizes stay even
        gain = F.struct((F.col("s") / (F.col("na") * F.col("nb"))).alias("g"), F.hash("a", "b").alias("t"), "a", "b")
        both = materialize(fits.select("a", "b", gain.alias("g")), "cuts")
        choice = both.select("a", "b", "g").unionByName(both.select(F.col("b").alias("a"), F.col("a").alias("b"), "g")).groupBy("a").agg(F.max_by("b", "g").alias("b"))
        mutual = choice.alias("p").join(choice.alias("q"), (F.col("p.b") == F.col("q.a")) & (F.col("q.b") == F.col("p.a"))).filter("p.a < p.b").select(F.col("p.b").alias("cell"), F.col("p.a").alias("into"))
        merged = materialize(now.join(mutual, "cell", "left").select("v", F.coalesce("into", "cell").alias("cell")), "cells")
        if mutual.isEmpty():
            return merged
        now = merged
    return now


def quality(cells: DataFrame, edges: DataFrame) -> DataFrame:
    """One row: cells, vertices in the largest and the mean cell, cut edges, border vertices."""
    from ..index import borders, cross_edges

    size = cells.groupBy("cell").agg(F.count("*").alias("n"))
    cut = cross_edges(edges, cells)
    return size.agg(F.count("*").alias("cells"), F.max("n").alias("max_size"), F.round(F.avg("n"), 6).alias("mean_size")).crossJoin(cut.agg(F.count("*").alias("cut_edges"))).crossJoin(borders(cut).agg(F.count("*").alias("border_vertices")))
