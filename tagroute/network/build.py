"""Networks: vertices(v, x, y) and edges(u, v, w) with u < v, integers throughout."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import table


def _grid(rows: DataFrame, key: str, size: Column) -> tuple[DataFrame, DataFrame]:
    """A grid of dense keys, row by row; a vertex' number of neighbours and lengths follow its key and size alone."""
    wide = F.ceil(F.sqrt(F.count("*"))).cast("long")
    dims = rows.agg(wide.alias("wide"))
    at = rows.select(F.col(key).cast("long").alias("v"), size.cast("long").alias("size")).crossJoin(F.broadcast(dims))  # one row
    vertices = at.select("v", (10 * (F.col("v") % F.col("wide"))).alias("x"), (10 * F.floor(F.col("v") / F.col("wide"))).alias("y"))
    far = at.select(F.col("v").alias("to"), F.col("size").alias("to_size"))
    w = (10 + (F.col("size") + F.col("to_size")) % 10).alias("w")
    row = lambda v: F.floor(v / F.col("wide"))
    right = at.withColumn("to", F.col("v") + 1).filter(row(F.col("v")) == row(F.col("to")))
    down = at.filter((F.col("v") % F.col("wide") == 0) | ((F.col("v") * 7919) % 11 != 0)).withColumn("to", F.col("v") + F.col("wide"))
    pairs = right.unionByName(down)  # two equi-joins in one: both have the neighbour's key
    return vertices, pairs.join(far, "to").select(F.col("v").alias("u"), F.col("to").alias("v"), w)


def lattice(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(vertices, edges) of the lattice over parts."""
    return _grid(table(spark, sf_dir, "part").select("p_partkey", "p_size"), "p_partkey", F.col("p_size"))


def lattice_from_orders(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(vertices, edges) of the larger lattice over orders."""
    return _grid(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), "o_orderkey", F.col("o_custkey") % 50 + 1)


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of customers (v = 2 * key) and suppliers (2 * key + 1) that trade: the more lines, the shorter."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    pairs = lines.join(orders, lines.l_orderkey == orders.o_orderkey).groupBy("o_custkey", "l_suppkey").agg(F.count("*").alias("n"))
    a, b = 2 * F.col("o_custkey"), 2 * F.col("l_suppkey") + 1
    return pairs.select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v"), (1 + F.floor(1000 / (1 + F.col("n")))).alias("w"))


def proximity(spark: SparkSession, sf_dir: str, neighbours: int = 6, block: int = 2048) -> DataFrame:
    """Edges to the nearest vectors, w = ceil(1e6 * distance): every block of vectors is compared with all, a block at a time in matrix form."""
    import numpy as np
    import pandas as pd

    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    # pairs of blocks: each task holds two blocks, and keeps the nearest of one in the other
    blocks = rows.withColumn("b", F.floor(F.col("vec_id") / block)).groupBy("b").agg(F.collect_list("vec_id").alias("ids"), F.collect_list("embedding").alias("e"))
    others = rows.select(F.floor(F.col("vec_id") / block).alias("b2")).distinct().agg(F.collect_set("b2").alias("all"))  # one number a block
    asked = blocks.crossJoin(F.broadcast(others)).select(F.col("ids").alias("i1"), F.col("e").alias("e1"), F.explode("all").alias("b2"))
    pairs = asked.join(blocks.select(F.col("b").alias("b2"), F.col("ids").alias("i2"), F.col("e").alias("e2")), "b2").select("i1", "e1", "i2", "e2")

    def near(batches):
        for pdf in batches:
            for i1, e1, i2, e2 in pdf.itertuples(index=False):
                a, b = np.stack(e1).astype(np.float64), np.stack(e2).astype(np.float64)
                ids1, ids2 = np.asarray(i1), np.asarray(i2)
                d = np.sqrt(np.maximum((a**2).sum(1)[:, None] + (b**2).sum(1)[None] - 2 * a @ b.T, 0))
                d[ids1[:, None] == ids2[None]] = np.inf
                k = min(neighbours, d.shape[1])
                at = np.argpartition(d, k - 1, axis=1)[:, :k]
                exact = np.sqrt(((a[:, None] - b[at]) ** 2).sum(2))
                exact[~np.isfinite(np.take_along_axis(d, at, 1))] = np.inf
                yield pd.DataFrame({"v": np.repeat(ids1, k), "to": ids2[at].ravel(), "d": exact.ravel()})

    from pyspark.sql import Window as W

    found = pairs.mapInPandas(near, "v long, to long, d double").filter(F.col("d") < float("inf"))
    best = found.withColumn("r", F.row_number().over(W.partitionBy("v").orderBy("d", "to"))).filter(F.col("r") <= neighbours)
    return best.select(F.least("v", "to").alias("u"), F.greatest("v", "to").alias("v"), F.ceil(F.col("d") * 1e6).alias("w")).groupBy("u", "v").agg(F.min("w").alias("w"))


def arcs(edges: DataFrame) -> DataFrame:
    """Both directions; loops go, of parallel edges the shortest stays with the search."""
    e = edges.filter("u <> v")
    return e.select("u", "v", "w").unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v"), "w"))
