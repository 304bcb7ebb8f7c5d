"""Cost and accuracy measures over answers and counters."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def search_space(found: DataFrame, m: int) -> DataFrame:
    """(qid, n_sets, n_orders): cover sets and their orders, never made. found: hits."""
    by_tag = found.groupBy("qid", "tag_pos").agg(F.count("*").alias("n"))
    product = F.aggregate(F.collect_list("n"), F.lit(1).cast("long"), lambda a, n: a * n)  # a number a tag
    return by_tag.groupBy("qid").agg(product.alias("n_sets"), F.count("*").alias("tags")).filter(F.col("tags") == m).select("qid", "n_sets", (F.col("n_sets") * math.factorial(m)).alias("n_orders"))


def stages(counters: DataFrame) -> DataFrame:
    """One row a query: cells, cover sets and orders of the whole network, of the region, and after pruning."""
    c = lambda name: F.col("counters")[name].alias(name)
    return counters.select("qid", *(c(n) for n in ("cells_rn", "cells_sr", "cells_bp", "sets_rn", "sets_sr", "sets_bp", "orders_sr", "orders_evaluated", "settled")), "seconds")


def percentages(staged: DataFrame, *by: str) -> DataFrame:
    """Shares that remain: region of network, pruned of network, evaluated orders of the region's."""
    share = lambda a, b: F.round(100 * F.sum(a) / F.sum(b), 4)
    return staged.groupBy(*by).agg(share("cells_sr", "cells_rn").alias("cells_region"), share("cells_bp", "cells_rn").alias("cells_pruned"), share("sets_sr", "sets_rn").alias("sets_region"), share("sets_bp", "sets_rn").alias("sets_evaluated"), share("orders_evaluated", "orders_sr").alias("orders_evaluated"))


def effectiveness(answers: DataFrame, *by: str) -> DataFrame:
    """Mean distance, rating sum and score of routes."""
    return answers.groupBy(*by).agg(F.count("*").alias("routes"), F.round(F.avg("dist"), 4).alias("dist"), F.round(F.avg("rating"), 4).alias("rating"), F.round(F.avg("score"), 4).alias("score"))


def gap(approximate: DataFrame, exact: DataFrame) -> DataFrame:
    """(qid, gap, hit): score lost by an approximate method's best route, and whether its set of POIs is among the exact ones."""
    best = lambda df: df.groupBy("qid").agg(F.max("score").alias("s"), F.collect_set(F.array_sort("pois")).alias("sets"))
    a, b = best(approximate), best(exact)
    return a.join(b.select("qid", F.col("s").alias("s2"), F.col("sets").alias("sets2")), "qid").select("qid", F.round(F.col("s2") - F.col("s"), 6).alias("gap"), F.arrays_overlap("sets", "sets2").alias("hit"))


def index_bytes(shortcuts: DataFrame, cells: DataFrame) -> DataFrame:
    """One row: bytes of the border index (24 a row) beside those of all pairs (8 a pair)."""
    return shortcuts.agg((F.count("*") * 24).alias("index_bytes")).crossJoin(cells.agg((F.count("*") * F.count("*") * 8).alias("all_pairs_bytes")))


def graph_size(graph: DataFrame, arcs: DataFrame) -> DataFrame:
    """(qid, graph_arcs, network_arcs): arcs of each query's graph beside those of the network."""
    return graph.groupBy("qid").agg(F.count("*").alias("graph_arcs")).crossJoin(F.broadcast(arcs.agg(F.count("*").alias("network_arcs"))))  # one row


def scope_measured(queries: DataFrame, sd: DataFrame, radius: DataFrame, n: DataFrame) -> DataFrame:
    """(qid, members, share): vertices within each query's radius, and their percentage of n (one row)."""
    inside = queries.select("qid", F.col("v_q").alias("s")).join(sd, "s").join(radius.filter("floor is not null").select("qid", "radius"), "qid").filter("dist <= radius")
    return inside.groupBy("qid").agg(F.count("*").alias("members")).crossJoin(F.broadcast(n)).select("qid", "members", F.round(100.0 * F.col("members") / F.col("n"), 4).alias("share"))


def engine(spark: SparkSession, answers: DataFrame) -> DataFrame:
    """One row: queries answered and routes, as a run observes them, and whether the plan has an exchange."""
    seen = Observation("batch")
    answers.observe(seen, F.count_if(F.col("rank") == 1).alias("queries"), F.count(F.lit(1)).alias("routes")).write.format("noop").mode("overwrite").save()
    spread = "Exchange" in answers._jdf.queryExecution().executedPlan().toString()
    return spark.createDataFrame([(seen.get["queries"], seen.get["routes"], spread)], "queries long, routes long, spread boolean")


def scope_estimate(z: Column, m: int, k: int, n_p: Column, alpha: float, d_tau: float) -> tuple[Column, Column]:
    """Predicted share of the network in the region: derived anew, and by the formula as printed (which lets an alpha drop)."""
    spread = 2.0 * F.pow(F.lit(float(k)), 1.0 / m) / F.sqrt(3.14 * n_p)
    diameter = F.sqrt(z) * spread
    anew = ((1 - alpha) * m * d_tau + alpha * diameter) / alpha
    printed = ((1 - alpha) * m * d_tau + diameter) / alpha
    return 3.14 * anew * anew / z, 3.14 * printed * printed / z


def cost_model(n_v: Column, n_e: Column, omega: Column, beta: Column, n_p: Column, gamma: Column, m: int) -> Column:
    """Predicted work in graph-distance evaluations."""
    return (n_v + n_e) * F.log(n_v) + omega * n_v * beta * F.pow(n_p, m - 1) * gamma * math.factorial(m)
