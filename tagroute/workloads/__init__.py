"""Experiments: grids of parameters over the query log, one batch a method and grid point."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import measures
from ..plans.rounds import materialize
from ..query import Engine

#: Defaults of the experiments, and the grid around them.
M, K, ALPHA = 4, 4, 0.6
GRID = {"m": (3, 4, 5), "k": (2, 4, 6), "alpha": (0.2, 0.4, 0.6)}
#: Settings of the comparisons: variant of the queries, whether they have a destination, the parameters varied, and the methods that support it.
COMPARISONS = {
    "fixed_equal_dest": ({"order": True, "ratings": "identical"}, True, ("m", "k"), ("ebs", "dominance", "ordered_pref", "ordered_astar", "budget_labels")),
    "fixed_varying_dest": ({"order": True}, True, ("m", "k"), ("ebs", "ordered_pref", "budget_labels")),
    "fixed_varying_nodest": ({"order": True}, False, ("m",), ("ebs", "ordered_pref", "budget_labels")),
    "flexible_equal": ({"ratings": "identical", "route_scope": "all_orders"}, False, ("m", "k"), ("ebs", "dominance", "budget_labels")),
}
#: Methods that search within a budget, of so many times the longest of our k routes of the query.
BUDGETED, BUDGET_FACTOR = {"ordered_pref", "ordered_astar", "budget_labels"}, 5
#: Methods that leave POIs of lower ratings out. The reference gives no value; this one leaves about the best two thirds of ratings from 1 to 90.
FLOORED, RATING_FLOOR = {"ordered_pref", "ordered_astar"}, 30
#: The methods whose routes are compared, with the order of visits that they need.
EFFECTIVENESS = {"ebs": {}, "dominance": {}, "ordered_pref": {"order": True}, "ordered_astar": {"order": True}, "budget_labels": {}, "greedy_nearest": {}, "greedy_rating": {}}
#: Quarters of the POIs in the ablation.
SHARES = (1, 2, 3, 4)
#: Ablations: prunings in use.
ABLATIONS = {"full": {"region", "cells", "sets", "orders"}, "no_region": {"cells", "sets", "orders"}, "no_cells": {"region", "sets", "orders"}, "no_orders": {"region", "cells", "sets"}}


def points(names: tuple[str, ...] | None = None, alpha: float = ALPHA) -> list[tuple[str, int, int, float]]:
    """(parameter, m, k, alpha): one parameter at a time."""
    out = []
    for name in names or tuple(GRID):
        for v in GRID[name]:
            p = {"m": M, "k": K, "alpha": alpha} | {name: v}
            out.append((name, p["m"], p["k"], p["alpha"]))
    return out


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), frames)


def pruning_table(engine: Engine, log) -> DataFrame:
    """Mean counts of cells, cover sets and orders at each stage, by parameter; log(m, k, alpha) makes the queries."""
    rows = [measures.stages(engine.counters(log(m, k, a))).select(F.lit(p).alias("parameter"), F.lit(m).alias("m"), F.lit(k).alias("k"), F.lit(a).alias("alpha"), "*") for p, m, k, a in points()]
    mean = [F.round(F.avg(c), 2).alias(c) for c in ("cells_rn", "cells_sr", "cells_bp", "sets_rn", "sets_sr", "sets_bp", "orders_sr", "orders_evaluated")]
    return _union(rows).groupBy("parameter", "m", "k", "alpha").agg(*mean)


def query_time(engine: Engine, log) -> DataFrame:
    rows = [engine.counters(log(m, k, a)).select(F.lit(p).alias("parameter"), F.lit(m).alias("m"), F.lit(k).alias("k"), F.lit(a).alias("alpha"), "seconds") for p, m, k, a in points()]
    return _union(rows).groupBy("parameter", "m", "k", "alpha").agg(F.round(F.avg("seconds") * 1000, 3).alias("ms"))


def _at(df: DataFrame, p: str, m: int, k: int, alpha: float) -> DataFrame:
    return df.select(F.lit(p).alias("parameter"), F.lit(m).alias("m"), F.lit(k).alias("k"), F.lit(alpha).alias("alpha"), "*")


def ablation(engine: Engine, log) -> DataFrame:
    """Work of each ablation by parameter, and by the quarters of the POIs that there are; answers are equal by construction and by test."""
    work = [F.round(F.avg("settled"), 2).alias("settled"), F.round(F.avg("sets_bp"), 2).alias("sets"), F.round(F.avg("orders_evaluated"), 2).alias("orders"), F.round(F.avg("seconds") * 1000, 3).alias("ms")]
    some = {s: engine if s == max(SHARES) else Engine(replace(engine.index, pois=engine.index.pois.filter(F.col("poi") % max(SHARES) < s)), engine.limit) for s in SHARES}
    grid = [(p, max(SHARES)) for p in points()] + [(("pois", M, K, ALPHA), s) for s in SHARES]
    rows = []
    for (p, m, k, a), s in grid:
        for n, prune in ABLATIONS.items():
            found = measures.stages(some[s].counters(log(m, k, a), prune=frozenset(prune))).agg(*work)
            rows.append(_at(found.select((F.lit(s) / max(SHARES)).alias("share"), F.lit(n).alias("variant"), "*"), p, m, k, a))
    return _union(rows)


def _budgeted(engine: Engine, queries: DataFrame, **variant) -> DataFrame:
    """The queries with their budgets; one without a route keeps none."""
    longest = engine.run_batch(queries, **variant).groupBy("qid").agg((F.max("dist") * BUDGET_FACTOR).alias("longest"))
    return materialize(queries.join(longest, "qid", "left").withColumn("budget", F.col("longest")).drop("longest"), "budgeted")


def _settings(method: str, queries: DataFrame, budgeted: DataFrame) -> tuple[DataFrame, dict]:
    return budgeted if method in BUDGETED else queries, {"rating_floor": RATING_FLOOR} if method in FLOORED else {}


def comparison(engine: Engine, log, name: str) -> DataFrame:
    """Mean time, and mean best score, of the methods that support a setting, by parameter. log(m, k, alpha, dest)."""
    variant, dest, names, methods = COMPARISONS[name]
    rows = []
    for p, m, k, alpha in points(names):
        q = materialize(log(m, k, alpha, dest), "asked")
        within = _budgeted(engine, q, **variant)
        for method in methods:
            asked, own = _settings(method, q, within)
            a = engine.run_batch(asked, method, **variant, **own).filter("rank = 1").agg(F.round(F.avg("score"), 4).alias("score"), F.count("*").alias("answered"))
            t = engine.counters(asked, method, **variant, **own).agg(F.round(F.avg("seconds") * 1000, 3).alias("ms"))
            rows.append(_at(a.crossJoin(t).select(F.lit(name).alias("setting"), F.lit(method).alias("method"), "*"), p, m, k, alpha))
    return _union(rows)


def budget(engine: Engine, log, factors: tuple[int, ...] = (1, 2, 3, 4, 5)) -> DataFrame:
    """Time under budgets of 1 to 5 times the longest of our k routes: the label search against ours."""
    q = materialize(log(M, K, ALPHA), "asked")
    longest = engine.run_batch(q).groupBy("qid").agg(F.max("dist").alias("longest"))
    rows = []
    for f in factors:
        b = q.drop("budget").join(longest, "qid").withColumn("budget", F.col("longest") * f).drop("longest")
        rows += [engine.counters(b, method).agg(F.round(F.avg("seconds") * 1000, 3).alias("ms")).select(F.lit(f).alias("factor"), F.lit(method).alias("method"), "ms") for method in ("ebs", "budget_labels")]
    return _union(rows)


def best_of(engine: Engine, log, methods: tuple[str, ...], alpha: float) -> DataFrame:
    """Mean distance, rating and score of the best routes of each method."""
    return _union([measures.effectiveness(engine.run_batch(log(M, K, alpha), m).filter("rank = 1").withColumn("method", F.lit(m)), "method") for m in methods])


def small_network(engine: Engine, rows: int = 22, step: int = 10) -> Engine:
    """The first rows of a lattice with what lies on them, as a network of its own."""
    ix = engine.index
    v = materialize(ix.vertices.filter(F.col("y") < rows * step), "small")
    kept = v.select("v")
    edges = ix.edges.join(kept.withColumnRenamed("v", "u"), "u", "left_semi").join(kept, "v", "left_semi")
    return Engine.build(v, edges, ix.pois.join(kept, "v", "left_semi"), ix.cells.join(kept, "v", "left_semi"), limit=engine.limit)


def model_vs_agent(engine: Engine, queries: DataFrame, methods: tuple[str, ...] = ("ebs", "greedy_nearest", "greedy_rating")) -> DataFrame:
    """Mean score and time of the search as an agent's tool and of two stand-ins for a model that picks places by itself, over the queries that have an answer."""
    rows = []
    for m in methods:
        found = engine.run_batch(queries, m).filter("rank = 1").agg(F.count("*").alias("answered"), F.round(F.avg("score"), 4).alias("score"), F.round(F.avg("dist"), 4).alias("dist"), F.round(F.avg("rating"), 4).alias("rating"))
        took = engine.counters(queries, m).agg(F.round(F.avg("seconds") * 1000, 3).alias("ms"))
        rows.append(found.crossJoin(took).select(F.lit(m).alias("method"), "*"))
    return _union(rows)


def remaining(layers: dict[str, tuple[Engine, DataFrame]]) -> DataFrame:
    """Shares of cells, cover sets and orders that remain, by layer of POIs."""
    return _union([measures.percentages(measures.stages(e.counters(q))).select(F.lit(name).alias("layer"), "*") for name, (e, q) in layers.items()])


def effectiveness(engine: Engine, log, alpha: float = 0.8) -> DataFrame:
    """Mean distance, rating and score of the routes of each method, by parameter: k and m at alpha, and alpha itself."""
    rows = []
    for p, m, k, a in [*points(alpha=alpha), ("alpha", M, K, alpha)]:
        q = materialize(log(m, k, a), "asked")
        within = _budgeted(engine, q)
        for method, variant in EFFECTIVENESS.items():
            asked, own = _settings(method, q, within)
            rows.append(_at(measures.effectiveness(engine.run_batch(asked, method, **variant, **own)).select(F.lit(method).alias("method"), "*"), p, m, k, a))
    return _union(rows)
