"""Queries over networks beyond one task: distances by rounds over cells, cover sets by bounded joins."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..distance.wide import sssp_wide
from ..functions import R_MAX, W_MAX, route_score
from ..plans.rounds import materialize
from . import tables

#: Variants of a query that change its answers and are known here; others are refused, as are prunings that can't be chosen.
VARIANTS = ("order", "precedence", "ratings", "user", "rating_floor", "route_scope")


def run_wide(index: DataFrame, cells: DataFrame, closed: DataFrame, cross: DataFrame, queries: DataFrame, *, personal: DataFrame | None = None, w_max: float = W_MAX, r_max: float = R_MAX, **variant) -> DataFrame:
    """The k best routes of each query, exact, by DataFrame rounds alone; a batch may mix numbers of tags, and queries with and without a destination."""
    if lacking := sorted(set(variant) - set(VARIANTS)):
        raise ValueError(f"not in the wide mode: {', '.join(lacking)}")
    asked = materialize(queries.withColumn("tags", F.array_distinct("tags")), "asked")
    size = F.size("tags")
    good = F.coalesce(F.col("alpha").between(0, 1) & (F.col("k") >= 1) & (size <= 8), F.lit(False))
    kinds = asked.groupBy(size.alias("m"), F.col("dest").isNotNull().alias("dest")).agg(F.min(good).alias("good")).collect()  # 16 rows at most, or an error
    if not all(x.good for x in kinds):
        raise ValueError("alpha is 0 to 1, k is 1 at least, and a query has up to 8 tags in the wide mode")
    if asked.groupBy("qid").count().filter("count > 1 or qid is null").limit(1).count():
        raise ValueError("each query has a qid of its own")
    parts = [_of_kind(index, cells, closed, cross, asked.filter((size == x.m) & (F.col("dest").isNotNull() == x.dest)), x.m, x.dest, personal, (w_max, r_max), **variant) for x in kinds]
    empty = asked.sparkSession.createDataFrame([], "qid long, rank int, score double, dist long, rating long, pois array<long>")
    return reduce(lambda a, b: a.unionByName(b), parts, empty)


def _hits(index: DataFrame, queries: DataFrame, personal: DataFrame | None, ratings: str, user: int | None, rating_floor: int | None) -> DataFrame:
    found = tables.hits(index, queries)
    if ratings == "identical":
        found = found.withColumn("rating", F.lit(50).cast("long"))
    elif user is not None and personal is not None:
        own = personal.filter(F.col("user") == user).select("poi", F.col("rating").alias("own"))
        found = found.join(own, "poi", "left").withColumn("rating", F.coalesce("own", "rating")).drop("own")
    return found if rating_floor is None else found.filter(F.col("rating") >= rating_floor)


def _of_kind(index: DataFrame, cells: DataFrame, closed: DataFrame, cross: DataFrame, queries: DataFrame, m: int, dest: bool, personal: DataFrame | None, scale: tuple[float, float], order: bool = False, precedence: tuple[tuple[str, str], ...] = (), ratings: str = "given", user: int | None = None, rating_floor: int | None = None, route_scope: str = "per_set") -> DataFrame:
    """Queries of m tags, all with a destination or all without.

    Hits' distances from the start give seeds, a floor and a radius; hits beyond it go before any
    cover set is made, and cover sets whose farthest member or ratings cannot reach the floor go
    before any order is. No leg of a route that reaches the floor is longer than the radius.
    """
    found = _hits(index, queries, personal, ratings, user, rating_floor)
    sd = materialize(sssp_wide(closed, cross, cells, queries.select(F.col("v_q").alias("s"))), "sd")
    near = materialize(tables.with_start_distance(found, queries, sd), "near")
    seeds = tables.ring_prefix(near, queries)
    pair = sssp_wide(closed, cross, cells, seeds.select(F.col("v").alias("s")))

    def best(sets: DataFrame, pair: DataFrame) -> DataFrame:
        return tables.best_routes(tables.routes(sets, queries, pair.unionByName(sd).distinct(), m, dest, order, tuple(precedence)), queries, route_scope, *scale)

    floor = materialize(tables.floors(best(tables.cover_sets(seeds, m), pair), queries), "floor")
    radius = materialize(tables.region_radius(near, queries, floor, *scale).select("qid", "radius"), "radius")
    inside = materialize(near.join(radius, "qid").filter(F.col("radius").isNull() | (F.col("dist") <= F.col("radius") + 1e-4)).drop("radius"), "inside")
    sets = tables.cover_sets(inside.select("qid", "tag_pos", "poi", "v", "cell", "rating"), m)
    # a route is no shorter than the way to its farthest member
    for j in range(m):
        sets = sets.join(inside.filter(F.col("tag_pos") == j).select("qid", F.col("poi").alias(f"p{j}"), F.col("dist").alias(f"d{j}")), ["qid", f"p{j}"])
    far = F.greatest(*(F.col(f"d{j}") for j in range(m))) if m > 1 else F.col("d0")
    kept = sets.withColumn("far", far).join(queries.select("qid", "alpha"), "qid").join(floor, "qid", "left").filter(F.col("floor").isNull() | (route_score(F.col("far"), F.col("rating"), F.col("alpha"), *scale) >= F.col("floor") - 2e-6))
    kept = materialize(kept.select("qid", *(f"p{j}" for j in range(m)), *(f"v{j}" for j in range(m)), "rating"), "sets")
    stops = kept.select(F.explode(F.array(*(f"v{j}" for j in range(m)))).alias("s"))
    widest = radius.agg(F.max("radius").alias("r"), F.count_if(F.col("radius").isNull()).alias("open")).first()
    limit = None if widest.r is None or widest.open else int(widest.r) + 2
    pair = materialize(sssp_wide(closed, cross, cells, stops, limit), "pair")
    return best(kept, pair).select("qid", "rank", "score", F.col("dist").cast("long").alias("dist"), F.col("rating").cast("long").alias("rating"), "pois")
