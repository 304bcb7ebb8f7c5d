from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class QuerySpec:
    """One query and its variants.

    order: True if tags are to be visited as listed.  precedence: pairs (a, b) of tags, a before b.
    budget: longest distance.  ratings: "given", or "identical" for equal ones.  route_scope:
    "per_set" for each cover set's best order, "all_orders" for every order as an answer of its own.
    rating_scope: "set" counts the chosen POIs, "path" the best hit POI of each tag on the way.
    prune: bounds in use, of region, cells, sets, orders.  lower_bound: euclid, grid or zero.
    tau_scope: "region" or "global" maxima in cell bounds.  cell_lb: "frontier" or "paper".
    """

    v_q: int
    tags: tuple[str, ...]
    alpha: float = 0.6
    k: int = 4
    qid: int = 0
    dest: int | None = None
    order: bool = False
    precedence: tuple[tuple[str, str], ...] = ()
    budget: int | None = None
    ratings: str = "given"
    user: int | None = None
    route_scope: str = "per_set"
    rating_scope: str = "set"
    prune: frozenset[str] = field(default_factory=lambda: frozenset({"region", "cells", "sets", "orders"}))
    lower_bound: str = "euclid"
    tau_scope: str = "region"
    cell_lb: str = "frontier"
    rating_floor: int | None = None
    epsilon: float = 0.0

    def __post_init__(self) -> None:
        object.__setattr__(self, "tags", tuple(dict.fromkeys(self.tags)))
        if not self.tags:
            raise ValueError("a query has a tag at least")
        if not 0 <= self.alpha <= 1:
            raise ValueError("alpha is 0 to 1")
        if self.k < 1:
            raise ValueError("k is 1 at least")


def queries_frame(spark: SparkSession, specs: Iterable[QuerySpec]) -> DataFrame:
    """(qid, v_q, tags, alpha, k, dest, budget) of a few queries."""
    return spark.createDataFrame([(s.qid, s.v_q, list(s.tags), s.alpha, s.k, s.dest, s.budget) for s in specs], "qid long, v_q long, tags array<string>, alpha double, k int, dest long, budget long")


def query_log(events: DataFrame, n: DataFrame, tags: DataFrame, m: int = 4, k: int = 4, alpha: float = 0.6) -> DataFrame:
    """Queries from events: a start vertex and m tags by arithmetic on the event's numbers. n: one row (n); tags: (key, tag)."""
    at = events.select(F.col("event_id").alias("qid"), "user_id", "event_id").crossJoin(F.broadcast(n))
    keys = at.select("qid", ((F.col("user_id") * 131 + F.col("event_id") * 17) % F.col("n")).alias("v_q"), F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda i: (F.col("event_id") * 7 + i * (1 + F.col("event_id") % 4)) % 25)).alias("pos", "key"))
    named = keys.join(F.broadcast(tags.select(F.col("key").cast("long").alias("key"), "tag")), "key")  # one row a nation
    return named.groupBy("qid", "v_q").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "tag"))), lambda x: x["tag"]).alias("tags")).select("qid", "v_q", "tags", F.lit(alpha).alias("alpha"), F.lit(k).alias("k"), F.lit(None).cast("long").alias("dest"), F.lit(None).cast("long").alias("budget"))
