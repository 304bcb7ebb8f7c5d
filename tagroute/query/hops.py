"""Routes hop by hop over networks beyond one task: each hop's distances come from strips of the whole network."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..distance.wide import Strips, sssp_strips
from ..functions import RATIO, route_score
from ..plans.rounds import materialize


def greedy_rating(index, asked: DataFrame, found: DataFrame, order: bool = False) -> DataFrame:
    """(qid, rank, score, dist, rating, pois) by the best rated POI of the tags still open, the nearest of those; one route a query.

    How far the best rated places lie is not known beforehand, so no part of the network would be enough by its size.
    asked: queries; found: their hits over the whole network (qid, tag_pos, poi, v, rating).
    """
    from ..network import arcs

    net = Strips(arcs(index.edges))
    found = materialize(found.select("qid", F.col("tag_pos").cast("long").alias("tag_pos"), "poi", "v", F.col("rating").cast("long").alias("rating")), "found")
    sizes = found.groupBy("qid").agg(F.count_distinct("tag_pos").alias("has"))
    whole = asked.join(sizes, "qid").filter(F.col("has") == F.size("tags")).join(index.vertices.select(F.col("v").alias("v_q")), "v_q", "left_semi")
    none = F.array().cast("array<long>")
    zero = F.lit(0).cast("long")
    at = materialize(whole.select("qid", F.col("v_q").alias("at"), zero.alias("dist"), zero.alias("rating"), none.alias("pois"), none.alias("taken"), F.size("tags").alias("m")), "hops")
    most = at.agg(F.max("m")).first()[0] or 0
    done = at.filter("size(pois) = m")
    for _ in range(most):
        going = at.filter("size(pois) < m").withColumnRenamed("rating", "so_far")
        open_hits = going.join(found, "qid").filter((F.col("tag_pos") == F.size("taken")) if order else ~F.array_contains("taken", F.col("tag_pos")))
        first = materialize(open_hits.withColumn("top", F.max("rating").over(W.partitionBy("qid"))).filter("rating = top").drop("top"), "best")
        apart = first.filter("at <> v").select(F.col("at").alias("s"), "v").distinct()
        leg = sssp_strips(net, apart, targets=apart).unionByName(first.filter("at = v").select(F.col("at").alias("s"), "v", zero.alias("dist")).distinct())
        by = first.join(leg.select(F.col("s").alias("at"), "v", F.col("dist").alias("leg")), ["at", "v"])
        nearest = W.partitionBy("qid").orderBy("leg", "tag_pos", "poi")
        step = by.withColumn("r", F.row_number().over(nearest)).filter("r = 1")
        at = materialize(step.select("qid", F.col("v").alias("at"), (F.col("dist") + F.col("leg")).alias("dist"), (F.col("so_far") + F.col("rating")).alias("rating"), F.array_append("pois", F.col("poi")).alias("pois"), F.array_append("taken", F.col("tag_pos")).alias("taken"), "m"), "hops")
        done = done.unionByName(at.filter("size(pois) = m"))
    ends = done.join(asked.select("qid", "alpha", "dest", "budget"), "qid")
    if not asked.filter("dest is not null").isEmpty():
        last = ends.filter("dest is not null and dest <> at").select(F.col("dest").alias("s"), F.col("at").alias("v")).distinct()
        home = sssp_strips(net, last, targets=last).select(F.col("s").alias("dest"), F.col("v").alias("at"), F.col("dist").alias("home"))
        ends = ends.join(index.vertices.select(F.col("v").alias("dest"), F.lit(True).alias("there")), "dest", "left").join(home, ["dest", "at"], "left")
        ends = ends.filter("dest is null or there").withColumn("home", F.when(F.col("dest").isNull() | (F.col("dest") == F.col("at")), zero).otherwise(F.col("home")))
        ends = ends.filter("home is not null").withColumn("dist", F.col("dist") + F.col("home"))
    score = route_score(F.col("dist"), F.col("rating"), F.col("alpha"), index.w_max, index.r_max * RATIO / index.ratio)
    return ends.filter("budget is null or dist <= budget").select("qid", F.lit(1).alias("rank"), score.alias("score"), "dist", "rating", "pois")
