"""POIs on vertices: pois(poi, v, tag, rating)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.rounds import materialize
from ..sources import table


def _n(spark: SparkSession, sf_dir: str) -> DataFrame:
    return F.broadcast(table(spark, sf_dir, "part").agg(F.count("*").alias("n")))  # one row


def _balance_rating(c: Column) -> Column:
    return 1 + F.floor((c + 1000) * 90 / 11000)


def pois_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, nation = table(spark, sf_dir, "supplier"), table(spark, sf_dir, "nation")
    return s.join(nation, s.s_nationkey == nation.n_nationkey).crossJoin(_n(spark, sf_dir)).select(F.col("s_suppkey").alias("poi"), ((F.col("s_suppkey") * 613 + 17) % F.col("n")).alias("v"), F.col("n_name").alias("tag"), _balance_rating(F.col("s_acctbal")).alias("rating"))


def pois_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "customer").crossJoin(_n(spark, sf_dir))
    return c.select(F.col("c_custkey").alias("poi"), ((F.col("c_custkey") * 389 + 5) % F.col("n")).alias("v"), F.col("c_mktsegment").alias("tag"), _balance_rating(F.col("c_acctbal")).alias("rating"))


def pois_part(spark: SparkSession, sf_dir: str, tag: str = "p_brand") -> DataFrame:
    p = table(spark, sf_dir, "part").filter(F.col("p_partkey") % 3 == 0)  # the layer's own density
    return p.select(F.col("p_partkey").alias("poi"), F.col("p_partkey").alias("v"), F.col(tag).alias("tag"), (1 + F.floor((F.col("p_size") - 1) * 89 / 49)).alias("rating"))


def explode_tags(pois: DataFrame) -> DataFrame:
    """One row a tag of pois(poi, v, tags, rating)."""
    return pois.select("poi", "v", F.explode(F.array_distinct("tags")).alias("tag"), "rating")


def pois_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document as a POI with two tags, its language and its source."""
    d, labels = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars"), table(spark, sf_dir, "labels").select("doc_id", "quality")
    rows = d.join(labels, "doc_id", "left").crossJoin(_n(spark, sf_dir))
    return explode_tags(rows.select(F.col("doc_id").alias("poi"), (F.col("doc_id") % F.col("n")).alias("v"), F.array("lang", "source").alias("tags"), (1 + 30 * F.coalesce("quality", F.lit(0)) + F.col("n_chars") % 30).cast("long").alias("rating")))


def personal_ratings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user, poi, rating): a customer's mean quantity from a supplier, as a rating of 1 to 90."""
    lines, orders = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity"), table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    mean = F.floor(F.avg("l_quantity"))
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey).groupBy(F.col("o_custkey").alias("user"), F.col("l_suppkey").alias("poi")).agg(F.greatest(F.lit(1), F.floor(F.least(F.lit(50), F.greatest(F.lit(1), mean)) * 90 / 50)).cast("long").alias("rating"))


def edge_pois(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(u, v, offset): a place on the edge to the right for every order line, as far as that edge exists."""
    from .build import lattice

    _, edges = lattice(spark, sf_dir)
    lines = table(spark, sf_dir, "lineitem").crossJoin(_n(spark, sf_dir)).select((F.col("l_orderkey") % F.col("n")).alias("u"), "l_linenumber")
    right = edges.filter(F.col("v") == F.col("u") + 1)
    return lines.join(right, "u").select("u", "v", (1 + F.col("l_linenumber") % (F.col("w") - 1)).cast("long").alias("offset")).distinct()


def split_edges(edges: DataFrame, places: DataFrame, first_new: int) -> tuple[DataFrame, DataFrame]:
    """(edges, new): each place (u, v, offset) within an edge becomes a vertex that splits it.

    New vertices are numbered from first_new by (u, v, offset). Places at an end, or off the edge, are left out.
    """
    inside = places.join(edges, ["u", "v"]).filter((F.col("offset") > 0) & (F.col("offset") < F.col("w"))).select("u", "v", "w", "offset").distinct()
    # numbers without a window over all rows: counts by edge, and running sums of counts over ranges of edges
    by_edge = W.partitionBy("u", "v").orderBy("offset")
    ranked = inside.withColumn("k", F.row_number().over(by_edge))
    counts = inside.groupBy("u", "v").agg(F.count("*").alias("c")).withColumn("g", F.floor(F.col("u") / 1024))
    groups = counts.groupBy("g").agg(F.sum("c").alias("s")).withColumn("before", F.coalesce(F.sum("s").over(W.orderBy("g").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).select("g", "before")
    base = counts.withColumn("inner", F.coalesce(F.sum("c").over(W.partitionBy("g").orderBy("u", "v").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).join(groups, "g").select("u", "v", (F.col("before") + F.col("inner")).alias("base"))
    new = ranked.join(base, ["u", "v"]).withColumn("at", F.lit(first_new) + F.col("base") + F.col("k") - 1)
    last = F.lead("at").over(by_edge)
    prev_at, prev_off = F.lag("at").over(by_edge), F.lag("offset").over(by_edge)
    pieces = new.select(F.coalesce(prev_at, F.col("u")).alias("a"), F.col("at").alias("b"), (F.col("offset") - F.coalesce(prev_off, F.lit(0))).alias("w"), "u", "v", "at", "offset", F.col("w").alias("whole"), last.isNull().alias("is_last"))
    tail = pieces.filter("is_last").select("at", "v", "whole", "offset")
    both = pieces.select("a", "b", "w").unionByName(tail.select(F.col("at").alias("a"), F.col("v").alias("b"), (F.col("whole") - F.col("offset")).alias("w")))
    rest = edges.join(inside.select("u", "v").distinct(), ["u", "v"], "left_anti").select("u", "v", "w")
    return rest.unionByName(both.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), "w")), new.select("u", "v", "offset", F.col("at").alias("vertex"))


def _snap_within(points: DataFrame, vertices: DataFrame, cell_size: int) -> DataFrame:
    cell = lambda c: F.floor(c / cell_size)
    around = F.explode(F.array(*(F.struct((cell(F.col("px")) + dx).alias("cx"), (cell(F.col("py")) + dy).alias("cy")) for dx in (-1, 0, 1) for dy in (-1, 0, 1))))
    asked = points.select("id", "px", "py", around.alias("c")).select("id", "px", "py", "c.cx", "c.cy")
    there = vertices.select("v", "x", "y", cell(F.col("x")).alias("cx"), cell(F.col("y")).alias("cy"))
    d = (F.col("px") - F.col("x")) * (F.col("px") - F.col("x")) + (F.col("py") - F.col("y")) * (F.col("py") - F.col("y"))
    return asked.join(there, ["cx", "cy"]).filter(d <= cell_size * cell_size).groupBy("id").agg(F.min_by("v", F.struct(d, "v")).alias("v"))


def snap_nearest(points: DataFrame, vertices: DataFrame, cell_size: int = 20) -> DataFrame:
    """(id, v) of points(id, px, py): the nearest vertex, the least among the nearest, by an equi-join on grid cells.

    A grid finds what lies within a cell's side; points without a vertex there go on to one of twice the side, until
    none is left. Only points without coordinates have no row.
    """
    placed = points.filter("px is not null and py is not null")
    every = placed.select(F.col("px").alias("x"), F.col("py").alias("y")).unionByName(vertices.select("x", "y"))
    span = every.agg((F.max("x") - F.min("x")).alias("dx"), (F.max("y") - F.min("y")).alias("dy")).first()
    reach = (span.dx or 0) + (span.dy or 0)  # no two places are farther apart
    out = found = materialize(_snap_within(placed, vertices, cell_size), "snapped")
    while cell_size < reach:
        placed = placed.join(found.select(F.col("id").alias("done")), F.col("id").eqNullSafe(F.col("done")), "left_anti")
        if placed.isEmpty():
            break
        cell_size *= 2
        found = materialize(_snap_within(placed, vertices, cell_size), "snapped")
        out = out.unionByName(found)
    return out
