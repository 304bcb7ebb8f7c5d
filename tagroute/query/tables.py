"""The search's stages as DataFrame operators over batches of queries.

Queries: (qid, v_q, tags, alpha, k, dest, budget).  These forms are for inspection, measures and
networks beyond one task; `search` does the same in one pass for each query.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.rounds import materialize
from ..functions import RATIO, R_MAX, W_MAX, line_length, orders_table, reach_radius, route_score


def hits(index: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, tag_pos, poi, v, cell, rating)."""
    asked = queries.select("qid", F.posexplode("tags").alias("tag_pos", "tag"))
    return asked.join(index, "tag").select("qid", "tag_pos", "poi", "v", "cell", "rating")


def live_cells(found: DataFrame) -> DataFrame:
    return found.groupBy("qid", "cell").agg(F.count("*").alias("n_hits"))


def dead_cells(cells: DataFrame, queries: DataFrame, live: DataFrame) -> DataFrame:
    every = queries.select("qid").crossJoin(cells.select("cell").distinct())
    return every.join(live, ["qid", "cell"], "left_anti")


def query_graph(edges: DataFrame, cells: DataFrame, border: DataFrame, cross: DataFrame, closed: DataFrame, queries: DataFrame, live: DataFrame) -> DataFrame:
    """(qid, u, v, w, kind): live cells whole, cross edges, shortcuts between borders of dead cells and from a start in one."""
    inside = edges.join(cells.select(F.col("v").alias("u"), "cell"), "u").join(cells.select("v", F.col("cell").alias("c2")), "v").filter("cell = c2").select("cell", "u", "v", "w")
    whole = live.select("qid", "cell").join(inside, "cell")
    whole = whole.select("qid", "u", "v", "w", F.lit("edge").alias("kind")).unionByName(whole.select("qid", F.col("v").alias("u"), F.col("u").alias("v"), "w", F.lit("edge").alias("kind")))
    over = queries.select("qid").crossJoin(cross.select("u", "v", "w").unionByName(cross.select(F.col("v").alias("u"), F.col("u").alias("v"), "w"))).select("qid", "u", "v", "w", F.lit("cross").alias("kind"))
    dead = dead_cells(cells, queries, live)
    short = closed.join(border.select("cell", F.col("v").alias("u")), ["cell", "u"], "left_semi").join(border, ["cell", "v"], "left_semi").filter("u <> v")
    by_border = dead.join(short, "cell").select("qid", "u", "v", F.col("dist").alias("w"), F.lit("shortcut").alias("kind"))
    start = queries.join(cells.withColumnRenamed("v", "v_q"), "v_q").join(live.select("qid", "cell"), ["qid", "cell"], "left_anti")
    from_start = start.select("qid", "cell", F.col("v_q").alias("u")).join(closed.filter("u <> v"), ["cell", "u"]).join(border, ["cell", "v"], "left_semi").select("qid", "u", "v", F.col("dist").alias("w"), F.lit("start").alias("kind"))
    return whole.unionByName(over).unionByName(by_border).unionByName(from_start)


def with_start_distance(found: DataFrame, queries: DataFrame, sd: DataFrame) -> DataFrame:
    """Hits with their distance from the query's start; unreachable ones go."""
    return found.join(queries.select("qid", F.col("v_q").alias("s")), "qid").join(sd, ["s", "v"]).drop("s")


def ring_prefix(near: DataFrame, queries: DataFrame) -> DataFrame:
    """Hits up to the least distance at which their cover sets number k: (qid, tag_pos, poi, v, cell, rating, dist)."""
    m = queries.select("qid", "k", F.size("tags").alias("m"))
    w = W.partitionBy("qid").orderBy("dist").rangeBetween(W.unboundedPreceding, 0)
    counted = near.join(m, "qid")
    widest = 8
    product = reduce(lambda a, b: a * b, (F.when(F.col("m") > j, F.sum(F.when(F.col("tag_pos") == j, 1).otherwise(0)).over(w)).otherwise(1) for j in range(widest)))
    reached = counted.withColumn("sets", product)
    limit = reached.filter(F.col("sets") >= F.col("k")).groupBy("qid").agg(F.min("dist").alias("limit"))
    return near.join(limit, "qid").filter("dist <= limit").drop("limit")


def cover_sets(found: DataFrame, m: int) -> DataFrame:
    """(qid, p0.., v0.., rating): every choice of a POI for each of m tags. Lists are joined one by one; for short lists alone."""
    lists = [found.filter(F.col("tag_pos") == j).select("qid", F.col("poi").alias(f"p{j}"), F.col("v").alias(f"v{j}"), F.col("rating").alias(f"r{j}")) for j in range(m)]
    joined = reduce(lambda a, b: a.join(b, "qid"), lists)
    return joined.select("qid", *(f"p{j}" for j in range(m)), *(f"v{j}" for j in range(m)), reduce(lambda a, b: a + b, (F.col(f"r{j}") for j in range(m))).alias("rating"))


def _at(order: list[Column], names: list[str], i: int) -> Column:
    return F.element_at(F.array(*(F.col(n) for n in names)), order[i] + 1)


def _before(a: str, b: str) -> Column:
    """Whether an order (of positions from 0) has tag a before tag b; true if the query lacks one of them."""
    at = lambda tag: F.array_position("tags", F.lit(tag))
    visited = lambda tag: F.array_position("order", (at(tag) - 1).cast("int"))
    return (at(a) == 0) | (at(b) == 0) | (visited(a) < visited(b))


def routes(sets: DataFrame, queries: DataFrame, pair: DataFrame, m: int, dest: bool = False, order: bool = False, precedence: tuple[tuple[str, str], ...] = ()) -> DataFrame:
    """(qid, pois, vs, order_no, dist, rating): every order (as listed, or by precedence) of every cover set with its distance; orders without a way go."""
    spark = sets.sparkSession
    o = [F.col(f"o{i + 1}") for i in range(m)]
    perms = orders_table(spark, m)  # m! rows, m up to 8
    if order:
        perms = perms.filter(reduce(lambda a, b: a & b, (c == i for i, c in enumerate(o))))
    elif precedence:
        asked = queries.select(F.col("qid").alias("of"), "tags").crossJoin(perms).withColumn("order", F.array(*o))
        perms = asked.filter(reduce(lambda a, b: a & b, (_before(a, b) for a, b in precedence))).drop("tags", "order")
    ordered = sets.join(perms, F.col("qid") == F.col("of")).drop("of") if "of" in perms.columns else sets.crossJoin(F.broadcast(perms))
    chosen = ordered.join(queries.select("qid", "v_q", F.col("dest").alias("end"), "budget"), "qid")
    chosen = chosen.select("qid", "v_q", "end", "budget", "rating", F.array(*o).alias("order"), F.array(*(_at(o, [f"p{j}" for j in range(m)], i) for i in range(m))).alias("pois"), F.array(*(_at(o, [f"v{j}" for j in range(m)], i) for i in range(m))).alias("vs"), F.array(*(F.col(f"p{j}") for j in range(m))).alias("members"))
    stops = F.concat(F.array("v_q"), F.col("vs"), F.array("end")) if dest else F.concat(F.array("v_q"), F.col("vs"))
    out = chosen.withColumn("stops", stops).withColumn("dist", F.lit(0).cast("long"))
    legs = pair.select("s", "v", F.col("dist").alias("leg"))
    for i in range(m + dest):
        out = out.join(legs, (F.element_at("stops", i + 1) == legs["s"]) & (F.element_at("stops", i + 2) == legs["v"])).withColumn("dist", F.col("dist") + F.col("leg")).drop("s", "v", "leg")
    return out


def best_routes(found: DataFrame, queries: DataFrame, route_scope: str = "per_set", w_max: float = W_MAX, r_max: float = R_MAX) -> DataFrame:
    """The k best of each query's routes: (qid, rank, score, dist, rating, pois). A route counts once, whichever of its POIs serves which tag."""
    scored = found.join(queries.select("qid", "alpha", "k"), "qid").withColumn("score", route_score(F.col("dist"), F.col("rating"), F.col("alpha"), w_max, r_max)).filter(F.col("budget").isNull() | (F.col("dist") <= F.col("budget")))
    if route_scope == "per_set":
        scored = scored.groupBy("qid", "members", "rating", "k").agg(F.min(F.struct("dist", "pois", "score")).alias("b")).select("qid", "k", "rating", "b.dist", "b.pois", "b.score")
    rank = F.row_number().over(W.partitionBy("qid").orderBy(F.desc("score"), "dist", "pois"))
    return scored.dropDuplicates(["qid", "score", "dist", "rating", "pois"]).withColumn("rank", rank).filter(F.col("rank") <= F.col("k")).select("qid", "rank", "score", "dist", "rating", "pois")


def floors(best: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, floor): the k-th score, where there are k routes."""
    return best.join(queries.select("qid", "k"), "qid").filter("rank = k").select("qid", F.col("score").alias("floor"))


def region_radius(found: DataFrame, queries: DataFrame, floor: DataFrame, w_max: float = W_MAX, r_max: float = R_MAX) -> DataFrame:
    """(qid, floor, tau, radius) from the best ratings of all hits."""
    tau = found.groupBy("qid", "tag_pos").agg(F.max("rating").alias("r")).groupBy("qid").agg(F.sum("r").alias("tau"))
    return queries.select("qid", "alpha").join(tau, "qid").join(floor, "qid", "left").select("qid", "floor", "tau", reach_radius(F.col("alpha"), F.col("tau"), F.col("floor"), w_max, r_max).alias("radius"))


def near_cells(live: DataFrame, border: DataFrame, cells: DataFrame, queries: DataFrame, sd: DataFrame) -> DataFrame:
    """(qid, cell, near): distance of each live cell's nearest border; 0 for the start's own cell."""
    reached = queries.select("qid", F.col("v_q").alias("s")).join(sd, "s").join(border, "v").groupBy("qid", "cell").agg(F.min("dist").alias("near"))
    home = queries.join(cells.withColumnRenamed("v", "v_q"), "v_q").select("qid", "cell", F.lit(True).alias("home"))
    return live.select("qid", "cell").join(reached, ["qid", "cell"], "left").join(home, ["qid", "cell"], "left").select("qid", "cell", F.when(F.col("home"), 0).otherwise(F.col("near")).alias("near")).filter("near is not null")


def region_fixpoint(near: DataFrame, found: DataFrame, queries: DataFrame, floor: DataFrame, m: int) -> DataFrame:
    """(qid, d_ub, tau_u, n_cells): the largest radius that agrees with the best ratings of the cells within it.

    Cells are sorted by distance; with running maxima by tag, the last cell that still lies within
    its own radius closes the region. One pass, whatever the number of shrinking rounds.
    """
    best = found.groupBy("qid", "cell").agg(*(F.max(F.when(F.col("tag_pos") == j, F.col("rating"))).alias(f"b{j}") for j in range(m)))
    w = W.partitionBy("qid").orderBy("near", "cell").rowsBetween(W.unboundedPreceding, 0)
    running = near.join(best, ["qid", "cell"])
    tau = reduce(lambda a, b: a + b, (F.coalesce(F.max(f"b{j}").over(w), F.lit(0)) for j in range(m)))
    at = running.withColumn("tau_u", tau).withColumn("n_cells", F.row_number().over(w.rowsBetween(W.unboundedPreceding, 0))).join(queries.select("qid", "alpha"), "qid").join(floor, "qid")
    at = at.withColumn("d_ub", reach_radius(F.col("alpha"), F.col("tau_u"), F.col("floor"))).filter("near <= d_ub")
    return at.groupBy("qid").agg(F.max_by(F.struct("d_ub", "tau_u", "n_cells"), F.col("n_cells")).alias("f")).select("qid", F.round("f.d_ub", 4).alias("d_ub"), "f.tau_u", F.col("f.n_cells").cast("long").alias("n_cells"))


def region_trace(near: DataFrame, found: DataFrame, start: DataFrame, queries: DataFrame, floor: DataFrame, m: int, steps: int) -> DataFrame:
    """(qid, step, radius, n_cells, tau): radii of the shrinking rounds, each from the best ratings of the cells within the one before."""
    best = found.groupBy("qid", "cell").agg(*(F.max(F.when(F.col("tag_pos") == j, F.col("rating"))).alias(f"b{j}") for j in range(m)))
    cells = materialize(near.join(best, ["qid", "cell"]), "near")
    now = region_radius(start, queries, floor).filter("floor is not null").join(queries.select("qid", "alpha"), "qid").select("qid", "alpha", "floor", "radius")
    tau = reduce(lambda a, b: a + b, (F.coalesce(F.max(f"b{j}"), F.lit(0)) for j in range(m)))
    rounds = []
    for i in range(steps):
        inside = materialize(now.join(cells, "qid").filter("near <= radius").groupBy("qid", "alpha", "floor", "radius").agg(tau.cast("long").alias("tau"), F.count("*").alias("n_cells")), "trace")
        rounds.append(inside.select("qid", F.lit(i).cast("long").alias("step"), F.round("radius", 4).alias("radius"), "n_cells", "tau"))
        now = inside.select("qid", "alpha", "floor", F.least("radius", reach_radius(F.col("alpha"), F.col("tau"), F.col("floor"))).alias("radius"))
    return reduce(lambda a, b: a.unionByName(b), rounds)


def cell_bounds(near: DataFrame, found: DataFrame, queries: DataFrame, floor: DataFrame, m: int) -> DataFrame:
    """(qid, cell, near, tau_cell, bound, pruned): the best score of a route over any POI of a cell, against the floor."""
    best = found.groupBy("qid", "cell").agg(*(F.max(F.when(F.col("tag_pos") == j, F.col("rating"))).alias(f"b{j}") for j in range(m)))
    all_ = found.groupBy("qid").agg(*(F.max(F.when(F.col("tag_pos") == j, F.col("rating"))).alias(f"a{j}") for j in range(m)))
    swap = F.least(*(F.col(f"a{j}") - F.col(f"b{j}") for j in range(m)), F.lit(10**9))
    tau = reduce(lambda a, b: a + b, (F.col(f"a{j}") for j in range(m))) - swap
    at = near.join(best, ["qid", "cell"]).join(all_, "qid").withColumn("tau_cell", tau).join(queries.select("qid", "alpha"), "qid").join(floor, "qid", "left")
    bound = -F.col("alpha") * F.col("near") / W_MAX + (1 - F.col("alpha")) * RATIO * F.col("tau_cell") / R_MAX
    return at.select("qid", "cell", "near", "tau_cell", F.round(bound, 6).alias("bound"), F.coalesce((F.col("near") > 0) & (F.round(bound, 6) < F.col("floor")), F.lit(False)).alias("pruned"))


def set_bounds(sets: DataFrame, queries: DataFrame, vertices: DataFrame, m: int) -> DataFrame:
    """(qid, members, rating, line, bound): a cover set's least line length over its orders, and its best possible score."""
    perms = F.broadcast(orders_table(sets.sparkSession, m))
    at = sets.join(queries.select("qid", "alpha", F.col("v_q").alias("vq")), "qid")
    for n in ["q", *range(m)]:
        at = at.join(vertices.select(F.col("v").alias(f"v{n}"), F.col("x").alias(f"x{n}"), F.col("y").alias(f"y{n}")), f"v{n}")
    o = [F.col(f"o{i + 1}") for i in range(m)]
    line = line_length([F.col("xq"), *(_at(o, [f"x{j}" for j in range(m)], i) for i in range(m))], [F.col("yq"), *(_at(o, [f"y{j}" for j in range(m)], i) for i in range(m))])
    least = at.crossJoin(perms).withColumn("line", line).groupBy("qid", F.array(*(F.col(f"p{j}") for j in range(m))).alias("members"), "rating", "alpha").agg(F.min("line").alias("line"))
    return least.select("qid", "members", "rating", F.round("line", 4).alias("line"), F.round(-F.col("alpha") * F.col("line") / W_MAX + (1 - F.col("alpha")) * RATIO * F.col("rating") / R_MAX, 4).alias("bound"))


def bovs(found: DataFrame, queries: DataFrame, vertices: DataFrame, m: int) -> DataFrame:
    """(qid, members, orders, evaluated, dist, pois): orders by line length are evaluated until that exceeds the best distance.

    Line lengths rise and the running best falls, so the orders evaluated are those whose line does
    not exceed the best distance before them.
    """
    at = found.join(vertices.select(F.col("v").alias("v_q"), F.col("x").alias("xq"), F.col("y").alias("yq")), "v_q")
    for i in range(m):
        at = at.withColumn(f"_v{i}", F.element_at("vs", i + 1)).join(vertices.select(F.col("v").alias(f"_v{i}"), F.col("x").alias(f"_x{i}"), F.col("y").alias(f"_y{i}")), f"_v{i}")
    line = line_length([F.col("xq"), *(F.col(f"_x{i}") for i in range(m))], [F.col("yq"), *(F.col(f"_y{i}") for i in range(m))])
    w = W.partitionBy("qid", "members").orderBy("line", "order")
    seen = at.withColumn("line", line).withColumn("before", F.min("dist").over(w.rowsBetween(W.unboundedPreceding, -1)))
    return seen.groupBy("qid", "members").agg(F.count("*").alias("orders"), F.sum((F.col("before").isNull() | (F.col("line") <= F.col("before") + 1e-6)).cast("long")).alias("evaluated"), F.min(F.struct("dist", "pois")).alias("b")).select("qid", "members", "orders", "evaluated", "b.dist", "b.pois")
