"""Landmarks, traces, sizes, further relational operators and streams, by name."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import functions, index, measures, network, operators, streaming
from .query import Engine, tables
from .registry import _CELLS, _FULL, _GOLD, _LOGGED, _OVERLAY, _RADIUS, _SD, _SEEDS, _TAGGED, _TAU, _CLOSED, _GRAPH, GOLD, Data, Stages, _flat_sql, _graph, _routes_sql, _top_sql, flat, gold_sql, register
from .sources import table
from .sql import sssp_sql, with_sql

# ------------------------------------------------------------------ index and query graph

_LANDMARKS = "SELECT CAST(floor(i * n / 8) AS BIGINT) AS s FROM dims, (SELECT unnest(range(8)) AS i) AS l"


@register("landmark_distances", with_sql("SELECT s AS landmark, v, dist FROM sd", recursive=sssp_sql(_LANDMARKS)))
def landmark_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distances of all vertices from eight landmarks."""
    d = Data(spark, sf_dir)
    return index.landmarks(d.arcs, index.spread_landmarks(d.vertices, 8))


@register("landmark_bounds", with_sql("""SELECT p.qid, p.a, p.b, max(abs(x.dist - y.dist)) AS bound FROM (SELECT DISTINCT h.qid, h.v AS a, g.v AS b FROM hit h JOIN hit g ON h.qid = g.qid AND h.v < g.v) AS p
  JOIN sd x ON x.v = p.a JOIN sd y ON y.v = p.b AND y.s = x.s GROUP BY p.qid, p.a, p.b""", _GOLD, sssp_sql(_LANDMARKS)))  # fmt: skip
def landmark_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What pairs of hit POIs are not nearer than, by the triangle inequality over landmarks."""
    d = Data(spark, sf_dir)
    found = tables.hits(d.index, d.gold()).select("qid", "v").distinct()
    pairs = found.withColumnRenamed("v", "a").join(found.withColumnRenamed("v", "b"), "qid").filter("a < b")
    return index.landmark_bound(pairs, index.landmarks(d.arcs, index.spread_landmarks(d.vertices, 8)))


register("m_graph_size", with_sql("SELECT qid, count(*) AS graph_arcs, (SELECT count(*) FROM arcs) AS network_arcs FROM graph GROUP BY qid", _GOLD | _GRAPH, _CLOSED))(lambda s, d: (lambda x: measures.graph_size(_graph(x), x.arcs))(Data(s, d)))


def _trace_sql(steps: int = 4) -> str:
    """Radius after radius, each from the best ratings of the cells within the one before."""
    parts = {**_CELLS, "trace0": f"SELECT t.qid, floor, {_RADIUS.format(tau='tau')} AS radius FROM tau_of t JOIN floor_of f ON f.qid = t.qid"}
    for i in range(steps):
        best = " + ".join(f"coalesce(max(b{j}), 0)" for j in range(4))
        parts[f"inside{i}"] = f"SELECT t.qid, t.floor, t.radius, {best} AS tau, count(*) AS n_cells FROM trace{i} t JOIN near_cell n ON n.qid = t.qid AND n.near <= t.radius JOIN cell_best c ON c.qid = n.qid AND c.cell = n.cell GROUP BY t.qid, t.floor, t.radius"
        parts[f"trace{i + 1}"] = f"SELECT qid, floor, least(radius, {_RADIUS.format(tau='tau')}) AS radius FROM inside{i}"
    return gold_sql(" UNION ALL ".join(f"SELECT qid, CAST({i} AS BIGINT) AS step, round(radius, 4) AS radius, n_cells, CAST(tau AS BIGINT) AS tau FROM inside{i}" for i in range(steps)), parts)


@register("region_trace", _trace_sql())
def region_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The region's radius over its first shrinking rounds."""
    x = Stages(Data(spark, sf_dir))
    return tables.region_trace(x.cells(), x.hits, x.near, x.q, x.floor(), 4, 4)


_MEASURED = f"SELECT t.qid, count(*) AS members, round(100.0 * count(*) / any_value(n), 4) AS share FROM tau_of t JOIN floor_of f ON f.qid = t.qid JOIN (SELECT DISTINCT qid, v_q FROM gold) AS g ON g.qid = t.qid JOIN sd s ON s.s = g.v_q CROSS JOIN dims WHERE s.dist <= {_RADIUS.format(tau='tau')} GROUP BY t.qid"


@register("m_scope_measured", gold_sql(_MEASURED, _SEEDS | _TAU))
def scope_measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices within the radius, and their share of the network: what `m_scope` predicts."""
    x = Stages(Data(spark, sf_dir))
    return measures.scope_measured(x.q, x.sd, tables.region_radius(x.near, x.q, x.floor()), x.d.n)


@register("m_engine", with_sql("SELECT count(*) AS queries, CAST(sum(least(4, sets)) AS BIGINT) AS routes, true AS spread FROM (SELECT qid, product(n) AS sets FROM (SELECT l.qid, l.pos, count(*) AS n FROM logged l JOIN tagged t ON t.tag = l.tag GROUP BY l.qid, l.pos) AS g GROUP BY qid HAVING count(*) = 4) AS h", {**_LOGGED, **_TAGGED}))
def engine_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries and routes of a batch as its run observes them, and whether its plan spreads queries by an exchange."""
    x = Data(spark, sf_dir)
    return measures.engine(spark, x.engine().run_batch(x.log()))


_ONE = {**_GOLD, "hit": "SELECT * FROM (SELECT g.qid, g.pos AS tag_pos, t.poi, t.v, t.cell, t.rating, min(t.poi) OVER (PARTITION BY g.qid, g.pos) AS one FROM gold g JOIN tagged t ON t.tag = g.tag) AS z WHERE tag_pos > 0 OR poi = one"}


@register("topk_landmark_tag", with_sql(_flat_sql(_top_sql("route")), _ONE | _FULL | _routes_sql("cover", "route"), _SD))
def landmark_tag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gold queries whose first tag names one place alone."""
    x = Data(spark, sf_dir)
    whole = x.engine().index
    first = x.nations.filter(F.col("key").isin([keys[0] for keys in GOLD])).select("tag")
    named = whole.pois.join(F.broadcast(first), "tag", "left_semi")  # two tags
    one = named.groupBy("tag").agg(F.min("poi").alias("poi"))
    pois = whole.pois.join(F.broadcast(first), "tag", "left_anti").unionByName(named.join(one, ["tag", "poi"]), allowMissingColumns=True)
    return flat(Engine(replace(whole, pois=pois.select("poi", "v", "tag", "rating"))).run_batch(x.gold()))


_PRUNING_HIT = {"logged": "SELECT qid, v_q, pos, n_name AS tag FROM log JOIN nation ON n_nationkey = nation", **_TAGGED, "hit": "SELECT l.qid, l.v_q, l.pos AS tag_pos, t.cell FROM logged l JOIN tagged t ON t.tag = l.tag"}


@register("cube_pruning", with_sql("""SELECT zone, parity, count(*) AS queries, CAST(sum(cells) AS BIGINT) AS cells_rn, bool_and(true) AS shrinks
  FROM (SELECT qid, floor(any_value(v_q) / 500) AS zone, CAST(qid % 2 AS DOUBLE) AS parity, count(DISTINCT cell) AS cells FROM hit GROUP BY qid) AS g GROUP BY CUBE (zone, parity)""", _PRUNING_HIT))  # fmt: skip
def cube_pruning(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Live cells, and whether region and pruning leave no more of them, over a cube of where the queries of all events start and of their halves."""
    x = Data(spark, sf_dir)
    log = x.log(whole=True)
    staged = measures.stages(x.engine().counters(log)).filter("cells_rn > 0").join(log.select("qid", F.floor(F.col("v_q") / 500).cast("double").alias("zone")), "qid")
    left = (F.col("cells_sr") <= F.col("cells_rn")) & (F.col("cells_bp") <= F.col("cells_rn"))
    return staged.withColumn("parity", (F.col("qid") % 2).cast("double")).cube("zone", "parity").agg(F.count("*").alias("queries"), F.sum("cells_rn").alias("cells_rn"), F.bool_and(left).alias("shrinks"))


# ------------------------------------------------------------------ relational operators

register("unpivot_pois", with_sql("SELECT poi, name, value FROM (SELECT poi, 'v' AS name, CAST(v AS BIGINT) AS value FROM suppliers UNION ALL SELECT poi, 'rating', rating FROM suppliers) AS u"))(lambda s, d: Data(s, d).pois.select("poi", F.col("v").cast("long").alias("v"), F.col("rating").cast("long").alias("rating")).unpivot(["poi"], ["v", "rating"], "name", "value"))
register("setops_vertices", with_sql("""SELECT 'both' AS kind, count(*) AS n FROM (SELECT v FROM suppliers INTERSECT SELECT v FROM customers) AS a UNION ALL SELECT 'supplier only', count(*) FROM (SELECT v FROM suppliers EXCEPT SELECT v FROM customers) AS b
  UNION ALL SELECT 'any', count(*) FROM (SELECT v FROM suppliers UNION SELECT v FROM customers) AS c"""))(lambda s, d: operators.set_counts(Data(s, d).pois.select("v"), network.pois_customer(s, d).select("v")))
register("sample_pois", with_sql("SELECT poi, v, tag, rating FROM customers WHERE substr(md5(CAST(poi AS VARCHAR)), 1, 2) < '40'"))(lambda s, d: operators.hash_sample(network.pois_customer(s, d), "poi", 0.25))
register("approx_pois", with_sql("SELECT tag, count(DISTINCT v) AS places, true AS close, true AS median_close FROM customers GROUP BY tag"))(lambda s, d: operators.approximate(network.pois_customer(s, d)))
_HOPS = {"hops(v, hop) USING KEY (v)": "SELECT CAST(floor(n / 2) AS BIGINT) AS v, CAST(0 AS BIGINT) AS hop FROM dims UNION SELECT a.v, min(h.hop) + 1 FROM hops h JOIN arcs a ON a.u = h.v LEFT JOIN recurring.hops r ON r.v = a.v WHERE r.v IS NULL AND h.hop < 4 GROUP BY a.v"}
register("k_hop", with_sql("SELECT v, hop FROM hops", recursive=_HOPS))(lambda s, d: operators.k_hop(Data(s, d).arcs, Data(s, d).n.select(F.floor(F.col("n") / 2).alias("v")), 4))
register("udf_scores", with_sql(f"SELECT poi, round(-0.6 * v / {functions.W_MAX} + (1 - 0.6) * {functions.RATIO} * rating / {functions.R_MAX}, 6) AS score FROM customers"))(lambda s, d: network.pois_customer(s, d).select("poi", functions.score_udf(0.6)(F.col("v").cast("double"), F.col("rating").cast("double")).alias("score")))
register("udaf_ratings", with_sql("SELECT tag, round(exp(avg(ln(rating))), 6) AS rating FROM customers GROUP BY tag"))(lambda s, d: network.pois_customer(s, d).groupBy("tag").agg(F.round(functions.geometric_mean()(F.col("rating").cast("double")), 6).alias("rating")))
_FOUR = "SELECT unnest([0, 1, 2, 3]) AS i"


@register("lateral_orders", with_sql(f"SELECT g.qid, p.a || ',' || p.b || ',' || p.c || ',' || p.d AS visits FROM (SELECT DISTINCT qid FROM asked) AS g CROSS JOIN (SELECT a.i AS a, b.i AS b, c.i AS c, d.i AS d FROM ({_FOUR}) a, ({_FOUR}) b, ({_FOUR}) c, ({_FOUR}) d WHERE a.i <> b.i AND a.i <> c.i AND a.i <> d.i AND b.i <> c.i AND b.i <> d.i AND c.i <> d.i) AS p", {"asked": _GOLD["asked"]}))
def lateral_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders of visit of each query by a table function in a lateral join."""
    functions.register_orders(spark)
    Data(spark, sf_dir).gold().createOrReplaceTempView("tcr_asked")
    return spark.sql("SELECT qid, o.visits FROM tcr_asked, LATERAL tcr_orders(size(tags)) AS o")


# ------------------------------------------------------------------ streams

register("stream_sliding", """SELECT CAST(w AS TIMESTAMP) AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean_value FROM (SELECT *, unnest([time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR * i FOR i IN [0, 1, 2, 3]]) AS w FROM events) AS e
  GROUP BY w, event_type""")(lambda s, d: streaming.drain(streaming.tumbling(streaming.events(s, d), "1 day", "6 hours")))  # fmt: skip
register("stream_purchases", "SELECT a.user_id, a.event_id AS viewed, b.event_id AS bought FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")(lambda s, d: streaming.drain(streaming.clicks_to_purchases(streaming.events(s, d)), "append"))
register("stream_with_pois", with_sql("SELECT tag, event_type, count(*) AS n FROM events JOIN suppliers ON poi = user_id % 10 GROUP BY tag, event_type"))(lambda s, d: streaming.drain(streaming.with_pois(streaming.events(s, d), Data(s, d).pois, F.col("user_id") % 10)))


@register("stream_late", "SELECT count(*) AS n, count(*) FILTER (ts < newest - INTERVAL 1 DAY AND event_id % 2 = 1) AS late FROM events, (SELECT max(ts) AS newest FROM events WHERE event_id % 2 = 0) AS m")
def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events that come more than a day behind the newest one seen in batches before: here the odd ones come after the even ones."""
    import uuid

    from .plans.rounds import shared_dir

    base = f"{shared_dir(spark).rstrip('/')}/late-{uuid.uuid4().hex}"
    for half in (0, 1):
        table(spark, sf_dir, "events").filter(F.col("event_id") % 2 == half).coalesce(1).write.parquet(f"{base}/in/{half}")
    return streaming.late_counts(spark, f"{base}/in", f"{base}/out", "1 day")
