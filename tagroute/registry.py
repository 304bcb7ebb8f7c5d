"""Every query of the route engine by name, and the SQL that checks it.

The gold queries start at the lattice's middle vertex and ask for four nations each; `log` is the
workload of 1,000 queries, with the experiments' defaults of 4 tags, 4 routes and alpha 0.6.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import index, network, partition
from .distance import same_cell_true, sssp, sssp_wide
from .functions import R_MAX, RATIO, W_MAX
from .query import Engine, tables
from .query.spec import query_log
from .query.wide import run_wide
from .sources import table
from .sql import sssp_sql, with_sql

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
#: Nation keys of the gold queries.
GOLD = ((3, 5, 7, 11), (0, 1, 2, 4))
#: Queries of the experiments' workload.
LOG_QUERIES = 1000

_engines: dict[tuple[str, str, str], Engine] = {}


def register(name: str, sql: str | None = None) -> Callable:
    def keep(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return keep


class Data:
    """Frames of a table folder."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.dir = spark, sf_dir
        self.vertices, self.edges = network.lattice(spark, sf_dir)
        self.arcs = network.arcs(self.edges)
        self.cells = partition.tiles(self.vertices)
        self.pois = network.pois_supplier(spark, sf_dir)
        self.cross = index.cross_edges(self.edges, self.cells)
        self.border = index.borders(self.cross)
        self.index = index.tag_index(self.pois, self.cells)
        self.n = table(spark, sf_dir, "part").agg(F.count("*").alias("n"))
        self.nations = table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("key"), F.col("n_name").alias("tag"))

    def gold(self, alpha: float = 0.6, k: int = 4, dest: bool = False, budget: int | None = None) -> DataFrame:
        asked = self.spark.createDataFrame([(q, p, key) for q, keys in enumerate(GOLD) for p, key in enumerate(keys)], "qid long, pos int, key int")
        named = asked.join(F.broadcast(self.nations), "key").groupBy("qid").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "tag"))), lambda x: x["tag"]).alias("tags"))
        v_q = F.floor(F.col("n") / 2)
        end = (v_q + F.floor(F.col("n") / 3)) % F.col("n")
        return named.crossJoin(F.broadcast(self.n)).select("qid", v_q.alias("v_q"), "tags", F.lit(alpha).alias("alpha"), F.lit(k).alias("k"), (end if dest else F.lit(None).cast("long")).alias("dest"), F.lit(budget).cast("long").alias("budget"))

    def log(self, m: int = 4, k: int = 4, alpha: float = 0.6, whole: bool = False) -> DataFrame:
        """The experiments' workload of LOG_QUERIES queries, or (whole) a query of every event."""
        events = table(self.spark, self.dir, "events").select("event_id", "user_id")
        return query_log(events if whole else events.filter(F.col("event_id") < LOG_QUERIES), self.n, self.nations, m, k, alpha)

    def engine(self, layer: str = "supplier") -> Engine:
        key = (self.spark.sparkContext.applicationId, self.dir, layer)
        if key not in _engines:
            pois = {"supplier": self.pois, "customer": network.pois_customer(self.spark, self.dir), "part": network.pois_part(self.spark, self.dir), "documents": network.pois_documents(self.spark, self.dir)}[layer]
            personal = network.personal_ratings(self.spark, self.dir) if layer == "supplier" else None
            _engines[key] = Engine.build(self.vertices, self.edges, pois, self.cells, personal=personal)
        return _engines[key]


def flat(answers: DataFrame) -> DataFrame:
    return answers.select("qid", F.col("rank").cast("long").alias("rank"), "score", "dist", "rating", F.array_join(F.transform("pois", lambda p: p.cast("string")), "-").alias("pois"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The four best routes over three brands of the medium layer, by the full method."""
    d = Data(spark, sf_dir)
    brands = [r[0] for r in network.pois_part(spark, sf_dir).select("tag").distinct().orderBy("tag").limit(3).collect()]
    return flat(d.engine("part").routes(0, brands, 4, 0.6))


# ------------------------------------------------------------------ networks and layers

register("net_lattice_edges", with_sql("SELECT u, v, w FROM edges"))(lambda s, d: Data(s, d).edges)
register("net_lattice_degree", with_sql("SELECT degree, count(*) AS n FROM (SELECT u, count(*) AS degree FROM arcs GROUP BY u) AS g GROUP BY degree"))(lambda s, d: Data(s, d).arcs.groupBy("u").agg(F.count("*").alias("degree")).groupBy("degree").agg(F.count("*").alias("n")))
register("net_large_lattice", with_sql("SELECT u, v, w FROM big_edges"))(lambda s, d: network.lattice_from_orders(s, d)[1])
_TRADE = "SELECT least(2 * o_custkey, 2 * l_suppkey + 1) AS u, greatest(2 * o_custkey, 2 * l_suppkey + 1) AS v, CAST(1 + floor(1000 / (1 + count(*))) AS BIGINT) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey, l_suppkey"
register("net_trade_edges", _TRADE)(network.trade)
_PROXIMITY = """SELECT u, v, min(w) AS w FROM (SELECT least(a, b) AS u, greatest(a, b) AS v, CAST(ceil(d * 1e6) AS BIGINT) AS w FROM
  (SELECT a, b, d, row_number() OVER (PARTITION BY a ORDER BY d, b) AS r FROM (SELECT x.vec_id AS a, y.vec_id AS b, list_distance(CAST(x.embedding AS DOUBLE[]), CAST(y.embedding AS DOUBLE[])) AS d FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) AS p) AS q
  WHERE r <= 6) AS z GROUP BY u, v"""
register("net_proximity_edges", _PROXIMITY)(network.proximity)
register("poi_supplier", with_sql("SELECT poi, v, tag, rating FROM suppliers"))(network.pois_supplier)
register("poi_customer", with_sql("SELECT poi, v, tag, rating FROM customers"))(network.pois_customer)
register("poi_part", with_sql("SELECT poi, v, tag, rating FROM parts"))(network.pois_part)
register("poi_documents_multitag", with_sql("SELECT poi, v, tag, rating FROM docs"))(network.pois_documents)
register("poi_personal_ratings", "SELECT o_custkey AS user, l_suppkey AS poi, CAST(greatest(1, floor(least(50, greatest(1, floor(avg(l_quantity)))) * 90 / 50)) AS BIGINT) AS rating FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey, l_suppkey")(network.personal_ratings)
_PLACES = "SELECT DISTINCT e.u, e.v, CAST(1 + l_linenumber % (e.w - 1) AS BIGINT) AS offs, e.w FROM lineitem CROSS JOIN dims JOIN edges e ON e.u = l_orderkey % n AND e.v = e.u + 1"


@register("net_edge_pois", with_sql(f"""SELECT least(a, b) AS u, greatest(a, b) AS v, w FROM (
  SELECT coalesce(lag(spot) OVER g, u) AS a, spot AS b, offs - coalesce(lag(offs) OVER g, 0) AS w FROM numbered WINDOW g AS (PARTITION BY u, v ORDER BY offs)
  UNION ALL SELECT max(spot), any_value(v), any_value(w) - max(offs) FROM numbered GROUP BY u, v
  UNION ALL SELECT u, v, w FROM edges e WHERE NOT EXISTS (SELECT 1 FROM places p WHERE p.u = e.u AND p.v = e.v)) AS z""",
  {"places": _PLACES, "numbered": "SELECT *, n + row_number() OVER (ORDER BY u, v, offs) - 1 AS spot FROM places, dims"}))
def net_edge_pois(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The lattice with a vertex at every place of an order line on an edge."""
    d = Data(spark, sf_dir)
    return network.split_edges(d.edges, network.edge_pois(spark, sf_dir), d.n.first()[0])[0]


@register("poi_snap_nearest", with_sql("""SELECT id, min_by(v, struct_pack(d := d, v := v)) AS v FROM (SELECT s_suppkey AS id, v, (px - x) * (px - x) + (py - y) * (py - y) AS d FROM
  (SELECT s_suppkey, CAST((s_suppkey * 37) % (10 * wide) AS BIGINT) AS px, CAST((s_suppkey * 91) % (10 * wide) AS BIGINT) AS py FROM supplier, dims) AS p CROSS JOIN vertices) AS z GROUP BY id"""))  # fmt: skip
def poi_snap_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Places off the network, each at its nearest vertex."""
    d = Data(spark, sf_dir)
    side = 10 * F.ceil(F.sqrt(F.col("n")))
    points = table(spark, sf_dir, "supplier").crossJoin(F.broadcast(d.n)).select(F.col("s_suppkey").alias("id"), ((F.col("s_suppkey") * 37) % side).alias("px"), ((F.col("s_suppkey") * 91) % side).alias("py"))
    return network.snap_nearest(points, d.vertices)


register("scale_factors", with_sql("SELECT w_max, r_max, 1.0 / w_max AS w_factor, 10.0 / r_max AS r_factor FROM (SELECT max(w) AS w_max FROM edges) AS e, (SELECT max(rating) AS r_max FROM suppliers) AS p"))(lambda s, d: network.fit_scale(Data(s, d).edges, Data(s, d).pois).select("w_max", "r_max", F.col("w_factor").cast("double").alias("w_factor"), F.col("r_factor").cast("double").alias("r_factor")))

# ------------------------------------------------------------------ partition and index

register("cells_tiles", with_sql("SELECT v, cell FROM cells"))(lambda s, d: Data(s, d).cells)


def _kd_sql(n_s: int = 64, levels: int = 24) -> str:
    """Halves by rank, as many levels as the number of vertices asks for."""
    parts = {"kd0": "SELECT v, x, y, CAST(1 AS BIGINT) AS cell FROM vertices"}
    for i in range(levels):
        by = "x, y, v" if i % 2 == 0 else "y, x, v"
        parts[f"kd{i + 1}"] = f"SELECT v, x, y, CASE WHEN (SELECT ceil(n / {2**i}) FROM dims) > {n_s} THEN cell * 2 + CASE WHEN row_number() OVER (PARTITION BY cell ORDER BY {by}) > ceil(count(*) OVER (PARTITION BY cell) / 2) THEN 1 ELSE 0 END ELSE cell END AS cell FROM kd{i}"
    parts["kd_cut"] = f"SELECT e.u, e.v, a.cell AS cu, b.cell AS cv FROM edges e JOIN kd{levels} a ON e.u = a.v JOIN kd{levels} b ON e.v = b.v WHERE a.cell <> b.cell"
    return with_sql(f"SELECT count(*) AS cells, max(n) AS max_size, round(avg(n), 6) AS mean_size, (SELECT count(*) FROM kd_cut) AS cut_edges, (SELECT count(*) FROM (SELECT cu, u FROM kd_cut UNION SELECT cv, v FROM kd_cut) AS b) AS border_vertices FROM (SELECT cell, count(*) AS n FROM kd{levels} GROUP BY cell) AS g", parts)


register("cells_kd", _kd_sql())(lambda s, d: partition.quality(partition.kd(Data(s, d).vertices, 64), Data(s, d).edges))
register("cells_multilevel")(lambda s, d: partition.quality(partition.multilevel(Data(s, d).edges, 64), Data(s, d).edges))
register("cells_propagate")(lambda s, d: partition.quality(partition.propagate(Data(s, d).edges, 64), Data(s, d).edges))
register("cells_quality", with_sql("SELECT count(*) AS cells, max(n) AS max_size, round(avg(n), 6) AS mean_size, (SELECT count(*) FROM cut) AS cut_edges, (SELECT count(*) FROM borders) AS border_vertices FROM (SELECT cell, count(*) AS n FROM cells GROUP BY cell) AS g"))(lambda s, d: partition.quality(Data(s, d).cells, Data(s, d).edges))
register("border_vertices", with_sql("SELECT cell, v FROM borders"))(lambda s, d: Data(s, d).border)
register("cross_edges", with_sql("SELECT u, v, w, cu, cv FROM cut"))(lambda s, d: Data(s, d).cross)
_CLOSED = sssp_sql("SELECT v AS s FROM cells", "inner_arcs", "inner_sd")
_CLOSURE = {"closed": "SELECT c.cell, i.s AS u, i.v, i.dist FROM inner_sd i JOIN cells c ON c.v = i.s"}
register("cell_closure", with_sql("SELECT cell, u, v, dist FROM closed", _CLOSURE, _CLOSED))(lambda s, d: index.closure(Data(s, d).edges, Data(s, d).cells))
_OVERLAY = {**_CLOSURE, "shorts": "SELECT c.u, c.v, c.dist FROM closed c JOIN borders a ON a.v = c.u AND a.cell = c.cell JOIN borders b ON b.v = c.v AND b.cell = c.cell WHERE c.u <> c.v"}
register("overlay_edges", with_sql("SELECT u, v, dist, 'shortcut' AS kind FROM shorts UNION ALL SELECT u, v, w, 'cross' FROM cut UNION ALL SELECT v, u, w, 'cross' FROM cut", _OVERLAY, _CLOSED))(lambda s, d: index.overlay(index.closure(Data(s, d).edges, Data(s, d).cells, "border"), Data(s, d).border, Data(s, d).cross))
_ALL = sssp_sql("SELECT v AS s FROM cells")


@register("same_cell_true_distance", with_sql("SELECT a.cell, s.s AS u, s.v, s.dist FROM sd s JOIN cells a ON a.v = s.s JOIN cells b ON b.v = s.v WHERE a.cell = b.cell", recursive=_ALL))
def same_cell(spark: SparkSession, sf_dir: str) -> DataFrame:
    """True distances of pairs in a cell, ways outside it included."""
    d = Data(spark, sf_dir)
    # distances between borders by arrays here; `same_cell_true` does it by rounds for networks beyond a task
    closed = index.closure(d.edges, d.cells)
    over = sssp(d.arcs, d.border.select(F.col("v").alias("s")))
    b = d.border
    loops = b.select("cell", F.col("v").alias("b1")).join(b.select("cell", F.col("v").alias("b2")), "cell").join(over.select(F.col("s").alias("b1"), F.col("v").alias("b2"), F.col("dist").alias("d")), ["b1", "b2"])
    out = closed.select("cell", "u", F.col("v").alias("b1"), F.col("dist").alias("d1")).join(loops, ["cell", "b1"]).groupBy("cell", "u", "b2").agg(F.min(F.col("d1") + F.col("d")).alias("d2"))
    through = out.join(closed.select("cell", F.col("u").alias("b2"), "v", F.col("dist").alias("d3")), ["cell", "b2"]).groupBy("cell", "u", "v").agg(F.min(F.col("d2") + F.col("d3")).alias("through"))
    return through.join(closed, ["cell", "u", "v"], "full").select("cell", "u", "v", F.least("through", "dist").alias("dist"))


_TAGGED = {"tagged": "SELECT tag, poi, s.v, cell, rating FROM suppliers s JOIN cells c ON c.v = s.v"}
register("tag_index", with_sql("SELECT tag, poi, v, cell, rating FROM tagged", _TAGGED))(lambda s, d: Data(s, d).index)
register("tag_max", with_sql("SELECT tag, max(rating) AS rating, count(*) AS n FROM tagged GROUP BY tag", _TAGGED))(lambda s, d: index.tag_max(Data(s, d).index))
register("tag_cell_max", with_sql("SELECT tag, cell, max(rating) AS rating, count(*) AS n FROM tagged GROUP BY tag, cell", _TAGGED))(lambda s, d: index.tag_cell_max(Data(s, d).index))

# ------------------------------------------------------------------ queries: hits, query graph, distances

_LOGGED = {"logged": f"SELECT qid, v_q, pos, n_name AS tag FROM log JOIN nation ON n_nationkey = nation WHERE qid < {LOG_QUERIES}"}
_GOLD = {
    "asked": " UNION ALL ".join(f"SELECT {q} AS qid, {p} AS pos, {key} AS key" for q, keys in enumerate(GOLD) for p, key in enumerate(keys)),
    "gold": "SELECT qid, pos, n_name AS tag, CAST(floor(n / 2) AS BIGINT) AS v_q, CAST((floor(n / 2) + floor(n / 3)) % n AS BIGINT) AS dest FROM asked JOIN nation ON n_nationkey = key, dims",
    **_TAGGED,
    "hit": "SELECT g.qid, g.pos AS tag_pos, t.poi, t.v, t.cell, t.rating FROM gold g JOIN tagged t ON t.tag = g.tag",
    "live": "SELECT qid, cell, count(*) AS n_hits FROM hit GROUP BY qid, cell",
}
_SOURCES = "SELECT DISTINCT v_q AS s FROM gold UNION SELECT DISTINCT v FROM hit"
_SD = sssp_sql(_SOURCES)


def gold_sql(final: str, more: dict[str, str] | None = None, sd: bool = True) -> str:
    return with_sql(final, _GOLD | (more or {}), _SD if sd else None)


register("query_log", with_sql("SELECT qid, v_q, string_agg(tag, '|' ORDER BY pos) AS tags FROM (SELECT qid, v_q, pos, n_name AS tag FROM log JOIN nation ON n_nationkey = nation) AS l GROUP BY qid, v_q"))(lambda s, d: query_log(table(s, d, "events"), Data(s, d).n, Data(s, d).nations).select("qid", "v_q", F.array_join("tags", "|").alias("tags")))
register("session_queries", "SELECT user_id, CAST(ts AS DATE) AS day, count(DISTINCT event_type) AS m, string_agg(DISTINCT event_type, '|' ORDER BY event_type) AS tags FROM events GROUP BY user_id, CAST(ts AS DATE)")(lambda s, d: table(s, d, "events").groupBy("user_id", F.to_date("ts").alias("day")).agg(F.count_distinct("event_type").alias("m"), F.array_join(F.array_sort(F.collect_set("event_type")), "|").alias("tags")))
register("query_hits", gold_sql("SELECT qid, tag_pos, poi, v, cell, rating FROM hit", sd=False))(lambda s, d: tables.hits(Data(s, d).index, Data(s, d).gold()))
register("live_cells", gold_sql("SELECT qid, cell, n_hits FROM live", sd=False))(lambda s, d: tables.live_cells(tables.hits(Data(s, d).index, Data(s, d).gold())))


@register("dead_cells", gold_sql("SELECT q.qid, c.cell FROM (SELECT DISTINCT qid FROM asked) AS q CROSS JOIN (SELECT DISTINCT cell FROM cells) AS c WHERE NOT EXISTS (SELECT 1 FROM live l WHERE l.qid = q.qid AND l.cell = c.cell)", sd=False))
def dead(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells without a hit POI."""
    d = Data(spark, sf_dir)
    return tables.dead_cells(d.cells, d.gold(), tables.live_cells(tables.hits(d.index, d.gold())))


_GRAPH = {
    **_OVERLAY,
    "graph": """SELECT l.qid, i.u, i.v, i.w, 'edge' AS kind FROM live l JOIN inner_arcs i ON i.cell = l.cell
      UNION ALL SELECT q.qid, c.u, c.v, c.w, 'cross' FROM (SELECT DISTINCT qid FROM asked) AS q CROSS JOIN (SELECT u, v, w FROM cut UNION ALL SELECT v, u, w FROM cut) AS c
      UNION ALL SELECT q.qid, c.u, c.v, c.dist, 'shortcut' FROM (SELECT DISTINCT qid FROM asked) AS q CROSS JOIN closed c JOIN borders a ON a.v = c.u AND a.cell = c.cell JOIN borders b ON b.v = c.v AND b.cell = c.cell
        WHERE c.u <> c.v AND NOT EXISTS (SELECT 1 FROM live l WHERE l.qid = q.qid AND l.cell = c.cell)
      UNION ALL SELECT q.qid, c.u, c.v, c.dist, 'start' FROM (SELECT DISTINCT qid, v_q FROM gold) AS q JOIN closed c ON c.u = q.v_q JOIN borders b ON b.v = c.v AND b.cell = c.cell
        WHERE c.u <> c.v AND NOT EXISTS (SELECT 1 FROM live l WHERE l.qid = q.qid AND l.cell = c.cell)""",
}


def _graph(d: Data) -> DataFrame:
    q = d.gold()
    return tables.query_graph(d.edges, d.cells, d.border, d.cross, index.closure(d.edges, d.cells), q, tables.live_cells(tables.hits(d.index, q)))


register("query_graph_edges", with_sql("SELECT qid, u, v, w, kind FROM graph", _GOLD | _GRAPH, _CLOSED))(lambda s, d: _graph(Data(s, d)))


@register("query_graph_distance_check", gold_sql("SELECT qid, v, dist FROM (SELECT DISTINCT qid, v_q FROM gold) AS q JOIN sd ON sd.s = q.v_q WHERE EXISTS (SELECT 1 FROM live l JOIN cells c ON c.cell = l.cell WHERE l.qid = q.qid AND c.v = sd.v) OR EXISTS (SELECT 1 FROM borders b WHERE b.v = sd.v) OR sd.v = q.v_q"))
def graph_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distances from the start over the query graph, which must be those over the network."""
    d = Data(spark, sf_dir)
    g = _graph(d)
    out = []
    for q in range(len(GOLD)):
        found = sssp(g.filter(F.col("qid") == q).select("u", "v", "w"), d.gold().filter(F.col("qid") == q).select(F.col("v_q").alias("s")))
        out.append(found.select(F.lit(q).cast("long").alias("qid"), "v", "dist"))
    return out[0].unionByName(out[1])


register("sssp_start", gold_sql("SELECT s, v, dist FROM sd WHERE s IN (SELECT v_q FROM gold)"))(lambda s, d: sssp(Data(s, d).arcs, Data(s, d).gold().select(F.col("v_q").alias("s"))))
register("sssp_multi", with_sql("SELECT s, v, dist FROM sd", recursive=sssp_sql("SELECT DISTINCT v AS s FROM suppliers")))(lambda s, d: sssp(Data(s, d).arcs, Data(s, d).pois.select(F.col("v").alias("s"))))


@register("sssp_wide", gold_sql("SELECT s, v, dist FROM sd WHERE s IN (SELECT v_q FROM gold)"))
def wide_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by DataFrame rounds over cells."""
    d = Data(spark, sf_dir)
    closed = index.materialize(index.closure(d.edges, d.cells), "closed")
    return sssp_wide(closed, d.cross, d.cells, d.gold().select(F.col("v_q").alias("s")))


# ------------------------------------------------------------------ stages of the search

_NEAR = {"near_hit": "SELECT h.*, s.dist, g.v_q FROM hit h JOIN (SELECT DISTINCT qid, v_q FROM gold) AS g ON g.qid = h.qid JOIN sd s ON s.s = g.v_q AND s.v = h.v"}
_RING = {
    **_NEAR,
    "counted": "SELECT *, " + " * ".join(f"sum(CASE WHEN tag_pos = {j} THEN 1 ELSE 0 END) OVER (PARTITION BY qid ORDER BY dist RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)" for j in range(4)) + " AS n_sets FROM near_hit",
    "ring": "SELECT n.* FROM near_hit n JOIN (SELECT qid, min(dist) AS reach FROM counted WHERE n_sets >= 4 GROUP BY qid) AS l ON l.qid = n.qid WHERE n.dist <= l.reach",
}


def _sets_sql(source: str, name: str) -> dict[str, str]:
    lists = " JOIN ".join(f"(SELECT qid AS q{j}, poi AS p{j}, v AS v{j}, rating AS r{j} FROM {source} WHERE tag_pos = {j}) AS t{j}" + (f" ON q{j} = q0" if j else "") for j in range(4))
    return {name: f"SELECT q0 AS qid, p0, p1, p2, p3, v0, v1, v2, v3, CAST(r0 + r1 + r2 + r3 AS BIGINT) AS rating FROM {lists}"}


_PERMS = {"four": "SELECT 0 AS i UNION ALL SELECT 1 UNION ALL SELECT 2 UNION ALL SELECT 3", "perms": "SELECT a.i AS o1, b.i AS o2, c.i AS o3, d.i AS o4 FROM four a, four b, four c, four d WHERE a.i <> b.i AND a.i <> c.i AND a.i <> d.i AND b.i <> c.i AND b.i <> d.i AND c.i <> d.i"}


def _routes_sql(sets: str, name: str, dest: bool = False, fixed: bool = False) -> dict[str, str]:
    pick = lambda what, o: f"[{', '.join(f'{what}{j}' for j in range(4))}][{o} + 1]"
    ordered = f"""SELECT z.qid, z.pois, z.members, z.rating, z.o1 * 1000 + z.o2 * 100 + z.o3 * 10 + z.o4 AS order_no, z.v_q, z.a1, z.a2, z.a3, z.a4, l1.dist + l2.dist + l3.dist + l4.dist AS dist FROM
      (SELECT s.qid, s.rating, o1, o2, o3, o4, g.v_q, [{', '.join(pick('p', f'o{i}') for i in range(1, 5))}] AS pois, [p0, p1, p2, p3] AS members, {', '.join(f"{pick('v', f'o{i}')} AS a{i}" for i in range(1, 5))}
        FROM {sets} s CROSS JOIN perms JOIN (SELECT DISTINCT qid, v_q FROM gold) AS g ON g.qid = s.qid {'WHERE o1 = 0 AND o2 = 1 AND o3 = 2' if fixed else ''}) AS z
      JOIN hop l1 ON l1.s = z.v_q AND l1.v = z.a1 JOIN hop l2 ON l2.s = z.a1 AND l2.v = z.a2 JOIN hop l3 ON l3.s = z.a2 AND l3.v = z.a3 JOIN hop l4 ON l4.s = z.a3 AND l4.v = z.a4"""
    out = {**_PERMS, "ends": "SELECT v FROM hit UNION SELECT dest FROM gold WHERE dest IS NOT NULL", "hop": "SELECT s.s, s.v, s.dist FROM sd s JOIN ends ON ends.v = s.v"}
    if not dest:
        return {**out, name: ordered}
    return {
        **out, f"{name}_open": ordered, "goal": "SELECT DISTINCT qid AS goal_qid, dest AS goal_v FROM gold", "home": "SELECT goal_qid, s AS home_s, dist AS home_dist FROM goal JOIN hop ON v = goal_v",
        name: f"SELECT qid, pois, members, rating, order_no, v_q, a1, a2, a3, a4, dist + home_dist AS dist FROM {name}_open JOIN home ON goal_qid = qid AND home_s = a4",
    }


def _score_sql(alpha: float, dist: str = "dist", rating: str = "rating") -> str:
    return f"round(-{alpha} * {dist} / {W_MAX} + (1 - {alpha}) * {RATIO} * {rating} / {R_MAX}, 6)"


def _top_sql(routes: str, alpha: float = 0.6, k: int = 4, per_set: bool = True, budget: int | None = None) -> str:
    inner = f"SELECT *, {_score_sql(alpha)} AS score FROM {routes}" + (f" WHERE dist <= {budget}" if budget is not None else "")
    if per_set:
        inner = f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid, members ORDER BY dist, pois) AS best FROM ({inner}) AS i) AS j WHERE best = 1"
    return f"SELECT qid, rank, score, dist, rating, pois FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, dist, pois) AS rank FROM ({inner}) AS x) AS y WHERE rank <= {k}"


def _flat_sql(top: str) -> str:
    return f"SELECT qid, rank, score, dist, rating, array_to_string(pois, '-') AS pois FROM ({top}) AS t"


_SEEDS = {**_RING, **_sets_sql("ring", "seed_set"), **_routes_sql("seed_set", "seed_route"), "seed_best": _top_sql("seed_route"), "floor_of": "SELECT qid, score AS floor FROM seed_best WHERE rank = 4"}
_TAU = {"tau_of": "SELECT qid, CAST(sum(r) AS BIGINT) AS tau FROM (SELECT qid, tag_pos, max(rating) AS r FROM near_hit GROUP BY qid, tag_pos) AS g GROUP BY qid"}
_RADIUS = f"{W_MAX} * ((1 - 0.6) * {RATIO} * {{tau}} / {R_MAX} - floor) / 0.6"
_CELLS = {
    **_SEEDS, **_TAU,
    "near_cell": """SELECT l.qid, l.cell, CASE WHEN l.cell = h.cell THEN 0 ELSE b.near END AS near FROM live l JOIN (SELECT DISTINCT g.qid, c.cell FROM gold g JOIN cells c ON c.v = g.v_q) AS h ON h.qid = l.qid
      LEFT JOIN (SELECT g.qid, b.cell, min(s.dist) AS near FROM (SELECT DISTINCT qid, v_q FROM gold) AS g JOIN sd s ON s.s = g.v_q JOIN borders b ON b.v = s.v GROUP BY g.qid, b.cell) AS b ON b.qid = l.qid AND b.cell = l.cell WHERE l.cell = h.cell OR b.near IS NOT NULL""",
    "cell_best": "SELECT qid, cell, " + ", ".join(f"max(CASE WHEN tag_pos = {j} THEN rating END) AS b{j}" for j in range(4)) + " FROM hit GROUP BY qid, cell",
}


class Stages:
    """The gold queries' stages, in order."""

    def __init__(self, d: Data):
        self.d, self.q = d, d.gold()
        self.hits = index.materialize(tables.hits(d.index, self.q), "hits")
        self.sd = index.materialize(sssp(d.arcs, self.q.select(F.col("v_q").alias("s")).unionByName(self.hits.select("v").withColumnRenamed("v", "s"))), "sd")
        self.near = tables.with_start_distance(self.hits, self.q, self.sd)
        self.ring = tables.ring_prefix(self.near, self.q)
        self.seeds = tables.cover_sets(self.ring, 4)
        self.seed_routes = tables.routes(self.seeds, self.q, self.sd, 4)

    def best(self) -> DataFrame:
        return tables.best_routes(self.seed_routes, self.q)

    def floor(self) -> DataFrame:
        return tables.floors(self.best(), self.q)

    def cells(self) -> DataFrame:
        return tables.near_cells(tables.live_cells(self.hits), self.d.border, self.d.cells, self.q, self.sd)


register("ring_prefix", gold_sql("SELECT qid, tag_pos, poi, v, rating, dist FROM ring", _RING))(lambda s, d: Stages(Data(s, d)).ring.select("qid", "tag_pos", "poi", "v", "rating", "dist"))
register("seed_sets", gold_sql("SELECT qid, p0, p1, p2, p3, rating FROM seed_set", _SEEDS))(lambda s, d: Stages(Data(s, d)).seeds.select("qid", "p0", "p1", "p2", "p3", "rating"))
register("seed_routes", gold_sql(_flat_sql("SELECT * FROM seed_best"), _SEEDS))(lambda s, d: flat(Stages(Data(s, d)).best()))
register("region_radius", gold_sql(f"SELECT t.qid, floor, tau, round({_RADIUS.format(tau='tau')}, 4) AS radius FROM tau_of t JOIN floor_of f ON f.qid = t.qid", _SEEDS | _TAU))(lambda s, d: (lambda x: tables.region_radius(x.near, x.q, x.floor()).filter("floor is not null").withColumn("radius", F.round("radius", 4)))(Stages(Data(s, d))))
_FIX = {
    **_CELLS,
    "running": "SELECT n.qid, n.near, row_number() OVER w AS n_cells, " + " + ".join(f"coalesce(max(b{j}) OVER w, 0)" for j in range(4)) + " AS tau_u FROM near_cell n JOIN cell_best c ON c.qid = n.qid AND c.cell = n.cell WINDOW w AS (PARTITION BY n.qid ORDER BY near, n.cell ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)",
    "closing": f"SELECT r.qid, {_RADIUS.format(tau='tau_u')} AS d_ub, tau_u, n_cells, near FROM running r JOIN floor_of f ON f.qid = r.qid",
}
register("region_fixpoint", gold_sql("SELECT qid, round(d_ub, 4) AS d_ub, tau_u, n_cells FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY n_cells DESC) AS r FROM closing WHERE near <= d_ub) AS z WHERE r = 1", _FIX))(lambda s, d: (lambda x: tables.region_fixpoint(x.cells(), x.hits, x.q, x.floor(), 4))(Stages(Data(s, d))))
register("region_cells", gold_sql(f"SELECT n.qid, n.cell, n.near FROM near_cell n JOIN tau_of t ON t.qid = n.qid JOIN floor_of f ON f.qid = n.qid WHERE n.near <= {_RADIUS.format(tau='tau')}", _CELLS))(lambda s, d: (lambda x: x.cells().join(tables.region_radius(x.near, x.q, x.floor()).filter("floor is not null").select("qid", "radius"), "qid").filter("near <= radius").select("qid", "cell", "near"))(Stages(Data(s, d))))
register("region_members", gold_sql(f"SELECT t.qid, count(*) AS vertices FROM tau_of t JOIN floor_of f ON f.qid = t.qid JOIN (SELECT DISTINCT qid, v_q FROM gold) AS g ON g.qid = t.qid JOIN sd s ON s.s = g.v_q WHERE s.dist <= {_RADIUS.format(tau='tau')} GROUP BY t.qid", _SEEDS | _TAU))(lambda s, d: (lambda x: x.q.select("qid", F.col("v_q").alias("s")).join(x.sd, "s").join(tables.region_radius(x.near, x.q, x.floor()).filter("floor is not null"), "qid").filter("dist <= radius").groupBy("qid").agg(F.count("*").alias("vertices")))(Stages(Data(s, d))))
_BOUNDS = {
    **_CELLS,
    "all_best": "SELECT qid, " + ", ".join(f"max(b{j}) AS a{j}" for j in range(4)) + " FROM cell_best GROUP BY qid",
    "cell_tau": "SELECT n.qid, n.cell, n.near, CAST(a0 + a1 + a2 + a3 - least(" + ", ".join(f"coalesce(a{j} - b{j}, 1000000000)" for j in range(4)) + ") AS BIGINT) AS tau_cell FROM near_cell n JOIN cell_best b ON b.qid = n.qid AND b.cell = n.cell JOIN all_best a ON a.qid = n.qid",
}
register("cell_bounds", gold_sql(f"SELECT t.qid, cell, near, tau_cell, {_score_sql(0.6, 'near', 'tau_cell')} AS bound, near > 0 AND {_score_sql(0.6, 'near', 'tau_cell')} < coalesce(floor, -1e18) AS pruned FROM cell_tau t LEFT JOIN floor_of f ON f.qid = t.qid", _BOUNDS))(lambda s, d: (lambda x: tables.cell_bounds(x.cells(), x.hits, x.q, x.floor(), 4))(Stages(Data(s, d))))
register("cell_pruned", gold_sql(f"SELECT t.qid, count(*) FILTER (near > 0 AND {_score_sql(0.6, 'near', 'tau_cell')} < coalesce(floor, -1e18)) AS pruned, count(*) AS n_cells FROM cell_tau t LEFT JOIN floor_of f ON f.qid = t.qid GROUP BY t.qid", _BOUNDS))(lambda s, d: (lambda x: tables.cell_bounds(x.cells(), x.hits, x.q, x.floor(), 4).groupBy("qid").agg(F.sum(F.col("pruned").cast("long")).alias("pruned"), F.count("*").alias("n_cells")))(Stages(Data(s, d))))
_XY = " ".join(f"JOIN vertices x{i} ON x{i}.v = r.a{i}" for i in range(1, 5)) + " JOIN vertices x0 ON x0.v = r.v_q"
_LINE = " + ".join(f"sqrt((x{i + 1}.x - x{i}.x) * (x{i + 1}.x - x{i}.x) + (x{i + 1}.y - x{i}.y) * (x{i + 1}.y - x{i}.y))" for i in range(4))
_LINES = {**_SEEDS, "lined": f"SELECT r.*, {_LINE} AS line FROM seed_route r {_XY}"}
register("set_bounds", gold_sql(f"SELECT qid, array_to_string(members, '-') AS members, rating, round(min(line), 4) AS line, round(-0.6 * min(line) / {W_MAX} + (1 - 0.6) * {RATIO} * rating / {R_MAX}, 4) AS bound FROM lined GROUP BY qid, members, rating", _LINES))(lambda s, d: (lambda x: tables.set_bounds(x.seeds, x.q, x.d.vertices, 4).withColumn("members", F.array_join("members", "-")))(Stages(Data(s, d))))
_BOVS = {**_LINES, "judged": "SELECT *, min(dist) OVER (PARTITION BY qid, members ORDER BY line, order_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM lined"}
register("bovs_best_order", gold_sql("SELECT qid, array_to_string(members, '-') AS members, dist, array_to_string(pois, '-') AS pois FROM (SELECT *, row_number() OVER (PARTITION BY qid, members ORDER BY dist, pois) AS r FROM seed_route) AS z WHERE r = 1", _SEEDS))(lambda s, d: (lambda x: tables.bovs(x.seed_routes, x.q, x.d.vertices, 4).select("qid", F.array_join("members", "-").alias("members"), "dist", F.array_join("pois", "-").alias("pois")))(Stages(Data(s, d))))
register("bovs_counts", gold_sql("SELECT qid, count(DISTINCT members) AS n_sets, count(*) AS orders, count(*) FILTER (before IS NULL OR line <= before + 1e-6) AS evaluated FROM judged GROUP BY qid", _BOVS))(lambda s, d: (lambda x: tables.bovs(x.seed_routes, x.q, x.d.vertices, 4).groupBy("qid").agg(F.count("*").alias("n_sets"), F.sum("orders").alias("orders"), F.sum("evaluated").alias("evaluated")))(Stages(Data(s, d))))
register("pair_distance", gold_sql("SELECT DISTINCT a.v AS u, s.v, s.dist FROM hit a JOIN hit b ON a.qid = b.qid JOIN sd s ON s.s = a.v AND s.v = b.v"))(lambda s, d: (lambda x: x.hits.select("qid", F.col("v").alias("s")).join(x.hits.select("qid", "v"), "qid").select("s", "v").distinct().join(x.sd, ["s", "v"]).select(F.col("s").alias("u"), "v", "dist"))(Stages(Data(s, d))))

# ------------------------------------------------------------------ answers

_FULL = {**_NEAR, **_sets_sql("hit", "cover")}


def _answers_sql(dest: bool = False, fixed: bool = False, **top) -> str:
    return gold_sql(_flat_sql(_top_sql("route", **top)), _FULL | _routes_sql("cover", "route", dest, fixed))


def _ebs(name: str, sql: str | None, method: str = "ebs", alpha: float = 0.6, k: int = 4, dest: bool = False, budget: int | None = None, **variant) -> None:
    register(name, sql)(lambda s, d: (lambda x: flat((x.engine().run_batch if method == "ebs" else x.engine().run)(x.gold(alpha, k, dest, budget), method, **variant)))(Data(s, d)))


@register("topk_exhaustive", _answers_sql())
def exhaustive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every order of every cover set, by joins."""
    x = Stages(Data(spark, sf_dir))
    return flat(tables.best_routes(tables.routes(tables.cover_sets(x.hits, 4), x.q, x.sd, 4), x.q))


@register("topk_wide", _answers_sql())
def wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The search by DataFrame rounds, for networks beyond a task."""
    d = Data(spark, sf_dir)
    closed = index.materialize(index.closure(d.edges, d.cells), "closed")
    return flat(run_wide(d.index, d.cells, closed, d.cross, d.gold()))


_ebs("topk_ebs", _answers_sql())
_ebs("topk_ebs_all_orders", _answers_sql(per_set=False), route_scope="all_orders")
_ebs("topk_ebs_path_rating", None, rating_scope="path")
_ebs("topk_fixed_order", _answers_sql(fixed=True), order=True)
_ebs("topk_budget", _answers_sql(budget=600), budget=600)
_ebs("topk_destination", gold_sql(_flat_sql(_top_sql("route")), _FULL | _routes_sql("cover", "route", True)), dest=True)
_ebs("topk_alpha0", _answers_sql(alpha=0.0), alpha=0.0)
_ebs("topk_alpha1", _answers_sql(alpha=1.0), alpha=1.0)
_SAME = {**_GOLD, "hit": _GOLD["hit"].replace("t.rating", "50 AS rating")}
_IDENTICAL = with_sql(_flat_sql(_top_sql("route")), _SAME | _FULL | _routes_sql("cover", "route"), _SD)
_IDENTICAL_ORDERS = with_sql(_flat_sql(_top_sql("route", per_set=False)), _SAME | _FULL | _routes_sql("cover", "route"), _SD)
_IDENTICAL_FIXED = with_sql(_flat_sql(_top_sql("route", per_set=False)), _SAME | _FULL | _routes_sql("cover", "route", fixed=True), _SD)
_ebs("topk_identical", _IDENTICAL, ratings="identical")
for _flag, _prune in (("no_region", {"cells", "sets", "orders"}), ("no_cells", {"region", "sets", "orders"}), ("no_orders", {"region", "cells", "sets"}), ("no_sets", {"region", "cells", "orders"})):
    _ebs(f"topk_{_flag}", _answers_sql(), prune=frozenset(_prune))
_ebs("topk_grid_bound", _answers_sql(), lower_bound="grid")


@register("topk_precedence", gold_sql(_flat_sql(_top_sql("(SELECT * FROM route WHERE list_position(pois, members[1]) < list_position(pois, members[2])) AS r")), _FULL | _routes_sql("cover", "route")))
def precedence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first tag before the second, the others at will."""
    x = Data(spark, sf_dir)
    names = {r.key: r.tag for r in x.nations.collect()}
    parts = [x.engine().run_batch(x.gold().filter(F.col("qid") == q), precedence=((names[keys[0]], names[keys[1]]),)) for q, keys in enumerate(GOLD)]
    return flat(parts[0].unionByName(parts[1]))


_MINE = "SELECT l_suppkey AS poi, CAST(greatest(1, floor(least(50, greatest(1, floor(avg(l_quantity)))) * 90 / 50)) AS BIGINT) AS own FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_custkey = 1 GROUP BY l_suppkey"
_PERSONAL = {**_GOLD, "mine": _MINE, "hit": "SELECT g.qid, g.pos AS tag_pos, t.poi, t.v, t.cell, coalesce(m.own, t.rating) AS rating FROM gold g JOIN tagged t ON t.tag = g.tag LEFT JOIN mine m ON m.poi = t.poi"}
_ebs("topk_personal", with_sql(_flat_sql(_top_sql("route")), _PERSONAL | _FULL | _routes_sql("cover", "route"), _SD), user=1)

_BATCH = {
    **_LOGGED, **_TAGGED, **_PERMS,
    "gold": "SELECT qid, pos, tag, v_q, CAST(NULL AS BIGINT) AS dest FROM logged",
    "hit": _GOLD["hit"], **_sets_sql("hit", "cover"), **_routes_sql("cover", "route"),
}
_BATCH_SQL = with_sql(_flat_sql(_top_sql("route")), _BATCH, sssp_sql("SELECT DISTINCT v_q AS s FROM logged UNION SELECT DISTINCT v FROM suppliers"))
register("topk_batch", _BATCH_SQL)(lambda s, d: (lambda x: flat(x.engine().run_batch(x.log())))(Data(s, d)))


@register("route_unfold", gold_sql("SELECT t.qid, t.rank, t.dist AS length, g.v_q AS first, h.v AS last FROM (" + _top_sql("route") + ") AS t JOIN (SELECT DISTINCT qid, v_q FROM gold) AS g ON g.qid = t.qid JOIN (SELECT DISTINCT poi, v FROM hit) AS h ON h.poi = t.pois[4]", _FULL | _routes_sql("cover", "route")))
def unfolded(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Routes vertex by vertex: where they start and end, and the length of their edges; a step that is no edge would leave its route short."""
    x = Data(spark, sf_dir)
    paths = x.engine().unfold(x.engine().run_batch(x.gold()), x.gold())
    steps = paths.select("qid", "rank", F.explode(F.arrays_zip(F.slice("path", F.lit(1), F.size("path") - 1).alias("u"), F.slice("path", F.lit(2), F.size("path") - 1).alias("v"))).alias("step")).select("qid", "rank", "step.u", "step.v")
    length = steps.join(x.arcs.groupBy("u", "v").agg(F.min("w").alias("w")), ["u", "v"]).groupBy("qid", "rank").agg(F.sum("w").alias("length"))
    ends = paths.select("qid", "rank", F.element_at("path", 1).alias("first"), F.element_at("path", -1).alias("last"))
    return ends.join(length, ["qid", "rank"], "left").select("qid", F.col("rank").cast("long").alias("rank"), F.coalesce("length", F.lit(0).cast("long")).alias("length"), "first", "last")


# ------------------------------------------------------------------ baselines

_ebs("base_exhaustive", _answers_sql(), "exhaustive")
_ebs("base_progressive", _answers_sql(fixed=True), "progressive", order=True)
_ebs("base_dominance", _IDENTICAL_ORDERS, "dominance", ratings="identical", route_scope="all_orders")
_ebs("base_dominance_fixed", _IDENTICAL_FIXED, "dominance", ratings="identical", order=True)
_ebs("base_ordered_pref", gold_sql(_flat_sql(_top_sql("route", per_set=False)), _FULL | _routes_sql("cover", "route", True, True)), "ordered_pref", dest=True, order=True)
_ebs("base_ordered_pref_nodest", _answers_sql(fixed=True, per_set=False), "ordered_pref", order=True)
_ebs("base_ordered_astar", with_sql(_flat_sql(_top_sql("route", per_set=False)), _SAME | _FULL | _routes_sql("cover", "route", True, True), _SD), "ordered_astar", dest=True, order=True, ratings="identical")
_ebs("base_budget_labels", gold_sql(_flat_sql(_top_sql("route", k=1, budget=900)), _FULL | _routes_sql("cover", "route", True)), "budget_labels", dest=True, budget=900)
_ebs("base_budget_labels_nodest", _answers_sql(k=1, budget=900), "budget_labels", budget=900)
_ebs("base_budget_labels_fixed", _answers_sql(k=1, budget=900, fixed=True), "budget_labels", budget=900, order=True)


def _greedy_sql(key: str) -> dict[str, str]:
    """greedy(qid, score, dist, rating, pois): hop by hop the least POI by a key of (dist, rating), its tag and number, among the tags still open."""
    parts = {"at0": "SELECT DISTINCT qid, v_q AS at, CAST(0 AS BIGINT) AS dist, CAST(0 AS BIGINT) AS rating, CAST([] AS BIGINT[]) AS pois, CAST([] AS BIGINT[]) AS taken FROM gold"}
    for i in range(4):
        parts[f"at{i + 1}"] = f"""SELECT qid, to_v AS at, dist + hop_dist AS dist, CAST(rating + hop_rating AS BIGINT) AS rating, list_append(pois, poi) AS pois, list_append(taken, tag_pos) AS taken FROM (
          SELECT a.*, h.v AS to_v, h.poi, CAST(h.tag_pos AS BIGINT) AS tag_pos, h.rating AS hop_rating, s.dist AS hop_dist, row_number() OVER (PARTITION BY a.qid ORDER BY {key}, h.tag_pos, h.poi) AS r
          FROM at{i} a JOIN hit h ON h.qid = a.qid AND NOT list_contains(a.taken, h.tag_pos) JOIN sd s ON s.s = a.at AND s.v = h.v) AS z WHERE r = 1"""
    return parts | {"greedy": f"SELECT qid, {_score_sql(0.6)} AS score, dist, rating, pois FROM at4"}


_NEAREST, _BEST_RATED = "s.dist, -h.rating", "-h.rating, s.dist"
for _name, _key in (("greedy_nearest", _NEAREST), ("greedy_rating", _BEST_RATED)):
    _ebs(f"base_{_name}", gold_sql("SELECT qid, CAST(1 AS BIGINT) AS rank, score, dist, rating, array_to_string(pois, '-') AS pois FROM greedy", _greedy_sql(_key)), _name)

from . import registry_more, registry_tools  # noqa: E402, F401
