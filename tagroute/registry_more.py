"""Measures, workloads, the agent, streams and relational operators, by name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import agent, index, measures, network, operators, streaming, workloads
from .query import tables
from .registry import _BATCH, _CLOSED, _LOGGED, _NEAREST, _OVERLAY, _TAGGED, ORACLE_SQL, Data, LOG_QUERIES, _greedy_sql, _top_sql, flat, register
from .sources import table
from .sql import sssp_sql, with_sql

_HIT = {**_LOGGED, **_TAGGED, "hit": "SELECT l.qid, l.pos AS tag_pos, t.poi, t.v, t.cell, t.rating FROM logged l JOIN tagged t ON t.tag = l.tag"}

register("m_search_space", with_sql("SELECT qid, CAST(round(exp(sum(ln(n)))) AS BIGINT) AS n_sets, CAST(round(exp(sum(ln(n)))) AS BIGINT) * 24 AS n_orders FROM (SELECT qid, tag_pos, count(*) AS n FROM hit GROUP BY qid, tag_pos) AS g GROUP BY qid HAVING count(*) = 4", _HIT))(lambda s, d: measures.search_space(tables.hits(Data(s, d).index, Data(s, d).log()), 4))
_STAGED = lambda s, d: (lambda x: measures.stages(x.engine().counters(x.log())))(Data(s, d))
register("m_cells", with_sql("SELECT qid, count(DISTINCT cell) AS cells_rn, true AS shrinks FROM hit GROUP BY qid", _HIT))(lambda s, d: _STAGED(s, d).filter("cells_rn > 0").select("qid", "cells_rn", ((F.col("cells_sr") <= F.col("cells_rn")) & (F.col("cells_bp") <= F.col("cells_rn"))).alias("shrinks")))
register("m_sets", with_sql("SELECT qid, CAST(round(exp(sum(ln(n)))) AS BIGINT) AS sets_rn, true AS shrinks FROM (SELECT qid, tag_pos, count(*) AS n FROM hit GROUP BY qid, tag_pos) AS g GROUP BY qid HAVING count(*) = 4", _HIT))(lambda s, d: _STAGED(s, d).filter("sets_rn > 0").select("qid", "sets_rn", ((F.col("sets_sr") <= F.col("sets_rn")) & (F.col("sets_bp") <= F.col("sets_rn"))).alias("shrinks")))
register("m_orders")(lambda s, d: _STAGED(s, d).select("qid", "orders_sr", "orders_evaluated", (F.col("orders_evaluated") <= F.col("sets_bp") * 24).alias("bounded")))
register("m_percent")(lambda s, d: measures.percentages(_STAGED(s, d)))
_BATCH_DISTANCES = sssp_sql("SELECT DISTINCT v_q AS s FROM logged UNION SELECT DISTINCT v FROM suppliers")
_BATCH_SQL = with_sql(f"SELECT CAST(count(*) AS BIGINT) AS routes, round(avg(dist), 4) AS dist, round(avg(rating), 4) AS rating, round(avg(score), 4) AS score FROM ({_top_sql('route')}) AS b", _BATCH, _BATCH_DISTANCES)
register("m_effectiveness", _BATCH_SQL)(lambda s, d: (lambda x: measures.effectiveness(x.engine().run_batch(x.log())))(Data(s, d)))
_GAP_SQL = with_sql(f"SELECT g.qid, round(max(t.score) - any_value(g.score), 6) AS gap, bool_or(list_sort(t.pois) = list_sort(g.pois)) AS hit FROM greedy g JOIN ({_top_sql('route')}) AS t ON t.qid = g.qid GROUP BY g.qid", {**_BATCH, **_greedy_sql(_NEAREST)}, _BATCH_DISTANCES)
register("m_gap", _GAP_SQL)(lambda s, d: (lambda x: measures.gap(x.engine().run_batch(x.log(), "greedy_nearest"), x.engine().run_batch(x.log())))(Data(s, d)))
register("m_index_bytes", with_sql("SELECT (SELECT count(*) FROM shorts) * 24 AS index_bytes, count(*) * count(*) * 8 AS all_pairs_bytes FROM cells", _OVERLAY, _CLOSED))(lambda s, d: (lambda x: measures.index_bytes(x.engine().index.shortcuts, x.cells))(Data(s, d)))


@register("m_scope", with_sql("""SELECT m, round(3.14 * pow((0.5 * m * 0.5 + 0.5 * diameter) / 0.5, 2) / z * 100, 6) AS omega_pct, round(3.14 * pow((0.5 * m * 0.5 + diameter) / 0.5, 2) / z * 100, 6) AS printed_pct
  FROM (SELECT m, z, sqrt(z) * 2 * pow(4.0, 1.0 / m) / sqrt(3.14 * n_p) AS diameter FROM (SELECT 3 AS m UNION ALL SELECT 4 UNION ALL SELECT 5) AS g, (SELECT 100.0 * n AS z FROM dims) AS d, (SELECT 1000.0 * count(*) / count(DISTINCT s_nationkey) AS n_p FROM supplier) AS p) AS h"""))  # fmt: skip
def scope(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Predicted share of the region for 3 to 5 tags: on the lattice's area, with the suppliers a nation and a thousand places."""
    area = Data(spark, sf_dir).n.select((F.lit(100.0) * F.col("n")).alias("z"))
    given = area.crossJoin(table(spark, sf_dir, "supplier").agg((F.lit(1000.0) * F.count("*") / F.count_distinct("s_nationkey")).alias("n_p")))  # one row
    out = None
    for m in (3, 4, 5):
        a, p = measures.scope_estimate(F.col("z"), m, 4, F.col("n_p"), 0.5, 0.5)
        row = given.select(F.lit(m).alias("m"), F.round(a * 100, 6).alias("omega_pct"), F.round(p * 100, 6).alias("printed_pct"))
        out = row if out is None else out.unionByName(row)
    return out


@register("m_cost_model")
def cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cost formula with measured shares, beside the work counted."""
    x = Data(spark, sf_dir)
    staged = _STAGED(spark, sf_dir).filter("sets_rn > 0")
    size = x.vertices.agg(F.count("*").alias("n_v")).crossJoin(x.edges.agg(F.count("*").alias("n_e")))
    at = staged.crossJoin(F.broadcast(size)).withColumn("n_p", F.pow(F.col("sets_rn"), 0.25))
    omega, beta, gamma = F.col("cells_sr") / F.col("cells_rn"), F.col("sets_bp") / F.greatest(F.lit(1), F.col("sets_sr")), F.col("orders_evaluated") / F.greatest(F.lit(1), F.col("sets_bp") * 24)
    return at.select("qid", F.round(measures.cost_model(F.col("n_v"), F.col("n_e"), omega, beta, F.col("n_p"), gamma, 4), 2).alias("predicted"), "settled", "orders_evaluated")


# ------------------------------------------------------------------ workloads


def _with_dest(x: Data):
    def log(m: int, k: int, alpha: float, dest: bool) -> DataFrame:
        q = x.log(m, k, alpha)
        return q.crossJoin(F.broadcast(x.n)).withColumn("dest", (F.col("v_q") + F.floor(F.col("n") / 2)) % F.col("n")).drop("n") if dest else q

    return log


register("w_pruning_table")(lambda s, d: (lambda x: workloads.pruning_table(x.engine(), x.log))(Data(s, d)))
register("w_query_time")(lambda s, d: (lambda x: workloads.query_time(x.engine(), x.log))(Data(s, d)))
register("w_ablation")(lambda s, d: (lambda x: workloads.ablation(x.engine(), x.log))(Data(s, d)))
for _name in workloads.COMPARISONS:
    register(f"w_{_name}")(lambda s, d, n=_name: (lambda x: workloads.comparison(x.engine(), _with_dest(x), n))(Data(s, d)))
register("w_budget")(lambda s, d: (lambda x: workloads.budget(x.engine(), x.log))(Data(s, d)))
register("w_effectiveness")(lambda s, d: (lambda x: workloads.effectiveness(x.engine(), x.log))(Data(s, d)))


@register("w_model_vs_agent")
def model_vs_agent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two routes of each of the log's queries on the lattice's first 22 rows, starts folded into them."""
    x = Data(spark, sf_dir)
    small = workloads.small_network(x.engine())
    size = small.index.vertices.agg(F.count("*").alias("size"))  # one row
    folded = x.log(4, 2).crossJoin(F.broadcast(size)).withColumn("v_q", F.col("v_q") % F.col("size")).drop("size")
    return workloads.model_vs_agent(small, index.materialize(folded, "asked"))


register("w_remaining")(lambda s, d: (lambda x: workloads.remaining({"supplier": (x.engine(), x.log()), "part": (x.engine("part"), _brand_log(x))}))(Data(s, d)))
register("w_dense_layer")(lambda s, d: (lambda x: flat(x.engine("part").run_batch(_brand_log(x))))(Data(s, d)))


def _brand_log(x: Data) -> DataFrame:
    """The log over the medium layer: three brands each."""
    brands = network.pois_part(x.spark, x.dir).select("tag").distinct().orderBy("tag")
    names = [r[0] for r in brands.collect()]  # 25 brands
    keyed = x.spark.createDataFrame(list(enumerate(names)), "key long, tag string")
    from .query.spec import query_log

    return query_log(table(x.spark, x.dir, "events").select("event_id", "user_id").filter(F.col("event_id") < LOG_QUERIES), x.n, keyed, 3, 4, 0.6)


# ------------------------------------------------------------------ agent

_WORDS = "[^a-zäöüßéèêçñáíó]+"
_VOCABULARY = {"vocabulary": f"SELECT word, row_number() OVER (ORDER BY c DESC, word) - 1 AS key FROM (SELECT word, count(*) AS c FROM (SELECT unnest(regexp_split_to_array(lower(text), '{_WORDS}')) AS word FROM documents) AS w WHERE length(word) >= 6 GROUP BY word ORDER BY c DESC, word LIMIT 25) AS t"}
register("agent_tags", "SELECT DISTINCT n_name AS tag FROM supplier JOIN nation ON n_nationkey = s_nationkey")(lambda s, d: agent.tags(Data(s, d).index))
register("agent_extract", with_sql(f"SELECT conv_id, string_agg(CAST(key AS VARCHAR), ',' ORDER BY key) AS keys FROM (SELECT DISTINCT conv_id, key FROM (SELECT conv_id, unnest(regexp_split_to_array(lower(text), '{_WORDS}')) AS said FROM conversations WHERE role = 'user') AS s JOIN vocabulary ON word = said) AS k GROUP BY conv_id", _VOCABULARY))(lambda s, d: agent.extract(table(s, d, "conversations"), agent.vocabulary(table(s, d, "documents"))).select("conv_id", F.array_join(F.transform("keys", lambda k: k.cast("string")), ",").alias("keys")))


@register("agent_routes")
def agent_routes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations that name tags, their queries, and a sentence for each route."""
    x = Data(spark, sf_dir)
    words = agent.vocabulary(table(spark, sf_dir, "documents"))
    found = agent.extract(table(spark, sf_dir, "conversations"), words)
    return agent.render(x.engine().run(agent.queries(found, x.nations, x.n.first()[0])))


# ------------------------------------------------------------------ relational operators

register("net_components", with_sql("SELECT v, min(v) OVER () AS root FROM vertices"))(lambda s, d: operators.connected(Data(s, d).edges))
register("rollup_pois", with_sql("SELECT r_name, n_name, count(*) AS n, round(avg(rating), 6) AS rating FROM suppliers JOIN nation ON n_name = tag JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)"))(lambda s, d: operators.rollup_pois(Data(s, d).pois, table(s, d, "nation"), table(s, d, "region")))
register("cube_pois", with_sql("SELECT tag, floor(v / 500) AS zone, count(*) AS n, CAST(sum(rating) AS BIGINT) AS rating FROM customers GROUP BY CUBE (tag, floor(v / 500))"))(lambda s, d: network.pois_customer(s, d).withColumn("zone", F.floor(F.col("v") / 500).cast("double")).cube("tag", "zone").agg(F.count("*").alias("n"), F.sum("rating").alias("rating")))
register("pivot_pois", with_sql("SELECT floor(v / 500) AS zone, count(*) FILTER (tag = 'BUILDING') AS building, count(*) FILTER (tag = 'MACHINERY') AS machinery FROM customers GROUP BY floor(v / 500)"))(lambda s, d: network.pois_customer(s, d).withColumn("zone", F.floor(F.col("v") / 500).cast("double")).groupBy("zone").pivot("tag", ["BUILDING", "MACHINERY"]).agg(F.count("poi")).select("zone", F.coalesce("BUILDING", F.lit(0)).alias("building"), F.coalesce("MACHINERY", F.lit(0)).alias("machinery")))
register("asof_rating", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, side, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS rated FROM (SELECT *, CASE WHEN event_type = 'purchase' THEN 0 ELSE 1 END AS side FROM events) AS e QUALIFY event_type = 'view'")(lambda s, d: (lambda e: operators.asof_join(e.filter("event_type = 'view'").select("user_id", "ts", "event_id"), e.filter("event_type = 'purchase'").select("user_id", "ts", F.col("value").alias("rated")), "user_id", "ts", "rated").select("event_id", "rated"))(table(s, d, "events")))
register("interval_events", "SELECT a.event_id AS viewed, b.event_id AS bought FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'view' AND b.event_type = 'purchase'")(lambda s, d: (lambda e: operators.interval_join(e.filter("event_type = 'view'").select("user_id", F.col("ts").alias("t1"), F.col("event_id").alias("viewed")), e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("t2"), F.col("event_id").alias("bought")), "user_id", "t1", "t2", 6 * 3600).select("viewed", "bought"))(table(s, d, "events")))

# ------------------------------------------------------------------ streams

register("stream_tumbling", "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, count(*) AS n, round(avg(value), 6) AS mean_value FROM events GROUP BY date_trunc('day', ts), event_type")(lambda s, d: streaming.drain(streaming.tumbling(streaming.events(s, d))))
register("stream_session", "SELECT user_id, min(ts) AS start, count(*) AS n, string_agg(DISTINCT event_type, '|' ORDER BY event_type) AS tags FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events) AS f) AS g GROUP BY user_id, k")(lambda s, d: streaming.drain(streaming.sessions(streaming.events(s, d))))
register("stream_profiles", "SELECT user_id, event_type, count(*) AS n, round(avg(value), 6) AS mean_value FROM events GROUP BY user_id, event_type")(lambda s, d: streaming.drain(streaming.profiles(streaming.events(s, d)), "update").groupBy("user_id", "event_type").agg(F.max("n").alias("n"), F.round(F.max_by("mean_value", "n"), 6).alias("mean_value")))
register("stream_dedup", "SELECT event_type, count(*) AS n FROM events GROUP BY event_type")(lambda s, d: streaming.drain(streaming.deduplicated(streaming.events(s, d)).select("event_id", "event_type"), "append").groupBy("event_type").agg(F.count("*").alias("n")))


@register("stream_routes", ORACLE_SQL["topk_batch"])
def stream_routes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries of the log as a stream of files, answered by micro-batch."""
    import uuid

    from .plans.rounds import shared_dir

    x = Data(spark, sf_dir)
    base = f"{shared_dir(spark).rstrip('/')}/routes-{uuid.uuid4().hex}"
    q = x.log()
    q.write.parquet(f"{base}/queries")
    streaming.routes(spark.readStream.schema(q.schema).parquet(f"{base}/queries"), x.engine(), f"{base}/answers").awaitTermination()
    return flat(spark.read.schema("qid long, rank int, score double, dist long, rating long, pois array<long>").parquet(f"{base}/answers"))


