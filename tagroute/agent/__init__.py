"""Tools of a conversational agent: the list of tags, and a search; tags are taken from what users say by exact words."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query import Engine


def tags(index: DataFrame) -> DataFrame:
    return index.select("tag").distinct()


def vocabulary(documents: DataFrame, n: int = 25, least: int = 6) -> DataFrame:
    """(key, word): the n commonest words of at least so many letters, numbered by frequency."""
    words = documents.select(F.explode(F.split(F.lower("text"), "[^a-zäöüßéèêçñáíó]+")).alias("word")).filter(F.length("word") >= least).groupBy("word").agg(F.count("*").alias("c"))
    top = words.orderBy(F.desc("c"), "word").limit(n)
    from pyspark.sql import Window as W

    return top.select((F.row_number().over(W.orderBy(F.desc("c"), "word")) - 1).alias("key"), "word")  # n rows


def extract(conversations: DataFrame, words: DataFrame) -> DataFrame:
    """(conv_id, keys): words of the vocabulary that a conversation's users say, in order of the vocabulary."""
    said = conversations.filter("role = 'user'").select("conv_id", F.explode(F.split(F.lower("text"), "[^a-zäöüßéèêçñáíó]+")).alias("word"))
    found = said.join(F.broadcast(words), "word").select("conv_id", "key").distinct()  # the vocabulary has n rows
    return found.groupBy("conv_id").agg(F.array_sort(F.collect_list("key")).alias("keys"))


def queries(found: DataFrame, names: DataFrame, n: int, most: int = 4, k: int = 2, alpha: float = 0.6) -> DataFrame:
    """Queries of conversations: up to `most` tags, and a start by arithmetic on the conversation."""
    asked = found.select("conv_id", F.posexplode(F.slice("keys", 1, most)).alias("pos", "key")).join(F.broadcast(names), "key")
    return asked.groupBy("conv_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "tag"))), lambda x: x["tag"]).alias("tags")).select(
        F.col("conv_id").alias("qid"), ((F.col("conv_id") * 37) % n).alias("v_q"), "tags", F.lit(alpha).alias("alpha"), F.lit(k).alias("k"), F.lit(None).cast("long").alias("dest"), F.lit(None).cast("long").alias("budget")
    )


def search(engine: Engine, requests: DataFrame) -> DataFrame:
    """JSON in, JSON out: (id, request) -> (id, reply); a request has v_q, tags, and may have k and alpha."""
    asked = requests.select(F.col("id").alias("qid"), F.from_json("request", "v_q long, tags array<string>, k int, alpha double").alias("r"))
    q = asked.select("qid", "r.v_q", "r.tags", F.coalesce("r.alpha", F.lit(0.6)).alias("alpha"), F.coalesce("r.k", F.lit(4)).alias("k"), F.lit(None).cast("long").alias("dest"), F.lit(None).cast("long").alias("budget"))
    routes = engine.run_batch(q).groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("rank", "score", "dist", "rating", "pois"))).alias("routes"))
    return asked.select("qid").join(routes, "qid", "left").select(F.col("qid").alias("id"), F.to_json(F.struct(F.coalesce("routes", F.array().cast("array<struct<rank:int,score:double,dist:bigint,rating:bigint,pois:array<bigint>>>")).alias("routes"))).alias("reply"))


def render(answers: DataFrame) -> DataFrame:
    """(qid, rank, line): a sentence for each route."""
    return answers.select("qid", "rank", F.format_string("Route %d goes to %s, %d long, ratings %d.", "rank", F.array_join(F.transform("pois", lambda p: p.cast("string")), ", then "), "dist", "rating").alias("line"))
