"""A corpus pipeline of five stages over `documents`; each stage's result is written and read again as the next one's input.

toxicity: documents that weak supervision scores as toxic go.
near_duplicates: of each group of near copies one row with the least id stays.
decontamination: documents with a passage of the benchmark go.
secrets: the spans of secrets are masked in the texts.
pieces: texts are segmented into sampled pieces, with digests of them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tagroute.llm import decontam_sa, piece_sampling, secret_ownership, shingle_join, toxicity_ws
from tagroute.llm.textblocks import materialize

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _carried(docs: DataFrame) -> DataFrame:
    """The rows with `_row`: all but the text, and whether that is null."""
    return docs.withColumn("_row", F.struct(*(c for c in COLUMNS if c != "text"), F.isnull("text").alias("no_text")))


def _restored(found: DataFrame, row: str) -> DataFrame:
    return found.select(*(F.when(~F.col(f"{row}.no_text"), F.col("text")).alias("text") if c == "text" else F.col(f"{row}.{c}").alias(c) for c in COLUMNS))


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    docs = docs.select(*COLUMNS)
    model = toxicity_ws.train(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return toxicity_ws.score(docs, model, keep=True).filter("toxic_score < 0.5").select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows without words, and rows with a null id, are in no group. Rows are told apart by id and text (a 64-bit hash of it): one row of each group stays."""
    docs = docs.select(*COLUMNS)
    keyed = docs.withColumn("_text", F.xxhash64("text"))
    key = F.when(F.col("doc_id").isNotNull(), F.struct(F.col("doc_id").alias("doc"), F.col("_text").alias("hash")))
    found = shingle_join.shingle_components(keyed.select(key.alias("_key"), "text"), id_col="_key")
    of = (F.col("id.doc").alias("doc_id"), F.col("id.hash").alias("_text"))
    out = keyed.join(found.filter("id <> component_id").select(*of).distinct(), ["doc_id", "_text"], "left_anti")
    twice = found.filter("id is not null").groupBy("id").count().filter("count > 1").select(*of)
    once = out.join(twice, ["doc_id", "_text"], "left_anti").unionByName(out.join(twice, ["doc_id", "_text"], "left_semi").dropDuplicates(["doc_id", "_text"]))
    return once.select(*COLUMNS)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    found = decontam_sa.contamination(_carried(docs), spark.read.parquet(f"{sf_dir}/benchmark.parquet"), id_col="_row")
    return _restored(found.filter("not contaminated"), "id")


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    found = secret_ownership.scan(_carried(docs), id_col="_row", keep_text=True)
    masked = secret_ownership.redact(F.col("text"), F.col("spans"))
    return _restored(found.withColumn("text", masked), "id").withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.lit(0).cast("long")))


def pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return piece_sampling.round_trip(docs, piece_sampling.default_model()).withColumnRenamed("id", "doc_id")


STAGES = [("toxicity", toxicity), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("secrets", secrets), ("pieces", pieces)]

#: Classifiers and sampling are beyond SQL; a test holds the whole run against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialize(docs, name)
    return docs
