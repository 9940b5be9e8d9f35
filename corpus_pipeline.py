"""A corpus pipeline: toxic documents go, one document of each near-duplicate group stays, documents that hold
benchmark templates go, the rest is packed.  Each stage is written as Parquet and read again by the next."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binlens.llm import decontaminate, jaccard_join, packing, toxicity
from binlens.llm.common import settle, shared_dir
from binlens.llm.queries import tokenizer

#: Ids that a filtering join may broadcast; beyond it the join shuffles.
BROADCAST_IDS = 1_000_000


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that the model rejects go.  It is fitted on this stage's own documents that carry labels; with none, or of one
    class only, nothing goes.  Rows are judged by their text alone, so null ids, repeated rows and further columns are
    kept as they are; null and empty texts stay; an empty table stays empty."""
    return toxicity.keep_clean(docs, toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each component the row with the smallest doc_id stays, null being the largest; rows that link with nothing
    stay, whatever their ids.  Rows are told apart by a key of their own, as ids may be null or repeat."""
    key = f"row_{uuid.uuid4().hex}"
    rows = settle(docs.withColumn(key, F.monotonically_increasing_id()), "rows")
    classes = settle(jaccard_join.jaccard_components(rows, key), "classes").select(F.col("doc_id").alias(key), "component_id")
    order = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", F.col(key).alias("row"))
    stay = classes.join(rows.select(key, "doc_id"), key).groupBy("component_id").agg(F.min(order)["row"].alias(key)).select(key)
    gone = settle(classes.select(key).join(stay, key, "left_anti"), "gone")
    if gone.count() <= BROADCAST_IDS:
        gone = F.broadcast(gone)
    return rows.join(gone, key, "left_anti").select(*docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows that hold a benchmark item's template go, judged by their text alone: null and empty texts and those with null
    ids stay, repeated rows go or stay alike, and without benchmark items nothing goes."""
    return decontaminate.keep_clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of every row: null and empty texts give one piece, the end id; null ids are kept; repeated rows are packed
    each for itself; an empty table gives no pieces."""
    return packing.pack(docs, tokenizer("word_bpe_49k.json"))


STAGES = [("toxicity", drop_toxic), ("jaccard_join", drop_near_copies), ("decontamination", drop_contaminated), ("packing", pack)]

#: Tokenizing and fitting aren't expressible in SQL; tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = f"{shared_dir(spark)}/pipeline-{name}-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
