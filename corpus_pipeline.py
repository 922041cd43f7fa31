"""The corpus pipeline: named stages over documents, each written as Parquet and read again by the next.

language    documents without a letter (or text), and those whose language the classifier can't tell, go
near        one document of each group of near duplicates (5-word shingles, Jaccard 0.8) stays, that with the smallest id
repeats     words in a 20-word sequence that starts earlier go from the text
benchmark   documents that hold a benchmark item go
encode      the text that is left as token ids, with digests; documents without tokens stay with none

Ties and repeated rows: of rows that share the smallest id of a group the first by text stays; rows without an id are kept unless their
text's group has a row with one. Leaks are judged row by row, so a row without an id goes if it holds an item, and rows that share an id don't go for each
other. Null texts go in the first stage. Empty tables stay empty. Extra columns pass through all stages but the last.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fixflow.llm import bpe, decontam, jaccard, langid, substring
from fixflow.llm.common import new_path, table
from fixflow.llm.exchange import text_key

LEAST_SURE = 0.5
ORACLE_SQL = None


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = langid.learn(docs)
    if not model[0]:  # nothing is labelled, so there is no language to tell
        return docs.where(F.col("text").rlike(r"\p{L}"))
    told = langid.predict(docs, model, keep=docs.columns) if "lang_pred" not in docs.columns and "score" not in docs.columns else None
    if told is None:  # the names are taken: predict beside them
        free = docs.select(*[F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns)])
        told = langid.predict(free, model, text=f"c{docs.columns.index('text')}")
        kept = told.where((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SURE))
        return kept.select(*[F.col(f"c{k}").alias(c) for k, c in enumerate(docs.columns)])
    return told.where((F.col("lang_pred") != "und") & (F.col("score") >= LEAST_SURE)).select(*[F.col(f"`{c}`") for c in docs.columns])


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    found = jaccard.near_duplicates(docs, k=5, percent=80, with_key=True)
    alone = F.col("doc_id").isNull() & F.col("component_id").isNull()
    stays = found.where(alone | (F.col("component_id") == F.col("doc_id"))).select(F.col("doc_id").alias("__id"), F.col("key").alias("__key")).distinct()
    out = docs.join(stays, F.col("doc_id").eqNullSafe(F.col("__id")) & text_key("text").eqNullSafe(F.col("__key")), "left_semi")
    if docs.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").limit(1).isEmpty():
        return out
    first = Window.partitionBy("doc_id").orderBy(F.col("text").asc_nulls_last())
    return out.withColumn("__n", F.row_number().over(first)).where(F.col("doc_id").isNull() | (F.col("__n") == 1)).drop("__n")


def repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return substring.remove_repeats(docs, 20, with_text=True)


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    row = F.xxhash64("doc_id", "text")
    leaks = decontam.find_leaks(docs.select(row.alias("__row"), "text"), table(spark, sf_dir, "benchmark"), doc_id="__row")
    return docs.join(leaks.select(F.col("doc_id").alias("__row")).distinct(), row == F.col("__row"), "left_anti")


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.digests(docs, bpe.vocabulary())


STAGES = [("language", language), ("near", near), ("repeats", repeats), ("benchmark", benchmark), ("encode", encode)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = new_path(spark, name)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
