"""A corpus pipeline over ``documents``: five operators of flowregions.llm one after another.

Each stage takes (spark, docs, sf_dir); its result is written as Parquet and read again as the next
stage's docs. All but the last return the columns of documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from flowregions.llm import bpe, line_dedup, mixture, quality, set_join
from flowregions.llm.common import cut, read, shared_dir, table
from flowregions.llm.queries import tokenizer

#: Numbers of near duplicates up to this many are broadcast (8 bytes each); beyond, they are joined by shuffle.
BROADCAST_IDS = 1_000_000


def whole(docs: DataFrame, *columns: str) -> DataFrame:
    """All columns of ``docs`` as one struct ``row``, beside the ones an operator reads: no name can clash with its results."""
    return docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), *[docs[c] for c in columns])


def good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts. Rows are judged one by one, by their texts: null and empty texts, repeated rows and rows without an id like all others."""
    model = quality.train(docs, read(spark, sf_dir, "labels"))
    rows = quality.scores(whole(docs, "text"), model, text_col="text", keep=("row",))
    return rows.filter(F.col("score") >= quality.THRESHOLD).select("row.*")


def without_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later repeats of three lines in a row, or of one or two lines with 50 words or more, are deleted; a document that loses all its lines goes. n_chars is counted anew where the text changed.

    Null and empty texts and rows without an id stay as they are; rows with one id count as one document.
    """
    rows = line_dedup.deduplicate(whole(docs, "doc_id", "text"), words=line_dedup.WORDS)
    changed = F.col("n_removed") > 0
    rows = rows.filter(~changed | (F.trim(F.translate("text", "\n\r\t", "   ")) != ""))
    new = {"text": F.col("text"), "n_chars": F.when(changed, F.length("text").cast("long")).otherwise(F.col("row")["n_chars"])}
    return rows.select(*[new.get(c, F.col("row")[c]).alias(c) for c in docs.columns])


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates one row stays: the one with the smallest id, rows without an id last.

    Rows are told apart by a number of their own, given as they are written, so rows with one id and different
    texts, repeated rows and rows without an id are all decided by their texts. Texts without words are in no group.
    """
    rows = table(whole(docs, "doc_id", "text").withColumn("number", F.monotonically_increasing_id()))
    found = cut(set_join.near_duplicates(rows, "number"))
    groups = found.filter("number != component_id").select("component_id").distinct()
    inside = found.join(groups, "component_id", "left_semi").join(rows.select("number", "doc_id"), "number").select("component_id", "number", "doc_id")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "number"))
    kept = inside.groupBy("component_id").agg(first.alias("first")).select(F.col("first.number").alias("number"))
    gone = cut(inside.join(kept, "number", "left_anti").select("number"))
    if gone.count() <= BROADCAST_IDS:
        gone = F.broadcast(gone)
    return rows.join(gone, "number", "left_anti").select("row.*")


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix of sources takes it; texts without words never, rows with one id or none alike."""
    return mixture.mix(docs)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens and the digests of ids and of the decoded text, of every row; null texts as empty ones."""
    return bpe.round_trip(docs, tokenizer())


STAGES = [("quality", good), ("line dedup", without_repeated_lines), ("near duplicates", one_of_each_group), ("mixture", mixed), ("bpe", encoded)]

#: The classifier and the tokenizer are beyond SQL; the stages are tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        path = f"{shared_dir(spark)}/stage-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
