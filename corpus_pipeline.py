"""The cleaning pipeline: STAGES in order, each reading what the one before wrote.

toxicity drops documents predicted toxic; line dedup rewrites texts and drops documents of which nothing but
earlier lines remains; near-dedup keeps one document of each group (five words, similarity 0.8);
decontamination drops documents by the rule of op3; packing returns the pieces of what is left.

Every stage but the last returns the columns of documents, whatever their names; only doc_id (an integer), text, lang
and n_chars have a meaning, and n_chars is counted again where a text was rewritten.  Null or empty texts pass all
filters and are packed as their closing id.  Null doc_ids are never toxic by label, come last in line dedup and are not
linked in near-dedup.  Repeated rows (one doc_id and one text) are one document to line dedup and near-dedup: all of them stay
or go together.  Empty tables give an empty result; without labels no text is toxic.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from skipsketch.llm import decontaminate, line_dedup, near_dedup, packing, toxicity
from skipsketch.llm.common import stored, table
from skipsketch.llm.queries import tokenizer_path


def own(docs: DataFrame) -> list[Column]:
    """Its columns by their exact names, which may hold dots."""
    return [F.col(f"`{c}`") for c in docs.columns]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.scored(docs, table(spark, sf_dir, "labels")).where("predicted = 0").select(*own(docs))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_dedup.dedup_lines(docs).where("kept").withColumn("n_chars", F.length("text").cast("long")).select(*own(docs))


def drop_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    gone = near_dedup.near_duplicates(docs, k=5, percent=80).where("not kept").select("doc_id").distinct()
    gone = gone.withColumnRenamed("doc_id", "__gone")
    return docs.join(gone, docs["doc_id"] == F.col("__gone"), "left_anti").select(*own(docs))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark")).select(*own(docs))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.packed(docs, packing.definition_of(tokenizer_path()))


STAGES = [("toxicity", drop_toxic), ("line_dedup", drop_lines), ("near_dedup", drop_near), ("decontamination", drop_contaminated), ("packing", pack)]

#: Training, tokenizing and packing cannot be written in SQL; tests/llm holds brute-force versions of the stages after training.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = stored(docs, name)
    return docs
