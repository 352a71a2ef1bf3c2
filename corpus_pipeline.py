"""Corpus pipeline: quality rules, line dedup, near dedup, mixing, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet
and read again as the next one's `docs`. All but the last return the columns of `documents`.

* quality: documents that the rules reject go; the model is fitted on `labels` and the
  documents they belong to.
* lines: repeated lines go; a document of which nothing is left goes too.
* near: one document of each group of near duplicates stays.
* mixing: the mixture is drawn, at most `EPOCHS` times each document, up to `SHARE` of the tokens
  that arrive.
* packing: what is drawn is laid out in bins of tokens.

Defined results, for every stage and so for the whole: columns beyond those of `documents`,
whatever their names, are left out. Null and blank texts are rejected by the first stage, and
would be kept by the others, with no token to draw or pack. Null languages and sources are
leaves of the mixture of their own; a null doc_id orders before all others. Repeated rows are
one document read twice: the quality stage keeps or rejects both, line dedup gives both the
same lines, near dedup keeps one of them. Ties go to the lower doc_id, then to the text's
fingerprint. Texts of any length are taken whole; a document longer than what the mixture may
spend on its leaf is not drawn. Without labelled documents of both classes nothing but blank
texts is rejected. Empty tables give an empty result at every stage.

Line dedup comes before near dedup, so copies that differ in a few lines have already lost
the lines they share when they are compared: near dedup then sees what is left of them, which
may be no copy of anything. That is why it catches fewer of the near copies than op9 does on
the documents as they are.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockwright.functions.scratch import cut
from blockwright.llm import line_dedup, mixing, near_dedup, packing, quality_rules

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
SHARE = 0.9
EPOCHS = 2


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return quality_rules.keep_good(docs.select(COLUMNS), quality_rules.fit(docs, labels))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = line_dedup.dedup_lines(docs.select(COLUMNS))
    return out.where((F.col("n_lines_removed") == 0) | F.col("text").rlike(r"\S")).select(COLUMNS)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dedup.keep_one(docs.select(COLUMNS)).select(COLUMNS)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs.select(COLUMNS), budget_share=SHARE, max_epochs=EPOCHS).select(COLUMNS)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs.select(COLUMNS))


STAGES = [("quality", quality), ("lines", lines), ("near", near), ("mixing", mixture), ("packing", packed)]

#: Model fitting, exact near-duplicate components and packing rounds are beyond SQL; tests/llm compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = cut(docs, name)
    return docs
