"""A corpus from raw documents to packed sequences, stage by stage.

Every stage works on all that its predecessor kept. Quality rules drop what the learned list or its
base rejects; of each group of near copies the smallest id stays; words of repeated passages go;
found secrets become a mark; the last stage returns the pieces of all documents with their places in
sequences. Stages but the last return the columns of ``documents``, with ``n_chars`` of the text as
it then is. Null and empty texts fail the quality base; an empty table stays empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from incwalk.llm import ngram_join, packing, quality, secrets, substring
from incwalk.llm.common import save, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _measured(docs: DataFrame) -> DataFrame:
    return docs.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    rules = quality.learn_list(docs, table(spark, sf_dir, "labels"))
    return quality.keep_good(docs.select(*COLUMNS), rules)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return ngram_join.keep_one_of_each(docs.select(*COLUMNS), size=5, num=80, den=100)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _measured(substring.substring_dedup(docs.select(*COLUMNS), window=50))


def secret_scans(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _measured(secrets.redact(docs.select(*COLUMNS)))


def sequence_packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return packing.pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"), room=4096, end_id=1)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("secret_scans", secret_scans),
    ("sequence_packing", sequence_packing),
]

#: SQL can express neither the learned list nor the tokenizer; tests compare with a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
