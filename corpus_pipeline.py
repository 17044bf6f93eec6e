"""Corpus pipeline: quality, near duplicates, personal data, source mix, packing. Each stage applies one operator to all
rows that the stage before kept; its result is written as Parquet and read again as the next one's documents.

The quality stage drops what the classifier holds for more likely bad than good (score under REJECT), which is more
lenient than the 0.7 of a plain prediction, so that clean documents stay. Of near duplicates the smallest id stays.
Personal data is replaced by its kind. The mix repeats and samples whole documents. The last stage returns the packed
pieces.

Every stage takes null and empty texts, texts of any length, repeated rows and an empty table, as its operator's
docstring states: a null text is empty (the classifier scores it, it is a class of its own among near duplicates, has no
personal data, and is not taken by the mix, which takes no document without words). Further columns keep their values,
whatever their names."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sidecar_ann.llm import mixing, neardup, packing, pii, quality
from sidecar_ann.llm.common import documents, stage

REJECT = 0.5


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    names = docs.columns
    vectors = quality.word_vectors(docs)
    network = quality.fit(docs, documents(spark, sf_dir, "labels"), vectors)
    name = "score"
    while name in names:
        name += "_"
    return quality.score(docs, network, vectors, name).filter(F.col(name) >= REJECT).select(*names)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return neardup.keep_one(docs)


def personal_data_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    done = pii.redact(docs)
    return done.withColumn("n_chars", F.char_length("text").cast("long")).select(*docs.columns) if "n_chars" in docs.columns else done


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.repeat_documents(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack_documents(docs)


STAGES = [
    ("quality", quality_stage),
    ("near_duplicates", near_duplicate_stage),
    ("personal_data", personal_data_stage),
    ("mixing", mixing_stage),
    ("packing", packing_stage),
]

#: SQL can express neither the classifier nor the tokenizer; tests compare each stage with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for name, apply in STAGES[:-1]:
        docs = stage(apply(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
