"""A corpus pipeline of five stages: low quality goes, boilerplate lines go, one document of each near-duplicate class
stays, documents with benchmark items go, and what is left is encoded.

Each stage takes (spark, docs, sf_dir) and gets all rows that the stage before it kept, read back from Parquet. All
but the last return the columns of documents, and further columns of theirs, whatever their names. Documents whose text
a stage has emptied stay and are judged as empty. An empty table gives an empty table in every stage; texts of any
length are taken whole; what a stage does with nulls, ties and repeated rows its docstring says.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from writelite.llm import bpe, decontam, lines, ngram_join, quality
from writelite.llm.common import shared_dir, sweep, written


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose score reaches the threshold; rules are learnt from the labels of documents that are still there.

    A null text scores as an empty one, a null key is scored by its text, equal texts share a fate, repeated rows stay
    or go together. Without labels every score is 0.5 and all rows stay.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return quality.score(docs, quality.fit(docs, labels)).where(F.col("__score") >= quality.THRESHOLD).select(*docs.columns)


def drop_boilerplate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that a large share of their source has; n_chars follows the text.

    No row goes. A null text stays null; rows without a source are a source of their own; copies of a text count as one
    page of it, and are cleaned alike.
    """
    cleaned = lines.clean(docs)
    return cleaned.withColumn("n_chars", F.when(F.col("n_dropped") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*docs.columns)


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of least id of each near-duplicate class.

    Null and empty texts are a class each and stay; rows with a null id all stay; of repeated rows of an id one stays.
    """
    return ngram_join.keep_one(docs)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item within its edit budget.

    Null and empty texts hold none and stay; rows with a null id are judged by their text; repeated rows go or stay
    together. An empty benchmark takes nothing away.
    """
    return decontam.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of every document that is left, one row a row.

    A null text has no tokens; null and repeated ids keep their rows.
    """
    return bpe.report(docs)


STAGES = [
    ("quality_classifier", keep_quality),
    ("line_dedup", drop_boilerplate),
    ("ngram_jaccard_join", keep_one_of_each),
    ("benchmark_decontamination", drop_benchmark),
    ("byte_bpe", encode),
]

#: SQL cannot fit the rules or run the merges; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written in the shared folder and read by the next stage.

    What a stage has written besides goes as soon as its result is there, and a stage's result once the next one has
    read it; the last one stays.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    top, last = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}", []
    for name, stage in STAGES:
        others = written()
        stage(spark, docs, sf_dir).write.parquet(f"{top}/{name}")
        docs = spark.read.parquet(f"{top}/{name}")
        sweep(spark, [*last, *(written() - others)])
        last = [f"{top}/{name}"]
    return docs
