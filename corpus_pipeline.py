"""Corpus pipeline: language identification, near-duplicates, personal data, source mixing, tokens.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; :func:`run` writes it as Parquet in the shared folder and reads it
back as the next stage's documents. All stages but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gnnspark.llm import bpe, langid, mixing, neardup, pii
from gnnspark.llm.registry import table, tokenizer_path
from gnnspark.llm.state import remove, run_dir

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with a letter stay, others and null go; a null lang becomes the network's, and stays null if no label could be learned.

    Repeated rows and ids are judged row by row; long texts are read in whole; further columns pass; an empty table stays empty.
    """
    read = docs.where(F.col("text").rlike(r"\p{L}"))
    told = langid.identify(read, langid.train(read), keep=tuple(docs.columns), names=("__lang", "__score"))
    lang = F.coalesce("lang", F.when(F.col("__lang") != langid.UNKNOWN, F.col("__lang")))
    return told.withColumn("lang", lang).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of documents linked by a five-word Jaccard similarity of at least 0.8 the one with the least id stays.

    Candidates come from SimHash blocks, and from min-hash bands for pairs whose fingerprints are farther apart than blocks can meet; an exact check decides.
    Null text is empty text; texts without words are copies of each other; ties in the id go by text and columns; a repeated or null id loses no
    row whose text is not linked; further columns pass; an empty table stays empty.
    """
    return neardup.keep_one(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans with personal data are replaced by their kind; n_chars follows the text.

    No row goes: null text and its n_chars stay null; repeated rows change alike; long texts are searched in whole; further columns pass.
    """
    clean = pii.redact(docs, pii.train(docs))
    return clean.withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of the target mix: a row for each time that a document is taken.

    A null source is a source; texts without words and null ids are taken like others of their hash; equal ids of a source are taken alike;
    further columns pass; an empty table stays empty.
    """
    return mixing.take_mix(docs)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Per row: id, language, source, number of tokens, and digests of ids and of the decoded text.

    Null text is empty text with no tokens; each of repeated rows has a result; long texts are encoded in whole; further columns are not read.
    """
    return bpe.digests(docs, tokenizer_path(), keep=("doc_id", "lang", "source"))


STAGES = [
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("personal_data", personal_data),
    ("mixture", mixture),
    ("tokens", tokens),
]

#: Networks, fingerprints and merges are not SQL; tests compare each stage with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs, before = table(spark, sf_dir, "documents"), None
    folder = run_dir(spark, "pipeline")
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before:  # nothing reads a stage's input once its output is written
            remove(spark, before)
        before = f"{folder}/{name}"
    return docs
