"""A corpus pipeline in five stages, each one an operator of ``tideline.llm``.

Every stage takes what the one before it kept and returns the columns of documents; the last returns packed pieces.
Nulls, empties and repeats are as each operator's module says; in short: a text that is null or has no letter leaves in the
first stage, repeated rows shrink to one in the second, texts that lose all their words leave in the third.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tideline.llm import langid, mixing, packing, simhash, substring
from tideline.sources.tables import shared_dir, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def _small_batches(spark: SparkSession) -> None:
    """Whole texts in Arrow batches of 2,000 rows at the most: a batch stands in the JVM and in the worker, once for each task."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(key)) not in range(1, 2001):
        spark.conf.set(key, "2000")


def identify_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sets ``lang`` to the predicted language; a document without any letter, hence without a language, goes.

    Where no row has a language to learn from, nothing is predicted: documents with a letter stay as they are.
    """
    _small_batches(spark)
    model = langid.train(docs.where(~langid.held_out()))
    if not model:
        return docs.where(F.col("text").rlike(r"\p{L}")).select(*COLUMNS)
    found = langid.predict(docs.select(*COLUMNS), model)
    return found.where(F.col("lang_pred") != langid.UNKNOWN).withColumn("lang", F.col("lang_pred")).select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of each group of near-duplicates.

    SimHash comes first: of documents that fingerprints within two bits link, the first stays. Among what it keeps, groups of texts that share
    4/5 and more of their 5-word shingles, whose fingerprints may be further apart, shrink to their first document too.
    """
    _small_batches(spark)
    return simhash.keep_similar(simhash.keep_one(docs.select(*COLUMNS))).select(*COLUMNS)


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts passages of 50 words and more that an earlier document has; a document with nothing left goes."""
    _small_batches(spark)
    found = substring.remove_repeats(docs, carry=["lang", "source", "n_chars"]).where("n_removed = 0 or n_removed < n_words")
    lost = F.col("n_removed") > 0
    text, size = F.when(lost, F.col("kept")).otherwise(F.col("text")), F.when(lost, F.length("kept")).otherwise(F.col("n_chars"))
    return found.withColumns({"text": text, "n_chars": size}).select(*COLUMNS)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """As many whole copies of each document as the mix takes, in the order of the curriculum."""
    _small_batches(spark)
    return mixing.whole_copies(docs.select(*COLUMNS))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of 2048 tokens."""
    _small_batches(spark)
    packed = packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))
    return packed.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


STAGES = [
    ("language_id", identify_languages),
    ("simhash_dedup", drop_near_duplicates),
    ("substring_dedup", drop_repeated_passages),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: Language profiles, fingerprints and packing have no SQL form; tests compare each stage with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over ``documents``, each written to the shared folder and read again."""
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
