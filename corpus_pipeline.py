"""From raw documents to packed sequences, in stages that are written and read again in between.

Quality classifier, exact dedup, near-duplicate join, secret redaction, packing. Each stage is a function of (spark, docs,
sf_dir); all but the last return the columns of documents, whatever their names.

Defined results: null and empty texts count as empty through all stages. The classifier scores them by its bias, exact dedup keeps one of
them, packing gives it one token. Rows with equal or null ids are told apart by row. Of equal or near texts the least id stays, nulls
last. An empty table, or one without labels, goes through: without labels all scores are 0.5 and every document is accepted.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orderless.llm import common, exact_dedup, near_dedup, packing, quality, secrets


def accept_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, fitted on the labelled ones, accepts (a score of 0.3 or more); texts stay as they are."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    score = quality.scorer(spark, quality.train(docs, labels))
    return docs.filter(quality.accepted(score(F.col("text"))))


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts equal up to white space: the least id, null ids last, then any one row."""
    return exact_dedup.kept_documents(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class (five words, similarity of 0.8 or more): the least id, null ids last."""
    return near_dedup.kept_documents(docs)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, secrets in their texts replaced by a mark until no base secret is left; n_chars follows the text, null texts stay null."""
    redact = secrets.redactor(spark)
    out = docs.withColumn("text", F.coalesce(redact(F.col("text")), F.col("text")))
    return out.withColumn("n_chars", F.length("text").cast("long")).select(*[common.col(c) for c in docs.columns])


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their places in sequences; an empty text is one token."""
    import public_tokenizers

    return packing.pack_documents(docs, public_tokenizers.path(packing.VOCABULARY))


STAGES = [
    ("quality classifier", accept_quality),
    ("exact dedup", drop_copies),
    ("n-gram Jaccard join", drop_near_copies),
    ("secret scans", redact_secrets),
    ("best-fit packing", pack_sequences),
]

#: The classifier and the network can't be said in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = common.stage(docs, name.replace(" ", "-"))
    return docs
