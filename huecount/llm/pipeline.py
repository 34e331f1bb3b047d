"""A corpus from raw documents to packed sequences, in five stages.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again as
the next one's docs. All but the last return the columns of documents. Text of unknown language goes,
one document of each class of near copies stays, secrets are replaced, sources are mixed to their
targets (documents may repeat), and what is left is packed: the result has the ids of every piece beside
its place, by sequence and offset.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from huecount.llm import langid, minhash, mixing, packing, secrets
from huecount.llm.common import fresh_dir, made, release, table


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return langid.identified(docs)


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return minhash.deduplicated(docs)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return secrets.redacted(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.placed(packing.sequences(docs))


STAGES = [
    ("language_id", known_language),
    ("near_dedup", one_of_each),
    ("secret_scan", without_secrets),
    ("mixing", mixed),
    ("packing", packed),
]

#: Trained networks, hashed darts and subset-sum packing have no SQL form; the tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage. What a stage has written for itself goes as soon as its result is written, and
    that goes when the next one's is."""
    docs, mark = table(spark, sf_dir, "documents"), made()
    for name, stage in STAGES:
        out = stage(spark, docs, sf_dir)
        path = fresh_dir(spark, f"stage-{name}")
        out.write.parquet(path)
        docs = spark.read.schema(out.schema).parquet(path)
        release(spark, mark, (path,))
    return docs
