"""The corpus pipeline: toxicity, near-duplicates, PII, mixing to target weights, packing.

Each stage takes all that the one before kept, written as Parquet to the shared folder and read again; all but the last
return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from graphslice.llm import minhash, mixing, packing, surrogates, toxicity
from graphslice.llm.common import Durable, settle, table


def civil(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, trained on these and the labels, does not reject.

    Null and empty texts have the prior's low score and stay; a score equal to the threshold is rejected; repeated rows are
    judged alike; an empty table trains a model that rejects nothing."""
    return toxicity.keep_civil(docs, table(spark, sf_dir, "labels"))


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: five words, a Jaccard similarity of 0.8 or more.

    The least doc_id of a group stays, with all its rows where a doc_id repeats; null, empty and wordless texts have no
    group and all stay."""
    settle(spark)
    return minhash.keep_representatives(docs, minhash.Forest())


def private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Entities replaced in the texts; null, empty and entity-free texts, and all other columns but n_chars, stay as they are.

    The key is the session's (`surrogates.session_key`)."""
    settle(spark)
    return surrogates.redacted(docs, surrogates.session_key(spark))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix of their sources takes them; texts without words have no size and are not taken.

    Which documents go on is decided by a digest of doc_id, ties by doc_id, so reruns agree; a null source is one source."""
    settle(spark)
    return mixing.mixed_documents(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in sequences of at most 1024 tokens; a null or empty text is one end token, and each copy of a
    repeated row is packed."""
    settle(spark)
    return packing.pack_documents(docs)


STAGES = [("toxicity", civil), ("near-duplicates", distinct), ("pii", private), ("mixing", mixed), ("packing", packed)]

#: Training and hashing are not SQL; tests compare the stages with plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    keep, docs = Durable(spark), table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = keep(docs, f"stage{i}")
    return docs
