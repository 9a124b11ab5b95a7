"""A corpus from raw documents to token ids, stage by stage.

Each stage works on every document that the one before kept. All but the last
return the columns of ``documents``, whatever further ones there are.

Of rows with nulls, empty texts or repeats: a null text counts as empty and
passes every filter (it has no word, so all such texts are one near-copy group,
of which the least id stays); rows that repeat an id stay or go together in the
near-copy stage and are judged by their own text elsewhere; rows without an id
are never dropped as copies. Texts of any length are read whole, and an empty
table gives an empty result of the same columns. Of near copies with equal
claims the least doc_id stays.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from edgeconn.llm import decontaminate, nearcopies, pieces, pii, toxicity
from edgeconn.llm.common import small_batches, table
from edgeconn.plans.staging import stage


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the compression-distance classifier calls toxic go."""
    small_batches(spark)
    return toxicity.without_toxic(docs, toxicity.train(docs, table(spark, sf_dir, "labels")))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the document of least id stays: SimHash
    links and shared shingles find pairs, the cosine of whole sets decides."""
    small_batches(spark)
    return nearcopies.one_of_each(docs)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a passage of the benchmark go."""
    small_batches(spark)
    return decontaminate.without_leaks(docs, table(spark, sf_dir, "benchmark"))


def hide_private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Validated numbers, dates and addresses get pseudonyms of their format."""
    small_batches(spark)
    return pii.pseudonymise(docs, s=pii.of_session(spark), report=False)


def to_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, two bytes each, with a digest of what they
    decode to."""
    small_batches(spark)
    return pieces.encode_decode(docs, outputs=("packed", "decoded_sha256")).withColumnsRenamed({"id": "doc_id", "packed": "ids"})


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", drop_near_copies),
    ("benchmark_decontamination", drop_leaks),
    ("pii", hide_private),
    ("sentencepiece", to_ids),
]

#: No stage but the last but one could be said in SQL; the tests hold each
#: stage against a plain version instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), name).df
    return STAGES[-1][1](spark, docs, sf_dir)
