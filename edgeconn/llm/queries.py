"""One query per operator, over its whole table, and SQL where it can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgeconn.llm import chat, decontaminate, fingerprint, lm, pieces, pii, sharding, tokencounts, toxicity
from edgeconn.llm.common import held_out, table, text_or_empty
from edgeconn.llm.simhash import SimHash, near_duplicates
from edgeconn.plans.staging import new_path, stage


#: Rank of a missing id: after all others.
FAR = (1 << 63) - 1


def op1_chat_perspectives(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every conversation rendered from each participant's seat, by pieces."""
    return chat.perspectives(table(spark, sf_dir, "conversations"))


def op2_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals after three batches: all documents counted, later copies of a
    text deleted, what is left counted anew by the next tokenizer version. The
    first and last batch are delivered twice."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "lang", text_or_empty("text").alias("text"))
    counted = docs.select("doc_id", "source", "lang", F.xxhash64("text").alias("h1"), F.md5("text").alias("h2"), tokencounts.words(F.col("text")).alias("v1"), tokencounts.words_and_marks(F.col("text")).alias("v2"))
    # A row per text, source and language, so that no text is a hot key of the join.
    held = counted.groupBy("h1", "h2", "source", "lang").agg(F.any_value("v1").alias("v1"), F.any_value("v2").alias("v2"), F.count(F.lit(1)).alias("n"), F.min(F.coalesce("doc_id", F.lit(FAR))).alias("own"))
    held = stage(held, "token-counts").df
    first = held.groupBy("h1", "h2").agg(F.min("own").alias("first"))
    marked = stage(held.join(first, ["h1", "h2"]).withColumn("keep", (F.col("own") == F.col("first")).cast("long")), "token-copies").df
    store = tokencounts.RollupStore(spark, new_path(spark, "token-store"))
    v1, v2, copies = F.col("v1"), F.col("v2"), F.col("n") - F.col("keep")
    batches = {
        "1-insert": tokencounts.insert(marked, "words-1", v1, F.col("n")),
        "2-delete": tokencounts.delete(marked.filter(copies > 0), "words-1", v1, copies),
        "3-revise": tokencounts.revise(marked.filter("keep = 1"), ("words-1", v1), ("words-2", v2)),
    }
    for name in ("1-insert", "2-delete", "1-insert", "3-revise", "3-revise"):
        store.commit(name, batches[name])
    return store.totals()


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity score of every document, learnt outside the held-out fold."""
    docs = table(spark, sf_dir, "documents")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    out = toxicity.score(docs, model).withColumnRenamed("id", "doc_id")
    return out.select("doc_id", held_out(F.col("doc_id"), 5).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op4_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every probe of a benchmark item found in a document, with its place."""
    return decontaminate.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).withColumnsRenamed({"id": "doc_id", "item": "item_id"})


def op5_syncmer_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint of every document and of its text with the next one's start
    put over its end, and how alike they are."""
    return fingerprint.edited_neighbours(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


def op6_hilbert_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in 24 shards of equal row counts along the curve."""
    out = sharding.shard(table(spark, sf_dir, "documents"), 24)
    return out.select(F.col("id").alias("doc_id"), "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve")


def op7_brown_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """log10 probability of every document under the class-based model, learnt
    outside the held-out tenth."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").withColumn("held_out", F.coalesce(held_out(F.col("doc_id"), 10), F.lit(False)))
    model = lm.train(docs.filter(~F.col("held_out")).select("text"))
    return lm.score(docs.select("doc_id", "held_out", "text"), model, ["doc_id", "held_out"])


def op8_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Component of every document at 3 or fewer differing SimHash bits."""
    out = near_duplicates(table(spark, sf_dir, "documents"), SimHash())
    return out.select(F.col("id").alias("doc_id"), F.lower(F.hex("fp")).alias("fingerprint"), F.col("component").alias("component_id"))


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its validated numbers, dates and addresses replaced."""
    out = pii.pseudonymise(table(spark, sf_dir, "documents").select("doc_id", "text"), "text", pii.of_session(spark))
    return out.select("doc_id", "n_replaced", "kinds", "text")


def op10_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids and decoded text of every document, as digests."""
    out = pieces.encode_decode(table(spark, sf_dir, "documents"), outputs=("ids_sha256", "decoded_sha256"))
    return out.withColumnRenamed("id", "doc_id")


def queries() -> dict:
    found = {k: v for k, v in globals().items() if k.startswith("op") and callable(v)}
    return dict(sorted(found.items(), key=lambda kv: int(kv[0][2:].split("_")[0])))


def oracle_sql() -> dict[str, str]:
    return {"op1_chat_perspectives": chat.ORACLE_SQL, "op2_token_rollup": tokencounts.ORACLE_SQL}
