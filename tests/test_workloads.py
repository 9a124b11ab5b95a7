"""Workload graphs whose pairs SQL does not give."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgeconn.plans.staging import new_path
from edgeconn.sources import workloads as W


@pytest.mark.parametrize("block", [4096, 60])
def test_neighbours_are_sought_among_all_vectors(spark, small, block):
    rows = sorted((r.vec_id, r.embedding) for r in spark.read.parquet(f"{small}/embeddings.parquet").collect())
    x = np.array([v for _, v in rows], np.float64)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    sim = np.round(x @ x.T, 12)
    np.fill_diagonal(sim, -2)
    ids = np.array([i for i, _ in rows])
    want = {(int(ids[i]), int(ids[j])) for i, row in enumerate(np.argsort(-sim, axis=1, kind="stable")[:, :8]) for j in row}
    got = [(r.a, r.b) for r in W.nearest(spark.read.parquet(f"{small}/embeddings.parquet"), 8, block).collect()]
    assert len(got) == 8 * len(rows) and set(got) == want
    if block == 4096:
        mutual = {(r.a, r.b) for r in W.embedding_neighbours(spark, small).collect()}
        assert mutual == {(a, b) for a, b in want if a < b and (b, a) in want}


def test_conversations_of_many_turns_stay_apart(spark):
    folder = new_path(spark, "long-talks")
    turns = spark.range(5000).select(F.lit(1).cast("long").alias("conv_id"), F.col("id").alias("turn"))
    more = spark.range(1000).select(F.lit(2).cast("long").alias("conv_id"), F.col("id").alias("turn"))
    turns.unionByName(more).write.parquet(f"{folder}/conversations.parquet")
    g = W.graph(spark, folder, "conversation_paths")
    assert g.edges.count() == 4999 + 999
    ends = g.degrees.groupBy("deg").count().collect()
    assert {r.deg: r["count"] for r in ends} == {1: 4, 2: 5996}
