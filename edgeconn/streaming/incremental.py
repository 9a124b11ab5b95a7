"""Edge connectivity under insertions, batch by batch.

Between rebuilds the frozen kernel keeps every cut of at most 3/2 times the
value at the build; insertions never shrink a cut, so the answer after a batch
is the least of the exact minimum degree and the kernel's cut with the new
edges added. Once the answer outgrows that bound, or a vertex appears that the
kernel doesn't know, the kernel is built anew from all edges so far.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgeconn.operators.contract import adaptive_threshold, collapse, contract_once, edge_votes, inter_component_edges, merge_low_votes, widen
from edgeconn.operators.graph import Graph, canonical_edges
from edgeconn.operators.mincut import solve_kernel
from edgeconn.plans.staging import Staged, new_path, stage


@dataclass
class IncrementalConnectivity:
    """State lives in staged tables: edges so far, labels, kernel. ``process``
    returns (batch, inserted, min_degree, value, rebuilt, touched) of a batch;
    a batch that comes again returns the same row and changes nothing.

    With ``path`` a manifest of the state is written there after each batch,
    and a new object on the same path goes on from the last one; tables that a
    manifest names are deleted only once the next one is written."""

    spark: SparkSession
    path: str | None = None
    eps: float = 0.5
    q: int = 16
    seed: int = 1
    vertices: DataFrame | None = None
    edges: Staged | None = None
    labels: Staged | None = None
    kernel: Staged | None = None
    built_at: float = 0.0
    log: dict[int, tuple] = field(default_factory=dict)
    spent: list[Staged] = field(default_factory=list)

    def __post_init__(self):
        if self.path and (found := self._manifests()):
            text = self.spark.read.text(f"{self.path}/{found[-1]}").first()[0]
            state = json.loads(text)
            self.edges, self.labels, self.kernel = (Staged(self.spark, p) if p else None for p in state["tables"])
            self.built_at = state["built_at"]
            self.log = {int(k): tuple(v) for k, v in state["log"].items()}

    def _manifests(self) -> list[str]:
        """Finished manifests, in the order they were written."""
        root = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(root):
            return []
        names = sorted(s.getPath().getName() for s in fs.listStatus(root) if s.getPath().getName().startswith("manifest-"))
        return [n for n in names if fs.exists(self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{n}/_SUCCESS"))]

    def _save(self) -> None:
        if self.path:
            tables = [x.path if x else None for x in (self.edges, self.labels, self.kernel)]
            text = json.dumps({"tables": tables, "built_at": self.built_at, "log": self.log})
            self.spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.path}/manifest-{len(self.log):09d}")
        while self.spent:
            self.spent.pop().drop()

    def process(self, batch: int, pairs: DataFrame) -> tuple:
        """pairs: (a, b) insertions; loops and known edges don't count."""
        if batch in self.log:
            return self.log[batch]
        fresh = canonical_edges(pairs)
        known = self.edges.df if self.edges else None
        if known is not None:
            fresh = fresh.join(known.select("src", "dst"), ["src", "dst"], "left_anti")
        new = stage(fresh, "stream-new")
        added = new.df.count()
        old = self.edges
        self.edges = stage(new.df if known is None else known.unionByName(new.df), "stream-edges")
        if old:
            self.spent.append(old)
        g = Graph.of(self.edges.df, self.vertices)
        delta = g.profile["min_degree"]
        rebuilt, touched = False, added
        value = self._with_kernel(new.df, delta) if self.labels else None
        if value is None or value > (2 - self.eps) * self.built_at:
            rebuilt, touched = True, touched + g.profile["m"]
            self._build(g)
            value = self._with_kernel(None, delta)
            self.built_at = value
        new.drop()
        self.log[batch] = (batch, added, delta, int(value), rebuilt, touched)
        self._save()
        return self.log[batch]

    def _build(self, g: Graph) -> None:
        """A kernel that keeps the cuts of at most 2 - eps times the least."""
        step = "uniform" if g.profile["min_degree"] >= 8 else "certificate"
        first = stage(contract_once(g, self.q, self.seed, edge_step=step, hashing="xxhash64"), "stream-first").df
        wide = stage(widen(first), "stream-wide").df
        votes = stage(edge_votes(inter_component_edges(g.edges, wide)), "stream-votes").df
        voted = merge_low_votes(g, wide, votes, adaptive_threshold(votes, g.profile["n"]))
        self.labels, self.kernel = stage(voted.labels, "stream-labels"), stage(collapse(voted.kernel), "stream-kernel")

    def _with_kernel(self, new: DataFrame | None, delta: int) -> float | None:
        """The least of degree and kernel cut, the batch's edges put into the
        kernel; None if an edge's end has no label."""
        if new is not None:
            a = self.labels.df.select(F.col("v").alias("src"), F.col("comp").alias("ca"))
            b = self.labels.df.select(F.col("v").alias("dst"), F.col("comp").alias("cb"))
            joined = new.join(a, "src", "left").join(b, "dst", "left")
            if not joined.filter("ca IS NULL OR cb IS NULL").isEmpty():
                return None
            more = joined.filter("ca <> cb").select(F.least("ca", "cb").alias("cu"), F.greatest("ca", "cb").alias("cv")).groupBy("cu", "cv").agg(F.count(F.lit(1)).alias("mult"))
            before = self.kernel
            self.kernel = stage(before.df.unionByName(more).groupBy("cu", "cv").agg(F.sum("mult").alias("mult")), "stream-kernel")
            self.spent.append(before)
        parts = self.labels.df.select("comp").distinct().count()
        if parts < 2:
            return float(delta)
        found = solve_kernel(self.kernel.df, self.labels.df).collect()
        if not found or found[0].vertices < parts:
            return 0.0  # a kernel vertex without an edge
        return min(float(delta), found[0].value)


def stream_connectivity(stream: DataFrame, state: IncrementalConnectivity, sink: list | None = None):
    """A started query over a stream of (a, b) rows that feeds ``state``."""

    def each(batch: DataFrame, batch_id: int) -> None:
        row = state.process(batch_id, batch.select("a", "b"))
        if sink is not None:
            sink.append(row)

    place = f"{state.path}/checkpoint" if state.path else new_path(state.spark, "stream-checkpoint")
    return stream.writeStream.option("checkpointLocation", place).foreachBatch(each).trigger(availableNow=True).start()
