"""Table functions for SQL: components and minimum cut of a table of edges."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="rep int, v long, comp long")
class EdgeComponents:
    """Rows (rep, src, dst), partitioned by rep; one partition in one task."""

    def __init__(self):
        self.rep, self.a, self.b = None, [], []

    def eval(self, row):
        self.rep = row["rep"]
        self.a.append(row["src"])
        self.b.append(row["dst"])

    def terminate(self):
        import numpy as np

        from edgeconn.operators.components import local_labels

        if self.a:
            for v, c in zip(*local_labels(np.array(self.a), np.array(self.b)), strict=True):
                yield self.rep, int(v), int(c)


@udtf(returnType="rep int, value long, vertices long")
class EdgeMinCut:
    """The least cut of each partition's edges; parallel edges add up."""

    def __init__(self):
        self.rep, self.rows = None, []

    def eval(self, row):
        self.rep = row["rep"]
        self.rows.append((row["src"], row["dst"], 1))

    def terminate(self):
        from edgeconn.operators.solve import dense, solve

        if self.rows:
            w, names = dense(self.rows)
            yield self.rep, int(solve(w)[0]), len(names)


def register(spark: SparkSession) -> None:
    spark.udtf.register("edge_components", EdgeComponents)
    spark.udtf.register("edge_min_cut", EdgeMinCut)
